"""Queries of the relational surface, functions, sources, baselines, plans and streams."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql.window import Window

from farpoint import features as X
from farpoint.baselines import local as B
from farpoint.composite import neighbours as N
from farpoint.detectors.statistical import CopulaDetector, HistogramDetector, PcaDetector
from farpoint.functions import sql as Q
from farpoint.model import FeatureFrame
from farpoint.operators import relational as R
from farpoint.operators.basic import histogram
from farpoint.plans.registry import OpNode, lower
from farpoint.queries.base import CUSTOMERS, CUSTOMERS_SCALED, LINE_KEYS, LINES, ORACLES, EVENTS, ORDERS, VECTORS, cdf_sql, dist_sql, edges_sql, knn_sql, r6, register, rounded, side_sums
from farpoint.queries.detectors import hbos_sql
from farpoint.queries.operators import LINE_FEATURES, customers_scaled
from farpoint.session import fresh_path, table
from farpoint.sources import io
from farpoint.streaming import score as ST

c = F.col


def both(name, f, sql):
    register(name, f, sql)


# Baselines against the engine's own SQL
both("baseline_broadcast_knn", lambda s, d: rounded(B.broadcast_knn(X.vectors(s, d), 10), "dist"), f"with {knn_sql(VECTORS, 10)} select i, j, cast(rank as int) as rank, round(dist, 6) as dist from n")
both("baseline_broadcast_lof", lambda s, d: rounded(B.broadcast_lof(X.vectors(s, d), 10), "score", digits=5), f"with {knn_sql(VECTORS, 10)}, kd as materialized (select i, max(dist) as kd from n group by i), d as materialized (select n.i, 1 / (avg(greatest(kd, dist)) + 1e-10) as lrd from n join kd on kd.i = n.j group by n.i) select n.i as id, round(avg(q.lrd) / any_value(p.lrd), 5) as score from n join d p on p.i = n.i join d q on q.i = n.j group by n.i")
both("baseline_local_knn", lambda s, d: rounded(B.local_frame("knn", X.vectors(s, d), k=5), "score"), f"with {knn_sql(VECTORS, 5)} select i as id, round(max(dist), 6) as score from n group by i")
both("baseline_local_hbos", lambda s, d: rounded(B.local_frame("hbos", X.order_prices(s, d)), "score"), f"with {hbos_sql(ORDERS, 'o_orderkey', ['price', 'days'], '10')} select o_orderkey as id, round(score, 6) + 0.0 as score from scores")
both("baseline_relational_knn", lambda s, d: rounded(R.nearest_by_sql(X.vectors(s, d), 5), "dist"), f"with {knn_sql(VECTORS, 5)} select i, j, cast(rank as int) as rank, round(dist, 6) as dist from n")


# Fusion rules: the same tree with and without
_tree = lambda s, d: OpNode("topk_smallest", (OpNode("pairwise_distance", (X.vectors(s, d),), {"blocks": 3}),), {"k": 5})
both("fusion_knn_tree", lambda s, d: rounded(lower(_tree(s, d)), "dist"), f"with {knn_sql(VECTORS, 5)} select i, j, cast(rank as int) as rank, round(dist, 6) as dist from n")
both("fusion_knn_unfused", lambda s, d: rounded(lower(_tree(s, d), False), "dist"), f"with {knn_sql(VECTORS, 5)} select i, j, cast(rank as int) as rank, round(dist, 6) as dist from n")
both("fusion_range_count", lambda s, d: lower(OpNode("count", (OpNode("within", (OpNode("pairwise_distance", (X.vectors(s, d),), {"blocks": 3}),), {"phi": 1.25}),))), f"with {edges_sql(VECTORS)} select i, count(*) as n from e where dist <= 1.25 group by i")
_lines_tree = lambda outer, inner, fused=True: lambda s, d: lower(OpNode(outer, (OpNode(inner, (X.line_measures(s, d).select(["quantity", "price", "discount"]) if outer == "square" else X.line_measures(s, d),)),)), fused)
for _name, _fused in (("", True), ("_unfused", False)):
    both(f"fusion_tails{_name}", lambda s, d, f=_fused: rounded(_lines_tree("log", "ecdf", f)(s, d), "u_left", "u_right", "u_skew"), ORACLES["tails_left_right_skew"])
    both(f"fusion_components{_name}", lambda s, d, f=_fused: rounded(_lines_tree("square", "project", f)(s, d), "score", digits=5), ORACLES["pca_all"])
both("fusion_histogram_unfused", lambda s, d: rounded(_lines_tree("lookup", "histogram", False)(s, d), "score"), f"with {hbos_sql(LINES, LINE_KEYS, LINE_FEATURES, '10')} select {LINE_KEYS}, round(score, 6) + 0.0 as score from scores")
both("fusion_histogram_score", lambda s, d: rounded(lower(OpNode("lookup", (OpNode("histogram", (X.line_measures(s, d),), {"bins": 10}),))), "score"), f"with {hbos_sql(LINES, LINE_KEYS, LINE_FEATURES, '10')} select {LINE_KEYS}, round(score, 6) + 0.0 as score from scores")


def _generated(s, d):
    x = X.points_of(table(s, d, "orders", c("o_orderkey").alias("id")), 4, 0.02, seed=2)
    return x.df.select("id", *(r6(f) for f in x.features), X.planted(0.02, 2).cast("int").alias("planted")).toDF("id", *x.features, "planted")


_noise = lambda k: f"(((id * (1103515 + 2 * {k}) + (2 * 7919 + {k} * 104729)) * 69069 + {k} * 15485863) % 1000003 / 1000003.0)"
_noise_d = lambda k: f"cast({_noise(k)} as double)"
both("synthetic_points", _generated, "with i as (select o_orderkey as id from orders) select id, " + ", ".join(f"round(case when (id * 7717 + 2) % 10007 < 200 then {_noise_d(k)} * 8 - 4 else (id % 4 * ({k} + 3) % 5 - 2) * cast(0.5 as double) + ({_noise_d(k)} + {_noise_d(k + 4)} - 1) * cast(0.5 as double) end, 6) + 0.0 as x{k}" for k in range(4)) + ", cast((id * 7717 + 2) % 10007 < 200 as int) as planted from i")

# Scans, filters, projections
both("relational_scan_pruned", lambda s, d: io.scan(s, d, "lineitem", ["l_orderkey", "l_linenumber", "l_quantity"], c("l_quantity") >= 45), "select l_orderkey, l_linenumber, l_quantity from lineitem where l_quantity >= 45")
both("relational_filters", lambda s, d: table(s, d, "orders", "o_orderkey", "o_orderstatus", "o_totalprice", "o_orderpriority").where(c("o_totalprice").between(1000, 100000) & c("o_orderstatus").isin("F", "O") & c("o_orderpriority").like("%H%") & c("o_orderkey").isNotNull()), "select o_orderkey, o_orderstatus, o_totalprice, o_orderpriority from orders where o_totalprice between 1000 and 100000 and o_orderstatus in ('F', 'O') and o_orderpriority like '%H%' and o_orderkey is not null")
both("relational_pack_unpivot", lambda s, d: X.order_prices(s, d).pack().unpack().long(), f"select o_orderkey as id, 'price' as feature, price as value from ({ORDERS}) union all select o_orderkey, 'days', days from ({ORDERS})")


def _round_trip(fmt):
    def run(s, d):
        path = fresh_path(s, f"trip-{fmt}")
        src = table(s, d, "supplier", "s_suppkey", "s_name", "s_acctbal")
        io.write_any(src, path, fmt)
        return io.read_any(s, path, fmt, src.schema)

    return run


for fmt in ("csv", "json", "orc"):
    both(f"source_{fmt}", _round_trip(fmt), "select s_suppkey, s_name, s_acctbal from supplier")


def _source_points(s, d):
    io.register_sources(s)
    """A source's point for every order, by its key."""
    keys = table(s, d, "orders", c("o_orderkey").alias("id"))
    rows = keys.agg(F.coalesce(F.max("id") + 1, F.lit(0))).first()[0]
    df = s.read.format("synthetic_points").option("rows", rows).option("features", 2).load()
    return keys.join(df, "id").select("id", r6("x0").alias("x0"), r6("x1").alias("x1"))


both("source_synthetic_points", _source_points, "select o_orderkey as id, round((o_orderkey * 31) % 1009 / 1009.0, 6) + 0.0 as x0, round((o_orderkey * 33 + 17) % 1009 / 1009.0, 6) + 0.0 as x1 from orders")


def _sink(s, d):
    path = fresh_path(s, "scores")
    x = X.line_measures(s, d)
    flagged = HistogramDetector(10).fit_score(x).withColumn("band", F.floor("score").cast("int"))
    io.write_scores(flagged, path, ["band"])
    return s.read.parquet(path).groupBy("band").agg(F.count("*").alias("n"))


both("sink_partitioned_scores", _sink, f"with {hbos_sql(LINES, LINE_KEYS, LINE_FEATURES, '10')} select cast(floor(score) as int) as band, count(*) as n from scores group by 1")


def _saved(s, d):
    path = fresh_path(s, "model")
    x = X.order_prices(s, d)
    io.save_model(s, HistogramDetector(10).fit(x), path)
    return rounded(io.load_model(s, path).score(x), "score")


both("sink_saved_model", _saved, f"with {hbos_sql(ORDERS, 'o_orderkey', ['price', 'days'], '10')} select o_orderkey, round(score, 6) + 0.0 as score from scores")

# Joins
both("join_inner", lambda s, d: table(s, d, "customer", "c_custkey", "c_nationkey").join(F.broadcast(table(s, d, "nation", "n_nationkey", "n_name")), c("c_nationkey") == c("n_nationkey")).select("c_custkey", "n_name"), "select c_custkey, n_name from customer join nation on c_nationkey = n_nationkey")
both("join_merge_hint", lambda s, d: table(s, d, "orders", "o_orderkey", "o_custkey").hint("merge").join(table(s, d, "customer", "c_custkey", "c_mktsegment"), c("o_custkey") == c("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n")), "select c_mktsegment, count(*) as n from orders join customer on o_custkey = c_custkey group by 1")
for how in ("left", "right", "full"):
    both(f"join_{how}_outer", lambda s, d, h=how: table(s, d, "documents", "doc_id", "lang").join(table(s, d, "labels", c("doc_id").alias("l_doc"), "quality"), c("doc_id") == c("l_doc"), h).select("doc_id", "lang", F.coalesce("quality", F.lit(-1)).alias("quality")), f"select doc_id, lang, coalesce(quality, -1) as quality from documents {how} join (select doc_id as l_doc, quality from labels) on doc_id = l_doc")
both("join_semi", lambda s, d: table(s, d, "documents", "doc_id", "lang").join(table(s, d, "labels", "doc_id", "toxic").where("toxic = 1"), "doc_id", "left_semi"), "select doc_id, lang from documents where doc_id in (select doc_id from labels where toxic = 1)")
both("join_anti", lambda s, d: table(s, d, "documents", "doc_id", "lang").join(table(s, d, "labels", "doc_id"), "doc_id", "left_anti"), "select doc_id, lang from documents where doc_id not in (select doc_id from labels)")
both("join_theta", lambda s, d: table(s, d, "supplier", "s_suppkey", "s_acctbal").join(table(s, d, "supplier", c("s_suppkey").alias("t"), c("s_acctbal").alias("b")), (c("s_acctbal") < c("b")) & (c("b") - c("s_acctbal") < 50)).select("s_suppkey", "t"), "select a.s_suppkey, b.s_suppkey as t from supplier a join supplier b on a.s_acctbal < b.s_acctbal and b.s_acctbal - a.s_acctbal < 50")
both("join_as_of_previous", lambda s, d: R.previous_event(table(s, d, "events", "event_id", "user_id", "ts", "value")), "select event_id, user_id, value, lag(event_id) over w as previous_id, lag(value) over w as previous_value, cast(floor(epoch(ts)) as bigint) - lag(cast(floor(epoch(ts)) as bigint)) over w as gap from events window w as (partition by user_id order by ts, event_id)")
both("join_near_in_time", lambda s, d: R.near_in_time(table(s, d, "events", "event_id", "user_id", "ts")), "select a.user_id as u, a.event_id as earlier, b.event_id as later from (select *, cast(floor(epoch(ts)) as bigint) as t from events) a join (select *, cast(floor(epoch(ts)) as bigint) as t from events) b on a.user_id = b.user_id and b.t - a.t between 0 and 3600 and (a.t < b.t or a.event_id < b.event_id)")


def _lateral(s, d):
    top = X.vectors(s, d)
    rows = top.df.join(table(s, d, "embeddings", c("vec_id").alias("id"), "label"), "id").select("id", "label", c("x")[0].alias("first"))
    labels = rows.select(c("label").alias("l")).distinct().alias("labels")
    best = rows.where(c("label") == c("l").outer()).orderBy(F.desc("first"), "id").limit(2).select("id", r6("first").alias("first"))
    return labels.lateralJoin(best).select(c("l").alias("label"), "id", "first")


both("join_lateral_top", _lateral, "select label, id, round(first, 6) + 0.0 as first from (select label, vec_id as id, cast(embedding[1] as double) as first, row_number() over (partition by label order by embedding[1] desc, vec_id) as r from embeddings) where r <= 2")

# Aggregation
both("agg_hash", lambda s, d: table(s, d, "events", "user_id", "value").groupBy("user_id").agg(F.count("*").alias("n"), F.sum(c("value").cast("decimal(18,4)")).cast("double").alias("total"), F.max("value").alias("top")), "select user_id, count(*) as n, cast(sum(cast(value as decimal(18,4))) as double) as total, max(value) as top from events group by user_id")
both("agg_count_distinct", lambda s, d: table(s, d, "events", "event_type", "user_id").groupBy("event_type").agg(F.count_distinct("user_id").alias("users")), "select event_type, count(distinct user_id) as users from events group by 1")
both("agg_approx_distinct", lambda s, d: table(s, d, "events", "user_id").agg(F.approx_count_distinct("user_id", 0.02).alias("users")), None)
_flags = lambda s, d: table(s, d, "lineitem", "l_returnflag", "l_linestatus", "l_quantity").withColumn("high", (c("l_quantity") > 45).cast("int"))
for kind in ("cube", "rollup"):
    both(f"agg_{kind}", lambda s, d, k=kind: getattr(_flags(s, d), k)("l_returnflag", "l_linestatus").agg(F.sum("high").alias("high"), F.count("*").alias("n")), f"select l_returnflag, l_linestatus, cast(sum(cast(l_quantity > 45 as int)) as bigint) as high, count(*) as n from lineitem group by {kind} (l_returnflag, l_linestatus)")
both("agg_grouping_sets", lambda s, d: _sets(s, d), "select l_returnflag, l_linestatus, count(*) as n from lineitem group by grouping sets ((l_returnflag), (l_linestatus), ())")


def _sets(s, d):
    table(s, d, "lineitem", "l_returnflag", "l_linestatus").createOrReplaceTempView("fp_lines")
    return s.sql("select l_returnflag, l_linestatus, count(*) as n from fp_lines group by grouping sets ((l_returnflag), (l_linestatus), ())")


both("agg_quantiles", lambda s, d: rounded(table(s, d, "orders", "o_orderstatus", "o_totalprice").groupBy("o_orderstatus").agg(F.percentile("o_totalprice", 0.25).alias("q1"), F.percentile("o_totalprice", 0.5).alias("q2")), "q1", "q2"), "select o_orderstatus, round(quantile_cont(o_totalprice, 0.25), 6) as q1, round(quantile_cont(o_totalprice, 0.5), 6) as q2 from orders group by 1")
both("agg_quantiles_approx", lambda s, d: table(s, d, "orders", "o_totalprice").agg(F.percentile_approx("o_totalprice", 0.5, 10000).alias("q2")), None)
both("agg_quantiles_sketch", lambda s, d: table(s, d, "orders", "o_totalprice").agg(F.kll_sketch_get_quantile_double(F.kll_sketch_agg_double("o_totalprice"), F.lit(0.5)).alias("q2")), None)
both("agg_filter_pivot", lambda s, d: table(s, d, "events", "user_id", "event_type", "event_id").groupBy("user_id").pivot("event_type", ["click", "purchase"]).agg(F.count("event_id")).na.fill(0), "select user_id, count(*) filter (where event_type = 'click') as click, count(*) filter (where event_type = 'purchase') as purchase from events group by user_id")
both("agg_max_by", lambda s, d: table(s, d, "events", "user_id", "event_id", "value").groupBy("user_id").agg(F.max_by("event_id", F.struct("value", "event_id")).alias("at_top"), F.min_by("event_id", F.struct("value", "event_id")).alias("at_low")), "select user_id, arg_max(event_id, row(value, event_id)) as at_top, arg_min(event_id, row(value, event_id)) as at_low from events group by user_id")
both("agg_correlation", lambda s, d: rounded(table(s, d, "lineitem", "l_quantity", "l_extendedprice").agg(F.corr("l_quantity", "l_extendedprice").alias("r")), "r"), "select round(corr(l_quantity, l_extendedprice), 6) as r from lineitem")

# Windows
_w = lambda: Window.partitionBy("user_id").orderBy("value", "event_id")
both("window_ranks", lambda s, d: table(s, d, "events", "event_id", "user_id", "value").select("event_id", F.row_number().over(_w()).alias("rn"), F.rank().over(Window.partitionBy("user_id").orderBy("value")).alias("rk"), F.dense_rank().over(Window.partitionBy("user_id").orderBy("value")).alias("dr"), r6(F.percent_rank().over(Window.partitionBy("user_id").orderBy("value"))).alias("pr"), r6(F.cume_dist().over(Window.partitionBy("user_id").orderBy("value"))).alias("cd"), F.ntile(4).over(_w()).alias("nt")), "select event_id, cast(row_number() over w as int) as rn, cast(rank() over v as int) as rk, cast(dense_rank() over v as int) as dr, round(percent_rank() over v, 6) + 0.0 as pr, round(cume_dist() over v, 6) + 0.0 as cd, cast(ntile(4) over w as int) as nt from events window w as (partition by user_id order by value, event_id), v as (partition by user_id order by value)")
both("window_lag_lead", lambda s, d: table(s, d, "events", "event_id", "user_id", "ts", "value").select("event_id", *(f.over(Window.partitionBy("user_id").orderBy("ts", "event_id")).alias(n) for n, f in (("before", F.lag("value")), ("after", F.lead("value")), ("first", F.first("value")), ("second", F.nth_value("value", 2))))), "select event_id, lag(value) over w as before, lead(value) over w as after, first_value(value) over w as first, nth_value(value, 2) over w as second from events window w as (partition by user_id order by ts, event_id)")
_events = lambda s, d: table(s, d, "events", "event_id", "user_id", "ts", "value")
_prior = lambda n: f"(partition by user_id order by ts, event_id rows between {n} preceding and 1 preceding)"
both("window_rolling_zscore", lambda s, d: rounded(R.rolling_zscore(_events(s, d)), "z", digits=5), f"select event_id, user_id, round(case when count(value) over w >= 2 and stddev_pop(value) over w > 0 then (value - avg(value) over w) / stddev_pop(value) over w end, 5) + 0.0 as z from events window w as {_prior(20)}")
both("window_rolling_median", lambda s, d: rounded(R.rolling_median_deviation(_events(s, d)), "deviation"), f"select event_id, user_id, round(abs(value - quantile_cont(value, 0.5) over w), 6) as deviation from events window w as {_prior(10)}")
both("window_trailing_day", lambda s, d: rounded(R.trailing_day(_events(s, d)), "mean_day"), "select event_id, user_id, count(*) over w as n_day, round(avg(value) over w, 6) as mean_day from (select *, cast(floor(epoch(ts)) as bigint) as t from events) window w as (partition by user_id order by t range between 86400 preceding and current row)")

# Order, limits, sets
_hs = lambda s, d: rounded(HistogramDetector(10).fit_score(X.customer_behaviour(s, d)), "score")
_hc = f"with {hbos_sql(CUSTOMERS, 'c_custkey', ['acctbal', 'n_orders', 'sum_price', 'avg_price', 'max_price', 'urgent_share'], '10')} select c_custkey, round(score, 6) + 0.0 as score from scores"
both("top_outliers", lambda s, d: R.top_outliers(_hs(s, d), 20, ["c_custkey"]), f"select * from ({_hc}) order by score desc, c_custkey limit 20")
both("top_outliers_offset", lambda s, d: R.top_outliers(_hs(s, d), 20, ["c_custkey"], offset=10), f"select * from ({_hc}) order by score desc, c_custkey limit 20 offset 10")
both("top_outliers_by_segment", lambda s, d: R.top_outliers(_hs(s, d).join(table(s, d, "customer", "c_custkey", "c_mktsegment"), "c_custkey"), 3, ["c_custkey"], ["c_mktsegment"]), f"select c_custkey, score, c_mktsegment, cast(r as int) as rank from (select *, row_number() over (partition by c_mktsegment order by score desc, c_custkey) as r from ({_hc}) join (select c_custkey, c_mktsegment from customer) using (c_custkey)) where r <= 3")
for name, op in (("union", "union all"), ("except", "except"), ("except_all", "except all")):
    f = {"union": lambda a, b: a.unionByName(b), "except": lambda a, b: a.subtract(b), "except_all": lambda a, b: a.exceptAll(b)}[name]
    both(f"set_{name}", lambda s, d, f=f: f(table(s, d, "orders", c("o_custkey").alias("k")), table(s, d, "events", c("user_id").alias("k"))), f"select o_custkey as k from orders {op} select user_id from events")

# Functions
both("fn_string", lambda s, d: table(s, d, "part", "p_partkey", "p_name", "p_brand").select("p_partkey", F.length("p_name").alias("n"), F.lower("p_name").alias("low"), F.translate("p_brand", "#", "-").alias("brand"), F.levenshtein("p_name", "p_brand").alias("lev"), F.size(F.split("p_name", " ")).alias("words")), "select p_partkey, cast(length(p_name) as int) as n, lower(p_name) as low, replace(p_brand, '#', '-') as brand, cast(levenshtein(p_name, p_brand) as int) as lev, cast(len(string_split(p_name, ' ')) as int) as words from part")
both("fn_date", lambda s, d: table(s, d, "events", "event_id", "ts").select("event_id", F.hour("ts").alias("h"), F.dayofweek("ts").alias("dow"), F.datediff(c("ts").cast("date"), F.lit("2024-01-01").cast("date")).alias("days"), F.date_format(F.date_trunc("month", "ts"), "yyyy-MM-dd").alias("month")), "select event_id, cast(hour(ts) as int) as h, cast(dayofweek(ts) + 1 as int) as dow, cast(date_diff('day', date '2024-01-01', cast(ts as date)) as int) as days, strftime(date_trunc('month', ts), '%Y-%m-%d') as month from events")
both("fn_math", lambda s, d: table(s, d, "orders", "o_orderkey", "o_totalprice").select("o_orderkey", r6(F.log("o_totalprice")).alias("ln"), r6(F.sqrt("o_totalprice")).alias("root"), F.signum(c("o_totalprice") - 100000).cast("int").alias("side"), F.width_bucket("o_totalprice", F.lit(0.0), F.lit(500000.0), F.lit(10)).cast("int").alias("b"), r6(F.try_divide(c("o_totalprice"), c("o_orderkey"))).alias("per")), "select o_orderkey, round(ln(o_totalprice), 6) as ln, round(sqrt(o_totalprice), 6) as root, cast(sign(o_totalprice - 100000) as int) as side, cast(floor(o_totalprice / 50000) + 1 as int) as b, round(o_totalprice / nullif(o_orderkey, 0), 6) as per from orders")
both("fn_array", lambda s, d: X.vectors(s, d).df.select("id", r6(F.aggregate("x", F.lit(0.0), lambda a, v: a + v)).alias("total"), F.size(F.filter("x", lambda v: v > 0)).alias("pos"), r6(F.array_max("x")).alias("top")), f"select id, round(list_sum(v), 6) + 0.0 as total, cast(len(list_filter(v, lambda q: q > 0)) as int) as pos, round(list_max(v), 6) as top from ({VECTORS})")
both("fn_json_map", lambda s, d: table(s, d, "events", "event_id", "props").select("event_id", F.from_json("props", "map<string,int>").alias("m")).select("event_id", c("m")["k"].alias("k"), F.size(F.map_keys("m")).alias("keys")), "select event_id, cast(json_extract_string(props, '$.k') as int) as k, cast(len(json_keys(props)) as int) as keys from events")


def _sql_functions(s, d):
    Q.register_sql_functions(s)
    X.vectors(s, d).df.createOrReplaceTempView("fp_vectors")
    return s.sql("select a.id, round(fp_sq_distance(a.x, b.x), 6) as sq, round(fp_cosine(a.x, b.x), 6) + 0D as cos from fp_vectors a join (select x from fp_vectors where id = (select min(id) from fp_vectors)) b")


both("fn_sql_distance", _sql_functions, f"with x as ({VECTORS}) select a.id, round({dist_sql('sqeuclidean')}, 6) as sq, round(1 - ({dist_sql('cosine')}), 6) + 0.0 as cos from x a, x b where b.id = (select min(id) from x)")
both("fn_arrow_udf", lambda s, d: X.vectors(s, d).df.select("id", r6(Q.norm_udf("x")).alias("norm")), f"select id, round(sqrt(list_sum(list_transform(v, lambda q: q * q))), 6) as norm from ({VECTORS})")
both("fn_pandas_grouped", lambda s, d: Q.median_of(table(s, d, "events", "user_id", "value"), "user_id", "value").select("user_id", r6("median").alias("median")), "select user_id, round(quantile_cont(value, 0.5), 6) as median from events group by 1")


def _udtf(s, d):
    """The two nearest customers that share a supplier's number, by a table function over each block of customers with each block of all of these."""
    s.udtf.register("fp_nearest_of", Q.nearest_of)
    x = customers_scaled(s, d).df
    ref = x.join(table(s, d, "supplier", c("s_suppkey").alias("id")), "id", "left_semi")
    for rows, name in ((x, "fp_customers"), (ref, "fp_points")):
        blocks = max(1, -(-rows.count() // 1024))
        lists = rows.groupBy(F.pmod(F.xxhash64("id"), F.lit(blocks)).alias("block")).agg(F.collect_list(F.struct("id", "x")).alias("l"))  # about 1024 rows
        lists = lists.select(F.transform("l", lambda v: v["id"]).alias("ids"), F.transform("l", lambda v: v["x"]).alias("vs"))
        (lists.repartition(s.sparkContext.defaultParallelism) if rows is x else lists).createOrReplaceTempView(name)
    near = s.sql("select t.i, t.id as j, t.dist from fp_customers c cross join fp_points p, lateral fp_nearest_of(c.ids, c.vs, p.ids, p.vs, 2) t")
    return rounded(N._ranked(near, 2), "dist")


both("fn_udtf", _udtf, f"with x as ({CUSTOMERS_SCALED}), e as (select a.id as i, b.id as j, {dist_sql()} as dist from x a join x b on b.id in (select s_suppkey from supplier)) select i, j, cast(rank as int) as rank, round(dist, 6) as dist from (select *, row_number() over (partition by i order by dist, j) as rank from e) where rank <= 2")
both("histogram_given_borders", lambda s, d: rounded(histogram(X.order_prices(s, d).select(["price"]), borders={"price": [0.0, 100000.0, 200000.0, 600000.0]}, kind="frequency"), "lo", "hi"), f"select 'price' as feature, cast(k as int) as bin, cast(lo as double) as lo, cast(hi as double) as hi, count(*) as count from (values (0, 0, 100000), (1, 100000, 200000), (2, 200000, 600000)) b(k, lo, hi) join ({ORDERS}) on price >= lo and price < hi group by all")


# Streams
def _stream_hbos(s, d):
    x = X.line_measures(s, d)
    model = HistogramDetector(10).fit(x)
    stream = ST.read_stream(s, d, "lineitem").withColumn("price", c("l_extendedprice")).withColumnsRenamed({"l_quantity": "quantity", "l_discount": "discount", "l_tax": "tax"})
    return rounded(ST.drain(ST.score_stream(model, stream, list(x.ids), list(x.features)), "hbos"), "score")


both("stream_hbos", _stream_hbos, f"with {hbos_sql(LINES, LINE_KEYS, LINE_FEATURES, '10')} select {LINE_KEYS}, round(score, 6) + 0.0 as score from scores")


def _stream_pca(s, d):
    x = X.line_measures(s, d)
    model = PcaDetector().fit(x)
    stream = ST.read_stream(s, d, "lineitem").withColumn("price", c("l_extendedprice")).withColumnsRenamed({"l_quantity": "quantity", "l_discount": "discount", "l_tax": "tax"})
    got = rounded(ST.drain(ST.score_stream(model, stream, list(x.ids), list(x.features)), "pca"), "score", digits=5)
    return got.exceptAll(rounded(model.score(x), "score", digits=5)).agg(F.count("*").alias("differences"))


both("stream_pca_equals_batch", _stream_pca, "select cast(0 as bigint) as differences")


def _windows(kind):
    def run(s, d):
        e = ST.with_event_time(ST.read_stream(s, d, "events"))
        w = {"tumbling": F.window("ts", "1 day"), "sliding": F.window("ts", "2 days", "1 day"), "session": F.session_window("ts", "6 hours")}[kind]
        by = ["user_id"] if kind == "session" else ["event_type"]
        out = ST.drain(ST.windowed_features(e, w, by), kind)
        return out.select(F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), *by, "n", "total", "top")

    return run


# Only windows that the watermark (latest event minus one hour) has passed are written.
_closed = "(select max(ts) - interval 1 hour from events)"
both("stream_tumbling", _windows("tumbling"), f"select strftime(w, '%Y-%m-%d %H:%M:%S') as start, event_type, count(*) as n, cast(sum(cast(value as decimal(18,4))) as double) as total, max(value) as top from (select *, time_bucket(interval 1 day, ts, timestamp '1970-01-01') as w from events) where w + interval 1 day <= {_closed} group by w, event_type")
both("stream_sliding", _windows("sliding"), f"select strftime(w, '%Y-%m-%d %H:%M:%S') as start, event_type, count(*) as n, cast(sum(cast(value as decimal(18,4))) as double) as total, max(value) as top from (select e.*, time_bucket(interval 1 day, ts, timestamp '1970-01-01') - k * interval 1 day as w from events e, (select unnest([0, 1]) as k)) where w + interval 2 day <= {_closed} group by w, event_type")
both("stream_session", _windows("session"), f"with g as (select *, case when ts >= lag(ts) over w + interval 6 hour or lag(ts) over w is null then 1 else 0 end as new from events window w as (partition by user_id order by ts, event_id)), s as (select *, sum(new) over (partition by user_id order by ts, event_id) as k from g) select strftime(min(ts), '%Y-%m-%d %H:%M:%S') as start, user_id, count(*) as n, cast(sum(cast(value as decimal(18,4))) as double) as total, max(value) as top from s group by user_id, k having max(ts) + interval 6 hour <= {_closed}")


def _running(s, d):
    out = ST.drain(ST.running_deviation(ST.read_stream(s, d, "events")), "running")
    return out.select("event_id", "user_id", "n_before", F.floor(c("mean_before") * 10 + 0.0123).alias("mean_tenths"), "flagged")


_all_before = "(partition by user_id order by ts, event_id rows between unbounded preceding and 1 preceding)"
both("stream_running_deviation", _running, f"select event_id, user_id, count(*) over w as n_before, cast(floor(avg(value) over w * 10 + 0.0123) as bigint) as mean_tenths, coalesce(count(*) over w >= 10 and abs(value - avg(value) over w) > 3 * stddev_pop(value) over w, false) as flagged from events window w as {_all_before}")


def _stream_static(s, d):
    e = ST.read_stream(s, d, "events").join(table(s, d, "customer", "c_custkey", "c_mktsegment"), c("user_id") == c("c_custkey")).where("value > 200")
    return ST.drain(e.select("event_id", "user_id", "c_mktsegment"), "alerts")


both("stream_static_join", _stream_static, "select event_id, user_id, c_mktsegment from events join customer on user_id = c_custkey where value > 200")


def _stream_stream(s, d):
    e = ST.with_event_time(ST.read_stream(s, d, "events").where("event_type = 'click'").select(c("user_id").alias("u"), c("event_id").alias("clicked"), "ts"))
    p = ST.with_event_time(ST.read_stream(s, d, "events").where("event_type = 'purchase'").select(c("user_id").alias("v"), c("event_id").alias("bought"), c("ts").alias("tp")), "tp")
    return ST.drain(e.join(p, F.expr("u = v and tp >= ts and tp <= ts + interval 1 hour")).select("u", "clicked", "bought"), "joined")


both("stream_stream_join", _stream_stream, "select a.user_id as u, a.event_id as clicked, b.event_id as bought from events a join events b on a.user_id = b.user_id and a.event_type = 'click' and b.event_type = 'purchase' and b.ts >= a.ts and b.ts <= a.ts + interval 1 hour")


def _stream_copula(s, d):
    """A copula model fitted on the table scores the same table as a stream."""
    x = X.event_values(s, d).staged()
    model = CopulaDetector().fit(x)
    e = ST.read_stream(s, d, "events").select("event_id", "value", F.hour("ts").alias("hour"), F.get_json_object("props", "$.k").cast("int").alias("k"))
    return rounded(ST.drain(ST.score_stream(model, e, ["event_id"], ["value", "hour", "k"]), "copula"), "score")


both("stream_copula", _stream_copula, f"with {cdf_sql(EVENTS, 'event_id', ['value', 'hour', 'k'])} select event_id, round({side_sums(['value', 'hour', 'k'])}, 6) + 0.0 as score from t")


def _stream_zscore(s, d):
    e = ST.with_event_time(ST.read_stream(s, d, "events"))
    return rounded(ST.drain(ST.window_zscores(e, "1 day", "event_type"), "zscore").select(F.date_format("start", "yyyy-MM-dd").alias("day"), "event_type", "event_id", "z"), "z", digits=5)


both("stream_zscore", _stream_zscore, f"select strftime(w, '%Y-%m-%d') as day, event_type, event_id, round((value - avg(value) over g) / nullif(stddev_pop(value) over g, 0), 5) + 0.0 as z from (select *, time_bucket(interval 1 day, ts, timestamp '1970-01-01') as w from events) where w + interval 1 day <= {_closed} window g as (partition by w, event_type)")
