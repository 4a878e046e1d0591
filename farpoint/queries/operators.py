"""Queries of leaf and composite operators."""

from __future__ import annotations

import random

from pyspark.sql import functions as F

from farpoint import features as X
from farpoint.composite import neighbours as N
from farpoint.detectors.proximity import neighbour_angles, reach_density
from farpoint.detectors.statistical import tail_scores
from farpoint.operators import basic as O
from farpoint.operators.ecdf import ecdf, ecdf_window
from farpoint.queries.base import CUSTOMERS_SCALED, EVENTS, LINE_KEYS, LINES, ORDERS, PARTS, VECTORS, cdf_sql, dist_sql, edges_sql, knn_sql, r6, register, rounded
from farpoint.session import table

LINE_FEATURES = ["quantity", "price", "discount", "tax"]


def customers_scaled(spark, sf):
    return O.scale(X.customer_behaviour(spark, sf).staged()).pack()


# Pairwise distances
for name, metric, blocks in (("cdist_sqeuclid", "sqeuclidean", 3), ("cdist_manhattan", "manhattan", None), ("cdist_cosine", "cosine", None)):
    register(name, lambda s, d, m=metric, b=blocks: rounded(N.pairwise_distance(X.vectors(s, d), m, blocks=b), "dist"), f"with x as ({VECTORS}) select a.id as i, b.id as j, round({dist_sql(metric)}, 6) + 0.0 as dist from x a join x b on a.id <> b.id")

# Top-k
_topk = "with x as (%s), u as (select id, unnest(v) as value, generate_subscripts(v, 1) - 1 as idx from x) select id, cast(rank as int) as rank, cast(idx as int) as index, value from (select *, row_number() over (partition by id order by value %s, idx) as rank from u) where rank <= 5" % (VECTORS, "%s")
register("topk_rows_largest", lambda s, d: O.topk_rows(X.vectors(s, d), 5), _topk % "desc")
register("topk_rows_smallest", lambda s, d: O.topk_rows(X.vectors(s, d), 5, False), _topk % "asc")
for bits in (16, 32):
    register(f"topk_quantized{bits}", lambda s, d, b=bits: N.topk_quantized(X.vectors(s, d), 5, b), _topk % "desc")
register("topk_quantized16_smallest", lambda s, d: N.topk_quantized(X.vectors(s, d), 5, 16, False), _topk % "asc")
register("topk_global", lambda s, d: O.topk_global(table(s, d, "orders", "o_orderkey", "o_totalprice"), "o_totalprice", 20, ["o_orderkey"]), "select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 20")
register("topk_groups", lambda s, d: O.topk_groups(table(s, d, "customer", "c_custkey", "c_mktsegment", "c_acctbal"), ["c_mktsegment"], "c_acctbal", 3, ["c_custkey"]), "select * from (select c_custkey, c_mktsegment, c_acctbal, cast(row_number() over (partition by c_mktsegment order by c_acctbal desc, c_custkey) as int) as rank from customer) where rank <= 3")

# Intersections
register("intersect_sets", lambda s, d: O.intersect(table(s, d, "orders", F.col("o_custkey").alias("k")), table(s, d, "events", F.col("user_id").alias("k"))), "select o_custkey as k from orders intersect select user_id from events")
_flag = lambda s, d, f: table(s, d, "lineitem", "l_partkey", "l_returnflag").where(F.col("l_returnflag") == f).select("l_partkey")
register("intersect_all_parts", lambda s, d: O.intersect(_flag(s, d, "R"), _flag(s, d, "A"), False), "select l_partkey from lineitem where l_returnflag = 'R' intersect all select l_partkey from lineitem where l_returnflag = 'A'")


def _shared(s, d):
    lists = N.knn(X.vectors(s, d), 10).groupBy("i").agg(F.array_sort(F.collect_list("j")).alias("a"))
    nxt = N.knn(X.vectors(s, d), 10).select("i", F.col("j").alias("m"))
    pairs = nxt.join(lists.select(F.col("i").alias("m"), F.col("a").alias("b")), "m").join(lists, "i")
    return pairs.select("i", F.col("m").alias("j"), F.size(O.intersect_lists(F.col("a"), F.col("b"))).alias("shared"), F.array_join(O.intersect_lists(F.col("a"), F.col("b")), ",").alias("both"))


register("intersect_lists", _shared, f"with {knn_sql(VECTORS, 10)}, l as (select i, list(j) as a from n group by i) select n.i, n.j, cast(len(list_intersect(p.a, q.a)) as int) as shared, coalesce(array_to_string(list_sort(list_intersect(p.a, q.a)), ','), '') as both from n join l p on p.i = n.i join l q on q.i = n.j")

# Histograms
_bins = lambda view, f, n: f"select '{f}' as feature, cast(bin as int) as bin, round(lo + bin * w, 6) + 0.0 as lo, round(lo + (bin + 1) * w, 6) + 0.0 as hi, count(value) as count from (select min({f}) as lo, (max({f}) - min({f})) / {n} as w from ({view})) r cross join (select unnest(range(0, cast({n} as bigint))) as bin) b left join (select {f} as value, least(floor(({f} - (select min({f}) from ({view}))) / (select (max({f}) - min({f})) / {n} from ({view}))), {n} - 1) as vb from ({view})) v on v.vb = b.bin group by all"
register("histogram_width", lambda s, d: rounded(O.histogram(X.line_measures(s, d), 10), "lo", "hi"), " union all ".join(_bins(LINES, f, 10) for f in LINE_FEATURES))
register("histogram_quantized32", lambda s, d: rounded(O.histogram(X.line_measures(s, d), 10, precision=32), "lo", "hi"), " union all ".join(_bins(LINES, f, 10) for f in LINE_FEATURES))
register("histogram_sqrt_bins", lambda s, d: rounded(O.histogram(X.order_prices(s, d), "sqrt"), "lo", "hi"), " union all ".join(_bins(ORDERS, f, "(select ceil(sqrt(count(*))) from orders)") for f in ("price", "days")))
_fd = lambda f: f"(select ceil((max({f}) - min({f})) / (2 * (quantile_cont({f}, 0.75) - quantile_cont({f}, 0.25)) / pow(count(*), 1.0 / 3))) from ({ORDERS}))"
register("histogram_fd_bins", lambda s, d: rounded(O.histogram(X.order_prices(s, d), "fd"), "lo", "hi"), " union all ".join(_bins(ORDERS, f, _fd(f)) for f in ("price", "days")))
register("histogram_frequency", lambda s, d: rounded(O.histogram(X.order_prices(s, d).select(["price"]), 10, "frequency"), "lo", "hi"), "with q as (select " + ", ".join(f"quantile_cont(price, {k / 10}) as q{k}" for k in range(11)) + f" from ({ORDERS})), b as (" + " union all ".join(f"select {k} as k, q{k} as lo, q{k + 1} as hi from q" for k in range(10)) + f") select 'price' as feature, cast(k as int) as bin, round(lo, 6) + 0.0 as lo, round(hi, 6) + 0.0 as hi, count(price) as count from b left join ({ORDERS}) on price >= lo and (price < hi or k = 9 and price <= hi) group by all")

# Feature sampling: the draw is made with a fixed seed when the plan is built.
def _drawn(x):
    f = O.feature_sample(x, 1, 2, 3)[0]
    return f.df.select(*f.ids, *f.features)


_pick = sorted(random.Random(3).sample(range(4), 2))
register("feature_subset", lambda s, d: _drawn(X.line_measures(s, d)), f"select {LINE_KEYS}, {', '.join(LINE_FEATURES[i] for i in _pick)} from ({LINES})")

# Empirical CDF
_cdf = lambda f, side: f"count(*) over (order by {f} range between {'unbounded preceding and current row' if side == 'l' else 'current row and unbounded following'}) / cast(count(*) over () as double)"
register("ecdf_left", lambda s, d: rounded(ecdf(X.line_measures(s, d), "left"), "f_left"), " union all ".join(f"select {LINE_KEYS}, '{f}' as feature, round({_cdf(f, 'l')}, 6) + 0.0 as f_left from ({LINES})" for f in LINE_FEATURES))
register("ecdf_right", lambda s, d: rounded(ecdf(X.line_measures(s, d), "right"), "f_right"), " union all ".join(f"select {LINE_KEYS}, '{f}' as feature, round({_cdf(f, 'r')}, 6) + 0.0 as f_right from ({LINES})" for f in LINE_FEATURES))
_ties = " union all ".join(f"select event_id, '{f}' as feature, round({_cdf(f, 'l')}, 6) + 0.0 as f_left, round({_cdf(f, 'r')}, 6) + 0.0 as f_right from ({EVENTS})" for f in ("value", "hour", "k"))
register("ecdf_ties", lambda s, d: rounded(ecdf(X.event_values(s, d)), "f_left", "f_right"), _ties)
register("ecdf_window", lambda s, d: ecdf_window(X.event_values(s, d).select(["value"])).select("event_id", r6("l_value").alias("f_left"), r6("r_value").alias("f_right")), f"select event_id, round({_cdf('value', 'l')}, 6) + 0.0 as f_left, round({_cdf('value', 'r')}, 6) + 0.0 as f_right from ({EVENTS})")

# Moments, covariance, scaling
_mom = lambda f: f"select '{f}' as feature, count(*) as n, round(cast(sum(cast({f} as decimal(18,4))) as double) / count(*), 6) as mean, round(sqrt(avg(pow({f} - m, 2))), 6) as sd, min({f}) as min, max({f}) as max, round(avg(pow({f} - m, 3)) / pow(avg(pow({f} - m, 2)), 1.5), 6) as skew, round(avg(pow({f} - m, 4)) / pow(avg(pow({f} - m, 2)), 2) - 3, 6) as kurt from (select {f}, avg({f}) over () as m from ({LINES}))"
register("moments_all", lambda s, d: rounded(O.moments(X.line_measures(s, d), exact=True), "mean", "sd", "skew", "kurt"), " union all ".join(map(_mom, LINE_FEATURES)))


def _cov(s, d):
    x = X.line_measures(s, d)
    c = O.covariance(x)
    return rounded(s.createDataFrame([(a, b, float(c[i, j])) for i, a in enumerate(x.features) for j, b in enumerate(x.features)], "a string, b string, cov double"), "cov", digits=5)


register("covariance_matrix", _cov, " union all ".join(f"select '{a}' as a, '{b}' as b, round(covar_samp({a}, {b}), 5) + 0.0 as cov from ({LINES})" for a in LINE_FEATURES for b in LINE_FEATURES))


def _cov_wide(s, d):
    c = O.covariance(X.vectors(s, d))
    return rounded(s.createDataFrame([(i, j, float(c[i, j])) for i in range(64) for j in range(64)], "a int, b int, cov double"), "cov")


register("covariance_gram", _cov_wide, f"with x as ({VECTORS}), u as (select id, unnest(v) as z, generate_subscripts(v, 1) - 1 as k from x) select cast(p.k as int) as a, cast(q.k as int) as b, round(covar_samp(p.z, q.z), 6) + 0.0 as cov from u p join u q using (id) group by p.k, q.k")
_scaled = lambda kind: lambda s, d: rounded(O.scale(X.line_measures(s, d), kind).df, *LINE_FEATURES)
_per = lambda expr: f"select {LINE_KEYS}, {', '.join(f'round({expr.format(f=f)}, 6) + 0.0 as {f}' for f in LINE_FEATURES)} from ({LINES}), (select {', '.join(f'min({f}) as lo_{f}, max({f}) as hi_{f}, avg({f}) as m_{f}, stddev_pop({f}) as s_{f}, quantile_cont({f}, 0.25) as a_{f}, quantile_cont({f}, 0.5) as b_{f}, quantile_cont({f}, 0.75) as c_{f}' for f in LINE_FEATURES)} from ({LINES}))"
register("scale_minmax", _scaled("minmax"), _per("({f} - lo_{f}) / (hi_{f} - lo_{f})"))
register("scale_zscore", _scaled("zscore"), _per("({f} - m_{f}) / s_{f}"))
register("scale_robust", _scaled("robust"), _per("({f} - b_{f}) / (c_{f} - a_{f})"))
register("scale_pow2", _scaled("pow2"), _per("{f} * pow(2, -ceil(log2(greatest(hi_quantity, hi_price, hi_discount, hi_tax))))"))
register("row_norms", lambda s, d: rounded(O.row_norms(X.vectors(s, d)), "norm"), f"select id, round(sqrt(list_sum(list_transform(v, lambda q: q * q))), 6) as norm from ({VECTORS})")
register("x_max", lambda s, d: s.createDataFrame([(O.x_max(X.vectors(s, d)),)], "x_max double"), f"select max(list_max(list_transform(v, lambda q: abs(q)))) as x_max from ({VECTORS})")

# k nearest neighbours: one SQL for all forms
_knn = f"with {knn_sql(VECTORS, 10)} select i, j, cast(rank as int) as rank, round(dist, 6) as dist from n"
register("knn_direct", lambda s, d: rounded(N.knn(X.vectors(s, d), 10, mode="direct"), "dist"), _knn)
register("knn_concat", lambda s, d: rounded(N.knn(X.vectors(s, d), 10, mode="concat", blocks=3), "dist"), _knn)
register("knn_fused", lambda s, d: rounded(N.knn(X.vectors(s, d), 10, blocks=3), "dist"), _knn)
register("knn_symmetric", lambda s, d: rounded(N.knn_symmetric(X.vectors(s, d), 10, 4), "dist"), _knn)
for bits in (16, 32):
    register(f"knn_quantized{bits}", lambda s, d, b=bits: rounded(N.knn(X.vectors(s, d), 10, blocks=3, precision=b), "dist"), _knn)
register("knn_customers", lambda s, d: rounded(N.knn(customers_scaled(s, d), 5), "dist"), f"with {knn_sql(CUSTOMERS_SCALED, 5)} select i, j, cast(rank as int) as rank, round(dist, 6) as dist from n")


def _split(s, d):
    from farpoint.model import FeatureFrame

    rows = table(s, d, "embeddings", "vec_id", "embedding", "label")
    frame = lambda low: FeatureFrame.packed(rows.where(F.col("label") < 5 if low else F.col("label") >= 5), "vec_id", "embedding", 64, "trust")
    return rounded(N.knn(frame(True), 5, y=frame(False), blocks=3), "dist")


register("knn_reference_split", _split, f"with x as (select id, v, label from ({VECTORS}) join embeddings on vec_id = id), e as (select a.id as i, b.id as j, {dist_sql()} as dist from x a join x b on a.label < 5 and b.label >= 5) select i, j, cast(rank as int) as rank, round(dist, 6) as dist from (select *, row_number() over (partition by i order by dist, j) as rank from e) where rank <= 5")
register("knn_metric_manhattan", lambda s, d: rounded(N.knn(X.vectors(s, d), 5, blocks=3, metric="manhattan"), "dist"), f"with x as ({VECTORS}), e as (select a.id as i, b.id as j, {dist_sql('manhattan')} as dist from x a join x b on a.id <> b.id) select i, j, cast(rank as int) as rank, round(dist, 6) as dist from (select *, row_number() over (partition by i order by dist, j) as rank from e) where rank <= 5")

# Neighbours within range: one SQL for all precisions and bounds
_nwr = f"with {edges_sql(VECTORS)} select i, j from e where dist <= 1.25"
register("nwr_exact", lambda s, d: N.nwr(X.vectors(s, d), 1.25), _nwr)
register("nwr_q32_sound", lambda s, d: N.nwr(X.vectors(s, d), 1.25, precision=32, bound="sound"), _nwr)
for kind in ("paper", "sound", "rowwise", "residual"):
    register(f"nwr_q16_{kind}", lambda s, d, b=kind: N.nwr(X.vectors(s, d), 1.25, precision=16, bound=b, blocks=3), _nwr)
register("nwr_squared_threshold", lambda s, d: N.nwr(X.vectors(s, d), 1.5625, squared=True, precision=16), _nwr)
register("nwr_counts", lambda s, d: N.nwr_counts(X.vectors(s, d), [1.2, 1.25, 1.3], 3), f"with {edges_sql(VECTORS)} select i, cast(phi as double) as phi, count(*) filter (where dist <= phi) as n from e, (select unnest([1.2, 1.25, 1.3]) as phi) group by i, phi")
register("nwr_grid", lambda s, d: N.nwr_grid(X.part_dims(s, d), 1.5), f"with x as ({PARTS}) select a.p_partkey as i, b.p_partkey as j from x a join x b on a.p_partkey <> b.p_partkey and abs(a.size - b.size) <= 2 and sqrt((a.size - b.size) * (a.size - b.size) + (a.price - b.price) * (a.price - b.price)) <= 1.5")
register("nwr_customers_q16", lambda s, d: N.nwr(customers_scaled(s, d), 0.1, precision=16), f"with {edges_sql(CUSTOMERS_SCALED)} select i, j from e where dist <= 0.1")


# Cosines, tails, axes, density
def _angles(s, d):
    x = X.vectors(s, d)
    return neighbour_angles(x, N.knn(x, 5, blocks=3)).select("i", "a", "b", r6(F.col("dot") / (F.sqrt("na") * F.sqrt("nb"))).alias("cos"))


_diffs = f"{knn_sql(VECTORS, 5)}, w as materialized (select n.i, n.j, list_transform(list_zip(q.v, p.v), lambda z: z[1] - z[2]) as w from n join x p on p.id = n.i join x q on q.id = n.j), c as materialized (select a.i, a.j as a, b.j as b, list_sum(list_transform(list_zip(a.w, b.w), lambda z: z[1] * z[2])) as dot, list_sum(list_transform(a.w, lambda q: q * q)) as na, list_sum(list_transform(b.w, lambda q: q * q)) as nb from w a join w b on a.i = b.i and a.j < b.j)"
register("neighbour_angles", _angles, f"with {_diffs} select i, a, b, round(dot / (sqrt(na) * sqrt(nb)), 6) + 0.0 as cos from c")
_far = lambda s, d: N.knn(X.vectors(s, d), 3, blocks=3, metric="cosine")
register("cosine_pairs", lambda s, d: rounded(_far(s, d).drop("rank"), "dist"), f"with x as ({VECTORS}), e as (select a.id as i, b.id as j, {dist_sql('cosine')} as dist from x a join x b on a.id <> b.id) select i, j, round(dist, 6) as dist from (select *, row_number() over (partition by i order by dist, j) as rank from e) where rank <= 3")
register("tails_left_right_skew", lambda s, d: rounded(tail_scores(X.line_measures(s, d)), "u_left", "u_right", "u_skew"), f"with {cdf_sql(LINES, LINE_KEYS, LINE_FEATURES)} " + " union all ".join(f"select {LINE_KEYS}, '{f}' as feature, round(ul_{f}, 6) + 0.0 as u_left, round(ur_{f}, 6) + 0.0 as u_right, round(us_{f}, 6) + 0.0 as u_skew from t" for f in LINE_FEATURES))


def _axes(s, d):
    import numpy as np

    x = X.order_prices(s, d)
    c = O.covariance(x)
    sd = np.sqrt(np.diag(c))
    values, _ = O.eigh_sorted(c / np.outer(sd, sd))
    return rounded(s.createDataFrame([(i + 1, float(v)) for i, v in enumerate(values)], "component int, eigenvalue double"), "eigenvalue")


register("axes_eigenvalues", _axes, f"with r as (select abs(corr(price, days)) as r from ({ORDERS})) select 1 as component, round(1 + r, 6) as eigenvalue from r union all select 2, round(1 - r, 6) from r")
_lrd = f"{{knn}}, kd as materialized (select i, max(dist) as kd from n group by i), d as materialized (select n.i, 1 / (avg(greatest(kd, dist)) + 1e-10) as lrd from n join kd on kd.i = n.j group by n.i)"
register("reach_density", lambda s, d: rounded(reach_density(N.knn(customers_scaled(s, d), 10)), "lrd"), f"with {_lrd.format(knn=knn_sql(CUSTOMERS_SCALED, 10))} select i, round(lrd, 6) as lrd from d")
