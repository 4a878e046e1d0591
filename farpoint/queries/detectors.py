"""Queries of detectors, ensembles, thresholds and measures."""

from __future__ import annotations

import random
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from farpoint import features as X
from farpoint import metrics as M
from farpoint.composite import neighbours as N
from farpoint.detectors import statistical as S
from farpoint.detectors.proximity import AngleDetector, KnnDetector, LociDetector, LofDetector
from farpoint.model import FeatureFrame
from farpoint.queries.base import CONVERSATION_FEATURES, CONVERSATIONS, CUSTOMER_FEATURES, CUSTOMERS, CUSTOMERS_SCALED, DOCUMENT_FEATURES, DOCUMENTS, EVENTS, LINE_KEYS, LINES, ORDERS, PAGE_FEATURES, PAGES, USER_FEATURES, USERS, VECTORS, cdf_sql, edges_sql, knn_sql, register, rounded, side_sums
from farpoint.queries.operators import LINE_FEATURES, customers_scaled
from farpoint.quantize.bounds import distance_bound, gamma
from farpoint.session import stage, table

_lines = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice"]


def scored(name, f, sql, digits=6):
    register(name, lambda s, d: rounded(f(s, d), "score", digits=digits), sql)


# k-th neighbour distance
for method, agg in (("largest", "max(dist)"), ("mean", "avg(dist)"), ("median", "quantile_cont(dist, 0.5)")):
    scored(f"knn_score_{method}", lambda s, d, m=method: KnnDetector(5, m, blocks=3).fit_score(X.vectors(s, d)), f"with {knn_sql(VECTORS, 5)} select i as id, round({agg}, 6) as score from n group by i")
scored("knn_score_quantized16", lambda s, d: KnnDetector(5, precision=16, blocks=3).fit_score(X.vectors(s, d)), f"with {knn_sql(VECTORS, 5)} select i as id, round(max(dist), 6) as score from n group by i")
scored("knn_score_customers", lambda s, d: KnnDetector(5, "mean").fit_score(customers_scaled(s, d)), f"with {knn_sql(CUSTOMERS_SCALED, 5)} select i as id, round(avg(dist), 6) as score from n group by i")

# Local outlier factor
_lof = ", kd as materialized (select i, max(dist) as kd from n group by i), d as materialized (select n.i, 1 / (avg(greatest(kd, dist)) + 1e-10) as lrd from n join kd on kd.i = n.j group by n.i) select n.i as id, round(avg(q.lrd) / any_value(p.lrd), 5) as score from n join d p on p.i = n.i join d q on q.i = n.j group by n.i"
scored("lof_exact_k", lambda s, d: LofDetector(10).fit_score(customers_scaled(s, d)), f"with {knn_sql(CUSTOMERS_SCALED, 10)}{_lof}", 5)
scored("lof_vectors", lambda s, d: LofDetector(10, blocks=3).fit_score(X.vectors(s, d)), f"with {knn_sql(VECTORS, 10)}{_lof}", 5)
scored("lof_quantized16", lambda s, d: LofDetector(10, precision=16, blocks=3).fit_score(X.vectors(s, d)), f"with {knn_sql(VECTORS, 10)}{_lof}", 5)
scored("lof_ties", lambda s, d: LofDetector(10, ties="all").fit_score(customers_scaled(s, d)), f"with {edges_sql(CUSTOMERS_SCALED)}, r as (select *, rank() over (partition by i order by dist) as rank from e), n as materialized (select * from r where rank <= 10){_lof}", 5)
scored("lof_range", lambda s, d: LofDetector(10, phi=1.3, blocks=3).fit_score(X.vectors(s, d)), f"with {edges_sql(VECTORS)}, n as materialized (select * from (select *, row_number() over (partition by i order by dist, j) as rank from e where dist <= 1.3) where rank <= 10), kd as materialized (select i, max(dist) as kd from n group by i), d as materialized (select n.i, 1 / (avg(greatest(kd, dist)) + 1e-10) as lrd from n join kd on kd.i = n.j group by n.i), l as (select n.i, avg(q.lrd) / any_value(p.lrd) as score from n join d p on p.i = n.i join d q on q.i = n.j group by n.i) select x.id, round(coalesce(score, cast('inf' as double)), 5) as score from x left join l on l.i = x.id", 5)

# Angles
_pairs = f"{knn_sql(VECTORS, 5)}, w as materialized (select n.i, n.j, list_transform(list_zip(q.v, p.v), lambda z: z[1] - z[2]) as w from n join x p on p.id = n.i join x q on q.id = n.j), c as materialized (select a.i, list_sum(list_transform(list_zip(a.w, b.w), lambda z: z[1] * z[2])) as dot, list_sum(list_transform(a.w, lambda q: q * q)) as na, list_sum(list_transform(b.w, lambda q: q * q)) as nb from w a join w b on a.i = b.i and a.j < b.j)"
scored("abod_mean_cosine", lambda s, d: AngleDetector(5, blocks=3).fit_score(X.vectors(s, d)), f"with {_pairs} select i as id, round(avg(dot / (sqrt(na) * sqrt(nb))), 6) + 0.0 as score from c group by i")
scored("abod_fast_variance", lambda s, d: AngleDetector(5, "fast_variance", 3).fit_score(X.vectors(s, d)), f"with {_pairs}, f as (select i, dot / (na * nb) as f, 1 / (sqrt(na) * sqrt(nb)) as w from c) select i as id, round(-(sum(w * f * f) / sum(w) - pow(sum(w * f) / sum(w), 2)), 6) + 0.0 as score from f group by i")
scored("abod_raw_cosine", lambda s, d: AngleDetector(5, "raw", 3).fit_score(X.vectors(s, d)), f"with {knn_sql(VECTORS, 5)} select n.i as id, round(avg(1 - list_sum(list_transform(list_zip(p.v, q.v), lambda z: z[1] * z[2])) / (sqrt(list_sum(list_transform(p.v, lambda z: z * z))) * sqrt(list_sum(list_transform(q.v, lambda z: z * z))))), 6) as score from n join x p on p.id = n.i join x q on q.id = n.j group by n.i")


def _users(s, d):
    from farpoint.operators.basic import scale

    return scale(X.user_activity(s, d).staged()).pack()


_unit = ", ".join(f"case when hi_{f} > lo_{f} then ({f} - lo_{f}) / (hi_{f} - lo_{f}) else {f} * 0.0 end" for f in USER_FEATURES)
_users_scaled = f"select user_id as id, [{_unit}] as v from ({USERS}), (select {', '.join(f'min({f}) as lo_{f}, max({f}) as hi_{f}' for f in USER_FEATURES)} from ({USERS}))"
_all_angles = f"x as materialized ({_users_scaled}), w as materialized (select p.id as i, q.id as j, list_transform(list_zip(q.v, p.v), lambda z: z[1] - z[2]) as w from x p join x q on p.id <> q.id), m as materialized (select *, list_sum(list_transform(w, lambda q: q * q)) as n from w), c as (select a.i, list_sum(list_transform(list_zip(a.w, b.w), lambda z: z[1] * z[2])) as dot, a.n as na, b.n as nb from m a join m b on a.i = b.i and a.j < b.j and a.n > 0 and b.n > 0)"
scored("abod_full_pairs", lambda s, d: AngleDetector(None).fit_score(_users(s, d)), f"with {_all_angles} select x.id, round(coalesce(avg(dot / (sqrt(na) * sqrt(nb))), 0.0), 6) + 0.0 as score from x left join c on c.i = x.id group by x.id")


# Correlation integral
_radii = (0.1, 0.2, 0.3)
_ratio = lambda k: f"case when s{k} > 1e-12 then (m{k} - o{k}) / s{k} else 0 end"
scored("loci", lambda s, d: LociDetector(_radii, n_min=1).fit_score(customers_scaled(s, d)), f"with {edges_sql(CUSTOMERS_SCALED)}, w as materialized (select * from e where dist <= 0.3 union all select id, id, 0.0 from x), c as materialized (select i, {', '.join(f'count(*) filter (where dist <= {0.5 * r!r}) as c{k}' for k, r in enumerate(_radii))} from w group by i), m as (select w.i, {', '.join(f'max(c{k}) filter (where w.i = w.j) as o{k}, avg(c{k}) filter (where dist <= {r!r}) as m{k}, stddev_pop(c{k}) filter (where dist <= {r!r}) as s{k}' for k, r in enumerate(_radii))} from w join c on c.i = w.j group by w.i) select i as id, round(greatest({', '.join(map(_ratio, range(3)))}), 5) + 0.0 as score from m", 5)


# Histogram scores
def hbos_sql(view, keys, features, bins, where="true", alpha=0.1):
    """CTEs up to scores(keys, score); heights from the rows of where."""
    n = lambda f: bins.format(f=f)
    lim = ", ".join(f"min({f}) as lo_{f}, max({f}) as hi_{f}, (max({f}) - min({f})) / {n(f)} as w_{f}" for f in features)
    binned = ", ".join(f"least(floor(({f} - lo_{f}) / ((hi_{f} - lo_{f}) / {n(f)})), {n(f)} - 1) as b_{f}" for f in features)
    heights = ", ".join(f"h_{f} as (select b_{f}, count(*) / cast(max(count(*)) over () as double) as h_{f} from b where fitted group by b_{f})" for f in features)
    joins = " ".join(f"left join h_{f} using (b_{f})" for f in features)
    total = " + ".join(f"case when hi_{f} > lo_{f} then -ln(coalesce(h_{f}, 0) + {alpha}) else 0.0 end" for f in features)  # a constant feature adds nothing
    return f"x as (select *, ({where}) as fitted from ({view})), r as (select {lim} from x where fitted), b as materialized (select x.*, r.*, {binned} from x, r), {heights}, scores as (select {keys}, {total} as score from b {joins})"


scored("hbos_width", lambda s, d: S.HistogramDetector(10).fit_score(X.line_measures(s, d)), f"with {hbos_sql(LINES, LINE_KEYS, LINE_FEATURES, '10')} select {LINE_KEYS}, round(score, 6) + 0.0 as score from scores")
scored("hbos_sqrt_bins", lambda s, d: S.HistogramDetector("sqrt").fit_score(X.order_prices(s, d)), f"with {hbos_sql(ORDERS, 'o_orderkey', ['price', 'days'], '(select ceil(sqrt(count(*))) from orders)')} select o_orderkey, round(score, 6) + 0.0 as score from scores")
_fd = f"(select ceil((max({{f}}) - min({{f}})) / (2 * (quantile_cont({{f}}, 0.75) - quantile_cont({{f}}, 0.25)) / pow(count(*), 1.0 / 3))) from ({ORDERS}))"
scored("hbos_fd_bins", lambda s, d: S.HistogramDetector("fd").fit_score(X.order_prices(s, d)), f"with {hbos_sql(ORDERS, 'o_orderkey', ['price', 'days'], _fd)} select o_orderkey, round(score, 6) + 0.0 as score from scores")
scored("hbos_events", lambda s, d: S.HistogramDetector(20).fit_score(X.event_values(s, d)), f"with {hbos_sql(EVENTS, 'event_id', ['value', 'hour', 'k'], '20')} select event_id, round(score, 6) + 0.0 as score from scores")
_qs = ", ".join(f"quantile_cont(price, {k / 10}) as q{k}" for k in range(11))
scored("hbos_frequency", lambda s, d: S.HistogramDetector(10, "frequency").fit_score(X.order_prices(s, d).select(["price"])), f"with q as (select {_qs} from ({ORDERS})), e as (" + " union all ".join(f"select {k} as k, q{k} as lo, q{k + 1} as hi from q" for k in range(10)) + f"), p as (select o_orderkey, k, hi - lo as w from ({ORDERS}) join e on price >= lo and (price < hi or k = 9 and price <= hi)), h as (select k, count(*) / any_value(w) as h from p group by k), t as (select max(h) as t from h) select o_orderkey, round(-ln(h / t + 0.1), 6) + 0.0 as score from p join h using (k), t")


def _unseen(s, d):
    x = X.line_measures(s, d)
    flag = table(s, d, "lineitem", *_lines, "l_returnflag").where("l_returnflag = 'N'").select(*_lines)
    seen = FeatureFrame(x.df.join(flag, _lines, "left_semi"), x.ids, x.features)
    return S.HistogramDetector(10).fit(seen).score(x)


def _unseen_sql():
    # Values within half a bin outside the fitted range count as the nearest bin, farther ones have height 0.
    lim = ", ".join(f"min({f}) as lo_{f}, max({f}) as hi_{f}" for f in LINE_FEATURES)
    binned = ", ".join(f"case when {f} < lo_{f} then case when {f} >= lo_{f} - 0.5 * (hi_{f} - lo_{f}) / 10 then 0 else -1 end when {f} > hi_{f} then case when {f} <= hi_{f} + 0.5 * (hi_{f} - lo_{f}) / 10 then 9 else -1 end else least(floor(({f} - lo_{f}) / ((hi_{f} - lo_{f}) / 10)), 9) end as b_{f}" for f in LINE_FEATURES)
    heights = ", ".join(f"h_{f} as (select b_{f}, count(*) / cast(max(count(*)) over () as double) as h_{f} from b where fitted group by b_{f})" for f in LINE_FEATURES)
    joins = " ".join(f"left join h_{f} using (b_{f})" for f in LINE_FEATURES)
    total = " + ".join(f"-ln(coalesce(h_{f}, 0) + 0.1)" for f in LINE_FEATURES)
    return f"with x as (select {LINE_KEYS}, l_quantity as quantity, l_extendedprice as price, l_discount as discount, l_tax as tax, l_returnflag = 'N' as fitted from lineitem), r as (select {lim} from x where fitted), b as materialized (select x.*, {binned} from x, r), {heights} select {LINE_KEYS}, round({total}, 6) + 0.0 as score from b {joins}"


scored("hbos_unseen_rows", _unseen, _unseen_sql())

# Principal components
_three = ["quantity", "price", "discount"]
_z = ", ".join(f"({f} - avg({f}) over ()) / stddev_samp({f}) over () as z{i}" for i, f in enumerate(_three))
scored("pca_all", lambda s, d: S.PcaDetector().fit_score(X.line_measures(s, d).select(_three)), f"with z as (select {LINE_KEYS}, {_z} from ({LINES})), c as (select corr(quantity, price) as a, corr(quantity, discount) as b, corr(price, discount) as c from ({LINES})), i as (select *, 1 + 2 * a * b * c - a * a - b * b - c * c as det from c) select {LINE_KEYS}, round(((1 - c * c) * z0 * z0 + (1 - b * b) * z1 * z1 + (1 - a * a) * z2 * z2 + 2 * (b * c - a) * z0 * z1 + 2 * (a * c - b) * z0 * z2 + 2 * (a * b - c) * z1 * z2) / det, 5) + 0.0 as score from z, i", 5)
_two = f"with z as (select o_orderkey, (price - avg(price) over ()) / stddev_samp(price) over () as u, (days - avg(days) over ()) / stddev_samp(days) over () as v from ({ORDERS})), c as (select corr(price, days) as r from ({ORDERS}))"
_major, _minor = "pow((u + sign(r) * v) / sqrt(2), 2)", "pow((u - sign(r) * v) / sqrt(2), 2)"
scored("pca_major", lambda s, d: S.PcaDetector("major", 1).fit_score(X.order_prices(s, d)), f"{_two} select o_orderkey, round({_major} / (1 + abs(r)), 5) + 0.0 as score from z, c", 5)
scored("pca_minor", lambda s, d: S.PcaDetector("minor", 1).fit_score(X.order_prices(s, d)), f"{_two} select o_orderkey, round({_minor} / (1 - abs(r)), 5) + 0.0 as score from z, c", 5)
scored("pca_reconstruction", lambda s, d: S.PcaDetector("major", 1, method="reconstruction").fit_score(X.order_prices(s, d)), f"{_two} select o_orderkey, round(u * u + v * v - {_major}, 5) + 0.0 as score from z, c", 5)
scored("pca_unweighted", lambda s, d: S.PcaDetector(weighted=False).fit_score(X.order_prices(s, d)), f"{_two} select o_orderkey, round(u * u + v * v, 5) + 0.0 as score from z, c", 5)
scored("pca_vectors", lambda s, d: S.PcaDetector().fit_score(X.vectors(s, d)), None)

# Copula and empirical-CDF scores
_line_tails = f"with {cdf_sql(LINES, LINE_KEYS, LINE_FEATURES)}"
_cust_tails = f"with {cdf_sql(CUSTOMERS, 'c_custkey', CUSTOMER_FEATURES)}"
_pair_sum = lambda fs: " + ".join(f"greatest(us_{f}, (ul_{f} + ur_{f}) / 2)" for f in fs)
_triple = lambda fs: " + ".join(f"greatest(ul_{f}, ur_{f}, us_{f})" for f in fs)
scored("copod_sum_max", lambda s, d: S.CopulaDetector().fit_score(X.line_measures(s, d)), f"{_line_tails} select {LINE_KEYS}, round({side_sums(LINE_FEATURES)}, 6) + 0.0 as score from t")
scored("copod_max_sum", lambda s, d: S.CopulaDetector("max_then_sum").fit_score(X.customer_behaviour(s, d)), f"{_cust_tails} select c_custkey, round({_pair_sum(CUSTOMER_FEATURES)}, 6) + 0.0 as score from t")
scored("ecod_sum_max", lambda s, d: S.ecdf_detector(X.customer_behaviour(s, d)), f"{_cust_tails} select c_custkey, round({side_sums(CUSTOMER_FEATURES)}, 6) + 0.0 as score from t")
scored("ecod_max_sum", lambda s, d: S.ecdf_detector(X.line_measures(s, d), "max_then_sum"), f"{_line_tails} select {LINE_KEYS}, round({_triple(LINE_FEATURES)}, 6) + 0.0 as score from t")

# Ensembles: the subsets are drawn with a fixed seed
_rng = random.Random(3)
_draws = []
for _ in range(4):
    _draws.append([LINE_FEATURES[i] for i in sorted(_rng.sample(range(4), 2))])
_bags = "with " + ", ".join(f"s{k} as (with {hbos_sql(LINES, LINE_KEYS, fs, '10')} select {LINE_KEYS}, (score - avg(score) over ()) / stddev_pop(score) over () as score from scores)" for k, fs in enumerate(_draws)) + ", u as (" + " union all ".join(f"select * from s{k}" for k in range(4)) + ")"
for how, agg in (("mean", "avg"), ("max", "max")):
    scored(f"bagging_{how}", lambda s, d, h=how: S.BaggingDetector(S.HistogramDetector(10), 4, h, 2).fit_score(X.line_measures(s, d)), f"{_bags} select {LINE_KEYS}, round({agg}(score), 5) + 0.0 as score from u group by all", 5)
_places = " union all ".join(f"select {LINE_KEYS}, row_number() over (order by round(score, 9) desc, {LINE_KEYS}) * 4 + {k} as place from s{k}" for k in range(4))
scored("bagging_breadth_first", lambda s, d: S.BaggingDetector(S.HistogramDetector(10), 4, "breadth_first", 2).fit_score(X.line_measures(s, d)), f"{_bags}, p as ({_places}) select {LINE_KEYS}, cast(-min(place) as double) as score from p group by all")


def _labelled(name, how, flag):
    hb = hbos_sql(LINES, LINE_KEYS, LINE_FEATURES, "10")
    register(name, lambda s, d: rounded(S.label(rounded(S.HistogramDetector(10).fit_score(X.line_measures(s, d)), "score"), ids=_lines, **how), "score"), f"with {hb}, rs as (select {LINE_KEYS}, round(score, 6) + 0.0 as score from scores) select {LINE_KEYS}, score, {flag} as is_outlier from rs")


_labelled("label_contamination", {"contamination": 0.05}, "score > (select quantile_cont(score, 0.95) from rs)")
_labelled("label_contamination_count", {"contamination": 0.01, "exact_count": True}, f"row_number() over (order by score desc, {LINE_KEYS}) <= ceil(0.01 * (select count(*) from rs))")
_labelled("label_iqr", {"rule": "iqr"}, "score > (select quantile_cont(score, 0.75) + 1.5 * (quantile_cont(score, 0.75) - quantile_cont(score, 0.25)) from rs)")
_labelled("label_threshold", {"threshold": 4.0}, "score > 4.0")

_hist = f"with {hbos_sql(CUSTOMERS, 'c_custkey', CUSTOMER_FEATURES, '10')} select c_custkey, round(score, 6) + 0.0 as score from scores"
_cop = f"{_cust_tails} select c_custkey, round({side_sums(CUSTOMER_FEATURES)}, 6) + 0.0 as score from t"


def _two_detectors(s, d):
    x = X.customer_behaviour(s, d).staged()
    return rounded(S.HistogramDetector(10).fit_score(x), "score"), rounded(S.CopulaDetector().fit_score(x), "score")


def _rank_mean(s, d):
    return S.combine([S.normalize(f, "rank") for f in _two_detectors(s, d)], ["c_custkey"])


_rank = lambda v: f"select c_custkey, (rank() over (order by score) - 1) / cast(count(*) over () as double) as score from ({v})"
scored("ensemble_rank_mean", _rank_mean, f"select c_custkey, round((a.score + b.score) / 2, 6) + 0.0 as score from ({_rank(_hist)}) a join ({_rank(_cop)}) b using (c_custkey)")
_norm = lambda e: f"select c_custkey, round({e}, 6) + 0.0 as score from ({_hist})"
scored("normalize_minmax", lambda s, d: S.normalize(_two_detectors(s, d)[0]), _norm("(score - min(score) over ()) / (max(score) over () - min(score) over ())"))
scored("normalize_zscore", lambda s, d: S.normalize(_two_detectors(s, d)[0], "zscore"), _norm("(score - avg(score) over ()) / stddev_pop(score) over ()"))
_t = f"(1 / (1 + {S.ERF_P} * abs(z)))"
_erf = f"sign(z) * (1 - ({' + '.join(f'({a}) * pow({_t}, {k + 1})' for k, a in enumerate(S.ERF_A))}) * exp(-z * z))"
scored("normalize_gauss", lambda s, d: S.normalize(_two_detectors(s, d)[0], "gauss"), f"select c_custkey, round(greatest(0.0, {_erf}), 6) + 0.0 as score from (select c_custkey, (score - avg(score) over ()) / stddev_pop(score) over () / sqrt(2) as z from ({_hist}))")
scored("ensemble_max", lambda s, d: S.combine([S.normalize(f) for f in _two_detectors(s, d)], ["c_custkey"], "max"), f"select c_custkey, round(greatest(a.s, b.s), 6) + 0.0 as score from (select c_custkey, (score - min(score) over ()) / (max(score) over () - min(score) over ()) as s from ({_hist})) a join (select c_custkey, (score - min(score) over ()) / (max(score) over () - min(score) over ()) as s from ({_cop})) b using (c_custkey)")


def _agree(s, d):
    a, b = (f.orderBy(F.desc("score"), "c_custkey").limit(100).select("c_custkey") for f in _two_detectors(s, d))
    n = lambda df, w: df.agg(F.count("*").alias("n")).select(F.lit(w).alias("what"), "n")
    return n(a.intersect(b), "both").union(n(a.exceptAll(b), "first only"))


register("detector_agreement", _agree, f"with a as (select c_custkey from ({_hist}) order by score desc, c_custkey limit 100), b as (select c_custkey from ({_cop}) order by score desc, c_custkey limit 100) select 'both' as what, count(*) as n from (select * from a intersect select * from b) union all select 'first only', count(*) from (select * from a except select * from b)")


# Measures: copula score of text statistics against the labels
def judged(s, d, scores=None):
    scores = scores if scores is not None else S.CopulaDetector().fit_score(X.document_stats(s, d).staged())
    truth = table(s, d, "labels", "doc_id", "quality")
    return stage(rounded(scores, "score").join(truth, "doc_id").select("doc_id", "score", (F.col("quality") == 0).alias("truth")), "judged")


_judged = f"with {cdf_sql(DOCUMENTS, 'doc_id', DOCUMENT_FEATURES)}, j as (select doc_id, round({side_sums(DOCUMENT_FEATURES)}, 6) + 0.0 as score, quality = 0 as truth from t join labels using (doc_id))"
register("measure_roc_auc", lambda s, d: rounded(M.roc_auc(judged(s, d)), "auc"), f"{_judged}, r as (select truth, rank() over (order by score) + (count(*) over (partition by score) - 1) / 2.0 as r from j) select round((sum(r) filter (where truth) - count(*) filter (where truth) * (count(*) filter (where truth) + 1) / 2.0) / (count(*) filter (where truth) * count(*) filter (where not truth)), 6) as auc from r")
register("measure_precision_at_n", lambda s, d: rounded(M.precision_at(judged(s, d), 50, ["doc_id"]), "precision"), f"{_judged} select round(avg(cast(truth as int)), 6) as precision from (select * from j order by score desc, doc_id limit 50)")
register("measure_average_precision", lambda s, d: rounded(M.average_precision(judged(s, d)), "ap"), f"{_judged}, g as (select score, sum(cast(truth as int)) as p, count(*) as n from j group by score), c as (select p, sum(p) over (order by score desc) as tp, sum(n) over (order by score desc) as al from g) select round(sum(p * tp / cast(al as double)) / sum(p), 6) as ap from c")


def _agreement(s, d):
    x = X.vectors(s, d)
    return M.agreement(N.nwr(x, 1.25, precision=16), N.nwr(x, 1.25))


register("measure_agreement_exact", _agreement, "select cast(0 as bigint) as missing, cast(0 as bigint) as extra")


def _bounds(s, d):
    from farpoint.operators.basic import x_max

    top = x_max(X.vectors(s, d))
    return rounded(s.createDataFrame([(b, k, distance_bound(64, top, b, k, "sequential")) for b in (16, 32) for k in ("paper", "sound")], "bits int, kind string, bound double"), "bound", digits=9)


_b = lambda bits, eps, tiny, kind, m: f"select {bits} as bits, '{kind}' as kind, round(4 * 64 * top * top * (pow(1 + {eps}, {m}) - 1{' + pow(1 + pow(2, -53), 67) - 1' if kind == 'sound' else ''}) + {f'(8 * 64 * top + 4 * 64 + 3) * {tiny}' if kind == 'sound' else '0'}, 9) as bound from m"
register("measure_bound_value", _bounds, f"with m as (select max(list_max(list_transform(v, lambda q: abs(q)))) as top from ({VECTORS})) " + " union all ".join([_b(16, "pow(2, -11)", "pow(2, -25)", "paper", 9), _b(16, "pow(2, -11)", "pow(2, -25)", "sound", 68), _b(32, "pow(2, -24)", "pow(2, -150)", "paper", 9), _b(32, "pow(2, -24)", "pow(2, -150)", "sound", 68)]))


def _recalc(s, d):
    x = X.vectors(s, d)
    n = x.df.count()
    one = lambda k: M.recalc_share(N.nwr(x, 1.25, precision=16, bound=k, tally=True), n * (n - 1)).select(F.lit(k).alias("bound"), "fraction")
    out = one("paper")
    for k in ("sound", "rowwise", "residual"):
        out = out.union(one(k))
    return out


register("measure_recalc_fraction", _recalc)


def _flips(s, d):
    """Range search and top-k in 16 bit without the check: how many results differ from the exact ones."""
    x = X.vectors(s, d)
    one = lambda name, a, b: M.agreement(a, b).select(F.lit(name).alias("what"), "missing", "extra")
    ranges = N.nwr_flips(x, 1.25).select(F.lit("nwr").alias("what"), "missing", "extra")
    return ranges.union(one("topk", N.topk_quantized(x, 5, 16, verify=False), N.topk_quantized(x, 5, 64)))


register("baseline_unverified_flips", _flips)


def _auc_rows(s, d, forms):
    """ROC-AUC of the mean distance to 10 neighbours, in several forms, on text statistics against the quality labels and on generated points with planted outliers."""
    from farpoint.operators.basic import scale

    docs = scale(X.document_stats(s, d).staged()).pack().staged()
    points = X.synthetic(s, 1500, 6, 0.03).pack()
    bad = table(s, d, "labels", F.col("doc_id").alias("id"), (F.col("quality") == 0).alias("truth"))
    out = []
    for data, x, truth in (("documents", docs, bad), ("generated", points, points.df.select("id", X.planted(0.03).alias("truth")))):
        for name, detector in forms:
            found = stage(rounded(detector.fit_score(x), "score", digits=9).join(truth, "id"), "scores")  # the measure reads them more than once
            out.append(M.roc_auc(found).select(F.lit(data).alias("data"), F.lit(name).alias("form"), "auc"))
    return rounded(reduce(DataFrame.unionByName, out), "auc")


_CHECKED = [("64", KnnDetector(10, "mean")), ("16 checked", KnnDetector(10, "mean", precision=16))]
_noise = lambda k: f"(((id * ({1103515 + 2 * k}) + ({7919 + k * 104729})) * 69069 + {k * 15485863}) % 1000003 / 1000003.0::double)"
_out = "((id * 7717 + 1) % 10007 < 300)"
_points = "select id, [" + ", ".join(f"case when {_out} then {_noise(k)} * 8 - 4 else (((id % 4) * {k + 3}) % 5 - 2) * 0.5::double + ({_noise(k)} + {_noise(k + 6)} - 1) * 0.5::double end" for k in range(6)) + f"] as v, {_out} as truth from (select unnest(range(1500)) as id)"
_doc_range = ", ".join(f"min({f}) as lo_{f}, max({f}) as hi_{f}" for f in DOCUMENT_FEATURES)
_doc_points = f"select doc_id as id, [{', '.join(f'case when hi_{f} > lo_{f} then ({f} - lo_{f}) / (hi_{f} - lo_{f}) else {f} * 0.0 end' for f in DOCUMENT_FEATURES)}] as v from ({DOCUMENTS}), (select {_doc_range} from ({DOCUMENTS}))"


def _auc_sql(data, points, truth):
    return f"select '{data}' as data, auc from (with {knn_sql(points, 10)}, j as (select i, round(avg(dist), 9) as score from n group by i), t as ({truth}), r as (select truth, rank() over (order by score) + (count(*) over (partition by score) - 1) / 2.0 as r from j join t on t.id = j.i) select round((sum(r) filter (where truth) - count(*) filter (where truth) * (count(*) filter (where truth) + 1) / 2.0) / (count(*) filter (where truth) * count(*) filter (where not truth)), 6) as auc from r)"


_forms_sql = ", ".join(f"('{name}')" for name, _ in _CHECKED)
register("workload_auc_change", lambda s, d: _auc_rows(s, d, _CHECKED), f"select data, form, auc from ({_auc_sql('documents', _doc_points, 'select doc_id as id, quality = 0 as truth from labels')} union all {_auc_sql('generated', f'select id, v from ({_points})', f'select id, truth from ({_points})')}), (values {_forms_sql}) f(form)")
register("workload_auc_unchecked", lambda s, d: _auc_rows(s, d, [("16 unchecked", KnnDetector(10, "mean", precision=16, verify=False))]))

# Detectors on the remaining feature sets of the given tables
scored("hbos_line_subset", lambda s, d: S.HistogramDetector(10).fit_score(X.line_subset(s, d)), f"with {hbos_sql(f'select * from ({LINES}) where l_orderkey < 500', LINE_KEYS, LINE_FEATURES, '10')} select {LINE_KEYS}, round(score, 6) + 0.0 as score from scores")
scored("copod_users", lambda s, d: S.CopulaDetector().fit_score(X.user_activity(s, d).staged()), f"with {cdf_sql(USERS, 'user_id', USER_FEATURES)} select user_id, round({side_sums(USER_FEATURES)}, 6) + 0.0 as score from t")
scored("hbos_pages", lambda s, d: S.HistogramDetector(10).fit_score(X.page_stats(s, d).staged()), f"with {hbos_sql(PAGES, 'page_id', PAGE_FEATURES, '10')} select page_id, round(score, 6) + 0.0 as score from scores")
scored("hbos_conversations", lambda s, d: S.HistogramDetector(10).fit_score(X.conversation_stats(s, d).staged()), f"with {hbos_sql(CONVERSATIONS, 'conv_id', CONVERSATION_FEATURES, '10')} select conv_id, round(score, 6) + 0.0 as score from scores")
