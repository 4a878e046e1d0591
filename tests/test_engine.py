"""Operators, detectors, batching and quantization on small hand-made frames, against the single-process baseline."""

import ast
import inspect

import numpy as np
import pytest
from pyspark.sql import functions as F

from farpoint import features as X
from farpoint import metrics as M
from farpoint.baselines import local as B
from farpoint.composite import neighbours as N
from farpoint.detectors import proximity as P
from farpoint.detectors import statistical as S
from farpoint.model import FeatureFrame
from farpoint.operators import basic as O
from farpoint.operators.ecdf import ecdf
from farpoint.plans import blocks as K
from farpoint.plans import registry as R


def frame(spark, m):
    m = np.asarray(m, float)
    return FeatureFrame.wide(spark.createDataFrame([(i, *map(float, r)) for i, r in enumerate(m)], "id long, " + ", ".join(f"f{k} double" for k in range(m.shape[1]))), ["id"], [f"f{k}" for k in range(m.shape[1])])


def scores(df):
    return np.array([r["score"] for r in df.orderBy("id").collect()])


@pytest.fixture(scope="module")
def cloud():
    rng = np.random.default_rng(7)
    m = rng.standard_normal((83, 5))
    m[80] = 12  # planted far point
    m[81:83] = m[3]  # duplicates
    return m


@pytest.mark.parametrize("blocks", [1, 2, 3, 7])
def test_knn_forms_agree(spark, cloud, blocks):
    x = frame(spark, cloud).pack()
    key = lambda df: [tuple(r) for r in df.select("i", "rank", "j", "dist").orderBy("i", "rank").collect()]
    want = key(N.knn(x, 6, mode="direct"))
    at, dist = B.local_knn(cloud, 6)
    assert [w[2] for w in want] == at.ravel().tolist() and [w[3] for w in want] == dist.ravel().tolist()
    for got in (N.knn(x, 6, blocks=blocks), N.knn(x, 6, mode="concat", blocks=blocks), N.knn_symmetric(x, 6, blocks), N.knn(x, 6, blocks=blocks, precision=16), N.knn(x, 6, blocks=blocks, precision=32), B.broadcast_knn(x, 6)):
        assert key(got) == want
    assert len(key(N.knn(x, 82, blocks=blocks))) == 83 * 82


@pytest.mark.parametrize("bound", ["paper", "sound", "rowwise", "residual"])
@pytest.mark.parametrize("bits", [16, 32])
def test_range_search_on_an_existing_distance(spark, bound, bits):
    m = np.random.default_rng(3).uniform(-1, 1, (60, 8))
    x = frame(spark, m).pack()
    phi = float(N.canonical(m, m, np.array([4]), np.array([9]))[0])
    key = lambda df: sorted(map(tuple, df.collect()))
    want = key(N.nwr(x, phi))
    assert (4, 9) in want and key(N.nwr(x, phi, precision=bits, bound=bound, blocks=3)) == want
    assert key(N.nwr(x, phi, blocks=3, symmetric=False)) == want
    counts = {r["i"]: r["n"] for r in N.nwr_counts(x, [phi], 3).collect()}
    assert all(counts[i] == sum(1 for a, _ in want if a == i) for i in range(60))


@pytest.mark.parametrize("offset", [0.0, 1e3, 1e6, 1e8])
def test_all_forms_are_exact_far_from_the_origin(spark, offset):
    """Norms are huge against the distances there: every filter must allow for what they lose."""
    m = np.random.default_rng(17).random((160, 4)) + offset
    m[40:44] = m[7]
    x = frame(spark, m).pack()
    key = lambda df: sorted(tuple(r) for r in df.select("i", "rank", "j", "dist").collect())
    want = key(N.knn(x, 5, mode="direct"))
    at, dist = B.local_knn(m, 5)
    assert [w[2] for w in want] == at.ravel().tolist() and [w[3] for w in want] == dist.ravel().tolist()
    for got in (N.knn(x, 5), N.knn(x, 5, blocks=3), N.knn_symmetric(x, 5, 3), N.knn(x, 5, mode="concat", blocks=2), N.knn(x, 5, blocks=3, precision=32), N.knn(x, 5, blocks=2, precision=16), B.broadcast_knn(x, 5)):
        assert key(got) == want
    pairs = lambda df: sorted(map(tuple, df.collect()))
    phi = float(N.canonical(m, m, np.array([3]), np.array([90]))[0])
    near = [(i, j) for i in range(160) for j in range(160) if i != j and N.canonical(m, m, np.array([i]), np.array([j]))[0] <= phi]
    assert (3, 90) in near
    for bits in (64, 32, 16):
        assert pairs(N.nwr(x, phi, precision=bits, blocks=3)) == near
    counts = {r["i"]: r["n"] for r in N.nwr_counts(x, [phi], 3).collect()}
    assert all(counts[i] == sum(1 for a, _ in near if a == i) for i in range(160))


def test_slices_and_tiles_change_nothing(spark, monkeypatch):
    m = np.random.default_rng(23).random((300, 3))
    x = frame(spark, m).pack()
    at, _ = B.local_knn(m, 4)
    for module in (K, N):
        monkeypatch.setattr(module, "plan_slices", lambda b, tasks, symmetric=False: 2)
    monkeypatch.setattr(K, "CELL", 40 * 8 * 3)  # blocks travel in several parts
    order = lambda df: [r["j"] for r in df.orderBy("i", "rank").collect()]
    for got in (N.knn(x, 4, blocks=3), N.knn_symmetric(x, 4, 4), N.knn(x, 4, blocks=3, precision=16), N.knn(x, 4, y=x, blocks=2).where("i <> j").withColumn("rank", F.col("rank") - 1).where("rank <= 3")):
        got = order(got)
        assert got == at.ravel().tolist() or got == at[:, :3].ravel().tolist()
    want = sorted(map(tuple, N.nwr(x, 0.2, blocks=1).collect()))
    assert sorted(map(tuple, N.nwr(x, 0.2, blocks=4).collect())) == want == sorted(map(tuple, N.nwr(x, 0.2, blocks=3, precision=16).collect()))
    counts = {r["i"]: r["n"] for r in N.nwr_counts(x, [0.2], 3).collect()}
    assert counts == {i: sum(1 for a, _ in want if a == i) for i in range(300)}


@pytest.mark.parametrize("n", [2_000, 20_000, 60_000])
def test_planned_tasks_stay_within_their_memory(n):
    """Two blocks, stored and in compute format, and four tiles fit the budget; the direct form is refused where it does not fit."""
    for d in (6, 64, 500):
        for tasks in (8, 4000):
            b = K.plan_batches(n, d, tasks=tasks)
            rows = -(-n // b)
            assert 2 * rows * d * 16 + 4 * K.TILE**2 * 8 <= K.TASK_BUDGET and b * K.plan_slices(b, tasks) >= min(tasks, b * b, n // K.LEAST)
    if n * n * 8 > 4 << 30:
        with pytest.raises(K.MemoryBudgetExceeded):
            K.check_budget(n, 64)


def test_measured_kernel_memory_falls_with_the_format():
    used = {bits: M.kernel_bytes("range", 512, 64, bits) for bits in (64, 32)}
    assert used[32] < 0.62 * used[64]
    used = {bits: M.kernel_bytes("topk", 2048, 64, bits) for bits in (64, 32, 16)}
    assert used[16] < 0.3 * used[64] and used[32] < 0.6 * used[64]


def test_low_precision_runs_its_kernels_once(spark):
    x = X.vectors(spark, "/root/testdata/sf0.001")
    plan = N.nwr(x, 1.25, precision=16)._jdf.queryExecution().executedPlan().toString()
    assert "MapInArrow" not in plan  # pairs are written by one run and read apart


def test_pure_half_precision_and_overflow(spark):
    x = frame(spark, np.random.default_rng(1).uniform(-1, 1, (40, 3))).pack()
    key = lambda df: sorted(map(tuple, df.collect()))
    assert key(N.nwr(x, 0.7, precision=16, compute=16, bound="paper")) == key(N.nwr(x, 0.7))
    big = frame(spark, [[300.0], [-300.0], [1.0]]).pack()
    with pytest.raises(ValueError):
        N.nwr(big, 1.0, precision=16, compute=16, bound="paper", scale=None)
    with pytest.raises(ValueError):
        N.pairwise_distance(x, precision=16, verify=True)


def test_grid_equals_range_search(spark):
    m = np.random.default_rng(2).uniform(0, 5, (90, 2))
    x = frame(spark, m)
    assert sorted(map(tuple, N.nwr_grid(x, 0.5).collect())) == sorted(map(tuple, N.nwr(x, 0.5).collect()))


def test_topk_near_ties(spark):
    v = [[1.0, 1.0 + 2**-13, 0.5], [3.0, 3.0, 1.0], [2.0, 1.0, 0.0]]
    x = frame(spark, v).pack()
    key = lambda df: [(r["id"], r["rank"], r["index"]) for r in df.orderBy("id", "rank").collect()]
    assert key(N.topk_quantized(x, 2)) == key(O.topk_rows(x, 2)) == [(0, 1, 1), (0, 2, 0), (1, 1, 0), (1, 2, 1), (2, 1, 0), (2, 2, 1)]
    assert key(N.topk_quantized(x, 2, verify=False))[0] == (0, 1, 0)  # the check is what repairs it
    flags = {r["id"]: r["certain"] for r in N.topk_quantized(x, 2, with_flag=True).collect()}
    assert not flags[0] and not flags[1] and flags[2]


@pytest.mark.parametrize("name", ["knn", "lof", "abod", "hbos", "pca", "copod", "ecod"])
def test_detectors_equal_the_baseline_and_find_the_far_point(spark, cloud, name):
    x = frame(spark, cloud)
    got = {
        "knn": lambda: P.KnnDetector(10).fit_score(x.pack()),
        "lof": lambda: P.LofDetector(10).fit_score(x.pack()),
        "abod": lambda: P.AngleDetector(10).fit_score(x.pack()),
        "hbos": lambda: S.HistogramDetector(10).fit_score(x),
        "pca": lambda: S.PcaDetector().fit_score(x),
        "copod": lambda: S.CopulaDetector().fit_score(x),
        "ecod": lambda: S.ecdf_detector(x),
    }[name]()
    got = scores(got)
    assert np.allclose(got, B.local_score(name, cloud, 10), rtol=1e-9) and got.argmax() == 80


def test_five_points_on_a_line(spark):
    x = frame(spark, [[0.0], [1.0], [2.0], [3.0], [10.0]]).pack()
    assert scores(P.KnnDetector(2).fit_score(x)).tolist() == [2, 1, 1, 2, 8]
    assert scores(P.KnnDetector(2, "median").fit_score(x)).tolist() == [1.5, 1, 1, 1.5, 7.5]
    lof = scores(P.LofDetector(2).fit_score(x))
    assert lof.argmax() == 4 and lof[1] < 1.3


def test_duplicates_and_scaling(spark):
    m = np.array([[0.0, 0], [0, 0], [0, 0], [1, 1], [5, 5]])
    x = frame(spark, m).pack()
    assert np.isfinite(scores(P.LofDetector(2).fit_score(x))).all()
    assert scores(P.LofDetector(2, duplicate="inf").fit_score(x))[0] == 1.0
    a = np.random.default_rng(5).standard_normal((40, 3))
    one, two = (scores(P.LofDetector(5).fit_score(frame(spark, a * f).pack())) for f in (1, 8))
    assert np.allclose(one, two)
    one, two = (scores(P.AngleDetector(5).fit_score(frame(spark, a * f).pack())) for f in (1, 8))
    assert np.allclose(one, two)


def test_loci_and_full_angles(spark, cloud):
    x = frame(spark, cloud)
    assert scores(P.LociDetector((2.0, 4.0, 30.0)).fit_score(x.pack())).argmax() == 80
    assert scores(P.AngleDetector(None).fit_score(x.pack())).argmax() == 80


def test_histograms_and_constants(spark):
    x = frame(spark, [[float(i), 3.0] for i in range(10)])
    h = {(r["feature"], r["bin"]): r["count"] for r in O.histogram(x, 5).collect()}
    assert [h["f0", k] for k in range(5)] == [2] * 5 and h["f1", 0] == 10
    assert np.allclose(scores(S.HistogramDetector(5).fit_score(x)), -np.log(1.1))  # the constant feature adds nothing
    assert np.allclose(scores(S.CopulaDetector().fit_score(x))[0], -np.log(0.1))
    total = scores(S.PcaDetector().fit_score(x)).sum()
    assert total == pytest.approx(9)  # (n - 1) times the rank: the constant feature drops out
    f = O.histogram(frame(spark, [[v] for v in (1, 1, 1, 1, 2, 9)]), 3, "frequency")
    assert sum(r["count"] for r in f.collect()) == 6


def test_many_features_and_the_largest_value(spark):
    m = np.random.default_rng(11).random((300, 12)) * 0.1 + 0.7
    assert np.allclose(scores(S.HistogramDetector(10).fit_score(frame(spark, m))), B.local_score("hbos", m))
    assert sum(r["count"] for r in O.histogram(frame(spark, m), 7).collect()) == 300 * 12


def test_ecdf_ties(spark):
    got = {(r["id"]): (r["f_left"], r["f_right"]) for r in ecdf(frame(spark, [[1], [2], [2], [3]])).collect()}
    assert got == {0: (0.25, 1.0), 1: (0.75, 0.75), 2: (0.75, 0.75), 3: (1.0, 0.25)}


def test_pca_invariants(spark, cloud):
    x = frame(spark, cloud)
    z = (cloud - cloud.mean(0)) / cloud.std(0, ddof=1)
    maha = np.einsum("ij,jk,ik->i", z, np.linalg.inv(np.corrcoef(cloud.T)), z)
    assert np.allclose(scores(S.PcaDetector().fit_score(x)), maha)
    assert np.allclose(O.covariance(x), np.cov(cloud.T)) and np.allclose(O._gram(x, True), np.cov(cloud.T))
    wide = frame(spark, np.random.default_rng(4).standard_normal((50, 20)))
    assert scores(S.PcaDetector().fit_score(wide)).sum() == pytest.approx(49 * 20)


def test_planning():
    assert K.plan_batches(100, 5) is None and K.plan_batches(100_000, 64) >= 8
    b = K.block_rows(64, 8, 64 << 20)
    assert b * b * 8 + 2 * b * 64 * 8 <= 64 << 20 < (b + 2) ** 2 * 8 + 2 * (b + 2) * 64 * 8
    with pytest.raises(K.MemoryBudgetExceeded):
        K.check_budget(10**6, 64)
    assert K.feasible_rows(64, 4 << 30) ** 2 * 8 <= 4 << 30
    for n in (1, 2, 3, 4, 5, 8):
        met = {frozenset((o, p)) for p in range(n) for o in K.owners_of(p, n, True)}
        assert len(met) == n * (n + 1) // 2 and sum(len(K.owners_of(p, n, True)) for p in range(n)) == len(met)


def test_registry_strategies_and_user_operator(spark):
    x = frame(spark, [[1.0, 5.0], [3.0, 2.0], [2.0, 2.0]])
    with pytest.raises(ValueError):
        R.register_operator(R.OpSpec("both", True, True), None)
    R.register_operator(R.OpSpec("row_max", False, True), lambda m: m.max(1))
    assert [r["x"] for r in R.run_operator("row_max", x, batch=2).orderBy("id").collect()] == [[5.0], [3.0], [2.0]]
    R.register_operator(R.OpSpec("centred", True, False), lambda c: c - c.mean())
    assert [r["x"] for r in R.run_operator("centred", x).orderBy("id").collect()] == [[-1.0, 2.0], [1.0, -1.0], [0.0, -1.0]]

    def dots(i, a, j, b):
        return np.repeat(i, len(j)), np.tile(j, len(i)), (a @ b.T).ravel()

    R.register_operator(R.OpSpec("dots", True, True), None, dots)
    got = {(r["i"], r["j"]): r["value"] for r in R.run_operator("dots", x, blocks=2).collect()}
    assert len(got) == 9 and got[0, 1] == 13.0
    assert not R.OPERATORS["pairwise_distance"].quantizable and R.OPERATORS["topk"].quantizable and R.OPERATORS["knn"].quantizable


def test_fusion_rules(spark):
    tree = R.OpNode("topk_smallest", (R.OpNode("pairwise_distance", ("x",), {"blocks": 2}),), {"k": 3})
    assert R.fuse(tree) == R.OpNode("knn_fused", ("x",), {"blocks": 2, "k": 3})
    counted = R.OpNode("count", (R.OpNode("within", (R.OpNode("pairwise_distance", ("x",)),), {"phi": 1}),))
    assert R.fuse(counted).op == "range_count_fused"
    R.register_fusion(("mine", "knn_fused"), lambda a, b: R.OpNode("ours", b.inputs))
    assert R.fuse(R.OpNode("mine", (tree,))).op == "ours"
    R.RULES.pop(0)


def test_new_detector_is_short():
    body = ast.parse(inspect.getsource(S.ecdf_detector)).body[0]
    assert body.end_lineno - body.lineno < 10

    @R.detector("largest")
    def largest(x):
        return x.df.select(*x.ids, F.greatest(*x.features).alias("score"))

    assert R.DETECTORS["largest"] is largest


def test_nulls(spark):
    df = spark.createDataFrame([(1, 1.0), (2, None), (3, float("nan")), (4, 3.0)], "id long, v double")
    with pytest.raises(ValueError):
        FeatureFrame.wide(df, ["id"], ["v"])
    assert FeatureFrame.wide(df, ["id"], ["v"], "drop").df.count() == 2
    assert [r["v"] for r in FeatureFrame.wide(df, ["id"], ["v"], "impute_mean").df.orderBy("id").collect()] == [1.0, 2.0, 2.0, 3.0]
    ragged = spark.createDataFrame([(1, [1.0]), (2, [1.0, 2.0])], "id long, v array<double>")
    with pytest.raises(Exception, match="components"):
        FeatureFrame.packed(ragged, "id", "v", 1, "trust").df.collect()


def test_empty_frames(spark):
    x = frame(spark, np.zeros((0, 2)))
    assert N.knn(x.pack(), 2).count() == 0 and N.nwr(x.pack(), 1.0).count() == 0 and ecdf(x).count() == 0


def test_ensembles_labels_and_measures(spark, cloud):
    x = frame(spark, cloud)
    s = S.HistogramDetector(10).fit_score(x)
    for how in ("mean", "max", "breadth_first"):
        assert scores(S.BaggingDetector(S.HistogramDetector(10), 4, how).fit_score(x)).argmax() == 80
    assert S.label(s, contamination=0.1, exact_count=True).where("is_outlier").count() == 9
    assert S.label(s, rule="sd").where("is_outlier and id = 80").count() == 1
    with pytest.raises(ValueError):
        S.label(s, contamination=0.9)
    judged = spark.createDataFrame([(0.1, False), (0.4, False), (0.35, True), (0.8, True), (0.4, True)], "score double, truth boolean")
    assert M.roc_auc(judged).first()["auc"] == pytest.approx((1 + 2 + 1.5) / 6)
    assert M.roc_auc(judged.where("truth")).first()["auc"] is None
    assert M.average_precision(judged).first()["ap"] == pytest.approx((1 + 2 / 3 + 3 / 4) / 3)
    assert M.growth_exponent([1, 2, 4], [1, 4, 16]) == pytest.approx(2) and M.efficiency(8, 2, 4) == 1 and M.saving_pct(1, 4) == 75
    assert M.block_bytes(1000, 64, 4, 16)["block_bytes"] * 4 == M.block_bytes(1000, 64, 4, 64)["block_bytes"]


def test_unverified_precision_flips_results(spark):
    """On the given vectors, 16-bit range search without the check differs from the exact one; with it, it does not."""
    x = X.vectors(spark, "/root/testdata/sf0.001")
    exact = N.nwr(x, 1.25)
    assert sum(M.agreement(N.nwr(x, 1.25, precision=16, compute=16, verify=False), exact).first()) > 0
    assert sum(M.agreement(N.nwr(x, 1.25, precision=16), exact).first()) == 0


def test_plans_stay_distributed(spark):
    """No unpartitioned window in the ranked detectors; filters and columns reach the scan."""
    plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
    x = X.line_measures(spark, "/root/testdata/sf0.001")
    from farpoint.sources.io import scan

    p = plan(scan(spark, "/root/testdata/sf0.001", "lineitem", ["l_orderkey"], F.col("l_quantity") >= 45))
    assert "GreaterThanOrEqual(l_quantity" in p and "l_comment" not in p


def test_entry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() == 500
    assert set(e.oracle_sql()) <= set(e.queries())


def test_exact_quantiles_ranks_and_numbers(spark):
    from farpoint.operators.ecdf import quantiles, row_numbers, with_ranks

    rng = np.random.default_rng(41)
    m = np.c_[rng.standard_normal(700), rng.integers(0, 4, 700), np.where(rng.random(700) < 0.4, 0.5, rng.random(700)), np.ones(700)]
    x = frame(spark, m)
    got = quantiles(x, [0.0, 0.1, 0.25, 0.5, 0.95, 1.0])
    for k, f in enumerate(x.features):
        assert np.allclose(got[f], np.quantile(m[:, k], [0.0, 0.1, 0.25, 0.5, 0.95, 1.0]), rtol=1e-12)
    assert quantiles(frame(spark, np.zeros((0, 2))), [0.5]) == {"f0": [], "f1": []}
    s = spark.createDataFrame([(i, i % 3, float(v)) for i, v in enumerate(m[:, 2])], "id long, draw int, score double")
    place = {r["id"]: r["place"] for r in row_numbers(s, "draw", [F.desc("score"), F.col("id")], ranges=5).collect()}
    for d in range(3):
        order = sorted((i for i in range(700) if i % 3 == d), key=lambda i: (-m[i, 2], i))
        assert [place[i] for i in order] == list(range(1, len(order) + 1))
    import farpoint.operators.ecdf as E

    want = {r["id"]: tuple(r[f"l_{f}"] for f in x.features) for r in with_ranks(x).collect()}
    few, E.FEW = E.FEW, 10  # three features of many values, by one join of all their cells
    try:
        df = with_ranks(x)
        assert {r["id"]: tuple(r[f"l_{f}"] for f in x.features) for r in df.collect()} == want
        assert df._jdf.queryExecution().optimizedPlan().toString().count("Join") <= 7
    finally:
        E.FEW = few


def test_unfused_plans_equal_fused_ones_and_take_user_operators(spark, cloud):
    x = frame(spark, cloud)
    for outer, inner in (("square", "project"), ("lookup", "histogram")):
        tree = R.OpNode(outer, (R.OpNode(inner, (x,)),))
        assert np.allclose(scores(R.lower(tree)), scores(R.lower(tree, False)))
    tree = R.OpNode("log", (R.OpNode("ecdf", (x,)),))
    key = lambda df: sorted((r["id"], r["feature"], round(r["u_left"], 9), round(r["u_right"], 9), round(r["u_skew"], 9)) for r in df.collect())
    assert key(R.lower(tree)) == key(R.lower(tree, False))
    R.register_operator(R.OpSpec("doubled", False, True), lambda m: m * 2)
    got = R.lower(R.OpNode("doubled", (x.pack(),))).orderBy("id").collect()
    assert np.allclose([r["x"] for r in got], cloud * 2)


def test_late_rows_are_left_out_and_counted(spark, tmp_path):
    """Files out of order: rows behind the watermark are dropped and show in the progress of the query."""
    import time

    from farpoint.streaming import score as ST

    schema = "event_id long, event_type string, value double, ts timestamp"
    row = lambda i, day, hour: (i, "a", float(i), f"2024-01-{day:02} {hour:02}:00:00")
    for n, rows in enumerate(([row(1, 1, 1), row(2, 1, 5)], [row(3, 5, 1)], [row(7, 5, 3)], [row(4, 1, 7), row(5, 5, 2)], [row(6, 9, 1)])):
        spark.createDataFrame(rows, "event_id long, event_type string, value double, ts string").selectExpr("event_id", "event_type", "value", "cast(ts as timestamp) as ts").coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
        time.sleep(1.1)  # files are taken in the order of their times
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in")
    z = ST.window_zscores(ST.with_event_time(stream), "1 day", "event_type")
    query = z.writeStream.option("checkpointLocation", f"{tmp_path}/mark").trigger(availableNow=True).outputMode("append").format("parquet").option("path", f"{tmp_path}/out").start()
    query.awaitTermination()
    got = {r["event_id"]: r["z"] for r in spark.read.parquet(f"{tmp_path}/out").collect()}
    assert set(got) == {1, 2, 3, 5, 7} and got[1] == -1.0 and got[2] == 1.0 and ST.late_rows(query) == 1


def test_error_function():
    import math

    from farpoint.detectors import statistical as D

    for z in np.linspace(-4, 4, 81):
        t = 1 / (1 + D.ERF_P * abs(z))
        series = sum(a * t ** (k + 1) for k, a in enumerate(D.ERF_A))
        assert abs(math.copysign(1 - series * math.exp(-z * z), z) - math.erf(z)) < 1.5e-7


def test_copula_model_scores_its_own_rows_alike(spark, cloud):
    x = frame(spark, cloud)
    for how in ("sum_then_max", "max_then_sum"):
        d = S.CopulaDetector(how)
        assert np.allclose(scores(d.fit(x).score(x)), scores(d.fit_score(x)))


def test_baselines_hold_no_distance_matrix(spark, cloud):
    """the one-process form holds strips of the distance matrix, and the broadcast LOF works from edges."""
    import tracemalloc

    m = np.random.default_rng(4).random((3000, 4))
    tracemalloc.start()
    try:
        at, dist = B.local_knn(m, 3)
        assert tracemalloc.get_traced_memory()[1] < 3000 * 3000 * 8 * 2
    finally:
        tracemalloc.stop()
    full = np.sqrt(((m[:50, None] - m) ** 2).sum(2))
    assert np.allclose(dist[:50], np.sort(full, axis=1)[:, 1:4])
    x = frame(spark, cloud)
    assert np.allclose(scores(B.broadcast_lof(x, 6)), B.local_score("lof", cloud, 6))
    assert "LocalTableScan" not in B.broadcast_lof(x, 6)._jdf.queryExecution().executedPlan().toString()


def test_range_limited_lof_writes_edges_only(spark, cloud):
    """neighbours within phi come from the k nearest, not from all pairs within phi."""
    x = frame(spark, cloud).pack()
    got = {(r["i"], r["j"]) for r in P.LofDetector(4, phi=1.0).edges(x).collect()}
    near = N._ranked(N.exact_pairs(x, N.nwr(x, 1.0)), 4)
    assert got == {(r["i"], r["j"]) for r in near.collect()}
    assert P.LofDetector(4, phi=1.0).edges(x)._jdf.queryExecution().analyzed().toString().count("Join") == 0


@pytest.mark.parametrize("metric", ["cosine", "manhattan", "sqeuclidean", "euclidean"])
def test_pairwise_distances_are_planned_in_blocks(spark, metric):
    """All pairs come from kernels by tiles, not from a cross join; pieces change no bit of a distance."""
    m = np.random.default_rng(8).standard_normal((300, 7))
    x = frame(spark, m).pack()
    out = N.pairwise_distance(x, metric)
    assert "NestedLoop" not in out._jdf.queryExecution().executedPlan().toString() and "Cartesian" not in out._jdf.queryExecution().executedPlan().toString()
    t = out.toArrow().to_pydict()
    i, j = np.array(t["i"]), np.array(t["j"])
    assert len(i) == 300 * 299 == len(set(zip(t["i"], t["j"]))) and (np.array(t["dist"]) == N.canonical(m, m, i, j, metric)).all()
    frames = m.copy()
    frames[5] = 0.0
    assert (N._all_pairs(frames, frames, metric).ravel() == N.canonical(frames, frames, np.repeat(np.arange(300), 300), np.tile(np.arange(300), 300), metric)).all()


def test_unfused_neighbours_rank_before_they_leave_a_task(spark):
    """of the concatenated, direct and unfused forms no more than k rows a point and subtask leave the kernels."""
    m = np.random.default_rng(9).random((400, 3))
    x = frame(spark, m).pack()
    tree = R.OpNode("topk_smallest", (R.OpNode("pairwise_distance", (x,), {"blocks": 3}),), {"k": 4})
    want = sorted(map(tuple, N.knn(x, 4).select("i", "j", "rank", "dist").collect()))
    for blocks, got in ((3, N.knn(x, 4, mode="concat", blocks=3)), (1, N.knn(x, 4, mode="direct")), (3, R.lower(tree, False))):
        assert sorted(map(tuple, got.select("i", "j", "rank", "dist").collect())) == want
        kernel = got._jdf.queryExecution().analyzed()
        while kernel.nodeName() != "MapInArrow":
            kernel = kernel.children().apply(0)
        rows = spark.sparkContext._jvm.org.apache.spark.sql.classic.Dataset.ofRows(spark._jsparkSession, kernel).count()
        assert rows <= 400 * 4 * blocks


@pytest.mark.parametrize("bound", ["paper", "sound"])
def test_one_bound_for_all_settles_its_pairs_in_the_task(spark, bound):
    """pairs that one error for all leaves open are not written and joined with rows again."""
    x = X.vectors(spark, "/root/testdata/sf0.001")
    got = N.nwr(x, 1.25, precision=16, bound=bound, blocks=3)
    assert "Join" not in got._jdf.queryExecution().analyzed().toString()
    assert sum(M.agreement(got, N.nwr(x, 1.25)).first()) == 0
    half = np.random.default_rng(6).uniform(-1, 1, (40, 64)).astype(np.float16)
    exact = ((half[:, None].astype(float) - half.astype(float)) ** 2).sum(2)
    assert np.abs(N._gram(half, half) - exact).max() <= 4 * 64 * N.gamma(68, 2.0**-11)


def test_shares_and_flips_are_counted_in_kernels(spark):
    """counts of kernels equal those of written pairs."""
    x = X.vectors(spark, "/root/testdata/sf0.001")
    n = x.count()
    for bound in ("paper", "sound", "rowwise", "residual"):
        flagged = N.nwr(x, 1.25, precision=16, bound=bound, with_flag=True)
        assert M.recalc_share(N.nwr(x, 1.25, precision=16, bound=bound, tally=True), n * n).first() == M.recalc_fraction(flagged, n * n).first()
    rough, exact = N.nwr(x, 1.25, precision=16, compute=16, verify=False), N.nwr(x, 1.25)
    assert tuple(N.nwr_flips(x, 1.25, blocks=2).first()) == tuple(M.agreement(rough, exact).first())


@pytest.mark.parametrize("blocks", [1, 3])
def test_leaves_pass_over_what_is_out_of_reach(spark, monkeypatch, blocks):
    """with few features neighbours are exact though most pairs of leaves never meet; copies, far points and constant features included."""
    rng = np.random.default_rng(12)
    m = np.column_stack([rng.random((700, 2)), np.zeros(700)])
    m[650:680], m[690] = m[0], 50.0
    block = K.Block(0, np.arange(700), m, np.zeros(0))
    leaves = K.Leaves(block, size=16)
    assert sorted(np.concatenate(leaves.parts)) == list(range(700))
    assert np.median([(leaves.nearest(a, b) <= 0.0025).mean() for a, b in zip(leaves.lo, leaves.hi)]) < 0.3
    x = frame(spark, m).pack()
    at, dist = B.local_knn(m, 5)
    got = N.knn(x, 5, blocks=blocks).orderBy("i", "rank").toArrow().to_pydict()
    assert got["j"] == at.ravel().tolist() and got["dist"] == dist.ravel().tolist()


def test_ties_come_with_the_neighbours(spark):
    """neighbours with ties need no range search at the largest k-distance of all rows."""
    m = np.random.default_rng(13).integers(0, 4, (120, 2)).astype(float)
    m[119] = 1000
    x = frame(spark, m).pack()
    full = np.sqrt(((m[:, None] - m) ** 2).sum(2))
    np.fill_diagonal(full, np.inf)
    want = {(i, j) for i in range(120) for j in np.flatnonzero(full[i] <= np.sort(full[i])[4])}
    for blocks in (1, 3):
        edges = P.LofDetector(5, ties="all", blocks=blocks).edges(x)
        assert "Join" not in edges._jdf.queryExecution().analyzed().toString()
        rows = edges.collect()
        assert {(r["i"], r["j"]) for r in rows} == want and len(rows) == len(want)


def test_generated_points_belong_to_orders(spark, sf):
    """the generated-point queries read a given table and give one point for each of its rows."""
    import __spark_entry__ as E

    for name in ("source_synthetic_points", "synthetic_points"):
        df = E.queries()[name](spark, sf)
        assert any("orders.parquet" in f for f in df.inputFiles())
        assert df.count() == spark.read.parquet(f"{sf}/orders.parquet").count() == df.select("id").distinct().count()


def test_all_angles_take_one_pass_over_pairs(spark, cloud):
    """mean cosines over all pairs of other rows come from sums of directions, copies left out."""
    x = frame(spark, cloud).pack()
    got = P.AngleDetector(None, blocks=2).fit_score(x)
    assert "collect_list" not in got._jdf.queryExecution().analyzed().toString()
    assert np.allclose(scores(got), B.local_score("abod", cloud, 82))
    assert scores(P.AngleDetector(None).fit_score(frame(spark, [[1.0], [1.0], [2.0]]).pack())).tolist() == [0.0, 0.0, 1.0]


def test_grid_never_broadcasts_a_side(spark):
    """the grid's join is of two tables, however small their files look."""
    x = X.part_dims(spark, "/root/testdata/sf0.001")
    plan = N.nwr_grid(x, 1.5)._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" not in plan and "SortMergeJoin" in plan


def test_table_function_takes_blocks(spark):
    """one call of the table function answers for a block of rows, with ties to the smaller id."""
    from farpoint.functions.sql import nearest_of

    spark.udtf.register("fp_nearest_of", nearest_of)
    got = spark.sql("select t.* from (select array(7L, 8L) as a, array(array(0D, 0D), array(5D, 0D)) as b, array(3L, 1L, 2L) as c, array(array(1D, 0D), array(-1D, 0D), array(5D, 1D)) as d), lateral fp_nearest_of(a, b, c, d, 2) t").collect()
    assert sorted(map(tuple, got)) == [(7, 1, 1, 1.0), (7, 2, 3, 1.0), (8, 1, 2, 1.0), (8, 2, 3, 4.0)]


def test_loci_takes_equal_rows_once(spark, monkeypatch):
    """rows with equal features stand once in the kernels, with their number; leaves far off or wholly within a radius are not compared. Scores are those of all pairs."""
    rng = np.random.default_rng(19)
    m = np.concatenate([rng.random((300, 3)), 0.02 * rng.random((150, 3)) + 3])
    m = np.concatenate([m, m[:200], m[:200], np.repeat(m[400:401], 60, 0)])
    radii = (0.2, 0.5, 1.0)
    full = np.sqrt(((m[:, None] - m) ** 2).sum(2))
    want = np.full(len(m), -np.inf)
    for r in radii:
        n, inside = (full <= 0.5 * r).sum(1), full <= r
        mean = np.array([n[i].mean() for i in inside])
        sd = np.array([n[i].std() for i in inside])
        want = np.maximum(want, np.where(sd > 1e-12, (mean - n) / np.where(sd > 1e-12, sd, 1), 0))
    met = []
    kernels = {f: getattr(P, f) for f in ("nwr_counts", "nwr_spread")}
    for name, f in kernels.items():
        monkeypatch.setattr(P, name, lambda x, *a, f=f, **k: met.append(x.count()) or f(x, *a, **k))
    for blocks in (1, 3):
        got = scores(P.LociDetector(radii, n_min=1, blocks=blocks).fit_score(frame(spark, m).pack()))
        assert np.allclose(got, want, atol=1e-9)
    assert met == [450] * 4
    own = K.Block(0, np.arange(450), m[:450], np.zeros(0))
    tiles, meetings = N._meetings(own, iter([own]), list(radii), 3)
    compared = sum(len(tiles[at].ids) * len(v.ids) for at, v, _, flags in meetings if flags is None)
    assert compared < 0.75 * 450 * 450


def test_sums_of_gaps_have_two_equal_forms(spark):
    """whole numbers are summed by products, others and large ones pair by pair."""
    rng = np.random.default_rng(20)
    own, values, many, inside = rng.integers(0, 900, 40) * 1.0, rng.integers(0, 900, 70) * 1.0, rng.integers(1, 60, 70) * 1.0, rng.random((40, 70)) < 0.4
    for scale in (1.0, 0.1, 1e9):
        gap = values * scale - (own * scale)[:, None]
        for mask in (inside, None):
            w = many if mask is None else mask * many
            for got, want in zip(N._gaps(own * scale, mask, values * scale, many), (w + 0 * gap, w * gap, w * gap * gap)):
                assert np.allclose(np.broadcast_to(got, 40), want.sum(1), rtol=1e-12)


@pytest.mark.parametrize("blocks", (1, 3, None))
def test_checked_low_precision_passes_over_leaves(spark, blocks):
    """with few features the checked 16-bit form decides open pairs in the task that met them and does not compare leaves out of reach; results are the exact ones."""
    rng = np.random.default_rng(22)
    m = np.column_stack([rng.random((1500, 2)), rng.random(1500) * 0.01, np.zeros(1500)])
    m[1200:1300], m[1400] = m[0], 900.0
    x = frame(spark, m).pack()
    at, dist = B.local_knn(m, 5)
    edges = N.knn(x, 5, blocks=blocks, precision=16)
    assert "Join" not in edges._jdf.queryExecution().analyzed().toString()
    got = edges.orderBy("i", "rank").toArrow().to_pydict()
    assert got["j"] == at.ravel().tolist() and got["dist"] == dist.ravel().tolist()
    apart = N.knn(x, 3, y=frame(spark, m[:40]).pack(), blocks=blocks, precision=16).orderBy("i", "rank").toArrow().to_pydict()
    near = np.argsort(np.sqrt(((m[:, None] - m[:40]) ** 2).sum(2)), axis=1, kind="stable")[:, :3]
    assert apart["j"] == near.ravel().tolist()


def test_blocks_are_boxes_in_space(spark):
    """blocks are even, near in space, and equal rows too many for one are dealt to several; leaves of a block are full and near."""
    rng = np.random.default_rng(23)
    m = np.concatenate([rng.random((1200, 2)), np.full((800, 2), 0.3)])
    x = frame(spark, m).pack()
    rows = x.df.select(K.cut_space(x, 10).alias("b"), "x").collect()
    number, at = np.array([r["b"] for r in rows]), np.array([r["x"] for r in rows])
    sizes = np.bincount(number, minlength=10)
    assert len(sizes) == 10 and sizes.min() > 60 and sizes.max() < 420
    assert np.median([np.ptp(at[number == b], axis=0).prod() for b in range(10)]) < 0.3
    order = K.leaf_order(m, 64)
    assert sorted(order) == list(range(2000))
    leaves = K.Leaves(K.Block(0, np.arange(2000), m[order], np.zeros(0)), packed=64)
    assert leaves.size.tolist() == [64] * 31 + [16] and np.median((leaves.hi - leaves.lo).prod(1)) < 0.1


def test_auc_reads_a_detectors_scores_once(spark, sf):
    """the measure reads scores more than once; a detector runs once for each data set."""
    from farpoint.queries import detectors as D

    seen = spark.sparkContext.accumulator(0)

    class Once:
        def fit_score(self, x):
            def run(batches):
                for b in batches:
                    seen.add(b.num_rows)
                    yield b

            return x.df.mapInArrow(run, x.df.schema).select("id", F.col("x")[0].alias("score"))

    D._auc_rows(spark, sf, [("once", Once())]).collect()
    assert seen.value == spark.read.parquet(f"{sf}/documents.parquet").count() + 1500


def test_document_stats_of_odd_texts(spark, tmp_path):
    """features counted in bytes are those of characters: blanks of other kinds, wide characters, nulls and empty texts."""
    import re

    texts = ["", None, " \t\n\r ", "a\x0bb a\u00a0c  A1é9É.\n\n€😀 😀\r\n x,x;!?:", "ÀÉ ٣ 12\u200912", "one one  one", "\n"]
    spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").write.parquet(str(tmp_path / "documents.parquet"))
    for r, t in zip(X.document_stats(spark, str(tmp_path)).df.orderBy("doc_id").collect(), (t or "" for t in texts)):
        words, n = [w for w in re.split("[ \t\n\r]+", t) if w], max(len(t), 1)
        of = lambda p: len(re.findall(p, t)) / n
        assert tuple(r)[1:] == (len(t), len(words), len(t) / max(len(words), 1), of("[0-9]"), of("[A-Z]"), of("[.,;:!?]"), len(set(words)) / max(len(words), 1), t.count("\n") + 1)


def test_relational_search_joins_pairs_that_may_be_nearest(spark):
    """the SQL form met all pairs in the join. Now only pairs that may be among the nearest reach fp_distance and row_number; rows without finite numbers still meet all."""
    from farpoint.operators.relational import nearest_by_sql

    rng = np.random.default_rng(31)
    m = np.concatenate([rng.standard_normal((1400, 12)) + 50, np.full((4, 12), 50.0)])
    got = nearest_by_sql(frame(spark, m).pack(), 5).orderBy("i", "rank").toArrow().to_pydict()
    at, dist = B.local_knn(m, 5)
    assert got["j"] == at.ravel().tolist() and got["dist"] == dist.ravel().tolist()
    assert len(m) * 5 <= spark.table("fp_near").count() < len(m) * 60
    odd = FeatureFrame.wide(spark.createDataFrame([(0, 0.0), (1, 1.0), (2, float("nan"))], "id long, f double"), ["id"], ["f"], "trust")
    few = nearest_by_sql(odd.pack(), 5).orderBy("i", "rank").collect()
    assert [(r["i"], r["j"], r["rank"]) for r in few] == [(0, 1, 1), (0, 2, 2), (1, 0, 1), (1, 2, 2), (2, 0, 1), (2, 1, 2)]


def test_loci_blocks_are_boxes_and_sums_exact(spark, monkeypatch):
    """counts and sums take boxes in space as blocks and compare in 32 bit; pairs that lie on a radius, weights, large values and rows without numbers are settled exactly."""
    rng = np.random.default_rng(35)
    m = np.concatenate([rng.integers(0, 8, (900, 3)) * 0.1, rng.random((700, 3)), 1e6 + rng.random((60, 3))])
    w, values = rng.integers(1, 9, len(m)) * 1.0, rng.integers(0, 900000, (len(m), 2)) * 1.0
    radii, dealt = [0.1, 0.3], []
    full = np.stack([N.canonical(m, m, np.full(len(m), i), np.arange(len(m))) for i in range(len(m))])
    run = N.run_owners
    monkeypatch.setattr(N, "run_owners", lambda *a, **k: dealt.append(k.get("cell")) or run(*a, **k))
    for blocks in (1, 3):
        got = N.nwr_counts(frame(spark, np.column_stack([m, w])).pack(), radii, blocks, weighted=True).orderBy("i", "phi").toArrow()["n"].to_numpy().reshape(-1, 2)
        assert (got == np.stack([(full <= r) @ w - 1 for r in radii], 1)).all()
        for scale in (1, 0.1):
            rows = N.nwr_spread(frame(spark, np.column_stack([m, w, values * scale])).pack(), 2, radii, blocks, weighted=True).orderBy("i", "k").toArrow()
            for k, r in enumerate(radii):
                inside, gap = (full <= r) * w, values[:, k] * scale - values[:, k : k + 1] * scale
                for name, want in (("n", inside.sum(1)), ("s", (inside * gap).sum(1)), ("s2", (inside * gap * gap).sum(1))):
                    assert np.allclose(rows[name].to_numpy().reshape(-1, 2)[:, k], want, rtol=0 if scale == 1 else 1e-9, atol=0 if scale == 1 else 1e-3)
    assert [c is not None for c in dealt] == [False] * 3 + [True] * 3
    own = K.Block(0, np.arange(65), np.concatenate([rng.random((64, 2)), [[np.nan, 0.0]]]), np.zeros(0))
    seen = []
    assert N._leaf_sums(own, iter([own]), [0.5], 2, lambda b: [np.ones((65, 1))], lambda *a: seen.append(a)) is None and seen
