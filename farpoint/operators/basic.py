"""Feature-independent and row-wise operators: moments, scaling, histograms, feature samples, top-k, intersections, linear maps.

All are Spark expressions; what reaches the driver is a number or a few for each feature.
"""

from __future__ import annotations

import math
import random
from collections.abc import Sequence
from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from farpoint.model import FeatureFrame
from farpoint.operators.ecdf import quantiles


def moments(x: FeatureFrame, exact: bool = False) -> DataFrame:
    """(feature, n, mean, sd, min, max, skew, kurt), population moments, one pass; a constant feature has skew and kurt 0.

    exact: the mean's sum is taken over decimals of 18 places, so that it does not vary with the order of rows (values from 1e-3 to 1e15 in size, else the plain mean).
    """
    w = x.unpack()

    def mean(f: str) -> Column:
        if not exact:
            return F.avg(f)
        top = F.max(F.abs(f))
        total = F.sum(F.when(F.abs(f) < 1e15, F.col(f)).cast("decimal(38,18)")).cast("double")
        return F.when((top >= 1e-3) & (top < 1e15), total / F.count(f)).otherwise(F.avg(f))

    one = lambda f: F.struct(F.lit(f).alias("feature"), F.count(f).alias("n"), mean(f).alias("mean"), F.stddev_pop(f).alias("sd"), F.min(f).alias("min"), F.max(f).alias("max"), _finite(F.skewness(f)).alias("skew"), _finite(F.kurtosis(f)).alias("kurt"))
    return w.df.agg(F.array(*(one(f) for f in w.features)).alias("m")).select(F.inline("m"))


def skews(x: FeatureFrame) -> dict[str, float]:
    """Population skewness of every feature, 0 where it is constant: one aggregate."""
    w = x.unpack()
    row = w.df.agg(*(_finite(F.skewness(f)).alias(f"k{i}") for i, f in enumerate(w.features))).first()
    return dict(zip(w.features, row))


def _finite(c: Column) -> Column:
    return F.when(c.isNull() | F.isnan(c), F.lit(0.0)).otherwise(c)


def stats(x: FeatureFrame) -> dict[str, dict]:
    """moments() on the driver: a row for each feature."""
    return {r["feature"]: r.asDict() for r in moments(x).collect()}


def scale(x: FeatureFrame, kind: str = "minmax") -> FeatureFrame:
    """minmax: to [0, 1]; zscore: mean 0 and population sd 1; robust: median and quartile range; pow2: one power of two for all features so that no value exceeds 1 (exact). Constant features become 0."""
    if kind == "pow2":
        top = x_max(x)
        factor = 2.0 ** -math.ceil(math.log2(top)) if top > 0 else 1.0
        return x.map(lambda f, c: c * factor)
    if kind == "robust":
        q = quantiles(x, [0.25, 0.5, 0.75])
        return x.map(lambda f, c: (c - q[f][1]) / (q[f][2] - q[f][0]) if q[f] and q[f][2] > q[f][0] else c * 0.0)
    if kind == "minmax":
        w = x.unpack()
        row = w.df.agg(*(F.struct(F.min(f), F.max(f)) for f in w.features)).first()
        ends = {f: tuple(r) for f, r in zip(w.features, row)}
        return x.map(lambda f, c: (c - ends[f][0]) / (ends[f][1] - ends[f][0]) if ends[f][1] > ends[f][0] else c * 0.0)
    if kind == "zscore":
        s = stats(x)
        return x.map(lambda f, c: (c - s[f]["mean"]) / s[f]["sd"] if s[f]["sd"] > 0 else c * 0.0)
    raise ValueError(kind)


def x_max(x: FeatureFrame) -> float:
    """Largest absolute value: one aggregate."""
    if x.is_packed:
        return float(x.df.agg(F.max(F.array_max(F.transform("x", F.abs)))).first()[0] or 0.0)
    return float(x.df.agg(F.greatest(*(F.max(F.abs(f)) for f in x.features), F.lit(0.0))).first()[0] or 0.0)


def row_norms(x: FeatureFrame) -> DataFrame:
    """(id, norm), summed in feature order."""
    p = x.pack()
    return p.df.select("id", F.sqrt(F.aggregate("x", F.lit(0.0), lambda a, v: a + v * v)).alias("norm"))


def edges_of(x: FeatureFrame, bins: int | str = 10, kind: str = "width") -> dict[str, list[float]]:
    """Bin borders of every feature. bins: a number, 'sqrt' (of the rows) or 'fd' (width from the quartile range and the cube root of the rows). Equal borders of 'frequency' bins are merged."""
    w = x.unpack()
    row = w.df.agg(F.count("*").alias("n"), *(c for f in w.features for c in (F.min(f).alias(f"lo_{f}"), F.max(f).alias(f"hi_{f}")))).first()
    n, s = row["n"], {f: {"min": row[f"lo_{f}"], "max": row[f"hi_{f}"]} for f in w.features}
    if not n:
        return {f: [0.0, 0.0] for f in w.features}
    count = dict.fromkeys(w.features, bins if isinstance(bins, int) else max(1, math.ceil(math.sqrt(n))))
    if bins == "fd":
        q = quantiles(w, [0.25, 0.75])
        for f in w.features:
            step = 2 * (q[f][1] - q[f][0]) / n ** (1 / 3) if n else 0
            if step > 0:
                count[f] = max(1, math.ceil((s[f]["max"] - s[f]["min"]) / step))
    if kind == "frequency":
        cuts = {n: quantiles(w.select([f for f in w.features if count[f] == n]), [k / n for k in range(n + 1)]) for n in set(count.values())}
        return {f: sorted(set(cuts[count[f]][f])) for f in w.features}
    out = {}
    for f in w.features:
        lo, hi = s[f]["min"], s[f]["max"]
        out[f] = [*(lo + k * ((hi - lo) / count[f]) for k in range(count[f])), hi] if hi > lo else [lo, lo]  # the last border is the maximum itself
    return out


def bin_of(c: Column, borders: list[float], kind: str = "width") -> Column:
    """Bin number of a value; the last bin is closed. Values outside get the bins -1 and number of bins."""
    n = len(borders) - 1
    if n < 1 or borders[-1] == borders[0]:
        return F.when(c < borders[0], -1).when(c > borders[0], max(1, n)).otherwise(0)
    if kind == "width":
        inner = F.least(F.floor((c - borders[0]) / ((borders[-1] - borders[0]) / n)).cast("int"), F.lit(n - 1))
    else:
        inner = F.least(F.size(F.filter(F.array(*map(F.lit, borders[1:])), lambda b: b <= c)), F.lit(n - 1))
    return F.when(c < borders[0], -1).when(c > borders[-1], n).otherwise(inner)


def _checked_bin(c: Column, borders: list[float], kind: str) -> Column:
    """The bin of the 32-bit value where both ends of its rounding interval share it, else that of the full value."""
    low = c.cast("float").cast("double")
    err = F.abs(low) * 2.0**-24 * (1 + 2.0**-20) + 2.0**-149
    a, b = bin_of(low - err, borders, kind), bin_of(low + err, borders, kind)
    return F.when(a == b, a).otherwise(bin_of(c, borders, kind))


def histogram(x: FeatureFrame, bins: int | str = 10, kind: str = "width", borders: dict[str, list[float]] | None = None, precision: int = 64) -> DataFrame:
    """(feature, bin, lo, hi, count), empty bins included. One aggregation over (feature, bin), combined before the shuffle. precision 32 bins rounded values and looks again at those near a border."""
    w = x.unpack()
    borders = borders or edges_of(w, bins, kind)
    placed = bin_of if precision == 64 else _checked_bin
    # One small integer for each cell of (feature, bin): bins outside the borders are -1 and the number of bins.
    wide = max(len(b) for b in borders.values()) + 2
    cells = F.explode(F.array(*((placed(F.col(f), borders[f], kind) + (i * wide + 1)).cast("int") for i, f in enumerate(w.features))))
    named = F.element_at(F.array(*map(F.lit, w.features)), (F.floor(F.col("cell") / wide) + 1).cast("int"))
    counts = w.df.select(cells.alias("cell")).groupBy("cell").agg(F.count("*").alias("count")).select(named.alias("feature"), (F.pmod("cell", F.lit(wide)) - 1).cast("int").alias("bin"), "count")
    ranges = [(f, k, float(b[k]), float(b[k + 1])) for f, b in borders.items() for k in range(max(1, len(b) - 1))]
    frame = w.df.sparkSession.createDataFrame([r if len(borders[r[0]]) > 1 else (*r[:2], borders[r[0]][0], borders[r[0]][0]) for r in ranges], "feature string, bin int, lo double, hi double")
    return frame.join(counts, ["feature", "bin"], "left").select("feature", "bin", "lo", "hi", F.coalesce("count", F.lit(0)).alias("count"))


def feature_sample(x: FeatureFrame, draws: int = 1, size: int | None = None, seed: int = 3) -> list[FeatureFrame]:
    """Random feature subsets, drawn on the driver; without size, each has between half and all but one of the features. Projection only."""
    if x.d < 2:
        raise ValueError("one feature cannot be sampled")
    rng = random.Random(seed)
    picks = [sorted(rng.sample(range(x.d), size or rng.randint(max(1, x.d // 2), x.d - 1))) for _ in range(draws)]
    return [x.select([x.features[i] for i in p]) for p in picks]


def topk_rows(x: FeatureFrame, k: int, largest: bool = True) -> DataFrame:
    """(id, rank, index, value): the k largest or smallest values of each row, ties to the smaller index. Row by row, no shuffle."""
    p = x.pack()
    sign = -1.0 if largest else 1.0
    keyed = F.transform("x", lambda v, i: F.struct((v * sign).alias("k"), i.alias("i"), v.alias("v")))
    best = F.slice(F.array_sort(keyed), 1, k)
    return p.df.select("id", F.posexplode(best).alias("r", "b")).select("id", (F.col("r") + 1).alias("rank"), F.col("b.i").cast("int").alias("index"), F.col("b.v").alias("value"))


def topk_global(df: DataFrame, value: str, k: int, ids: Sequence[str], largest: bool = True) -> DataFrame:
    """The k rows with the largest values: a heap in every task, k rows to the last."""
    return df.orderBy(F.desc(value) if largest else F.asc(value), *ids).limit(k)


def topk_groups(df: DataFrame, by: Sequence[str], value: str, k: int, ids: Sequence[str], largest: bool = True) -> DataFrame:
    """The k largest of each group, with rank; Spark limits groups before the shuffle."""
    w = Window.partitionBy(*by).orderBy(F.desc(value) if largest else F.asc(value), *ids)
    return df.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def intersect(a: DataFrame, b: DataFrame, distinct: bool = True) -> DataFrame:
    return a.intersect(b) if distinct else a.intersectAll(b)


def intersect_lists(a: Column, b: Column) -> Column:
    """Common elements of two arrays, sorted."""
    return F.array_sort(F.array_intersect(a, b))


def covariance(x: FeatureFrame, sample: bool = True) -> np.ndarray:
    """d x d matrix. Up to 12 features: built-in aggregates; beyond: centred partial Gram sums, one small row a task."""
    if x.d <= 12:
        w = x.unpack()
        f = F.covar_samp if sample else F.covar_pop
        pairs = [(i, j) for i in range(w.d) for j in range(i, w.d)]
        row = w.df.agg(*(f(w.features[i], w.features[j]).alias(f"c{k}") for k, (i, j) in enumerate(pairs))).first()
        out = np.zeros((w.d, w.d))
        for k, (i, j) in enumerate(pairs):
            out[i, j] = out[j, i] = row[k] if row[k] is not None else 0.0
        return out
    return _gram(x, sample)


def _gram(x: FeatureFrame, sample: bool) -> np.ndarray:
    import pyarrow as pa

    from farpoint.plans.arrow import matrix
    from farpoint.session import ship

    p, d = x.pack(), x.d
    ship(p.df.sparkSession)
    centre = np.array(p.df.agg(F.array(*(F.avg(F.col("x")[i]) for i in range(d)))).first()[0])

    def run(batches):
        total, n = np.zeros((d, d)), 0
        for b in batches:
            m = matrix(b.column(0), d) - centre
            total += m.T @ m
            n += len(m)
        yield pa.RecordBatch.from_arrays([pa.array([n], pa.int64()), pa.array([total.ravel().tolist()], pa.list_(pa.float64()))], names=["n", "s"])

    parts = p.df.select("x").mapInArrow(run, "n long, s array<double>")
    cells = parts.select("n", F.posexplode("s").alias("at", "v")).groupBy("at").agg(F.sum("v").alias("v"), F.sum("n").alias("n")).collect()  # d * d numbers
    out = np.zeros(d * d)
    n = cells[0]["n"] if cells else 0
    for c in cells:
        out[c["at"]] = c["v"]
    return out.reshape(d, d) / max(1, n - 1 if sample else n)


def eigh_sorted(c: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Eigenvalues falling and their vectors as columns, each with its largest entry positive."""
    values, vectors = np.linalg.eigh(c)
    values, vectors = values[::-1], vectors[:, ::-1]
    sign = np.sign(vectors[np.abs(vectors).argmax(0), np.arange(len(values))])
    return values, vectors * np.where(sign == 0, 1, sign)


def project(x: FeatureFrame, w: np.ndarray) -> FeatureFrame:
    """x @ w as column expressions."""
    u = x.unpack()
    dot = lambda k: reduce(lambda a, b: a + b, (F.col(f) * float(w[i, k]) for i, f in enumerate(u.features)))
    names = [f"p{k}" for k in range(w.shape[1])]
    return FeatureFrame(u.df.select(*u.ids, *(dot(k).alias(n) for k, n in enumerate(names))), u.ids, tuple(names))
