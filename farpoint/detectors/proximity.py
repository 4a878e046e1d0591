"""Detectors on neighbour edges: k-th-neighbour distance, local outlier factor, angle based, correlation integral.

Each takes a packed FeatureFrame and gives (id, score), larger being more outlying. Edges are written once to the shared folder when they are read more than once.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from farpoint.composite.neighbours import direction_sums, distance_column, knn, nwr_counts, nwr_spread
from farpoint.model import FeatureFrame
from farpoint.session import stage


@dataclass(frozen=True)
class KnnDetector:
    """method: 'largest' (distance to the k-th neighbour), 'mean' or 'median' of the k distances."""

    k: int = 5
    method: str = "largest"
    precision: int = 64
    verify: bool = True
    mode: str = "fused"
    blocks: int | None = None

    def fit_score(self, x: FeatureFrame, y: FeatureFrame | None = None) -> DataFrame:
        """y: reference rows (default: the other rows of x)."""
        edges = knn(x, self.k, y=y, mode=self.mode, blocks=self.blocks, precision=self.precision, verify=self.verify)
        f = {"largest": F.max("dist"), "mean": F.avg("dist"), "median": F.percentile("dist", 0.5)}[self.method]
        return edges.groupBy(F.col("i").alias("id")).agg(f.alias("score"))


def reach_density(edges: DataFrame, duplicate: str = "eps") -> DataFrame:
    """(i, lrd): inverse mean of max(k-distance of j, distance). 'eps' adds 1e-10 to the mean; 'inf' gives infinite density to points among their duplicates."""
    kdist = edges.groupBy(F.col("i").alias("n")).agg(F.max("dist").alias("kdist"))
    mean = F.avg(F.greatest("kdist", "dist"))
    lrd = 1 / (mean + 1e-10) if duplicate == "eps" else F.when(mean == 0, F.lit(float("inf"))).otherwise(1 / F.when(mean == 0, 1.0).otherwise(mean))
    return edges.join(kdist, F.col("j") == F.col("n")).groupBy("i").agg(lrd.alias("lrd"))


def lof_scores(edges: DataFrame, duplicate: str = "eps") -> DataFrame:
    lrd = reach_density(edges, duplicate)
    other = lrd.select(F.col("i").alias("n"), F.col("lrd").alias("lrd_j"))
    own = F.first("lrd")
    ratio = F.when(own == float("inf"), F.lit(1.0)).otherwise(F.avg("lrd_j") / own)
    return edges.join(other, F.col("j") == F.col("n")).join(lrd, "i").groupBy(F.col("i").alias("id")).agg(ratio.alias("score"))


@dataclass(frozen=True)
class LofDetector:
    """ties: 'exact' (k neighbours, ties to the smaller id) or 'all' (everything not farther than the k-th). phi: neighbours are instead the k nearest of those within phi (all of them if fewer); a point without any gets an infinite score."""

    k: int = 20
    ties: str = "exact"
    duplicate: str = "eps"
    phi: float | None = None
    blocks: int | None = None
    precision: int = 64

    def edges(self, x: FeatureFrame) -> DataFrame:
        if self.phi is not None:
            # The k nearest of those within phi are those of the k nearest that are within phi: no pair beyond n * k is written.
            return knn(x, self.k, blocks=self.blocks, precision=self.precision).where(F.col("dist") <= self.phi)
        if self.ties == "exact":
            return knn(x, self.k, blocks=self.blocks, precision=self.precision)
        return knn(x, self.k, blocks=self.blocks, ties=True).select("i", "j", "dist")  # 64 bit: ties are a matter of exact distances

    def fit_score(self, x: FeatureFrame) -> DataFrame:
        scores = lof_scores(stage(self.edges(x), "lof-edges"), self.duplicate)
        if self.phi is None:
            return scores
        return x.pack().df.select("id").join(scores, "id", "left").select("id", F.coalesce("score", F.lit(float("inf"))).alias("score"))


def _dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, v: s + v)


def neighbour_angles(x: FeatureFrame, edges: DataFrame) -> DataFrame:
    """(i, a, b, dot, na, nb): for each pair a < b of i's neighbours, inner product and squared norms of their differences to i; zero differences are left out."""
    rows = x.pack().df
    point, other = rows.select(F.col("id").alias("p"), F.col("x").alias("u")), rows.select(F.col("id").alias("q"), F.col("x").alias("v"))
    diff = edges.join(point, F.col("i") == F.col("p")).join(other, F.col("j") == F.col("q")).select("i", "j", F.zip_with("v", "u", lambda s, t: s - t).alias("w"))
    lists = diff.withColumn("n", _dot(F.col("w"), F.col("w"))).where("n > 0").groupBy("i").agg(F.array_sort(F.collect_list(F.struct("j", "w", "n"))).alias("l"))  # k entries
    pairs = F.flatten(F.transform("l", lambda s, k: F.transform(F.slice("l", k + 2, F.size("l")), lambda t: F.struct(s["j"].alias("a"), t["j"].alias("b"), _dot(s["w"], t["w"]).alias("dot"), s["n"].alias("na"), t["n"].alias("nb")))))
    return lists.select("i", F.inline(pairs))


@dataclass(frozen=True)
class AngleDetector:
    """'mean_cosine': mean cosine between the differences to neighbours (all on one side: outlying). 'raw': 1 minus the mean cosine with each neighbour.
    'fast_variance': minus the weighted variance of the cosines over squared lengths. k=None uses all other rows: for 'mean_cosine' by sums over pairs, for the others by all pairs of neighbours (small n)."""

    k: int | None = 10
    method: str = "mean_cosine"
    blocks: int | None = None

    def fit_score(self, x: FeatureFrame) -> DataFrame:
        ids = x.pack().df.select("id")
        if self.k is None and self.method == "mean_cosine":
            pairs = F.col("m") * (F.col("m") - 1) / 2
            found = direction_sums(x.pack(), self.blocks).select(F.col("i").alias("id"), F.when(F.col("m") > 1, F.col("dots") / F.when(F.col("m") > 1, pairs)).alias("s"))
            return ids.join(found, "id", "left").select("id", F.coalesce("s", F.lit(0.0)).alias("score"))
        k = self.k or x.df.count() - 1
        edges = knn(x, k, blocks=self.blocks)
        if self.method == "raw":
            rows = x.pack().df
            point, other = rows.select(F.col("id").alias("p"), F.col("x").alias("u")), rows.select(F.col("id").alias("q"), F.col("x").alias("v"))
            each = edges.join(point, F.col("i") == F.col("p")).join(other, F.col("j") == F.col("q")).select("i", distance_column(F.col("u"), F.col("v"), "cosine").alias("c"))
            return each.groupBy(F.col("i").alias("id")).agg(F.avg("c").alias("score"))
        pairs = neighbour_angles(x, edges)
        size = F.sqrt("na") * F.sqrt("nb")
        if self.method == "mean_cosine":
            found = pairs.groupBy(F.col("i").alias("id")).agg(F.avg(F.col("dot") / size).alias("s"))
        else:
            f, w = F.col("dot") / (F.col("na") * F.col("nb")), 1 / size
            m = F.sum(w * f) / F.sum(w)
            found = pairs.groupBy(F.col("i").alias("id")).agg((-(F.sum(w * f * f) / F.sum(w) - m * m)).alias("s"))
        return ids.join(found, "id", "left").select("id", F.coalesce("s", F.lit(0.0)).alias("score"))


@dataclass(frozen=True)
class LociDetector:
    """For each radius r: counts within alpha * r of all rows within r (self included), their mean and deviation; score is the largest (1 - n / mean) / (sd / mean), 0 where sd is 0 or fewer than n_min rows are within. Flag above 3.
    Two passes of kernels that give counts and sums, so memory and output stay at a few numbers a row. Rows with equal features have equal scores: each such set stands once in both passes, with its size."""

    radii: tuple[float, ...]
    alpha: float = 0.5
    n_min: int = 20
    blocks: int | None = None

    def fit_score(self, x: FeatureFrame) -> DataFrame:
        p, many = x.pack(), len(self.radii)
        rows = stage(p.df.select("id", "x"), "rows")
        sets = stage(rows.groupBy("x").agg(F.min("id").alias("id"), F.count("*").cast("double").alias("w")).select("id", "x", "w"), "sets")
        of = lambda df, *more: FeatureFrame(df, ("id",), (*p.features, "w", *more), True, df.count())
        inner = nwr_counts(of(sets.select("id", F.concat("x", F.array("w")).alias("x"))), [self.alpha * r for r in self.radii], self.blocks, weighted=True)
        at = F.when(F.lit(False), 0)
        for k, r in enumerate(self.radii):
            at = at.when(F.col("phi") == self.alpha * r, F.lit(k))
        counts = inner.groupBy("i").agg(F.transform(F.array_sort(F.collect_list(F.struct(at.alias("k"), (F.col("n") + 1.0).alias("n")))), lambda c: c["n"]).alias("c"))  # one count a radius
        both = stage(sets.join(counts, F.col("id") == F.col("i")).select("id", F.concat("x", F.array("w"), "c").alias("x")), "counted")
        mean = F.col("s") / F.col("n")
        sd = F.sqrt(F.greatest(F.col("s2") / F.col("n") - mean * mean, F.lit(0.0)))
        ratio = F.when((sd > 1e-12) & (F.col("n") >= self.n_min), mean / F.when(sd > 1e-12, sd)).otherwise(0.0)
        spread = nwr_spread(of(both, *(f"n{k}" for k in range(many))), many, list(self.radii), self.blocks, weighted=True)
        scores = spread.groupBy("i").agg(F.max(ratio).alias("score"))
        return rows.join(sets.select(F.col("id").alias("i"), F.col("x").alias("same")), F.col("x") == F.col("same")).join(scores, "i").select("id", "score")
