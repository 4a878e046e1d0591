"""Baselines: one NumPy process over a whole matrix, and single-kernel forms that broadcast the reference side.

They are what the engine is compared with; sizes are checked before anything is collected or broadcast.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from farpoint.composite.neighbours import _best, centred_squares, canonical
from farpoint.model import FeatureFrame
from farpoint.plans.arrow import matrix
from farpoint.plans.blocks import MemoryBudgetExceeded
from farpoint.session import ship, stage


def collect_matrix(x: FeatureFrame, budget: int = 1 << 30) -> tuple[np.ndarray, np.ndarray]:
    """(ids, rows) on the driver; refused beyond the budget."""
    n = x.df.count()
    if n * x.d * 8 > budget:
        raise MemoryBudgetExceeded(f"{n} rows do not fit the driver")
    t = x.pack().df.orderBy("id").toArrow().combine_chunks()
    return t["id"].to_numpy(), matrix(t["x"].combine_chunks() if isinstance(t["x"], pa.ChunkedArray) else t["x"], x.d)


def local_topk(x: np.ndarray, k: int, largest: bool = True) -> np.ndarray:
    return np.argsort(-x if largest else x, axis=1, kind="stable")[:, :k]


def local_intersect(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.intersect1d(a, b)


#: Bytes of one strip of the distance matrix.
STRIP = 32 << 20


def strip_rows(n: int) -> int:
    """Rows whose distances to n others fit a strip."""
    return max(1, min(512, STRIP // (8 * max(n, 1))))


def local_knn(x: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(neighbour positions, distances), ties to the smaller position; the distance matrix strip by strip, so memory grows with the rows and not with their square."""
    at, far, step = np.zeros((len(x), k), np.int64), np.zeros((len(x), k)), strip_rows(len(x))
    for lo in range(0, len(x), step):
        q = x[lo : lo + step]
        near, slack = centred_squares(q, x)
        near[np.arange(len(q)), lo + np.arange(len(q))] = np.inf
        cut = np.partition(near, k - 1, axis=1)[:, k - 1]
        a, b = np.nonzero((near <= (cut + 2 * slack)[:, None]) & np.isfinite(near))
        dist = canonical(q, x, a, b)
        keep = _best(a, b, dist, k)
        at[lo : lo + step], far[lo : lo + step] = b[keep].reshape(-1, k), dist[keep].reshape(-1, k)
    return at, far


def _tails(x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    n = len(x)
    s = np.sort(x, axis=0)
    left = np.column_stack([np.searchsorted(s[:, k], x[:, k], "right") for k in range(x.shape[1])]) / n
    right = 1 - np.column_stack([np.searchsorted(s[:, k], x[:, k], "left") for k in range(x.shape[1])]) / n
    c = x - x.mean(0)
    sd = x.std(0)
    skew = np.divide((c**3).mean(0), sd**3, out=np.zeros(x.shape[1]), where=sd > 0)
    ul, ur = -np.log(left), -np.log(right)
    return ul, ur, np.where(skew < 0, ul, ur)


def local_score(name: str, x: np.ndarray, k: int = 10, bins: int = 10, alpha: float = 0.1) -> np.ndarray:
    """Scores of all rows by one of knn, lof, abod, hbos, pca, copod, ecod."""
    if name in ("knn", "lof", "abod"):
        at, dist = local_knn(x, k)
        if name == "knn":
            return dist[:, -1]
        if name == "lof":
            lrd = 1 / (np.maximum(dist[:, -1][at], dist).mean(1) + 1e-10)
            return lrd[at].mean(1) / lrd
        out = np.zeros(len(x))
        for i in range(len(x)):
            w = x[at[i]] - x[i]
            size = np.sqrt((w * w).sum(1))
            w, size = w[size > 0], size[size > 0]
            a, b = np.triu_indices(len(w), 1)
            out[i] = ((w @ w.T)[a, b] / (size[a] * size[b])).mean() if len(a) else 0.0
        return out
    if name == "hbos":
        out = np.zeros(len(x))
        for c in x.T:
            lo, hi = c.min(), c.max()
            if hi > lo:
                b = np.minimum(np.floor((c - lo) / ((hi - lo) / bins)).astype(int), bins - 1)
                h = np.bincount(b, minlength=bins)
                out -= np.log(h[b] / h.max() + alpha)
        return out
    if name == "pca":
        z = (x - x.mean(0)) / x.std(0, ddof=1)
        values, vectors = np.linalg.eigh(np.cov(z.T))
        return ((z @ vectors) ** 2 / values).sum(1)
    ul, ur, us = _tails(x)
    if name in ("copod", "ecod"):
        return np.maximum(np.maximum(ul.sum(1), ur.sum(1)), us.sum(1))
    raise ValueError(name)


def broadcast_knn(x: FeatureFrame, k: int, budget: int = 256 << 20) -> DataFrame:
    """(i, j, rank, dist): the whole reference side in every task, map-only. Refused beyond the budget."""
    ids, rows = collect_matrix(x, budget)
    spark, d = ship(x.df.sparkSession), x.d
    sent = spark.sparkContext.broadcast((ids, rows))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ref_ids, ref = sent.value
        for big in batches:
            step = strip_rows(len(ref_ids))
            for at in range(0, big.num_rows, step):
                b = big.slice(at, step)
                own, q = b.column(0).to_numpy(zero_copy_only=False), matrix(b.column(1), d)
                near, slack = centred_squares(q, ref)
                near[own[:, None] == ref_ids] = np.inf
                cut = np.partition(near, k - 1, axis=1)[:, k - 1]
                a, c = np.nonzero((near <= (cut + 2 * slack)[:, None]) & np.isfinite(near))
                dist = canonical(q, ref, a, c)
                keep = _best(a, ref_ids[c], dist, k)
                i = a[keep]
                yield pa.RecordBatch.from_arrays([pa.array(own[i]), pa.array(ref_ids[c[keep]]), pa.array(np.arange(len(i)) - np.searchsorted(i, i) + 1, pa.int32()), pa.array(dist[keep])], names=["i", "j", "rank", "dist"])

    rows = x.pack().df.select("id", "x").repartition(spark.sparkContext.defaultParallelism, "id")  # a small file is one partition
    return rows.mapInArrow(run, "i long, j long, rank int, dist double")


def broadcast_lof(x: FeatureFrame, k: int, budget: int = 256 << 20) -> DataFrame:
    """Neighbours by broadcast; densities from these k edges a row, so that no distance matrix is held anywhere."""
    from farpoint.detectors.proximity import lof_scores

    return lof_scores(stage(broadcast_knn(x, k, budget), "broadcast-edges"))


def local_frame(name: str, x: FeatureFrame, **p) -> DataFrame:
    """local_score as (id, score)."""
    ids, rows = collect_matrix(x)
    return x.df.sparkSession.createDataFrame(pa.table({"id": ids, "score": local_score(name, rows, **p)})).select("id", F.col("score").cast("double").alias("score"))
