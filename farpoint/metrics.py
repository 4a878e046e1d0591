"""Cost and accuracy measures."""

from __future__ import annotations

import math
import time
from collections.abc import Callable, Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from farpoint.model import FeatureFrame
from farpoint.operators.ecdf import value_ranks


def roc_auc(scores: DataFrame, truth: str = "truth") -> DataFrame:
    """One row (auc): rank-sum form, ties averaged; null when a class is missing. Ranks come from value counts, not from a window over all rows."""
    ranks = value_ranks(FeatureFrame(scores.select("score"), (), ("score",))).select(F.col("value").alias("v"), "f_left", "f_right")
    n = F.count("*")
    placed = scores.select("score", F.col(truth).cast("int").alias("t")).join(ranks, F.col("score") == F.col("v"))
    pos = F.sum("t")
    # The average rank of a value is (rows not above it + rows strictly below it + 1) / 2.
    mean = F.sum(F.when(F.col("t") == 1, (F.col("f_left") + 1 - F.col("f_right")) / 2))
    return placed.agg(F.when((pos > 0) & (pos < n), (mean * n + pos / 2 - pos * (pos + 1) / 2) / (pos * (n - pos))).alias("auc"))


def precision_at(scores: DataFrame, n: int, ids: Sequence[str] = ("id",), truth: str = "truth") -> DataFrame:
    return scores.orderBy(F.desc("score"), *ids).limit(n).agg(F.avg(F.col(truth).cast("double")).alias("precision"))


def average_precision(scores: DataFrame, truth: str = "truth") -> DataFrame:
    """Mean over positives of the precision at their score; equal scores form one step. Counts of rows not below a score come from value counts of all rows and of the positives."""
    positives = scores.where(F.col(truth).cast("int") == 1)
    ranks = lambda df, name: value_ranks(FeatureFrame(df.select("score"), (), ("score",))).select(F.col("value").alias(f"{name}_v"), F.col("f_right").alias(name))
    sizes = scores.agg(F.count("*").alias("n"), F.sum(F.col(truth).cast("int")).alias("p"))  # one row
    placed = positives.select("score").join(ranks(scores, "above"), F.col("score") == F.col("above_v")).join(ranks(positives, "hits"), F.col("score") == F.col("hits_v")).crossJoin(F.broadcast(sizes))
    return placed.agg(F.avg(F.col("hits") * F.col("p") / (F.col("above") * F.col("n"))).alias("ap"))


def agreement(a: DataFrame, b: DataFrame) -> DataFrame:
    """(missing, extra): rows of b that a lacks and the other way round; both 0 for equal results."""
    return b.exceptAll(a).agg(F.count("*").alias("missing")).crossJoin(a.exceptAll(b).agg(F.count("*").alias("extra")))


def recalc_fraction(flagged: DataFrame, pairs: int) -> DataFrame:
    """Share of all pairs (or rows) that the low precision could not decide."""
    return flagged.agg((F.count_if(~F.col("certain")) / F.lit(pairs)).alias("fraction"))


def recalc_share(tally: DataFrame, pairs: int) -> DataFrame:
    """recalc_fraction from counts of kernels (met, open): no pair is written."""
    return tally.agg((F.coalesce(F.sum("open"), F.lit(0)) / F.lit(pairs)).alias("fraction"))


def timed(df: DataFrame) -> float:
    """Seconds to compute all rows without keeping them."""
    t = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - t


def growth_exponent(sizes: Sequence[float], seconds: Sequence[float]) -> float:
    """Slope of the log-log line."""
    x, y = [math.log(v) for v in sizes], [math.log(v) for v in seconds]
    mx, my = sum(x) / len(x), sum(y) / len(y)
    return sum((a - mx) * (b - my) for a, b in zip(x, y)) / sum((a - mx) ** 2 for a in x)


def efficiency(one: float, many: float, workers: int) -> float:
    return one / many / workers


def saving_pct(low: float, full: float) -> float:
    return 100 * (1 - low / full)


def speedup_table(base: dict[str, float], engine: dict[str, float]) -> dict[str, float]:
    each = {k: base[k] / engine[k] for k in base if k in engine}
    return each | {"mean": sum(each.values()) / len(each)} if each else {}


def kernel_bytes(kind: str, n: int, d: int, bits: int, k: int = 10, seed: int = 5) -> int:
    """Measured: the most memory that the kernel of 'range' (a tile of a range search) or 'topk' (a batch of rows) holds at once, input included, in a format."""
    import tracemalloc

    import numpy as np

    from farpoint.composite.neighbours import centred_squares, _LowPrecision
    from farpoint.plans.blocks import FORMATS, Block

    values = np.random.default_rng(seed).random((n, d))
    tracemalloc.start()
    try:
        rows = values.astype(FORMATS[bits])
        if kind == "range":
            tile = Block(0, np.arange(n), rows, np.zeros(n))
            if bits == 64:
                centred_squares(rows, rows)
            else:
                _LowPrecision(tile, tile, bits)
        else:
            np.partition(rows, d - k, axis=1)[:, d - k :]
        return tracemalloc.get_traced_memory()[1]
    finally:
        tracemalloc.stop()


def block_bytes(n: int, d: int, blocks: int, bits: int, symmetric: bool = True) -> dict[str, float]:
    """Machine-independent cost of one all-pairs run: bytes of all blocks, bytes sent to owners, largest pair of blocks with its tile, distance evaluations."""
    rows, sends = math.ceil(n / blocks), blocks // 2 + 1 if symmetric else blocks
    body = n * d * bits // 8
    return {"block_bytes": body, "sent_bytes": body * sends, "task_bytes": 2 * rows * d * bits // 8 + rows * rows * min(8, bits // 8), "distances": n * n / (2 if symmetric else 1)}


def phases(run: dict[str, Callable[[], DataFrame]]) -> dict[str, float]:
    """Seconds of each named part, run in order."""
    return {k: timed(f()) for k, f in run.items()}
