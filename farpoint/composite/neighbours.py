"""Pairwise distances, k nearest neighbours and neighbours within range: direct, batched by blocks, fused, and in low precision with check.

Kernels may filter by the norm and inner-product form; every distance that leaves a kernel is summed by differences in feature
order, as Spark's own ``aggregate`` does it, so all forms give the same bits and ties go to the smaller id.
"""

from __future__ import annotations

import time
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from farpoint.model import FeatureFrame
from farpoint.operators.basic import x_max
from farpoint.plans.blocks import LEAST, LOW_D, TILE, Block, Leaves, blocks_for, cut_space, plan_batches, plan_slices, run_owners
from farpoint.quantize.bounds import FloatFormat, depth, distance_bound, gamma, rowwise_bound
from farpoint.session import stage

PAIR = "i long, j long, dist double"


def distance_column(a: Column, b: Column, metric: str = "euclidean") -> Column:
    """Distance of two arrays, summed in feature order."""
    total = lambda f: F.aggregate(F.zip_with(a, b, f), F.lit(0.0), lambda s, v: s + v)
    if metric == "manhattan":
        return total(lambda x, y: F.abs(x - y))
    if metric == "cosine":
        size = lambda v: F.sqrt(F.aggregate(v, F.lit(0.0), lambda s, x: s + x * x))
        return 1 - F.coalesce(F.try_divide(total(lambda x, y: x * y), size(a) * size(b)), F.lit(0.0))
    square = total(lambda x, y: (x - y) * (x - y))
    return square if metric == "sqeuclidean" else F.sqrt(square)


def canonical(x: np.ndarray, y: np.ndarray, a: np.ndarray, b: np.ndarray, metric: str = "euclidean") -> np.ndarray:
    """Distances of the row pairs (a, b), summed in feature order."""
    out = np.zeros(len(a))
    if metric == "cosine":
        nx, ny = np.zeros(len(x)), np.zeros(len(y))
        for k in range(x.shape[1]):
            nx += x[:, k] * x[:, k]
            ny += y[:, k] * y[:, k]
            out += x[a, k] * y[b, k]
        size = np.sqrt(nx)[a] * np.sqrt(ny)[b]
        return 1 - np.divide(out, size, out=np.zeros(len(a)), where=size > 0)
    for k in range(x.shape[1]):
        diff = x[a, k] - y[b, k]
        out += np.abs(diff) if metric == "manhattan" else diff * diff
    return np.sqrt(out) if metric == "euclidean" else out


#: Rows of both sides of a piece of _all_pairs: its sums stay in a core's cache.
PIECE = 64, 256


def _all_pairs(x: np.ndarray, y: np.ndarray, metric: str) -> np.ndarray:
    """canonical() of every row of x with every row of y, piece by piece."""
    out = np.zeros((len(x), len(y)))
    xs, ys, (m, n) = np.ascontiguousarray(x.T), np.ascontiguousarray(y.T), PIECE
    held = np.empty(PIECE)
    for p in range(0, len(x), m):
        for q in range(0, len(y), n):
            total = out[p : p + m, q : q + n]
            part = held[: total.shape[0], : total.shape[1]]
            for u, v in zip(xs[:, p : p + m], ys[:, q : q + n]):
                if metric == "cosine":
                    np.multiply.outer(u, v, out=part)
                else:
                    np.subtract.outer(u, v, out=part)
                    np.abs(part, out=part) if metric == "manhattan" else np.multiply(part, part, out=part)
                total += part
    if metric == "cosine":
        nx, ny = (sum((v * v for v in t), np.zeros(t.shape[1])) for t in (xs, ys))
        size = np.multiply.outer(np.sqrt(nx), np.sqrt(ny))
        return 1 - np.divide(out, size, out=np.zeros_like(out), where=size > 0)
    return np.sqrt(out, out=out) if metric == "euclidean" else out


def _gram(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Squared distances by norms and inner products; in place, so that one tile is all the memory it takes.
    Half precision has no fast product: it is summed in single precision and rounded once, which is within the bounds of a sum in half precision."""
    half = x.dtype == np.float16
    with np.errstate(over="ignore"):
        out = (x.astype(np.float32) @ (y.T.astype(np.float32) * np.float32(-2))).astype(np.float16) if half else x @ (y.T * np.array(-2, y.dtype))
    out += (x * x).sum(1)[:, None]
    out += (y * y).sum(1)
    return out


def centred_squares(x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Squared distances of doubles by _gram around the mean of x, and for each row of x a bound of their difference from what canonical() gives.

    A subtraction errs by eps of its result, an inner product by the depth of its sum times the product of the norms: all of it is in
    proportion to the square of the two centred norms, and centring keeps these small wherever the points lie.
    """
    c = x.mean(0) if len(x) else 0.0
    a, b = x - c, y - c
    norm = lambda m: np.sqrt(np.einsum("ij,ij->i", m, m))
    reach = norm(a) + norm(b).max(initial=0)
    return _gram(a, b), reach * reach * (gamma(3 * x.shape[1] + 16, 2.0**-53) * (1 + 1e-6))


def _pairs_batch(i, j, dist) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(i, pa.int64()), pa.array(j, pa.int64()), pa.array(dist, pa.float64())], names=["i", "j", "dist"])


def pairwise_distance(x: FeatureFrame, metric: str = "sqeuclidean", include_self: bool = False, blocks: int | None = None, y: FeatureFrame | None = None, precision: int = 64, verify: bool = False) -> DataFrame:
    """(i, j, dist) of all ordered pairs. Quadratic output, of which a task holds one tile. blocks: by default planned from rows, width and task memory."""
    if precision != 64 or verify:
        raise ValueError("raw distances are full-precision floats: checking them would be computing them")
    apart = y is not None

    def kernel(own: Block, partners: Iterator[Block]) -> Iterator[pa.RecordBatch]:
        for other in partners:
            for u in own.tiles():
                for v in other.tiles():
                    i, j, dist = np.repeat(u.ids, len(v.ids)), np.tile(v.ids, len(u.ids)), _all_pairs(u.stored, v.stored, metric).ravel()
                    keep = slice(None) if include_self or apart else i != j
                    yield _pairs_batch(i[keep], j[keep], dist[keep])

    blocks, slices = _batches(x, blocks, y)
    return run_owners(x, blocks, kernel, PAIR, y=y, slices=slices)


def _best(i: np.ndarray, j: np.ndarray, dist: np.ndarray, k: int, ties: bool = False) -> np.ndarray:
    """Positions of the k nearest of each i, by (dist, j); with ties also of all others as near as the k-th."""
    order = np.lexsort((j, dist, i))
    s = i[order]
    first = np.searchsorted(s, s)
    keep = np.arange(len(s)) - first < k
    if ties and len(s):
        last = np.searchsorted(s, s, "right") - 1
        keep |= dist[order] <= dist[order][np.minimum(first + k - 1, last)]
    return order[keep]


class _Nearest:
    """Running k nearest of n rows by (distance, id); reach is each row's k-th distance so far, infinite while there are fewer."""

    def __init__(self, n: int, k: int, ties: bool = False):
        self.n, self.k, self.ties = n, k, ties
        self.row, self.id, self.dist = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
        self.reach = np.full(n, np.inf)

    def add(self, row: np.ndarray, ids: np.ndarray, dist: np.ndarray) -> None:
        row, ids, dist = np.concatenate((self.row, row)), np.concatenate((self.id, ids)), np.concatenate((self.dist, dist))
        keep = _best(row, ids, dist, self.k, self.ties)
        self.row, self.id, self.dist = row[keep], ids[keep], dist[keep]
        last = np.full(self.n, np.inf)
        last[self.row] = self.dist  # rows are sorted by distance: the last entry stays
        self.reach = np.where(np.bincount(self.row, minlength=self.n) >= self.k, last, np.inf)

    def candidates(self, near: np.ndarray, slack: np.ndarray, square: bool, rows=slice(None)) -> tuple[np.ndarray, np.ndarray]:
        """Pairs of a tile (of some rows) that may be among the k nearest: within the reach, or within the tile's own k-th value while there is none."""
        cut = self.reach[rows] ** 2 if square else self.reach[rows].copy()
        fresh = np.flatnonzero(~np.isfinite(cut))
        if len(fresh):
            at = min(self.k, near.shape[1]) - 1
            cut[fresh] = np.partition(near[fresh], at, axis=1)[:, at]
        a, b = np.nonzero(near <= (cut + 2 * slack)[:, None])
        real = np.isfinite(near[a, b])
        return a[real], b[real]


def _meet(u: Block, v: Block, same: bool, metric: str) -> tuple[np.ndarray, np.ndarray]:
    """A tile of distances (squared for euclidean) with a bound of its rows' errors; a row and itself are infinitely far."""
    near, slack = centred_squares(u.stored, v.stored) if metric == "euclidean" else (_all_pairs(u.stored, v.stored, metric), np.zeros(len(u.ids)))
    if same:
        near[u.ids[:, None] == v.ids] = np.inf
    return near, slack


def _ranked(edges: DataFrame, k: int, ties: bool = False) -> DataFrame:
    w = Window.partitionBy("i")
    return edges.withColumn("rank", F.rank().over(w.orderBy("dist")) if ties else F.row_number().over(w.orderBy("dist", "j"))).where(F.col("rank") <= k).select("i", "j", "rank", "dist")


def _batches(x: FeatureFrame, blocks: int | None, y: FeatureFrame | None = None, bits: int = 64, symmetric: bool = False) -> tuple[int, int]:
    """(blocks, slices): planned from rows, width, format and task memory; a given number of blocks overrides."""
    b = blocks or blocks_for(x, y, bits)
    return b, plan_slices(b, x.df.sparkSession.sparkContext.defaultParallelism, symmetric) if b > 1 else 1


def knn(x: FeatureFrame, k: int, y: FeatureFrame | None = None, mode: str = "fused", blocks: int | None = None, metric: str = "euclidean", precision: int = 64, verify: bool = True, clock=None, ties: bool = False) -> DataFrame:
    """(i, j, rank, dist): the k nearest rows of y (default: the other rows of x) of each row of x, ties to the smaller id.

    'direct' and 'concat': the exact distances of every pair, tile by tile, and a top-k over these tiles in the same task ('direct' plans its blocks whatever is
    given). 'fused': inner products settle most pairs and only the rest is summed. In all of them n * k rows leave a subtask. precision 32 or 16 keeps, in low precision, all that may be among the
    k nearest and ranks these exactly; verify=False trusts the low-precision order. blocks: by default planned from rows, width and task memory.
    ties: all rows as near as the k-th are kept, and rank is that of their distance. With few features blocks are boxes in space, sorted into leaves, and leaves out of a row's reach are passed
    over; there low precision is checked in the task that met the pair, as full rows are at hand.
    """
    if ties and (mode != "fused" or precision != 64):
        raise ValueError("ties are kept by the fused form in full precision")
    if mode in ("direct", "concat"):
        return _concatenated_knn(x, k, y, blocks if mode == "concat" else None, metric)
    apart, square = y is not None, metric == "euclidean"
    low = square and x.d <= LOW_D
    if precision != 64 and not (low and verify):
        return _quantized_knn(x, k, y, blocks, precision, verify)
    if low:
        return _knn_in_space(x, k, y, blocks, precision, clock, ties)
    blocks, slices = _batches(x, blocks, y)

    def kernel(own: Block, partners: Iterator[Block]) -> Iterator[pa.RecordBatch]:
        tiles = [(u, _Nearest(len(u.ids), k, ties)) for u in own.tiles()]
        for other in partners:
            for v in other.tiles():
                for u, best in tiles:
                    near, slack = _meet(u, v, not apart and other.number == own.number, metric)
                    a, b = best.candidates(near, slack, square)
                    best.add(a, v.ids[b], canonical(u.stored, v.stored, a, b, metric))
        yield from _neighbours(tiles)

    found = run_owners(x, blocks, kernel, NEIGHBOUR, y=y, clock=clock, slices=slices)
    return found if slices == 1 and not ties else _ranked(found, k, ties)


NEIGHBOUR = "i long, j long, rank int, dist double"


def _neighbours(tiles: list[tuple[Block, _Nearest]], factor: float = 1.0) -> Iterator[pa.RecordBatch]:
    for u, best in tiles:
        place = np.arange(len(best.row)) - np.searchsorted(best.row, best.row) + 1
        yield pa.RecordBatch.from_arrays([pa.array(u.ids[best.row]), pa.array(best.id), pa.array(place, pa.int32()), pa.array(best.dist / factor)], names=["i", "j", "rank", "dist"])


#: Rows of a leaf of k neighbours; blocks a task in space, so that tasks even out.
NEAR_LEAF, NEAR_BLOCKS = 64, 4


def _knn_in_space(x: FeatureFrame, k: int, y: FeatureFrame | None, blocks: int | None, precision: int, clock, ties: bool) -> DataFrame:
    """knn of few features: a leaf meets partner leaves from the nearest on, and of it only rows whose reach they are in."""
    apart, tasks = y is not None, x.df.sparkSession.sparkContext.defaultParallelism
    if not blocks:
        n = max(x.count(), y.count() if apart else 0)
        blocks = max(plan_batches(n, x.d, tasks=tasks), min(NEAR_BLOCKS * tasks, n // LEAST)) if n > TILE else 1
    slices = plan_slices(blocks, tasks) if blocks > 1 else 1
    cell = cut_space(y if apart else x, blocks) if blocks > 1 else None
    top = max(x_max(x), x_max(y) if apart else 0.0) if precision != 64 else 0.0
    factor = 2.0 ** -int(np.ceil(np.log2(top))) if top > 0 else 1.0  # no value exceeds 1 in the stored form

    def within_reach(part: Block, best: _Nearest, rows: np.ndarray, v: Block, light: Block | None, same: bool) -> tuple[np.ndarray, np.ndarray]:
        """Pairs of some rows of a leaf and partner rows that may be among the k nearest."""
        if light is None:
            return best.candidates(*_meet(part, v, same, "euclidean"), True, rows)
        low = _LowPrecision(part.lowered(precision), light, 32)
        if same:
            low.square[part.ids[:, None] == v.ids] = np.inf
        cut = best.reach[rows]
        fresh = np.flatnonzero(~np.isfinite(cut))
        if len(fresh):
            at = min(k, len(v.ids)) - 1
            nearest = np.partition(low.square[fresh], at, axis=1)[:, at].astype(np.float64)
            cut[fresh] = np.sqrt(np.maximum(nearest + low.row_err[fresh], 0)) + low.row_left[fresh]
        a, b = low.not_above(cut)
        real = np.isfinite(low.square[a, b])
        return a[real], b[real]

    def kernel(own: Block, partners: Iterator[Block]) -> Iterator[pa.RecordBatch]:
        mine = Leaves(own, packed=NEAR_LEAF)
        tiles = [(u := mine.rows([at]), _Nearest(len(u.ids), k, ties)) for at in range(len(mine.parts))]
        for other in partners:
            same, theirs = not apart and other.number == own.number, Leaves(other, packed=NEAR_LEAF)
            light = other.lowered(precision) if precision != 64 else None
            reach = np.array([best.reach.max() for _, best in tiles])
            far = mine.nearest(other.stored.min(0), other.stored.max(0))
            for at in np.flatnonzero(far <= reach * reach * (1 + 1e-9)):
                u, best = tiles[at]
                near = theirs.nearest(mine.lo[at], mine.hi[at])
                order = np.argsort(near, kind="stable")
                near, done, size = near[order], 0, max(2 * k, 4 * NEAR_LEAF)
                while done < len(order):
                    top = best.reach.max()
                    many = min(-(-size // NEAR_LEAF), int(np.searchsorted(near[done:], top * top * (1 + 1e-9), "right")))
                    if not many:
                        break
                    which, rows = order[done : done + many], np.arange(len(u.ids))
                    done, size = done + many, 4 * TILE
                    if np.isfinite(best.reach).any():
                        need = theirs.nearest(u.stored, u.stored, which) <= (best.reach * best.reach * (1 + 1e-9))[:, None]
                        which, rows = which[need.any(0)], np.flatnonzero(need.any(1))
                        if not len(rows):
                            continue
                    part, v = u.take(rows), theirs.rows(which)
                    a, b = within_reach(part, best, rows, v, light and theirs.rows(which, light), same)
                    if len(a):
                        best.add(rows[a], v.ids[b], canonical(part.stored, v.stored, a, b))
        yield from _neighbours(tiles, factor)

    found = run_owners(x, blocks, kernel, NEIGHBOUR, factor=factor, y=y, clock=clock, slices=slices, cell=cell, leaf=NEAR_LEAF)
    return found if slices == 1 and not ties else _ranked(found, k, ties)


def _concatenated_knn(x: FeatureFrame, k: int, y: FeatureFrame | None, blocks: int | None, metric: str) -> DataFrame:
    apart = y is not None

    def tiles_of(mine: list[Block], own: Block, partners: Iterator[Block]) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
        """All distances: the place of an own tile, the partner rows' ids and the tile of distances, a row and itself infinitely far."""
        for other in partners:
            for v in other.tiles():
                for at, u in enumerate(mine):
                    dist = _all_pairs(u.stored, v.stored, metric)
                    if not apart and other.number == own.number:
                        dist[u.ids[:, None] == v.ids] = np.inf
                    yield at, v.ids, dist

    def kernel(own: Block, partners: Iterator[Block]) -> Iterator[pa.RecordBatch]:
        mine = own.tiles()
        best = [_Nearest(len(u.ids), k) for u in mine]
        for at, ids, dist in tiles_of(mine, own, partners):
            a, b = best[at].candidates(dist, np.zeros(len(dist)), False)
            best[at].add(a, ids[b], dist[a, b])
        for u, found in zip(mine, best):
            yield _pairs_batch(u.ids[found.row], found.id, found.dist)

    blocks, slices = _batches(x, blocks, y)
    return _ranked(run_owners(x, blocks, kernel, PAIR, y=y, slices=slices), k)


def knn_symmetric(x: FeatureFrame, k: int, blocks: int | None = None) -> DataFrame:
    """Fused, each pair of blocks met once: the own block's running k best and each partner's k best leave the kernel and are merged."""
    blocks, slices = _batches(x, blocks, symmetric=True)

    def kernel(own: Block, partners: Iterator[Block]) -> Iterator[pa.RecordBatch]:
        tiles = [(u, _Nearest(len(u.ids), k)) for u in own.tiles()]
        for other in partners:
            same = other.number == own.number
            for v in other.tiles():
                back = _Nearest(len(v.ids), k)
                for u, best in tiles:
                    near, slack = _meet(u, v, same, "euclidean")
                    a, b = best.candidates(near, slack, True)
                    best.add(a, v.ids[b], canonical(u.stored, v.stored, a, b))
                    if not same:
                        b, a = back.candidates(near.T, np.full(len(v.ids), slack.max(initial=0)), True)
                        back.add(b, u.ids[a], canonical(v.stored, u.stored, b, a))
                yield _pairs_batch(v.ids[back.row], back.id, back.dist)
        for u, best in tiles:
            yield _pairs_batch(u.ids[best.row], best.id, best.dist)

    return _ranked(run_owners(x, blocks, kernel, PAIR, symmetric=True, slices=slices), k)


class _LowPrecision:
    """Squared distances of two blocks in the compute format, with what bounds their errors: arithmetic by the rows' norms, storage by
    the rows' residuals and the triangle inequality. Pairs are sorted out by one comparison per row; the exact interval is worked out
    only for those that remain."""

    def __init__(self, own: Block, other: Block, compute: int):
        kind = {64: np.float64, 32: np.float32, 16: np.float16}[compute]
        a, b = own.stored.astype(kind), other.stored.astype(kind)
        self.loose = (own.stored.shape[1] + 8) * 2.0**-52  # rounding of the exact distance that decides
        self.square = _gram(a, b)
        self.norm_a, self.norm_b = (np.sqrt(np.einsum("ij,ij->i", s, s, dtype=np.float64)) for s in (own.stored.astype(np.float32), other.stored.astype(np.float32)))
        self.left_a, self.left_b = own.residual * (1 + 1e-9), other.residual * (1 + 1e-9)
        d, f = own.stored.shape[1], FloatFormat(compute)
        self.rate, self.floor = gamma(d + 3, f.eps) * (1 + 1e-6), (8 * d + 8) * f.tiny
        # Largest errors of a row of the own block with any row of the other.
        self.row_err = (self.norm_a + self.norm_b.max(initial=0)) ** 2 * self.rate + self.floor
        self.row_left = self.left_a + self.left_b.max(initial=0)

    def not_above(self, limit: np.ndarray | float, among: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """Pairs (a, b), of a mask of them, that may be at a true distance of at most limit (one for all rows, or one each)."""
        reach = (limit + self.row_left) ** 2 * (1 + 1e-9) + self.row_err
        with np.errstate(over="ignore"):
            cut = np.nextafter(reach.astype(self.square.dtype), np.inf, dtype=self.square.dtype)
        near = self.square <= cut[:, None]
        return np.nonzero(near if among is None else near & among)

    def surely_within(self, limit: float) -> np.ndarray:
        """Pairs whose true distance is at most limit whatever the errors of their row."""
        reach = np.maximum(limit * (1 - self.loose) - self.row_left, 0) ** 2 * (1 - 1e-9) - self.row_err
        kind = self.square.dtype
        cut = np.nextafter(np.minimum(reach, float(np.finfo(kind).max)).astype(kind), -np.inf, dtype=kind)
        return (self.square <= cut[:, None]) & (reach > 0)[:, None]

    def interval(self, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(surely not above, surely not below) the true distances of the pairs."""
        square = self.square[a, b].astype(np.float64)
        err = (self.norm_a[a] + self.norm_b[b]) ** 2 * self.rate + self.floor
        apart = self.left_a[a] + self.left_b[b]
        return (np.sqrt(np.maximum(square - err, 0)) - apart) * (1 - self.loose), (np.sqrt(np.maximum(square + err, 0)) + apart) * (1 + self.loose)


def exact_pairs(x: FeatureFrame, pairs: DataFrame, y: FeatureFrame | None = None, metric: str = "euclidean") -> DataFrame:
    """Distances of the listed pairs only, from the full-precision rows: two equi-joins."""
    left = x.pack().df.select(F.col("id").alias("i"), F.col("x").alias("u"))
    right = (y or x).pack().df.select(F.col("id").alias("j"), F.col("x").alias("v"))
    return pairs.join(left, "i").join(right, "j").select("i", "j", distance_column(F.col("u"), F.col("v"), metric).alias("dist"))


def _quantized_knn(x: FeatureFrame, k: int, y: FeatureFrame | None, blocks: int | None, precision: int, verify: bool) -> DataFrame:
    band = near_band(x, k, y, blocks, precision, verify)
    return _ranked(exact_pairs(x, band.select("i", "j"), y) if verify else band, k)


def near_band(x: FeatureFrame, k: int, y: FeatureFrame | None = None, blocks: int | None = None, precision: int = 32, verify: bool = True) -> DataFrame:
    """(i, j, dist): with verify all pairs that may be among i's k nearest by what their low-precision distances (dist: the upper ends) leave open, for an
    exact form to rank; every pair is met. Without it the k nearest by these distances."""
    apart = y is not None
    top = max(x_max(x), x_max(y) if y is not None else 0.0)
    factor = 2.0 ** -int(np.ceil(np.log2(top))) if top > 0 else 1.0  # no value exceeds 1 in the stored form
    blocks, slices = _batches(x, blocks, y, precision)

    def kernel(own: Block, partners: Iterator[Block]) -> Iterator[pa.RecordBatch]:
        # Of every tile: candidates (row, id, lower end, upper end) and each row's k-th smallest upper end so far.
        tiles = [[u, (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0), np.zeros(0)), np.full(len(u.ids), np.inf)] for u in own.tiles()]
        for other in partners:
            for v in other.tiles():
                for t in tiles:
                    u, held, reach = t
                    n = len(u.ids)
                    low = _LowPrecision(u, v, 32)
                    if not apart and other.number == own.number:
                        low.square[u.ids[:, None] == v.ids] = np.inf
                    cut = reach.copy()
                    fresh = np.flatnonzero(~np.isfinite(cut))
                    if len(fresh):
                        at = min(k, len(v.ids)) - 1
                        nearest = np.partition(low.square[fresh], at, axis=1)[:, at].astype(np.float64)
                        # not below the k-th true distance, if checked
                        cut[fresh] = np.sqrt(np.maximum(nearest + low.row_err[fresh], 0)) + low.row_left[fresh] if verify else np.sqrt(np.maximum(nearest, 0))
                    a, b = low.not_above(cut)
                    real = np.isfinite(low.square[a, b])
                    a, b = a[real], b[real]
                    ends = low.interval(a, b) if verify else (np.sqrt(np.maximum(low.square[a, b].astype(np.float64), 0)),) * 2
                    i, j, lo, hi = (np.concatenate(p) for p in zip(held, (a, v.ids[b], *ends)))
                    best = _best(i, j, hi, k)
                    last = np.full(n, -np.inf)
                    np.maximum.at(last, i[best], hi[best])
                    reach = np.where(np.bincount(i[best], minlength=n) >= k, last, np.inf)
                    # Whoever's lower end is above the k-th upper end is out.
                    keep = lo <= reach[i] if verify else best
                    t[1:] = (i[keep], j[keep], lo[keep], hi[keep]), reach
        for u, (i, j, _, hi), _ in tiles:
            yield _pairs_batch(u.ids[i], j, hi / factor)

    return run_owners(x, blocks, kernel, PAIR, bits=precision, y=y, factor=factor, slices=slices)


def nwr(x: FeatureFrame, phi: float, squared: bool = False, precision: int = 64, compute: int | None = None, bound: str = "residual", verify: bool = True, blocks: int | None = None, symmetric: bool = True, scale: str | None = "pow2", include_self: bool = False, with_flag: bool = False, tally: bool = False, clock=None, phases: dict | None = None) -> DataFrame:
    """(i, j) of all ordered pairs at a distance of at most phi (squared: phi is a squared distance).

    In low precision each pair is surely in, surely out, or ambiguous; only ambiguous pairs are computed again from full-precision rows.
    bound: 'residual' and 'rowwise' for each pair, 'sound' and 'paper' one number for all. verify=False trusts the low precision.
    scale 'pow2' multiplies rows and phi by one power of two so that no value exceeds 1. with_flag gives (i, j, certain) before the second pass.
    The kernels run once: their pairs are written to the shared folder, where certain and ambiguous ones are read apart. 'sound' and 'paper' leave
    so many pairs open that writing them would be writing all: there full rows are sent, and open pairs are settled in the task that met them.
    tally: (met, open), how many pairs each tile keeps and how many of them are ambiguous, in place of the pairs. phases: accumulators
    'distance' and 'check' that get the seconds of low-precision distances and of bounding them.
    """
    d = x.d
    limit = phi**0.5 if squared else phi
    top = x_max(x) if precision != 64 else 1.0
    factor = 2.0 ** -int(np.ceil(np.log2(top))) if precision != 64 and scale == "pow2" and top > 0 else 1.0
    compute = compute or (32 if precision == 16 and bound in ("residual", "rowwise") else precision)
    reach = top * factor
    if precision == 16 and 4 * d * reach**2 > FloatFormat(16).top and compute == 16:
        raise ValueError("squared norms may pass the largest 16-bit number; use scale='pow2' or compute=32")
    err = distance_bound(d, reach, compute if compute != 64 else precision, bound, "sequential") if bound in ("paper", "sound") and precision != 64 else 0.0
    if bound == "sound" and precision != compute:  # the cast is to the storage format
        err += 4 * d * reach**2 * gamma(2, FloatFormat(precision).eps)
    goal = limit * factor

    one_number = bound in ("paper", "sound") and precision != 64 and verify
    inline = one_number and not with_flag and not tally
    blocks, slices = _batches(x, blocks, None, 64 if inline else precision, symmetric)

    def masks(low: _LowPrecision) -> tuple[np.ndarray, np.ndarray]:
        """Tiles of the pairs that one error for all surely has within, and of those that it leaves open."""
        square = low.square.astype(np.float64)
        e = err + low.loose * square
        sure = square <= goal * goal - e
        return sure, (square <= goal * goal + e) & ~sure

    def settled(u: Block, v: Block, low: _LowPrecision) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Pairs of two tiles of full rows: what the low precision leaves open is decided by the exact form here."""
        inside, left = masks(low)
        many = np.count_nonzero(left)
        if 64 * many > left.size:
            for _, exact in _within(u, v, [goal], False):
                inside |= left & exact
        elif many:
            p, q = np.nonzero(left)
            inside[p, q] = canonical(u.stored, v.stored, p, q) <= goal
        a, b = np.nonzero(inside)
        return a, b, np.ones(len(a), bool)

    def decide(u: Block, v: Block) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Pairs (a, b) of two tiles that are within, or may be, and whether they surely are."""
        began = time.perf_counter()
        if precision == 64:
            for _, inside in _within(u, v, [goal], False):
                a, b = np.nonzero(inside)
            return a, b, np.ones(len(a), bool)
        low = _LowPrecision(u.lowered(precision), v.lowered(precision), compute) if inline else _LowPrecision(u, v, compute)
        met = time.perf_counter()
        a, b, sure = settled(u, v, low) if inline else bounded(u, v, low)
        if phases is not None:
            phases["distance"].add(met - began)
            phases["check"].add(time.perf_counter() - met)
        return a, b, sure

    def bounded(u: Block, v: Block, low: _LowPrecision) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        if not verify:
            a, b = np.nonzero(low.square <= np.array(goal * goal, low.square.dtype))
            return a, b, np.ones(len(a), bool)
        if bound == "residual":
            # One comparison a row settles all pairs but those of a narrow band, whose own intervals are worked out.
            inside = low.surely_within(goal)
            near, far = low.not_above(goal, ~inside)
            lower, upper = low.interval(near, far)
            keep = lower <= goal
            a, b = np.nonzero(inside)
            return np.concatenate((a, near[keep])), np.concatenate((b, far[keep])), np.concatenate((np.ones(len(a), bool), upper[keep] <= goal))
        if one_number:
            inside, left = masks(low)
            a, b = np.nonzero(inside | left)
            return a, b, inside[a, b]
        cast, floor = gamma(2, FloatFormat(precision).eps), (8 * d * reach + 4 * d) * FloatFormat(precision).tiny
        na, nb = low.norm_a + u.residual, low.norm_b + v.residual
        top_e = rowwise_bound(na, nb.max(initial=0)[None], d, reach, compute, cast=False)[:, 0] + (na + nb.max(initial=0)) ** 2 * cast + floor
        with np.errstate(over="ignore"):
            cut = np.nextafter((goal * goal * (1 + 1e-9) + top_e).astype(low.square.dtype), np.inf, dtype=low.square.dtype)
        a, b = np.nonzero(low.square <= cut[:, None])
        square = low.square[a, b].astype(np.float64)
        m = 1 + depth(d, "sequential") + 2
        g = (gamma(m, FloatFormat(compute).eps) + gamma(m, 2.0**-53)) * (1 + 1e-9)
        e = (na[a] + nb[b]) ** 2 * (g + cast) + (8 * d * reach + 4 * d + 3) * FloatFormat(compute).tiny + floor
        e = e + low.loose * square
        keep = square <= goal * goal + e
        return a[keep], b[keep], square[keep] <= goal * goal - e[keep]

    def kernel(own: Block, partners: Iterator[Block]) -> Iterator[pa.RecordBatch]:
        mine = own.tiles()
        for other in partners:
            same = other.number == own.number
            for v in other.tiles():
                for u in mine:
                    a, b, sure = decide(u, v)
                    i, j = u.ids[a], v.ids[b]
                    if same and not include_self:
                        keep = i != j
                        i, j, sure = i[keep], j[keep], sure[keep]
                    if tally:
                        both = 2 if symmetric and not same else 1
                        yield pa.RecordBatch.from_arrays([pa.array([both * len(i)]), pa.array([both * int(np.count_nonzero(~sure))])], names=["met", "open"])
                        continue
                    if symmetric and not same:
                        i, j, sure = np.concatenate((i, j)), np.concatenate((j, i)), np.concatenate((sure, sure))
                    if len(i):
                        yield pa.RecordBatch.from_arrays([pa.array(i, pa.int64()), pa.array(j, pa.int64()), pa.array(sure)], names=["i", "j", "certain"])

    schema = "met long, open long" if tally else "i long, j long, certain boolean"
    found = run_owners(x, blocks, kernel, schema, bits=64 if inline else precision, symmetric=symmetric, factor=factor, clock=clock, slices=slices)
    if with_flag or tally:
        return found
    if precision == 64 or not verify or inline:
        return found.select("i", "j")
    found = stage(found, "pairs")
    again = exact_pairs(x, found.where(~F.col("certain")).select("i", "j")).where(F.col("dist") <= limit).select("i", "j")
    return found.where("certain").select("i", "j").unionByName(again)


def _within(u: Block, v: Block, radii: list[float], same: bool, width: int | None = None) -> Iterator[tuple[int, np.ndarray]]:
    """For each radius its number and a boolean tile of the pairs within it; only pairs that the inner-product form leaves open are summed by differences."""
    a, b = u.stored[:, :width], v.stored[:, :width]
    square, slack = centred_squares(a, b)
    if same:
        square[u.ids[:, None] == v.ids] = np.inf
    for k, r in enumerate(radii):
        inside = square <= (r * r - slack)[:, None]
        p, q = np.nonzero((square <= (r * r + slack)[:, None]) & ~inside)
        inside[p, q] = canonical(a, b, p, q) <= r
        yield k, inside


def nwr_flips(x: FeatureFrame, phi: float, precision: int = 16, compute: int = 16, blocks: int | None = None) -> DataFrame:
    """(missing, extra), one row: how many pairs nwr(verify=False) in a low precision lacks of the exact ones, and has beside them.
    Both forms decide the same tile in one task and only the counts leave it."""
    top = x_max(x)
    factor = 2.0 ** -int(np.ceil(np.log2(top))) if top > 0 else 1.0
    goal = phi * factor
    blocks, slices = _batches(x, blocks, symmetric=True)

    def kernel(own: Block, partners: Iterator[Block]) -> Iterator[pa.RecordBatch]:
        mine, missing, extra = own.tiles(), 0, 0
        for other in partners:
            same = other.number == own.number
            for v in other.tiles():
                for u in mine:
                    square = _LowPrecision(u.lowered(precision), v.lowered(precision), compute).square
                    rough = square <= np.array(goal * goal, square.dtype)
                    if same:
                        rough[u.ids[:, None] == v.ids] = False
                    for _, exact in _within(u, v, [goal], same):
                        missing += (1 if same else 2) * int(np.count_nonzero(exact & ~rough))
                        extra += (1 if same else 2) * int(np.count_nonzero(rough & ~exact))
        yield pa.RecordBatch.from_arrays([pa.array([missing]), pa.array([extra])], names=["missing", "extra"])

    found = run_owners(x, blocks, kernel, "missing long, extra long", symmetric=True, factor=factor, slices=slices)
    return found.agg(*(F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in ("missing", "extra")))


def _meetings(own: Block, partners: Iterator[Block], radii: list[float], width: int) -> tuple[list[Block], Iterator[tuple[int, Block, bool, np.ndarray | None]]]:
    """The own rows in tiles, and what these meet: (place of a tile, partner rows, whether they are of the own block, None if pairs are to be compared).
    With few features tiles are leaves. Leaves beyond all radii are passed over, and of those whose box lies wholly within some radii and beyond all others
    no pair is compared: for these the last entry tells within which radii they are."""
    if width > LOW_D:
        tiles = own.tiles()
        return tiles, ((at, v, other.number == own.number, None) for other in partners for v in other.tiles() for at in range(len(tiles)))
    mine, squares = Leaves(own, width), np.array([r * r for r in radii])
    pieces = lambda which, size: np.split(which, np.flatnonzero(np.diff(np.cumsum(size[which]) // (2 * TILE))) + 1) if len(which) else []

    def met() -> Iterator[tuple[int, Block, bool, np.ndarray | None]]:
        for other in partners:
            same = other.number == own.number
            theirs = Leaves(other, width)
            for at in range(len(mine.parts)):
                near, far = theirs.nearest(mine.lo[at], mine.hi[at]), theirs.farthest(mine.lo[at], mine.hi[at])
                whole = far[:, None] <= squares
                edge = (~(near[:, None] > squares) & ~whole).any(1)
                for group in pieces(np.flatnonzero(edge), theirs.size):
                    yield at, theirs.rows(group), same, None
                settled = np.flatnonzero(~edge & whole.any(1))
                for flags in np.unique(whole[settled], axis=0):
                    for group in pieces(settled[(whole[settled] == flags).all(1)], theirs.size):
                        yield at, theirs.rows(group), same, flags

    return [mine.rows([at]) for at in range(len(mine.parts))], met()


#: Partner rows that an own leaf meets at a time; blocks a task where sums are taken.
WIDE, SUM_BLOCKS = 1024, 3


def _plan_sums(x: FeatureFrame, blocks: int | None, width: int) -> tuple[int, dict]:
    """(slices, how run_owners deals): with few features blocks are boxes in space, put leaf by leaf."""
    if width > LOW_D:
        blocks, slices = _batches(x, blocks)
        return slices, {"b": blocks, "slices": slices}
    tasks = x.df.sparkSession.sparkContext.defaultParallelism
    if not blocks:
        n = x.count()
        blocks = max(plan_batches(n, x.d, tasks=tasks), min(SUM_BLOCKS * tasks, n // LEAST)) if n > TILE else 1
    slices = plan_slices(blocks, tasks) if blocks > 1 else 1
    return slices, {"b": blocks, "slices": slices, "cell": cut_space(x, blocks, width) if blocks > 1 else None, "leaf": NEAR_LEAF, "width": width}


def _digits(columns: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(digits, weights): whole numbers as digits @ weights, digits at most 2^11 in size: in single precision WIDE of them have an exact sum."""
    digits, weights = [], []
    for at, c in enumerate(columns.T):
        size = 1.0
        while size == 1.0 or c.any():
            q = np.rint(c / 4096)
            digits.append(c - 4096 * q)
            weights.append(np.where(np.arange(columns.shape[1]) == at, size, 0.0))
            c, size = q, size * 4096
    return np.stack(digits, 1).astype(np.float32), np.array(weights)


def _leaf_sums(own: Block, partners: Iterator[Block], radii: list[float], width: int, columns, apart) -> np.ndarray:
    """(radius, own row, column): sums of a partner's columns over its rows within each radius of an own row, itself included.
    columns(block) gives an array (row, column) for each radius, whole numbers whose sums are exact in any order, or None. Where it gives None or a row is not finite,
    apart(rows, u, v, same, flags) is told what _meetings has. Leaves wholly within a radius come in by their sums, leaves beyond by nothing, and a pair of leaves is compared
    at the other radii only: by products in 32 bit around the own leaf's mean, whose bound leaves few pairs to be summed by differences."""
    mine, squares = Leaves(own, width, packed=NEAR_LEAF), np.array([r * r for r in radii])
    rows, bits, total = own.stored[:, :width], 1 << np.arange(len(radii)), None
    finite = bool(np.isfinite(rows).all())
    # The largest radius is about 1 in the compute format. Casts, products and the sum of width + 2 terms err by the square of both norms.
    unit = 2.0 ** -np.ceil(np.log2(max(max(radii), 1e-300)))
    rate, floor = gamma(width + 16, 2.0**-24) * (1 + 1e-6), 1e-36
    one = lambda v, to: np.nextafter(np.float32(v), np.float32(to))
    place = np.argsort(own.ids, kind="stable")
    for other in partners:
        each = columns(other) if finite and np.isfinite(other.stored[:, :width]).all() else None
        if each is None:
            tiles, met = _meetings(own, iter([other]), radii, width)
            at_rows = [place[np.searchsorted(own.ids, u.ids, sorter=place)] for u in tiles]
            for at, v, same, flags in met:
                apart(at_rows[at], tiles[at], v, same, flags)
            continue
        if total is None:
            total = np.zeros((len(radii), len(rows), each[0].shape[1]))
        theirs = Leaves(other, width, packed=NEAR_LEAF)
        sums = [np.add.reduceat(e, np.arange(0, len(other.ids), NEAR_LEAF)) for e in each]
        theirs_t, digits = np.ascontiguousarray(other.stored[:, :width].T) * unit, [_digits(e) for e in each]
        for at, part in enumerate(mine.parts):
            near, far = theirs.nearest(mine.lo[at], mine.hi[at])[:, None], theirs.farthest(mine.lo[at], mine.hi[at])[:, None]
            whole, own_rows = far <= squares, slice(part[0], part[-1] + 1)
            for k in np.flatnonzero(whole.any(0)):
                total[k, own_rows] += sums[k][whole[:, k]].sum(0)
            open_ = ((near <= squares) & ~whole) @ bits
            if not open_.any():
                continue
            u = rows[own_rows] * unit
            c = u.mean(0)
            u = u - c
            square_u = np.einsum("ij,ij->i", u, u)
            left, reach = np.column_stack((-2 * u, square_u, np.ones(len(u)))).astype(np.float32), np.sqrt(square_u.max())
            for kind in np.unique(open_[open_ > 0]):
                leaves = np.flatnonzero(open_ == kind)
                for first in range(0, len(leaves), WIDE // NEAR_LEAF):
                    to = (leaves[first : first + WIDE // NEAR_LEAF, None] * NEAR_LEAF + np.arange(NEAR_LEAF)).ravel()
                    to = to if to[-1] < len(other.ids) else to[to < len(other.ids)]
                    right = np.empty((width + 2, len(to)), np.float32)
                    v = np.take(theirs_t, to, 1)
                    v -= c[:, None]
                    square_v = np.einsum("ij,ij->j", v, v)
                    right[:width], right[width], right[width + 1] = v, 1, square_v
                    most = (reach + np.sqrt(square_v.max())) ** 2
                    near_by = most < 1e30
                    square = left @ right if near_by else None
                    for k in np.flatnonzero(kind & bits):
                        if near_by:
                            cut, slack = squares[k] * unit * unit, most * rate + floor
                            inside, surely = square <= one(cut + slack, np.inf), square <= one(cut - slack, -np.inf)
                            if np.count_nonzero(inside) != np.count_nonzero(surely):
                                p, q = np.divmod(np.flatnonzero(inside ^ surely), len(to))
                                inside[p, q] = canonical(rows, other.stored[:, :width], p + part[0], to[q]) <= radii[k]
                        else:
                            inside = _all_pairs(rows[own_rows], other.stored[to, :width], "euclidean") <= radii[k]
                        numbers, weights = digits[k]
                        total[k, own_rows] += (inside.astype(np.float32) @ np.take(numbers, to, 0)).astype(np.float64) @ weights
    return total


def nwr_counts(x: FeatureFrame, radii: list[float], blocks: int | None = None, weighted: bool = False) -> DataFrame:
    """(i, phi, n): how many other rows lie within each radius, rows without any included. Counts leave the kernels, not pairs.
    weighted: the last feature of x takes no part in distances; it is how many equal rows a row stands for, and all but one of a row's own are others."""
    width = x.d - 1 if weighted else x.d
    slices, plan = _plan_sums(x, blocks, width)
    many = lambda v: v.stored[:, width] if weighted else np.ones(len(v.ids))

    def kernel(own: Block, partners: Iterator[Block]) -> Iterator[pa.RecordBatch]:
        total, itself = np.zeros((len(own.ids), len(radii))), [0]

        def add(rows: np.ndarray, u: Block, v: Block, same: bool, flags: np.ndarray | None) -> None:
            # A row is not its own neighbour.
            if flags is not None:
                total[rows] += flags * (many(v).sum() - (np.isin(u.ids, v.ids) if same else np.zeros(len(u.ids), bool)))[:, None]
                return
            for k, inside in _within(u, v, radii, False, width):
                p, q = np.nonzero(inside & (u.ids[:, None] == v.ids)) if same else (np.zeros(0, int),) * 2
                total[rows, k] += inside @ many(v)
                total[rows[p], k] -= 1

        def columns(other: Block) -> list[np.ndarray]:
            itself[0] |= other.number == own.number
            return [many(other)[:, None]] * len(radii)

        if width > LOW_D:
            tiles, met = _meetings(own, partners, radii, width)
            for at, v, same, flags in met:
                add(np.arange(at * TILE, at * TILE + len(tiles[at].ids)), tiles[at], v, same, flags)
        elif (sums := _leaf_sums(own, partners, radii, width, columns, add)) is not None:
            total += sums[:, :, 0].T - itself[0]
        yield pa.RecordBatch.from_arrays([pa.array(np.repeat(own.ids, len(radii))), pa.array(np.tile(np.array(radii, float), len(own.ids))), pa.array(total.ravel().astype(np.int64))], names=["i", "phi", "n"])

    found = run_owners(x, kernel=kernel, schema="i long, phi double, n long", **plan)
    return found if slices == 1 else found.groupBy("i", "phi").agg(F.sum("n").alias("n"))


def _gaps(own: np.ndarray, inside: np.ndarray | None, values: np.ndarray, many: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For each row of a tile, over the values inside (None: all), each so many times: their number and the sums of (value - own) and of its square.
    Sums of whole numbers below 2^53 are exact in any form, so there products with the tile around one middle give them; others are summed pair by pair."""
    middle = np.rint(own.mean())
    gap, back = values - middle, middle - own
    top = np.abs(gap).max(initial=0) + np.abs(back).max(initial=0)
    if 4 * top * top * many.sum() < 2.0**53 and all((c == np.rint(c)).all() for c in (own, values, many)):
        each = np.stack((many, many * gap, many * gap * gap), 1)
        n, s, s2 = (each.sum(0)[None] if inside is None else inside @ each).T
        return n, s + back * n, s2 + 2 * back * s + back * back * n
    a, b = np.nonzero(np.ones((len(own), len(values)), bool) if inside is None else inside)
    gap = values[b] - own[a]
    return tuple(np.bincount(a, w, len(own)) for w in (many[b], many[b] * gap, many[b] * gap * gap))


def nwr_spread(x: FeatureFrame, values: int, radii: list[float], blocks: int | None = None, weighted: bool = False) -> DataFrame:
    """(i, k, n, s, s2): over all rows within radius k of row i, itself included, their number and the sum and sum of squares of (their k-th value - its own).
    The last ``values`` features of x are these values and take no part in distances. Sums leave the kernels, not pairs.
    weighted: the feature before the values takes no part either; it is how many equal rows a row stands for."""
    width, many = x.d - values - weighted, len(radii)
    slices, plan = _plan_sums(x, blocks, width)
    times = lambda v: v.stored[:, width] if weighted else np.ones(len(v.ids))

    def kernel(own: Block, partners: Iterator[Block]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((3, len(own.ids), many))
        mine = own.stored[:, width + weighted :]
        middle = np.rint(mine.mean(0))
        back = middle - mine

        def add(rows: np.ndarray, u: Block, v: Block, same: bool, flags: np.ndarray | None) -> None:
            for k, inside in _within(u, v, radii, False, width) if flags is None else ((k, None) for k in np.flatnonzero(flags)):
                at_k = width + weighted + k
                for place, sums in enumerate(_gaps(u.stored[:, at_k], inside, v.stored[:, at_k], times(v))):
                    total[place, rows, k] += sums

        def columns(other: Block) -> list[np.ndarray] | None:
            """As in _gaps, around one middle for the task."""
            gap, w = other.stored[:, width + weighted :] - middle, times(other)
            top = np.abs(gap).max(initial=0) + np.abs(back).max(initial=0)
            if not (4 * top * top * w.sum() < 2.0**53 and all((m == np.rint(m)).all() for m in (gap, back, w))):
                return None
            return [np.stack((w, w * g, w * g * g), 1) for g in gap.T]

        if width > LOW_D:
            tiles, met = _meetings(own, partners, radii, width)
            for at, v, same, flags in met:
                add(np.arange(at * TILE, at * TILE + len(tiles[at].ids)), tiles[at], v, same, flags)
        elif (sums := _leaf_sums(own, partners, radii, width, columns, add)) is not None:
            n, s, s2 = (sums[:, :, place].T for place in range(3))
            total += np.stack((n, s + back * n, s2 + 2 * back * s + back * back * n))
        cells = [pa.array(np.repeat(own.ids, many)), pa.array(np.tile(np.arange(many), len(own.ids)), pa.int32()), pa.array(total[0].ravel().astype(np.int64)), pa.array(total[1].ravel()), pa.array(total[2].ravel())]
        yield pa.RecordBatch.from_arrays(cells, names=["i", "k", "n", "s", "s2"])

    found = run_owners(x, kernel=kernel, schema="i long, k int, n long, s double, s2 double", **plan)
    return found if slices == 1 else found.groupBy("i", "k").agg(*(F.sum(c).alias(c) for c in ("n", "s", "s2")))


def direction_sums(x: FeatureFrame, blocks: int | None = None) -> DataFrame:
    """(i, m, dots): how many other rows differ from row i, and the sum of the cosines of all pairs of the differences to them.
    With unit differences e this sum is (|sum of e|^2 - m) / 2, so it takes one pass over pairs and not over triples."""
    blocks, slices = _batches(x, blocks)
    d = x.d

    def kernel(own: Block, partners: Iterator[Block]) -> Iterator[pa.RecordBatch]:
        tiles = [(u, np.zeros(len(u.ids), np.int64), np.zeros((len(u.ids), d))) for u in own.tiles()]
        for other in partners:
            for v in other.tiles():
                for u, many, total in tiles:
                    dist = _all_pairs(u.stored, v.stored, "euclidean")
                    rate = np.divide(1.0, dist, out=np.zeros_like(dist), where=dist > 0)
                    many += np.count_nonzero(dist, axis=1)
                    for k in range(d):
                        part = np.subtract.outer(-u.stored[:, k], -v.stored[:, k])
                        part *= rate
                        total[:, k] += part.sum(1)
        for u, many, total in tiles:
            yield pa.RecordBatch.from_arrays([pa.array(u.ids), pa.array(many), pa.array(list(total), pa.list_(pa.float64()))], names=["i", "m", "e"])

    found = run_owners(x, blocks, kernel, "i long, m long, e array<double>", slices=slices)
    sums = found.groupBy("i").agg(F.sum("m").alias("m"), *(F.sum(F.col("e")[k]).alias(f"e{k}") for k in range(d)))
    square = sum((F.col(f"e{k}") * F.col(f"e{k}") for k in range(d)), F.lit(0.0))
    return sums.select("i", "m", ((square - F.col("m")) / 2).alias("dots"))


def nwr_grid(x: FeatureFrame, phi: float) -> DataFrame:
    """(i, j) within phi for up to four features: rows meet only in neighbouring cells of side phi, by an equi-join."""
    w = x.unpack()
    if w.d > 4:
        raise ValueError("the grid is for at most four features")
    key = w.ids[0]
    cell = [F.floor(F.col(f) / phi) for f in w.features]
    near = F.array(F.lit(-1), F.lit(0), F.lit(1))
    left = w.df.select(F.col(key).alias("i"), *(F.col(f).alias(f"a_{f}") for f in w.features), *(c.alias(f"c_{f}") for c, f in zip(cell, w.features)))
    for f in w.features:
        left = left.withColumn("step", F.explode(near)).withColumn(f"c_{f}", F.col(f"c_{f}") + F.col("step")).drop("step")
    right = w.df.select(F.col(key).alias("j"), *(F.col(f).alias(f"b_{f}") for f in w.features), *(c.alias(f"d_{f}") for c, f in zip(cell, w.features)))
    on = [F.col(f"c_{f}") == F.col(f"d_{f}") for f in w.features] + [F.col("i") != F.col("j")]
    square = lambda: sum(((F.col(f"a_{f}") - F.col(f"b_{f}")) * (F.col(f"a_{f}") - F.col(f"b_{f}")) for f in w.features), F.lit(0.0))
    # Rows of a table: never a broadcast, whatever its files' size suggests.
    return left.join(right.hint("merge"), on).where(F.sqrt(square()) <= phi).select("i", "j")


def topk_quantized(x: FeatureFrame, k: int, bits: int = 16, largest: bool = True, verify: bool = True, with_flag: bool = False) -> DataFrame:
    """(id, rank, index, value): top-k of each row from low-precision values. A row whose low-precision gaps up to rank k all exceed twice its rounding error is certain; only the others are ranked again in full precision.

    Rows are ranked where they lie, so nothing is shipped that a narrower format would save: this is the faithful variant, topk_rows the fast one.
    What it saves is the memory of the ranking kernel (``metrics.kernel_bytes``)."""
    from farpoint.plans.arrow import matrix
    from farpoint.session import ship

    p, d, f = x.pack(), x.d, FloatFormat(bits)
    k = min(k, d)
    ship(p.df.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids, full = b.column(0).to_numpy(zero_copy_only=False), matrix(b.column(1), d)
            with np.errstate(over="ignore"):
                low = full.astype({64: np.float64, 32: np.float32, 16: np.float16}[bits])
            key = low if not largest else -low
            order = np.argsort(key, axis=1, kind="stable")[:, : k + 1]
            top = np.take_along_axis(low, order, 1).astype(np.float64)
            err = f.eps * np.abs(low).max(1).astype(np.float64) / (1 - f.eps) + f.tiny
            sure = (np.abs(np.diff(top, axis=1)) > 2 * err[:, None]).all(1) & np.isfinite(low).all(1)
            if verify:
                again = full[~sure]
                order[~sure] = np.argsort(again if not largest else -again, axis=1, kind="stable")[:, : k + 1]
            order = order[:, :k]
            n = len(ids)
            cols = [pa.array(np.repeat(ids, k)), pa.array(np.tile(np.arange(1, k + 1), n), pa.int32()), pa.array(order.ravel(), pa.int32()), pa.array(np.take_along_axis(full, order, 1).ravel()), pa.array(np.repeat(sure, k))]
            yield pa.RecordBatch.from_arrays(cols, names=["id", "rank", "index", "value", "certain"])

    out = p.df.select("id", "x").mapInArrow(run, "id long, rank int, index int, value double, certain boolean")
    return out if with_flag else out.drop("certain")
