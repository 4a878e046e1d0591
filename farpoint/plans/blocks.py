"""Pair-of-splits batching: rows packed into blocks, and every block sent to the owners that compare it with their own.

One owner is one subtask or a few. It holds its own block and streams its partners, so a task's memory is two blocks and a few tiles, and
nothing but results leaves it. In the symmetric plan owner i meets the partners (i + t) mod B for t up to B / 2 (for even B the last t
only when i < B / 2), so that each pair is met once and owners have equal work.
"""

from __future__ import annotations

import math
import time
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from farpoint.model import FeatureFrame
from farpoint.plans.arrow import grouped, matrix
from farpoint.session import ship

FORMATS = {64: np.float64, 32: np.float32, 16: np.float16}


class MemoryBudgetExceeded(MemoryError):
    """Raised before anything runs, from the estimated size."""


def block_rows(d: int, value_bytes: int = 8, budget: int = 256 << 20) -> int:
    """Most rows b of a block so that a tile of b * b doubles and two blocks fit the budget of a task."""
    b = int((-d * value_bytes + math.sqrt((d * value_bytes) ** 2 + 8 * budget)) / 8)
    return max(1, b)


def check_budget(n: int, d: int, budget: int = 4 << 30, what: str = "the direct form") -> None:
    need = n * n * 8 + n * d * 8
    if need > budget:
        raise MemoryBudgetExceeded(f"{what} needs about {need >> 20} MB; the budget is {budget >> 20} MB")


def feasible_rows(d: int, budget: int = 4 << 30) -> int:
    """Most rows that the direct form can take."""
    return int((-d + math.sqrt(d * d + budget / 2)) / 2)


#: Memory of a task for blocks and tiles, rows of a tile's side, fewest rows worth a block of their own, bytes of one binary cell.
TASK_BUDGET, TILE, LEAST, CELL = 256 << 20, 1024, 512, 16 << 20


def tiled_rows(d: int, value_bytes: int = 8, budget: int = TASK_BUDGET) -> int:
    """Most rows of a block where kernels work tile by tile: two blocks, stored and in compute format, and four tiles fit the budget of a task."""
    return max(TILE, (budget - 4 * TILE * TILE * 8) // (2 * d * (value_bytes + 8)))


def plan_batches(n: int, d: int, task_budget: int = TASK_BUDGET, value_bytes: int = 8, tasks: int = 8) -> int | None:
    """None: small enough to run unbatched. Otherwise the number of blocks: enough for the memory of a task and for all tasks to have work.
    Blocks grow with the square root of the tasks only, since every block is sent to half of the owners; owners are sliced for the rest."""
    if n <= TILE:
        return None
    return max(math.ceil(n / tiled_rows(d, value_bytes, task_budget)), min(math.ceil(math.sqrt(8 * tasks)), math.ceil(n / LEAST)))


def plan_slices(blocks: int, tasks: int, symmetric: bool = False) -> int:
    """Subtasks into which each owner's partners are dealt, so that blocks * slices reaches the tasks."""
    return max(1, min(blocks // 2 + 1 if symmetric else blocks, math.ceil(tasks / blocks)))


def blocks_for(x: FeatureFrame, y: FeatureFrame | None = None, bits: int = 64) -> int:
    """plan_batches for the rows at hand: one count, which a parquet scan answers from its footers."""
    n = max(x.count(), y.count() if y is not None else 0)
    return plan_batches(n, x.d, value_bytes=bits // 8, tasks=x.df.sparkSession.sparkContext.defaultParallelism) or 1


def owners_of(block: int, b: int, symmetric: bool) -> list[int]:
    if not symmetric:
        return list(range(b))
    return [(block - t) % b for t in range(b // 2 + 1) if not (b % 2 == 0 and t == b // 2 and b > 1) or (block - t) % b < b // 2]


#: Rows of the sample that places cuts through space.
CUT_SAMPLE = 8192


def cut_space(x: FeatureFrame, b: int, width: int | None = None) -> Column:
    """The number of each row's block, below b, where blocks are boxes in space: halves at a value of the widest feature, placed by a sample of at most CUT_SAMPLE rows.
    Every row has one block wherever the cuts lie, so the sample decides only how even blocks are. Equal rows too many for a block are dealt to several by their ids.
    width: only the first features are cut."""
    sample = x.pack().df.select("x", F.xxhash64("id").alias("h")).orderBy("h").limit(CUT_SAMPLE).select("x").toArrow()
    rows = matrix(sample.column(0).combine_chunks(), x.d)[:, :width] if sample.num_rows else np.zeros((0, width or x.d))
    rows = rows[np.isfinite(rows).all(1)]

    def cut(at: np.ndarray, first: int, many: int) -> Column:
        if many == 1:
            return F.lit(first).cast("long")
        spread = rows[at].max(0) - rows[at].min(0) if len(at) else np.zeros(width or x.d)
        if not spread.max() > 0:
            return F.pmod(F.xxhash64("id"), F.lit(many)) + first
        f, half = int(spread.argmax()), many // 2
        values = np.sort(rows[at, f])
        value = values[len(at) * half // many]
        value = value if value > values[0] else values[np.searchsorted(values, value, "right")]
        low = rows[at, f] < value
        # Where equal values moved the cut, each side gets blocks by its share of rows.
        half = min(max(1, round(many * low.mean())), many - 1)
        return F.when(F.col("x")[f] < float(value), cut(at[low], first, half)).otherwise(cut(at[~low], first + half, many - half))

    return cut(np.arange(len(rows)), 0, b)


def leaf_order(rows: np.ndarray, size: int) -> np.ndarray:
    """Rows in an order in which each ``size`` of them are near in space (all but the last leaf are full)."""
    parts, open_ = [], [np.arange(len(rows))]
    while open_:
        at = open_.pop()
        many = -(-len(at) // size)
        if many <= 1:
            parts.append(at)
            continue
        part, half = rows[at], many // 2 * size
        order = np.argpartition(part[:, np.nan_to_num(part.max(0) - part.min(0)).argmax()], half)
        open_ += [at[order[half:]], at[order[:half]]]
    return np.concatenate(parts)


def pack(x: FeatureFrame, b: int, bits: int = 64, factor: float = 1.0, cell: Column | None = None, leaf: int = 0, width: int | None = None) -> DataFrame:
    """(block, part, ids, body, residual): a block's rows in parts of at most CELL bytes; values times factor in the storage format, and each row's distance from its stored form.
    cell: the block of a row, by default dealt by its id. leaf: rows are put leaf by leaf, of so many rows, near in the first ``width`` features."""
    p, d, kind = x.pack(), x.d, FORMATS[bits]
    ship(p.df.sparkSession)
    most = max(1, CELL // (8 * max(d, 1)))
    most = max(leaf, most // leaf * leaf) if leaf else most

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for g in grouped(batches):
            if leaf:
                g = g.take(pa.array(leaf_order(matrix(g.column(2), d)[:, :width], leaf)))
            for part, at in enumerate(range(0, g.num_rows, most)):
                rows = g.slice(at, most)
                exact = matrix(rows.column(2), d) * factor
                with np.errstate(over="ignore"):
                    stored = exact.astype(kind)
                left = np.zeros(0) if bits == 64 else np.sqrt(((exact - stored.astype(np.float64)) ** 2).sum(1))
                yield pa.RecordBatch.from_arrays([rows.column(0).slice(0, 1), pa.array([part], pa.int32()), *(pa.array([a.tobytes()], pa.binary()) for a in (rows.column(1).to_numpy(zero_copy_only=False), stored, left))], names=["block", "part", "ids", "body", "residual"])

    rows = p.df.select((F.pmod(F.xxhash64("id"), F.lit(b)) if cell is None else cell).alias("block"), "id", "x").repartitionById(b, F.col("block").cast("int")).sortWithinPartitions("block", "id")
    return rows.mapInArrow(run, "block long, part int, ids binary, body binary, residual binary")


class Block:
    """Decoded rows of one block: a part of it, all of it, or a tile."""

    def __init__(self, number: int, ids: np.ndarray, stored: np.ndarray, residual: np.ndarray):
        self.number, self.ids, self.stored, self.residual = number, ids, stored, residual

    @staticmethod
    def decode(rows: list[dict], d: int, bits: int) -> Block:
        ids, stored, residual = ([np.frombuffer(r[c], t) for r in rows] for c, t in (("ids", np.int64), ("body", FORMATS[bits]), ("residual", np.float64)))
        join = lambda a: a[0] if len(a) == 1 else np.concatenate(a)
        return Block(rows[0]["block"], join(ids), join(stored).reshape(-1, d), join(residual))

    def lowered(self, bits: int) -> Block:
        """The rows in a storage format, with their distances from it; kept, as a tile meets many others."""
        held = self.__dict__.setdefault("_lowered", {})
        if bits not in held:
            with np.errstate(over="ignore"):
                stored = self.stored.astype(FORMATS[bits])
            held[bits] = Block(self.number, self.ids, stored, np.sqrt(((self.stored - stored.astype(np.float64)) ** 2).sum(1)))
        return held[bits]

    def take(self, at: np.ndarray) -> Block:
        return Block(self.number, self.ids[at], self.stored[at], self.residual[at] if len(self.residual) else self.residual)

    def tiles(self) -> list[Block]:
        return [Block(self.number, self.ids[at : at + TILE], self.stored[at : at + TILE], self.residual[at : at + TILE]) for at in range(0, len(self.ids), TILE)]


#: Rows of a leaf; most features for which leaves leave out enough to be worth sorting rows.
LEAF, LOW_D = 128, 16


class Leaves:
    """A block's rows in leaves that are near in space (halves at the median of the widest feature), with the box of each. Ids in a leaf stay sorted.
    packed: rows came leaf by leaf already, of so many rows."""

    def __init__(self, block: Block, width: int | None = None, size: int = LEAF, packed: int = 0):
        rows = block.stored[:, :width]
        if packed:
            at = np.arange(0, len(rows), packed)
            self.block, self.parts = block, np.split(np.arange(len(rows)), at[1:])
            self.lo, self.hi = np.minimum.reduceat(rows, at), np.maximum.reduceat(rows, at)
            self.size = np.diff(np.append(at, len(rows)))
            return
        parts, open_ = [], [np.arange(len(rows))]
        while open_:
            at = open_.pop()
            part = rows[at]
            spread = part.max(0) - part.min(0) if len(at) else np.zeros(rows.shape[1])
            if len(at) <= size or not spread.max() > 0:
                parts += [at[k : k + TILE] for k in range(0, len(at), TILE)]
                continue
            half = len(at) // 2
            order = np.argpartition(part[:, spread.argmax()], half)
            open_ += [np.sort(at[order[half:]]), np.sort(at[order[:half]])]
        self.block, self.parts = block, parts
        self.lo = np.array([rows[at].min(0) for at in parts]).reshape(len(parts), rows.shape[1])
        self.hi = np.array([rows[at].max(0) for at in parts]).reshape(len(parts), rows.shape[1])
        self.size = np.array([len(at) for at in parts], np.int64)

    def rows(self, which, of: Block | None = None) -> Block:
        """The rows of some leaves as one block; of: another form of the block's rows."""
        at = np.concatenate([self.parts[k] for k in which]) if len(which) else np.zeros(0, np.int64)
        return (of or self.block).take(at)

    def nearest(self, lo: np.ndarray, hi: np.ndarray, which=slice(None)) -> np.ndarray:
        """Squared distance of a box (or of several, row by row) to each leaf's box (or to some leaves'): no pair of their rows is nearer, roundings taken off. A feature without a number sets nothing apart."""
        gap = np.fmax(np.fmax(self.lo[which] - hi[..., None, :], lo[..., None, :] - self.hi[which]), 0)
        return (gap * gap).sum(-1) * (1 - 1e-9)

    def farthest(self, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        """Squared distance within which all pairs of rows of a box and each leaf lie."""
        gap = np.maximum(self.hi - lo, hi - self.lo)
        return (gap * gap).sum(1) * (1 + 1e-9)


Kernel = Callable[[Block, Iterator[Block]], Iterator[pa.RecordBatch]]


def run_owners(x: FeatureFrame, b: int, kernel: Kernel, schema: str, bits: int = 64, symmetric: bool = False, factor: float = 1.0, y: FeatureFrame | None = None, clock=None, slices: int = 1, cell: Column | None = None, leaf: int = 0, width: int | None = None) -> DataFrame:
    """kernel(own block, its partners) for every owner and slice. Without y the own block is its own first partner; with y partners are the blocks of y.
    Partners come part by part. slices: an owner's partners are dealt to so many subtasks, each with a copy of the own block; the caller merges
    what they give. cell, leaf, width: how pack deals and orders rows. clock: an accumulator that gets the seconds spent in kernels, waiting for partners left out."""
    d, apart = x.d, y is not None
    mine = pack(x, b, bits, factor, cell, leaf, width)
    if y is not None:
        reach, others = F.sequence(F.lit(0).cast("long"), F.lit(b - 1).cast("long")), pack(y, b, bits, factor, cell, leaf, width)
        met = F.transform(reach, lambda o: o * slices + F.pmod(F.col("block"), F.lit(slices)))
    else:
        half, others = b // 2, mine
        steps = F.sequence(F.lit(1).cast("long"), F.lit(half if symmetric else b - 1).cast("long")) if b > 1 else F.expr("cast(array() as array<bigint>)")
        owner = lambda t: F.pmod(F.col("block") - t, F.lit(b).cast("long"))
        met = F.transform(F.filter(steps, lambda t: (t < half) | (owner(t) < half)) if symmetric and b % 2 == 0 and b > 1 else steps, lambda t: owner(t) * slices + F.pmod(t, F.lit(slices).cast("long")))
    own = F.transform(F.sequence(F.lit(0).cast("long"), F.lit(slices - 1).cast("long")), lambda t: F.col("block") * slices + t)
    role = lambda owners, r: F.transform(owners, lambda o: F.struct(o.alias("owner"), F.lit(r).alias("role")))
    send = lambda df, copies: df.withColumn("to", F.explode(copies)).select("to.owner", "to.role", "block", "part", "ids", "body", "residual")
    # Without y the packed rows are read once: a block's own copies and those for its owners are exploded together.
    sent = send(mine, F.concat(role(own, 0), role(met, 1))) if y is None else send(mine, role(own, 0)).unionByName(send(others, role(met, 1)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = ({n: v for n, v in zip(r.schema.names, (c[0].as_py() for c in r.columns))} for big in batches for r in (big.slice(i, 1) for i in range(big.num_rows)))
        row = next(rows, None)
        while row is not None:
            owner = row["owner"]
            waited, held = [0.0], []
            while row is not None and row["owner"] == owner and row["role"] == 0:
                held.append(row)
                row = next(rows, None)
            ahead: list = [row]

            def partners():
                if not apart and owner % slices == 0:
                    yield own_block
                while ahead[0] is not None and ahead[0]["owner"] == owner:
                    yield Block.decode([ahead[0]], d, bits)
                    began = time.perf_counter()
                    ahead[0] = next(rows, None)
                    waited[0] += time.perf_counter() - began

            if held:  # none: blocks of y without rows of x
                own_block = Block.decode(held, d, bits)
                held = []
                began = time.perf_counter()
                found = list(kernel(own_block, partners())) if clock is not None else kernel(own_block, partners())
                if clock is not None:
                    clock.add(time.perf_counter() - began - waited[0])
                yield from found
            while ahead[0] is not None and ahead[0]["owner"] == owner:
                ahead[0] = next(rows, None)
            row = ahead[0]

    n = b * slices
    return sent.repartitionById(n, F.col("owner").cast("int")).sortWithinPartitions("owner", "role", "block", "part").mapInArrow(run, schema)
