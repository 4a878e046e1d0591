"""Sum-of-squares packing of token pieces into sequences of a fixed capacity.

A document's ids (a separator id last) longer than the capacity are cut into whole pieces of the capacity, the
first piece taking the remainder. Whole pieces are sequences of their own. Every other piece goes where the squared counts
of open sequences per residual gap become smallest: into an open sequence or a new one.

Pieces are dealt evenly by row number, not by key, into groups of bounded size, one task each. Sequences that
a group leaves far from full are dissolved and their pieces packed again in larger company, round by round, until
one group is left or dissolving no longer pays. Each round's table is written to the shared folder.

Defined results: null text counts as empty and is the separator alone; repeated rows are packed as often as they occur; an
empty table gives an empty result; texts of any length are cut, never truncated; further columns are ignored.
"""

from __future__ import annotations

import math
import zlib
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from farpoint.llm.tokens import byte_encoder
from farpoint.session import ship, stage

PIECES = "piece int, start long, length long, ids_crc32 long"


def cut(docs: DataFrame, tokenizer: str, ranks: str | None, capacity: int = 2048, separator: int = 0, id_col: str = "doc_id", text_col: str = "text", keep_ids: bool = False) -> DataFrame:
    """One row for each piece: id, piece, start, length, ids_crc32, and with keep_ids the ids."""
    ship(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = byte_encoder(tokenizer, ranks)
        for b in batches:
            rows = []
            for doc, text in zip(b.column(0), b.column(1).to_pylist()):
                ids = np.array([*encoder.ids(text or ""), separator], "<u4")
                first = len(ids) % capacity or capacity
                borders = [0, *range(first, len(ids) + 1, capacity)]
                for k, (a, z) in enumerate(zip(borders, borders[1:])):
                    part = ids[a:z].tobytes()
                    rows.append((doc.as_py(), k, a, z - a, zlib.crc32(part), ids[a:z].tolist() if keep_ids else None))
            cols = list(zip(*rows)) or [()] * 6
            kinds = [b.schema.field(0).type, pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.int64())]
            names = [id_col, "piece", "start", "length", "ids_crc32", "ids"]
            n = 6 if keep_ids else 5
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols[:n], kinds)], names=names[:n])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, text_col).mapInArrow(run, f"`{id_col}` {kind}, {PIECES}" + ", ids array<long>" * keep_ids)


def sum_of_squares(lengths: np.ndarray, capacity: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(sequence number, offset, the sequence's final gap) of each length, placed in the order given."""
    open_by_gap: list[list[int]] = [[] for _ in range(capacity + 1)]
    count = np.zeros(capacity + 1, np.int64)  # open sequences by gap; full and new ones are not counted
    gaps: list[int] = []
    sequence, offset = np.empty(len(lengths), np.int64), np.empty(len(lengths), np.int64)
    for i, size in enumerate(lengths.tolist()):
        gap, best = capacity, 2 * int(count[capacity - size]) + 1 if size < capacity else 0
        here = count[size:capacity]
        if len(here):
            change = 2 * (count[: capacity - size] - here) + 2
            change[0] -= 1  # an exact fit opens no gap
            change[here == 0] = np.iinfo(np.int64).max
            k = int(change.argmin())
            if change[k] <= best:
                gap = size + k
        if gap == capacity:
            seq = len(gaps)
            gaps.append(capacity)
        else:
            seq = open_by_gap[gap].pop()
            count[gap] -= 1
        sequence[i], offset[i] = seq, capacity - gap
        gaps[seq] = left = gap - size
        if left:
            open_by_gap[left].append(seq)
            count[left] += 1
    return sequence, offset, np.array(gaps, np.int64)[sequence] if len(lengths) else offset


def pack_group(lengths: np.ndarray, capacity: int, slack: int, rounds: int = 6) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """sum_of_squares, longest first; sequences whose gap is over slack are dissolved and their pieces placed again, in turn shuffled and longest first, while that saves sequences or fills some."""
    sequence, offset, gap = (np.zeros(len(lengths), np.int64) for _ in range(3))
    rng, used = np.random.default_rng(len(lengths)), 0
    left = np.argsort(-lengths, kind="stable")
    best = None
    for k in range(rounds):
        s, o, g = sum_of_squares(lengths[left], capacity)
        count = int(s.max()) + 1 if len(s) else 0
        sequence[left], offset[left], gap[left] = used + s, o, g
        if best is None or used + count <= best[0]:
            best = (used + count, sequence.copy(), offset.copy(), gap.copy())
        loose = g > slack
        if not loose.any():
            break
        fixed, renamed = np.unique(s[~loose], return_inverse=True)
        sequence[left[~loose]] = used + renamed
        used += len(fixed)
        left = left[loose]
        left = rng.permutation(left) if k % 2 else left[np.argsort(-lengths[left], kind="stable")]
    return best[1:] if best else (sequence, offset, gap)


def pack(pieces: DataFrame, capacity: int = 2048, group: int = 16_384, slack: float = 0.01) -> DataFrame:
    """pieces (any columns, with length) plus sequence_id and offset, which replace columns of these names. group: pieces of one task; slack: the share of a sequence that may stay empty without another round."""
    ship(pieces.sparkSession)
    pieces = pieces.drop("sequence_id", "offset")
    names = pieces.columns
    size = f"c{names.index('length')}"
    pieces = stage(pieces.toDF(*(f"c{k}" for k in range(len(names)))), "pieces")  # numbered names: none can clash with the columns made here
    whole = pieces.where(F.col(size) >= capacity).withColumn("sequence_id", -1 - F.monotonically_increasing_id()).withColumn("offset", F.lit(0).cast("long"))
    rest, done, level = pieces.where(F.col(size) < capacity), [whole], 0
    n = rest.count()
    while n:
        groups = math.ceil(n / group)

        def place(rows: pd.DataFrame) -> pd.DataFrame:
            sequence, offset, gap = pack_group(rows[size].to_numpy(), capacity, int(slack * capacity))
            base = (int(rows["level"].iloc[0]) << 56) + (int(rows["group"].iloc[0]) << 28)
            return rows.drop(columns=["group", "level"]).assign(sequence_id=base + sequence, offset=offset, gap=gap)

        dealt = rest.withColumn("group", F.pmod(F.xxhash64(F.monotonically_increasing_id()), F.lit(groups)).cast("long")).withColumn("level", F.lit(level))
        schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rest.schema) + ", sequence_id long, offset long, gap long"
        placed = stage(dealt.groupBy("group").applyInPandas(place, schema), f"packed-{level}")
        loose = placed.where(F.col("gap") > slack * capacity)
        left = loose.count() if groups > 1 else 0
        if groups == 1 or left > n / 2:  # nothing to gain from company
            done.append(placed.drop("gap"))
            break
        done.append(placed.where(F.col("gap") <= slack * capacity).drop("gap"))
        rest, n, level = loose.drop("gap", "sequence_id", "offset"), left, level + 1
    return reduce(DataFrame.unionByName, done).toDF(*names, "sequence_id", "offset")
