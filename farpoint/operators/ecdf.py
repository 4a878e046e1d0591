"""Empirical CDF of every feature, exact quantiles and row numbers, without a window over a whole column and whatever the number of features.

Distinct values of all features are counted by one grouping (combined before the shuffle), dealt into ranges by (feature, value), summed
inside each range, and shifted by the ranges' totals. Values of features with few distinct ones are broadcast to the rows; the cells of all other
features meet their values in one join and are put together again by one grouping.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from farpoint.model import FeatureFrame
from farpoint.session import ship, stage

#: Distinct values up to which a feature's CDF is broadcast, features up to which that is done one by one.
FEW, ONE_BY_ONE = 10_000, 16


def _cumulated(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Sorted rows (part, at, value, c) with the running count of their feature inside the range."""
    feature, carried = None, 0
    for b in batches:
        if not b.num_rows:
            continue
        at, c = b.column(1).to_numpy(zero_copy_only=False), b.column(3).to_numpy(zero_copy_only=False)
        total = np.cumsum(c)
        new = np.concatenate(([at[0] != feature], at[1:] != at[:-1]))
        start = np.maximum.accumulate(np.where(new, np.arange(len(at)), -1))
        upto = total - np.where(start >= 0, total[start] - c[start], -carried)
        feature, carried = at[-1], int(upto[-1])
        yield pa.RecordBatch.from_arrays([*b.columns, pa.array(upto)], names=["part", "at", "value", "c", "upto"])


def _dealt(df: DataFrame, ranges: int | None, *order: str | Column) -> DataFrame:
    """By default as many ranges as the session shuffles into, small ones put together at run time."""
    return df.repartitionByRange(ranges, *order) if ranges else df.repartitionByRange(*order)


@dataclass(frozen=True)
class Ranked:
    """values: (at, value, c, before) of every distinct value, before being the rows with a smaller one; rows and distinct values of each feature."""

    features: tuple[str, ...]
    values: DataFrame
    rows: tuple[int, ...]
    distinct: tuple[int, ...]


def ranked_values(x: FeatureFrame, ranges: int | None = None) -> Ranked:
    """Two shuffles of distinct values. What reaches the driver is a number for each range and feature."""
    w = x.unpack()
    spark = ship(w.df.sparkSession)
    cells = F.explode(F.array(*(F.struct(F.lit(k).alias("at"), F.col(f).alias("value")) for k, f in enumerate(w.features))))
    counts = w.df.select(cells.alias("c")).select("c.*").where(F.col("value").isNotNull()).groupBy("at", "value").agg(F.count("*").alias("c"))
    dealt = _dealt(counts, ranges, "at", "value").sortWithinPartitions("at", "value").select(F.spark_partition_id().alias("part"), "at", "value", "c")
    staged = stage(dealt.mapInArrow(_cumulated, "part int, at int, value double, c long, upto long"), "ranked")
    totals = staged.groupBy("at", "part").agg(F.max("upto").alias("n"), F.count("*").alias("d"), F.min("value").alias("least")).orderBy("at", "least").collect()  # at most ranges + features rows
    offsets, rows, distinct = [], [0] * w.d, [0] * w.d
    for r in totals:
        offsets.append((r["at"], r["part"], rows[r["at"]]))
        rows[r["at"]] += r["n"]
        distinct[r["at"]] += r["d"]
    shift = spark.createDataFrame(offsets, "o_at int, o_part int, shift long")
    before = (F.col("shift") + F.col("upto") - F.col("c")).alias("before")
    return Ranked(w.features, staged.join(F.broadcast(shift), (F.col("at") == F.col("o_at")) & (F.col("part") == F.col("o_part"))).select("at", "value", "c", before), tuple(rows), tuple(distinct))


def _sides(r: Ranked) -> tuple[Column, Column]:
    n = F.get(F.array(*(F.lit(float(v or 1)) for v in r.rows)), F.col("at"))
    return (F.col("before") + F.col("c")) / n, (n - F.col("before")) / n


def value_ranks(x: FeatureFrame, ranges: int | None = None) -> DataFrame:
    """(feature, value, f_left, f_right) of every distinct value: shares of rows not above and not below it."""
    r = ranked_values(x, ranges)
    left, right = _sides(r)
    return r.values.select(F.get(F.array(*map(F.lit, r.features)), F.col("at")).alias("feature"), "value", left.alias("f_left"), right.alias("f_right"))


def with_ranks(x: FeatureFrame, ranges: int | None = None) -> DataFrame:
    """x's wide rows plus l_<feature> and r_<feature>. Rows with a null feature drop out."""
    w = x.unpack()
    r = ranked_values(w, ranges)
    left, right = _sides(r)
    few = [k for k in range(w.d) if r.distinct[k] <= FEW][:ONE_BY_ONE]
    many = [k for k in range(w.d) if k not in few]
    out = w.df
    for k in few:
        f = w.features[k]
        one = r.values.where(F.col("at") == k).select(F.col("value").alias(f"v_{f}"), left.alias(f"l_{f}"), right.alias(f"r_{f}"))
        out = out.join(F.broadcast(one), F.col(f) == F.col(f"v_{f}")).drop(f"v_{f}")  # at most FEW rows
    if len(many) == 1:
        f = w.features[many[0]]
        one = r.values.where(F.col("at") == many[0]).select(F.col("value").alias(f"v_{f}"), left.alias(f"l_{f}"), right.alias(f"r_{f}"))
        out = out.join(one, F.col(f) == F.col(f"v_{f}")).drop(f"v_{f}")
    elif many:
        # Rows are numbered by position only to be put together again, so they are written first.
        out = stage(out.withColumn("_cell_row", F.monotonically_increasing_id()), "rows")
        cells = F.explode(F.array(*(F.struct(F.lit(k).alias("at"), F.col(w.features[k]).alias("value")) for k in many)))
        met = out.select("_cell_row", cells.alias("q")).select("_cell_row", F.col("q.at").alias("q_at"), F.col("q.value").alias("q_value"))
        met = met.join(r.values, (F.col("q_at") == F.col("at")) & (F.col("q_value") == F.col("value"))).select("_cell_row", "at", left.alias("l"), right.alias("r"))
        pick = lambda c, k: F.max(F.when(F.col("at") == k, F.col(c)))
        wide = met.groupBy("_cell_row").agg(*(a for k in many for a in (pick("l", k).alias(f"l_{w.features[k]}"), pick("r", k).alias(f"r_{w.features[k]}"))))
        wide = wide.where(F.col(f"l_{w.features[many[0]]}").isNotNull())
        out = out.join(wide, "_cell_row").drop("_cell_row")
    return out


def ecdf(x: FeatureFrame, side: str = "both") -> DataFrame:
    """(ids, feature, f_left, f_right) of every row and feature; side 'left' or 'right' keeps one of the two."""
    w = x.unpack()
    cells = F.explode(F.array(*(F.struct(F.lit(f).alias("feature"), F.col(f"l_{f}").alias("f_left"), F.col(f"r_{f}").alias("f_right")) for f in w.features)))
    out = with_ranks(w).select(*w.ids, cells.alias("c")).select(*w.ids, "c.*")
    return out if side == "both" else out.drop("f_right" if side == "left" else "f_left")


def quantiles(x: FeatureFrame, shares: Sequence[float]) -> dict[str, list[float]]:
    """Exact linearly interpolated quantiles of every feature (empty list without rows): the two neighbouring values of each come from one aggregate over ranked values."""
    r = ranked_values(x)
    n = F.get(F.array(*(F.lit(v) for v in r.rows)), F.col("at"))
    place = lambda p: F.lit(float(p)) * (n - 1)
    held = lambda rank: F.max(F.when((F.col("before") <= rank) & (rank < F.col("before") + F.col("c")), F.col("value")))
    rows = r.values.groupBy("at").agg(*(a for k, p in enumerate(shares) for a in (held(F.floor(place(p))).alias(f"a{k}"), held(F.ceil(place(p))).alias(f"b{k}")))).collect()  # one row a feature
    out: dict[str, list[float]] = {f: [] for f in r.features}
    for row in rows:
        for k, p in enumerate(shares):
            at = p * (r.rows[row["at"]] - 1)
            a, b = row[f"a{k}"], row[f"b{k}"]
            out[r.features[row["at"]]].append(a if a == b else (int(at) + 1 - at) * a + (at - int(at)) * b)
    return out


def row_numbers(df: DataFrame, by: str, order: Sequence[Column], name: str = "place", ranges: int | None = None) -> DataFrame:
    """df plus 1, 2, ... within each of the few values of by, in a total order: rows are dealt by that order into ranges and numbered there, then shifted."""
    dealt = _dealt(df, ranges, by, *order).sortWithinPartitions(by, *order)
    staged = stage(dealt.select("*", F.spark_partition_id().alias("_number_part"), F.monotonically_increasing_id().alias("_number_at")), "numbered")
    first = staged.groupBy(F.col(by).alias("_number_by"), F.col("_number_part").alias("_number_of")).agg(F.min("_number_at").alias("_number_first"), F.count("*").alias("_number_n"))
    offsets = first.withColumn("_number_before", F.sum("_number_n").over(Window.partitionBy("_number_by").orderBy("_number_of")) - F.col("_number_n"))  # at most ranges + values of by rows
    met = staged.join(F.broadcast(offsets), F.col(by).eqNullSafe(F.col("_number_by")) & (F.col("_number_part") == F.col("_number_of")))
    return met.withColumn(name, F.col("_number_at") - F.col("_number_first") + F.col("_number_before") + 1).select(*df.columns, name)


def ecdf_window(x: FeatureFrame) -> DataFrame:
    """The same by cume_dist: one task for each feature, for small inputs and as a cross-check."""
    w = x.unpack()
    cols = [c for f in w.features for c in (F.cume_dist().over(Window.orderBy(f)).alias(f"l_{f}"), F.cume_dist().over(Window.orderBy(F.desc(f))).alias(f"r_{f}"))]
    return w.df.select(*w.ids, *w.features, *cols)
