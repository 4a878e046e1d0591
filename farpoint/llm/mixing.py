"""Mixing sources to target weights by min-cost flow.

Documents are aggregated by membership pattern (the set of sources that they belong to). Words flow from
patterns to the sources they belong to and on to the sources' quotas; a pattern's first pass over its words is free and each further
pass costs more (convex), so nothing is repeated while something unused would do. The flow gives each pattern a number of words; in a
pattern, documents are taken in the order of a seeded hash, whole passes first, and the last document in part.

The cut in hash order is found from sums by hash range, in two levels of 4,096 ranges, and by a window over the
rows of the one remaining range, so no task sees a whole source.

Defined results: null text has size 0; null source is a source of its own, last in order; repeated rows count as often as they
occur; documents of size 0 are never taken; an empty table gives an empty result; further columns, whatever their names, stay in ``mix_rows`` and are
ignored in ``mix``. Equal hashes are ordered by id.
"""

from __future__ import annotations

import json
from collections import deque
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from farpoint.session import stage

WORD = r"[^\x20\x09-\x0D]+"
#: Membership patterns whose quotas are broadcast; more are joined by a shuffle. The driver holds a few numbers for each distinct pattern.
BROADCAST_PATTERNS = 200_000


class Transport:
    """Flow from many patterns to the few sources that each belongs to, in arrays: one entry for each membership.

    Costs are of a pattern's passes alone and equal for all patterns, so a min-cost maximal flow is found level by level: as much as
    can flow in first passes, then what more can in second ones, and so on; a pattern's words are rerouted later, never taken back. Words move in
    bulk along shortest paths over the sources: from all patterns with words left, over all that can change from one source to the next.
    """

    def __init__(self, patterns: list[tuple], sources: list, goal: dict):
        number = {s: i for i, s in enumerate(sources)}
        self.pattern = np.repeat(np.arange(len(patterns)), [len(p) for p in patterns])
        self.source = np.array([number[s] for p in patterns for s in p], np.int64)
        self.flow = np.zeros(len(self.source))
        self.room = np.array([float(goal[s]) for s in sources])
        self.free = np.zeros(len(patterns))
        # Memberships of each source, patterns rising.
        order = np.argsort(self.source, kind="stable")
        self.of = np.split(order, np.searchsorted(self.source[order], np.arange(1, len(sources)))) if len(sources) else []
        self.least = 1e-6

    def _common(self, s: int, t: int) -> tuple[np.ndarray, np.ndarray]:
        """Memberships of s and of t of the patterns that belong to both."""
        _, a, b = np.intersect1d(self.pattern[self.of[s]], self.pattern[self.of[t]], assume_unique=True, return_indices=True)
        return self.of[s][a], self.of[t][b]

    def _path(self) -> list[int] | None:
        """Sources from one with unused words to one with room, over patterns that can change."""
        start = np.unique(self.source[self.free[self.pattern] > self.least]).tolist()
        came, todo = dict.fromkeys(start), deque(start)
        while todo:
            s = todo.popleft()
            if self.room[s] > self.least:
                path = [s]
                while came[path[-1]] is not None:
                    path.append(came[path[-1]])
                return path[::-1]
            held = np.zeros(len(self.free), bool)
            mine = self.of[s]
            held[self.pattern[mine[self.flow[mine] > self.least]]] = True
            for t in np.unique(self.source[held[self.pattern]]).tolist():
                if t not in came:
                    came[t] = s
                    todo.append(t)
        return None

    @staticmethod
    def _in_order(amounts: np.ndarray, total: float) -> np.ndarray:
        """As much of each amount as the total allows, in order."""
        return np.clip(total - (np.cumsum(amounts) - amounts), 0.0, amounts)

    def level(self, words: np.ndarray) -> None:
        """Offer so many more words of every pattern and let as many flow as can."""
        self.free = words.astype(float)
        while (path := self._path()) is not None:
            first, last = path[0], path[-1]
            steps = [self._common(s, t) for s, t in zip(path, path[1:])]
            push = min([float(self.room[last]), float(self.free[self.pattern[self.of[first]]].sum()), *(float(self.flow[a].sum()) for a, _ in steps)])
            for a, b in steps:
                moved = self._in_order(self.flow[a], push)
                self.flow[a] -= moved
                self.flow[b] += moved
            at = self.of[first]
            moved = self._in_order(self.free[self.pattern[at]], push)
            self.flow[at] += moved
            self.free[self.pattern[at]] -= moved
            self.room[last] -= push


def targets(sizes: dict, weights: tuple[float, ...] = (3, 1, 2), share: float = 1.5, most: float = 2.0) -> dict:
    """Target words by source: weights repeat over the sources by code point (null last); no target passes ``most`` times its source's size, the rest being shared again by weight."""
    order = sorted(sizes, key=lambda s: (s is None, s or ""))
    weight = {s: weights[i % len(weights)] for i, s in enumerate(order)}
    goal = {s: 0.0 for s in order}
    left, free = share * sum(sizes.values()), [s for s in order if sizes[s] > 0]
    while free:
        unit = left / sum(weight[s] for s in free)
        over = [s for s in free if unit * weight[s] > most * sizes[s]]
        if not over:
            goal |= {s: unit * weight[s] for s in free}
            break
        for s in over:
            goal[s] = most * sizes[s]
            left -= goal[s]
        free = [s for s in free if s not in over]
    return goal


@dataclass(frozen=True)
class Plan:
    """words: to take from each pattern; routed: from pattern to source."""

    words: dict
    routed: dict


def plan(patterns: dict[tuple, int], goal: dict, passes: int = 2) -> Plan:
    """patterns: size by sorted tuple of member sources. Each pass over a pattern's words costs more than the one before."""
    names, sources = list(patterns), list(goal)
    size, net = np.array([patterns[p] for p in names], float), Transport(names, sources, goal)
    words = np.zeros(len(names))
    for _ in range(passes):
        net.level(size)
        words += size - net.free
    used = np.flatnonzero(net.flow > net.least)
    return Plan(dict(zip(names, words.tolist())), {(names[net.pattern[e]], sources[net.source[e]]): float(net.flow[e]) for e in used})


def _key(members: Column) -> Column:
    """A pattern as one string: JSON of the sorted distinct members, nulls kept."""
    return F.to_json(F.struct(F.array_sort(F.array_distinct(members)).alias("m")), {"ignoreNullFields": "false"})


def _small(df: DataFrame, rows: int) -> DataFrame:
    """A side of one row a pattern: broadcast while there are few patterns."""
    return F.broadcast(df) if rows <= BROADCAST_PATTERNS else df


def _take(sized: DataFrame, quota: DataFrame, ids: list[str], many: int) -> DataFrame:
    """sized: pattern, size, hash and more; quota: pattern, words (whole number), total. Adds taken."""
    cell = lambda shift: F.shiftrightunsigned("hash", shift).bitwiseAND(4095).cast("int")
    rows = sized.join(_small(quota, many), F.col("pattern") == F.col("q_pattern"), "left").drop("q_pattern")
    passes = F.when(F.col("total") > 0, F.floor(F.col("words") / F.col("total"))).otherwise(0)
    rows = rows.withColumn("passes", passes).withColumn("extra", F.col("words") - F.col("passes") * F.col("total")).withColumn("c1", cell(52)).withColumn("c2", cell(40))

    def border(level: DataFrame, c: str, goal: str) -> DataFrame:
        sums = level.groupBy("pattern", c).agg(F.sum("size").alias("s"), F.first(goal).alias("goal"))
        before = F.sum("s").over(Window.partitionBy("pattern").orderBy(c)) - F.col("s")
        return sums.withColumn("before", before).where((F.col("before") < F.col("goal")) & (F.col("goal") <= F.col("before") + F.col("s"))).select(F.col("pattern").alias("b_pattern"), F.col(c).alias("b_" + c), (F.col("goal") - F.col("before")).alias("left_" + c))

    def split(level: DataFrame, c: str, goal: str) -> tuple[DataFrame, DataFrame]:
        joined = level.join(_small(border(level, c, goal), many), F.col("pattern") == F.col("b_pattern"), "left").drop("b_pattern")  # one row for each pattern
        inside = F.coalesce(F.col(c) == F.col("b_" + c), F.lit(False))
        decided = joined.where(~inside).withColumn("more", F.when(F.col(c) < F.col("b_" + c), F.col("size")).otherwise(F.lit(0)).cast("long"))
        return decided.drop("b_" + c, "left_" + c), joined.where(inside).drop("b_" + c)

    sure1, inside1 = split(rows, "c1", "extra")
    sure2, inside2 = split(inside1, "c2", "left_c1")
    w = Window.partitionBy("pattern").orderBy("hash", *ids).rowsBetween(Window.unboundedPreceding, -1)
    last = inside2.withColumn("more", F.least(F.col("size"), F.greatest(F.lit(0), F.col("left_c2") - F.coalesce(F.sum("size").over(w), F.lit(0)))).cast("long"))
    keep = [*sized.columns, "passes", "more"]
    out = sure1.select(*keep).unionByName(sure2.select(*keep)).unionByName(last.select(*keep))
    return out.withColumn("taken", (F.col("passes") * F.col("size") + F.col("more")).cast("long")).drop("passes", "more")


def mix(docs: DataFrame, members: Column, seed: int = 7, weights: tuple[float, ...] = (3, 1, 2), share: float = 1.5, passes: int = 2, id_col: str = "doc_id", text_col: str = "text", carry: tuple[str, ...] = (), drawn_by: str | None = None) -> tuple[DataFrame, DataFrame]:
    """(id, pattern, size, taken, carry...) of every row, and (s_source, source_size, target) of every source. members: array of a row's sources. drawn_by: the column whose hash orders the rows (default: the id)."""
    spark = docs.sparkSession
    size = F.coalesce(F.regexp_count(F.col(text_col), F.lit(WORD)), F.lit(0)).cast("long")
    sized = stage(docs.select(F.col(id_col), *carry, _key(members).alias("pattern"), size.alias("size"), F.xxhash64(F.lit(seed), F.col(drawn_by or id_col), size).alias("hash")), "sized")
    found = sized.groupBy("pattern").agg(F.sum("size").alias("total")).orderBy("pattern").collect()  # one row for each distinct set of sources
    named = {r["pattern"]: tuple(json.loads(r["pattern"])["m"]) for r in found}
    by_pattern = {named[r["pattern"]]: r["total"] for r in found}
    sizes: dict = {}
    for p, n in by_pattern.items():
        for s in p:
            sizes[s] = sizes.get(s, 0) + n
    goal = targets(sizes, weights, share, passes)
    flow = plan(by_pattern, goal, passes)
    keys = [r["pattern"] for r in found]
    quota = spark.createDataFrame(pa.table({"q_pattern": pa.array(keys, pa.string()), "words": pa.array([int(round(flow.words[named[k]])) for k in keys], pa.int64()), "total": pa.array([int(r["total"]) for r in found], pa.int64())}))
    out = _take(sized, quota, [id_col], len(found))
    by_source = spark.createDataFrame(pa.table({"s_source": pa.array(list(sizes), pa.string()), "source_size": pa.array(list(sizes.values()), pa.int64()), "target": pa.array([float(goal[s]) for s in sizes], pa.float64())}))
    return out, by_source


def mix_rows(docs: DataFrame, source_col: str = "source", id_col: str = "doc_id", **options) -> DataFrame:
    """The mixed documents with all columns of docs: a row for each copy taken. The document at a cut counts as taken if at least half of it is; documents of size 0 stay once."""
    keyed = stage(docs.select(F.monotonically_increasing_id().alias("row"), F.struct("*").alias("doc")), "mix-rows")
    field = F.col("doc").getField
    text_col = options.pop("text_col", "text")
    parts = keyed.select("row", field(text_col).alias("text"), field(source_col).alias("source"), field(id_col).alias("drawn"))
    taken, _ = mix(parts, F.array("source"), id_col="row", text_col="text", drawn_by="drawn", **options)
    copies = F.when(F.col("size") > 0, F.floor(F.col("taken") / F.greatest(F.col("size"), F.lit(1)) + 0.5)).otherwise(1).cast("int")
    counted = taken.select(F.col("row").alias("t_row"), copies.alias("copies")).where("copies > 0")
    joined = keyed.join(counted, F.col("row") == F.col("t_row"))
    return joined.withColumn("copy", F.explode(F.sequence(F.lit(1), F.col("copies")))).select("doc.*")
