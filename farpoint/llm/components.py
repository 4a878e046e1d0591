"""Connected components of an edge table by alternating star contractions, each round written to the shared folder."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from farpoint.session import ship, stage

#: Half the most nodes whose edges are joined by broadcast.
HUBS = 2000


def _with_least(edges: DataFrame, links: int) -> tuple[DataFrame, DataFrame]:
    """edges (u, v) with k = u and m, the smallest v of u; and (k, m) of every u. Nodes of very many edges are joined by broadcast, so no task gets all
    edges of one: their limit grows with the number of links, so there are never more than 2 * HUBS of them."""
    limit = max(1000, links // HUBS)
    least = edges.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("n")).select(F.col("u").alias("k"), "m", "n")
    hubs = F.broadcast(least.where(F.col("n") > limit).drop("n"))  # at most 2 * HUBS rows
    there = F.col("u") == F.col("k")
    met = edges.join(hubs, there).unionByName(edges.join(hubs, there, "left_anti").join(least.where(F.col("n") <= limit).drop("n"), there))
    return met, least.select("k", "m")


def _large_star(edges: DataFrame, links: int) -> DataFrame:
    """Every node's larger neighbours are linked to the smallest of its neighbours and itself."""
    both = edges.select(F.col("a").alias("u"), F.col("b").alias("v")).union(edges.select("b", "a"))
    met = _with_least(both, links)[0].withColumn("m", F.least("u", "m"))
    return met.where("v > u and v <> m").select(F.col("v").alias("a"), F.col("m").alias("b")).distinct()


def _small_star(edges: DataFrame, links: int) -> DataFrame:
    """Every node and its smaller neighbours are linked to the smallest of them."""
    down = edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v"))
    moved, least = _with_least(down, links)
    return moved.where("v <> m").select(F.col("v").alias("a"), F.col("m").alias("b")).union(least).distinct()


def _contract(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Each batch's edges as links of its nodes to the smallest node that the batch connects them to."""
    for b in batches:
        root: dict[int, int] = {}

        def find(x: int) -> int:
            while root[x] != x:
                root[x] = root[root[x]]
                x = root[x]
            return x

        for a, c in zip(*(col.to_pylist() for col in b.columns)):
            x, y = find(root.setdefault(a, a)), find(root.setdefault(c, c))
            if x != y:
                root[max(x, y)] = min(x, y)
        links = [(x, find(x)) for x in root if find(x) != x]
        if links:
            yield pa.RecordBatch.from_arrays([pa.array(v, pa.int64()) for v in zip(*links)], names=["a", "b"])


def components(edges: DataFrame, name: str = "components") -> DataFrame:
    """(node, component): component is the smallest node of each connected part; nodes without an edge to another are left out.

    edges: a, b long. Batches are contracted first; rounds go on until every node has one link and it leads to a root. Each half of a round is
    written: in one plan the second half would hold the first many times over, and the driver keeps plans whole.
    """
    ship(edges.sparkSession)
    now = stage(edges.where("a <> b").select("a", "b").mapInArrow(_contract, "a long, b long").distinct(), name)
    while not (now.groupBy("a").count().where("count > 1").isEmpty() and now.join(now.select(F.col("a").alias("c")), F.col("b") == F.col("c"), "left_semi").isEmpty()):
        links = now.count()
        now = stage(_small_star(stage(_large_star(now, links), f"{name}-large"), links), name)
    return now.select(F.col("a").alias("node"), F.col("b").alias("component")).union(now.select(F.col("b"), F.col("b")).distinct())
