"""Approximate nearest neighbours by learned partitions.

A bounded sample's neighbour graph is cut into balanced parts (median splits refined by swaps that save
cut edges). A small network learns which parts hold a vector's neighbours; it assigns every row of the table to its likeliest part and
sends each query to its several likeliest ones, where all rows are compared exactly. How many parts a query visits is set on
held-out sample vectors, so that their recall reaches the target.

Only the k + 1 smallest ids of equal vectors can be among k nearest, so a vector that a third of the rows share costs k + 1 rows.
Parts grow with the rows up to an eighth of the sample; beyond that parts get slots, so a task's rows are bounded at any size.
Rows are compared in blocks of bounded size; no part is collected.

Defined results: vectors that are null, of another length than most, zero, or hold null or non-finite components take no part; rows
of the query's own id are no candidates; a repeated row (id and vector) counts once; ties go to the smaller id; with fewer than k
candidates all are returned; an empty table gives an empty result; further columns are ignored.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from farpoint.composite.neighbours import canonical, centred_squares
from farpoint.plans.arrow import grouped
from farpoint.session import ship, stage

#: Vectors that the partitioning and the classifier are fitted on, at most, and those of them that calibrate the number of visits.
SAMPLE, HELD_OUT = 8192, 1024
#: Recall on the held-out sample vectors.
RECALL = 0.95
#: Rows compared at once, and rows of a part that one task holds: larger parts are dealt into slots, each met by all of the part's queries.
BLOCK, SLOT = 2048, 65_536


def neighbour_graph(x: np.ndarray, k: int) -> np.ndarray:
    """Ids of the k nearest other rows of each row, by blocks."""
    out, norms = np.empty((len(x), k), np.int64), (x * x).sum(1)
    for at in range(0, len(x), 512):
        d = norms - 2 * x[at : at + 512] @ x.T
        d[np.arange(len(d)), at + np.arange(len(d))] = np.inf
        out[at : at + 512] = np.argpartition(d, k - 1, axis=1)[:, :k]
    return out


def balanced_parts(x: np.ndarray, graph: np.ndarray, levels: int, seed: int = 5) -> np.ndarray:
    """A part number below 2**levels for each row; sizes differ by one row a level at most."""
    part = np.zeros(len(x), np.int64)
    rng = np.random.default_rng(seed)
    source = np.repeat(np.arange(len(x)), graph.shape[1])
    target = graph.ravel()
    for _ in range(levels):
        half = np.zeros(len(x), np.int64)
        for p in np.unique(part):
            rows = np.flatnonzero(part == p)
            centred = x[rows] - x[rows].mean(0)
            axis = rng.standard_normal(x.shape[1])
            for _ in range(8):
                axis = centred.T @ (centred @ axis)
                axis /= np.linalg.norm(axis) + 1e-30
            half[rows[np.argsort(centred @ axis, kind="stable")[len(rows) // 2 :]]] = 1
        for _ in range(12):  # swaps inside each part: as many rows each way, those with the largest gains
            inside = part[source] == part[target]
            same = inside & (half[source] == half[target])
            pull = np.zeros(len(x))
            for a, b in ((source, target), (target, source)):
                np.add.at(pull, a[inside], np.where(same[inside], -1.0, 1.0))
            moved = 0
            for p in np.unique(part):
                rows = np.flatnonzero(part == p)
                a, b = rows[half[rows] == 0], rows[half[rows] == 1]
                a, b = a[np.argsort(-pull[a], kind="stable")], b[np.argsort(-pull[b], kind="stable")]
                n = min(len(a), len(b))
                good = int((pull[a[:n]] + pull[b[:n]] > 2).sum()) // 2
                half[a[:good]], half[b[:good]] = 1, 0
                moved += good
            if not moved:
                break
        part = 2 * part + half
    return part


@dataclass
class Router:
    """One hidden layer; scores of all parts for rows of vectors."""

    w1: np.ndarray
    b1: np.ndarray
    w2: np.ndarray
    b2: np.ndarray
    scale: float

    def logits(self, x: np.ndarray) -> np.ndarray:
        return np.maximum(x / self.scale @ self.w1 + self.b1, 0) @ self.w2 + self.b2

    @property
    def parts(self) -> int:
        return len(self.b2)


def train_router(x: np.ndarray, goal: np.ndarray, hidden: int = 128, rounds: int = 40, seed: int = 11) -> Router:
    """Cross-entropy against goal (rows of shares of parts) by Adam."""
    rng = np.random.default_rng(seed)
    scale = float(np.abs(x).mean()) or 1.0
    r = Router(rng.standard_normal((x.shape[1], hidden)).astype(np.float32) / x.shape[1] ** 0.5, np.zeros(hidden, np.float32), rng.standard_normal((hidden, goal.shape[1])).astype(np.float32) / hidden**0.5, np.zeros(goal.shape[1], np.float32), scale)
    names = ("w1", "b1", "w2", "b2")
    m, v, t = {n: 0.0 for n in names}, {n: 0.0 for n in names}, 0
    for k in range(rounds):
        order = rng.permutation(len(x))
        for at in range(0, len(x), 256):
            rows = order[at : at + 256]
            a = x[rows] / scale
            h = np.maximum(a @ r.w1 + r.b1, 0)
            z = h @ r.w2 + r.b2
            p = np.exp(z - z.max(1, keepdims=True))
            p /= p.sum(1, keepdims=True)
            dz = (p - goal[rows]) / len(rows)
            dh = dz @ r.w2.T * (h > 0)
            grads = {"w2": h.T @ dz, "b2": dz.sum(0), "w1": a.T @ dh, "b1": dh.sum(0)}
            t += 1
            for n in names:
                g = grads[n] + (1e-4 * getattr(r, n) if n[0] == "w" else 0)
                m[n], v[n] = 0.9 * m[n] + 0.1 * g, 0.999 * v[n] + 0.001 * g * g
                rate = 2e-3 * (1 - k / rounds)
                setattr(r, n, (getattr(r, n) - rate * (m[n] / (1 - 0.9**t)) / (np.sqrt(v[n] / (1 - 0.999**t)) + 1e-8)).astype(np.float32))
    return r


def fit(sample: np.ndarray, rows: int, k: int = 10, recall: float = RECALL) -> tuple[Router, int]:
    """(router, parts to visit) from sample vectors of a table with so many rows."""
    x = sample.astype(np.float32)
    levels = max(1, int(np.log2(max(2, rows / 400))))  # parts grow with the rows, as far as the sample tells them apart
    while 2**levels * 8 > len(x) and levels > 1:
        levels -= 1
    parts = 2**levels
    near = min(k, len(x) - 1)
    if near < 1:
        return Router(np.zeros((x.shape[1], 1), np.float32), np.zeros(1, np.float32), np.zeros((1, parts), np.float32), np.zeros(parts, np.float32), 1.0), parts
    graph = neighbour_graph(x, near)
    part = balanced_parts(x, graph, levels)
    goal = np.zeros((len(x), parts), np.float32)
    np.add.at(goal, (np.repeat(np.arange(len(x)), near), part[graph.ravel()]), 1.0)
    goal[np.arange(len(x)), part] += 2.0
    goal /= goal.sum(1, keepdims=True)
    held = np.arange(len(x)) % max(2, len(x) // HELD_OUT) == 0
    router = train_router(x[~held], goal[~held])
    scores = router.logits(x)
    home = scores.argmax(1)
    rank = np.argsort(np.argsort(-scores[held], axis=1), axis=1)
    need = np.take_along_axis(rank, home[graph[held]], axis=1)
    visits = next((n for n in range(1, parts + 1) if (need < n).mean() >= recall), parts)
    return router, visits


def usable(vector: Column) -> Column:
    """Not null, not zero, no null or non-finite component."""
    bad = lambda v: v.isNull() | F.isnan(v) | (F.abs(v) == float("inf"))
    return vector.isNotNull() & ~F.exists(vector, bad) & F.exists(vector, lambda v: v != 0)


def search(vectors: DataFrame, is_query: Column, k: int = 10, id_col: str = "vec_id", vector_col: str = "embedding", sample: int = SAMPLE, recall: float = RECALL) -> DataFrame:
    """(query_id, rank, id, score) of each query's k nearest found by Euclidean distance."""
    spark = ship(vectors.sparkSession)
    rows = vectors.where(usable(F.col(vector_col)) & F.col(id_col).isNotNull()).select(F.col(id_col).cast("long").alias("id"), F.transform(vector_col, lambda v: v.cast("double")).alias("v"), F.coalesce(is_query, F.lit(False)).alias("q"))
    rows = stage(rows, "vectors")
    widths = rows.groupBy(F.size("v").alias("d")).count().orderBy(F.desc("count"), "d").limit(1).collect()
    result = f"query_id long, rank int, `{id_col}` long, score double"
    if not widths:
        return spark.createDataFrame([], result)
    d, n = widths[0]
    rows = rows.where(F.size("v") == d).dropDuplicates(["id", "v"])
    base = stage(rows.withColumn("_r", F.row_number().over(Window.partitionBy("v").orderBy("id"))).where(F.col("_r") <= k + 1).select("id", "v"), "distinct-vectors")
    taken = np.array([r["v"] for r in base.select("v").distinct().orderBy(F.xxhash64("v")).limit(sample).collect()])  # at most `sample` vectors
    router, visits = fit(taken, n, k, recall)
    sent = spark.sparkContext.broadcast(pickle.dumps(router))  # at most sample / 8 parts by 128 units
    matrix = lambda c: c.flatten().to_numpy(zero_copy_only=False).reshape(-1, d)

    def routed(count: int):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            r = pickle.loads(sent.value)
            for b in batches:
                for at in range(0, b.num_rows, BLOCK):
                    part = b.slice(at, BLOCK)
                    best = np.argsort(-r.logits(matrix(part.column(1)).astype(np.float32)), axis=1, kind="stable")[:, :count].astype(np.int64)
                    pick = pa.array(np.repeat(np.arange(part.num_rows), best.shape[1]))
                    yield pa.RecordBatch.from_arrays([pa.array(best.ravel()), part.column(0).take(pick), part.column(1).take(pick)], names=["part", "id", "v"])

        return run

    def blocked(size: int):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                for g in grouped(iter([b])):
                    for at in range(0, g.num_rows, size):
                        s = g.slice(at, size)
                        yield pa.RecordBatch.from_arrays([s.column(0).slice(0, 1), pa.array([s.column(1).to_numpy(zero_copy_only=False).tobytes()]), pa.array([np.ascontiguousarray(matrix(s.column(2))).tobytes()])], names=["place", "ids", "body"])

        return run

    def routed_rows(df: DataFrame, count: int) -> DataFrame:
        return df.mapInArrow(routed(count), "part long, id long, v array<double>")

    def blocks(placed: DataFrame, size: int, name: str) -> DataFrame:
        sorted_ = placed.select("place", "id", "v").repartition("place").sortWithinPartitions("place")
        return sorted_.mapInArrow(blocked(size), "place long, ids binary, body binary").select("place", F.col("ids").alias(f"{name}_ids"), F.col("body").alias(f"{name}_body"))

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):
                q_ids, q, c_ids, c = (np.frombuffer(b.column(j)[i].as_buffer(), t) for j, t in enumerate((np.int64, np.float64, np.int64, np.float64)))
                q, c = q.reshape(-1, d), c.reshape(-1, d)
                near, slack = centred_squares(q, c)
                near[q_ids[:, None] == c_ids] = np.inf
                limit = np.partition(near, min(k, near.shape[1]) - 1, axis=1)[:, min(k, near.shape[1]) - 1]
                x, y = np.nonzero((near <= (limit + 2 * slack)[:, None]) & np.isfinite(near))
                exact = canonical(q, c, x, y)
                order = np.lexsort((c_ids[y], exact, x))
                x, y, exact = x[order], y[order], exact[order]
                place = np.arange(len(x)) - np.searchsorted(x, x)
                keep = place < k
                yield pa.RecordBatch.from_arrays([pa.array(q_ids[x[keep]]), pa.array(c_ids[y[keep]]), pa.array(exact[keep])], names=["query_id", "id", "score"])

    # A place is a slot of a part. Parts are learned, so their sizes in the table are counted, and a large one gets as many slots as it needs.
    homes = stage(routed_rows(base, 1), "homes")
    sizes = dict(homes.groupBy("part").count().collect())  # one row a part
    slots = F.array(*(F.lit(-(-sizes.get(p, 0) // SLOT)) for p in range(router.parts)))
    wide = max(1, max(-(-v // SLOT) for v in sizes.values()))
    many = F.greatest(F.get(slots, F.col("part").cast("int")), F.lit(1)).cast("long")
    base_places = homes.withColumn("place", F.col("part") * wide + F.pmod(F.xxhash64("id"), many))
    queries = routed_rows(rows.where("q").select("id", "v"), visits).withColumn("slot", F.explode(F.sequence(F.lit(0).cast("long"), many - 1))).withColumn("place", F.col("part") * wide + F.col("slot"))
    pairs = blocks(queries, 256, "q").join(blocks(base_places, BLOCK, "c"), "place").select("q_ids", "q_body", "c_ids", "c_body")
    found = pairs.mapInArrow(compare, "query_id long, id long, score double")
    ranked = found.withColumn("rank", F.row_number().over(Window.partitionBy("query_id").orderBy("score", "id")))
    return ranked.where(F.col("rank") <= k).select("query_id", "rank", F.col("id").alias(id_col), "score")


def exact_search(vectors: DataFrame, is_query: Column, k: int = 10, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """Brute force over the same rows by a query-against-all join in Spark expressions: for tests and for measuring recall."""
    rows = vectors.where(usable(F.col(vector_col))).select(F.col(id_col).cast("long").alias("id"), F.transform(vector_col, lambda v: v.cast("double")).alias("v"), is_query.alias("q")).dropDuplicates(["id", "v"])
    q = rows.where("q").select(F.col("id").alias("query_id"), F.col("v").alias("w"))
    apart = F.sqrt(F.aggregate(F.zip_with("v", "w", lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, x: s + x))
    pairs = q.join(rows, F.col("query_id") != F.col("id")).select("query_id", "id", apart.alias("score"))
    ranked = pairs.withColumn("rank", F.row_number().over(Window.partitionBy("query_id").orderBy("score", "id")))
    return ranked.where(F.col("rank") <= k).select("query_id", "rank", F.col("id").alias(id_col), "score")
