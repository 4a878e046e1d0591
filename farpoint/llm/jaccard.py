"""N-gram Jaccard similarity join by chosen paths.

Texts become sets of hashed word five-grams (words: lower-cased runs without ASCII white space; a text of one to four words is one gram).
1. Equal sets form one class, and only its representative goes on, so copies cost one aggregation.
2. Runs of chosen paths: in each run a set follows, level by level, the token that comes first in it under that level's random order, so two
   sets share a path of length k with probability similarity**k. Buckets of shared paths with few sets are compared by brute force on
   sketches; a large bucket first takes in everything very close to one of its pivots, and what is left is split by the next token, once for each of
   BRANCHES orders, so that a split parts a pair only if all its branches do.
   The number of runs follows from the target recall at the threshold, were every bucket split down to the deepest level; no two runs share an
   order on the first levels.
3. Sketch matches only join sets into candidate components. Inside these, all sets are compared exactly, block by block, by
   products of token-incidence matrices: the number of links of every set is counted and a spanning forest kept, so no list of all pairs
   of a group is ever made.
The result has one row for each row of the input: its class (the smallest id of all that links connect) and its number of links.

A pivot takes in sets of sketch similarity ``NEAR`` and links those from ``LOOSE``: anything as close as the threshold to a set taken in is
itself within LOOSE of the pivot by the triangle inequality of the Jaccard distance, so no link leaves the component.

Defined results: null and empty texts have no gram, no link and a class of their own; null ids are carried and never become a class while
another id is there; repeated rows are links of each other; an empty table gives an empty result; texts of any length are used
whole; further columns are ignored.
"""

from __future__ import annotations

import math
import random
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from farpoint.llm.components import components
from farpoint.plans.arrow import grouped
from farpoint.session import ship, stage

GRAM, THRESHOLD, RECALL = 5, 0.8, 0.9998
SKETCH = 64
#: First depth of the paths, largest bucket compared at once, sketch similarities of a pivot.
DEPTH, SMALL, NEAR, LOOSE = 3, 256, 0.8, 0.45
#: Pivots of a large bucket at each level: what they leave doubles with each split.
PIVOTS = 8
#: Levels after which what is left of large buckets is compared pivot by pivot, by pairs of blocks of about so many sets.
DEEPEST, DEEP_BLOCK = 10, 4096
#: Orders by which each set of a large bucket is split, and runs added because these orders are also those of other runs (by simulation: 18 runs
#: miss 0.0001 of pairs at the threshold when all buckets are split to DEEPEST, 14 would miss 0.0005).
BRANCHES, SPARE = 2, 4
#: Tokens and sets of one block of the exact comparison, rows of a tile of it (bounds the dense matrices), rows of a token up to which its pairs are listed.
BLOCK_TOKENS, BLOCK_SETS, TILE, RARE = 600_000, 1024, 2048, 16

_R, _K = 0x9E3779B97F4A7C15, 0xD6E8FEB86659FD93
_MASK = (1 << 64) - 1


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class Shingler:
    """Hashed word n-grams of many texts at once, from prefix sums of a polynomial hash modulo 2**64."""

    def __init__(self, gram: int = GRAM):
        self.gram = gram
        self.up = self.down = np.ones(1, np.uint64)

    def _powers(self, n: int) -> None:
        if len(self.up) <= n:
            size = 1 << n.bit_length()
            for name, base in (("up", _R), ("down", pow(_R, -1, 1 << 64))):
                steps = np.full(size, base, np.uint64)
                steps[0] = 1
                setattr(self, name, np.cumprod(steps, dtype=np.uint64))

    def sets(self, texts: list[str | None]) -> list[np.ndarray]:
        """Sorted distinct gram hashes of each text."""
        raw = [(t or "").lower().encode() for t in texts]
        out, at = [], 0
        while at < len(raw):
            stop, size = at, 0
            while stop < len(raw) and (stop == at or size + len(raw[stop]) < 1 << 20):
                size += len(raw[stop]) + 1
                stop += 1
            out += self._some(raw[at:stop])
            at = stop
        return out

    def _some(self, raw: list[bytes]) -> list[np.ndarray]:
        data = np.frombuffer(b" ".join(raw) + b" ", np.uint8)
        space = (data <= 32) & ((data == 32) | ((data >= 9) & (data <= 13)) | ((data >= 28) & (data <= 31)))
        edge = np.flatnonzero(np.diff(np.concatenate(([True], space, [True])).astype(np.int8)))
        start, end = edge[0::2], edge[1::2]
        self._powers(len(data))
        sums = np.zeros(len(data) + 1, np.uint64)
        np.cumsum((data.astype(np.uint64) + np.uint64(1)) * self.up[: len(data)], out=sums[1:])
        words = _mix((sums[end] - sums[start]) * self.down[start])
        borders = np.cumsum([0, *(len(r) + 1 for r in raw)])
        first = np.searchsorted(start, borders)
        g = self.gram
        n = max(0, len(words) - g + 1)
        grams = np.zeros(n, np.uint64)
        for k in range(g):
            grams = grams * np.uint64(_K) + words[k : k + n]
        grams = _mix(grams)
        out = []
        for a, z in zip(first[:-1].tolist(), first[1:].tolist()):
            if z - a >= g:
                out.append(np.unique(grams[a : z - g + 1]))
            elif z > a:
                h = z - a
                for w in words[a:z].tolist():
                    h = (h * _K + w) & _MASK
                out.append(_mix(np.array([h], np.uint64)))
            else:
                out.append(np.zeros(0, np.uint64))
        return out


_rng = random.Random(20240101)
_FACTORS = np.array([_rng.getrandbits(64) | 1 for _ in range(SKETCH)], np.uint64)[:, None]
_SHIFTS = np.array([_rng.getrandbits(64) for _ in range(SKETCH)], np.uint64)[:, None]


def sketch(grams: np.ndarray) -> np.ndarray:
    """The first token's hash under each of SKETCH random orders."""
    least = np.full(SKETCH, np.iinfo(np.uint32).max, np.uint32)
    for at in range(0, len(grams), 4096):
        least = np.minimum(least, ((grams[at : at + 4096] * _FACTORS + _SHIFTS) >> np.uint64(32)).astype(np.uint32).min(axis=1))
    return least.view(np.int32)


def runs_for(recall: float, threshold: float = THRESHOLD, depth: int = DEPTH) -> int:
    """Runs that find a pair at the threshold with this probability at any depth up to DEEPEST."""
    parted = 0.0  # probability that all branches below a bucket part a pair in it
    for _ in range(depth, DEEPEST):
        parted = (1 - threshold * (1 - parted)) ** BRANCHES
    runs = math.ceil(math.log(1 - recall) / math.log(1 - threshold**depth * (1 - parted))) + SPARE
    if runs * depth > SKETCH:
        raise ValueError(f"{runs} runs need a sketch of {runs * depth} orders")
    return runs


def _order(run: int, level: int) -> int:
    """Which of the random orders a run uses on one of the first levels: each run has its own."""
    return run * DEPTH + level


def _branch_order(run, node):
    """Which of the random orders leads to a node (1: root; children of n: BRANCHES * n and following) of a run's splits; numbers or long columns."""
    mixed = (run * 257 + node) * 2654435761
    return (mixed >> 16) % SKETCH if isinstance(mixed, int) else F.pmod(F.shiftright(mixed, 16), F.lit(SKETCH)).cast("int")


def _forest(n: int, pairs: Iterator[tuple[int, int]]) -> list[tuple[int, int]]:
    root, kept = list(range(n)), []

    def find(x: int) -> int:
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    for a, b in pairs:
        x, y = find(a), find(b)
        if x != y:
            root[max(x, y)] = min(x, y)
            kept.append((a, b))
    return kept


def _dense_forest(hit: np.ndarray, square: bool) -> list[tuple[int, int]]:
    """Edges (row, column) that connect whatever a boolean matrix connects, by breadth-first search over its rows; square: rows and columns are the same nodes."""
    kept: list[tuple[int, int]] = []
    new_row = np.ones(hit.shape[0], bool)
    new_column = new_row if square else np.ones(hit.shape[1], bool)
    for start in range(hit.shape[0]):
        if not new_row[start]:
            continue
        new_row[start] = False
        todo = [(start, True)]
        while todo:
            at, is_row = todo.pop()
            new = new_column if is_row else new_row
            met = np.flatnonzero((hit[at] if is_row else hit[:, at]) & new).tolist()
            new[met] = False
            kept += [(at, m) for m in met] if is_row else [(m, at) for m in met]
            todo += [(m, square or not is_row) for m in met]
    return kept


def _sketch_edges(sk: np.ndarray) -> list[tuple[int, int]]:
    """Links of one bucket that join all sets which a chain of loose sketch matches joins."""
    n, edges = len(sk), []
    if n <= SMALL:
        same = np.zeros((n, n), np.int16)
        for k in range(SKETCH):
            same += sk[:, k][:, None] == sk[:, k]
        a, b = np.nonzero(np.triu(same >= LOOSE * SKETCH, 1))
        return _forest(n, zip(a.tolist(), b.tolist()))
    left = np.ones(n, bool)
    for p in range(n):
        if left[p]:
            left[p] = False
            same = (sk == sk[p]).sum(axis=1)
            hit = np.flatnonzero((same >= LOOSE * SKETCH) & (np.arange(n) != p))
            edges += [(p, int(x)) for x in hit]
            left[same >= NEAR * SKETCH] = False
    return _forest(n, iter(edges))


def _edges_within(rows: DataFrame) -> DataFrame:
    """rows: bucket, rid, sketch. Brute force inside each bucket, one pass over sorted rows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out_a, out_b = [], []
        for g in grouped(batches):
            rid = g.column(1).to_numpy(zero_copy_only=False)
            sk = g.column(2).flatten().to_numpy(zero_copy_only=False).reshape(-1, SKETCH)
            for x, y in _sketch_edges(sk):
                out_a.append(rid[x])
                out_b.append(rid[y])
            if len(out_a) > 50_000:
                yield pa.RecordBatch.from_arrays([pa.array(out_a, pa.int64()), pa.array(out_b, pa.int64())], names=["a", "b"])
                out_a, out_b = [], []
        yield pa.RecordBatch.from_arrays([pa.array(out_a, pa.int64()), pa.array(out_b, pa.int64())], names=["a", "b"])

    return rows.select("bucket", "rid", "sketch").repartition("bucket").sortWithinPartitions("bucket").mapInArrow(run, "a long, b long")


def _block_pairs(large: DataFrame) -> DataFrame:
    """(bucket, rid) for every pair of blocks of every bucket (path, rid, n): buckets of bounded size in which all pairs of sets of the large one meet."""
    blocks = F.ceil(F.col("n") / DEEP_BLOCK)
    own = large.select("path", "rid", blocks.alias("blocks"), F.pmod(F.xxhash64("rid"), blocks).alias("own"))
    met = own.withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)))
    return met.select(F.xxhash64("path", F.least("own", "other"), F.greatest("own", "other")).alias("bucket"), "rid")


def _pivots(large: DataFrame, reps: DataFrame) -> DataFrame:
    """(p_path, pivots): at most PIVOTS random sets of every bucket, as structs (rid, sketch)."""
    drawn = [F.min(F.struct(F.xxhash64("rid", F.lit(k)).alias("draw"), "rid")).getField("rid") for k in range(PIVOTS)]
    chosen = large.groupBy("path").agg(F.array_distinct(F.array(*drawn)).alias("rids")).select("path", F.explode("rids").alias("rid"))
    return chosen.join(reps, "rid").groupBy(F.col("path").alias("p_path")).agg(F.collect_list(F.struct("rid", "sketch")).alias("pivots"))


def candidate_edges(reps: DataFrame, recall: float = RECALL, threshold: float = THRESHOLD) -> DataFrame:
    """reps: rid, sketch. Chosen paths, then (a, b) joining all likely similar sets."""
    runs = runs_for(recall, threshold)
    token = lambda run, level: F.col("sketch")[_order(run, level)]
    first = F.array(*(F.struct(F.lit(r).alias("run"), F.xxhash64(F.lit(r), *(token(r, k) for k in range(DEPTH))).alias("path")) for r in range(runs)))
    keys = reps.select("rid", F.explode(first).alias("k")).select("rid", "k.run", F.lit(1).cast("long").alias("node"), "k.path")
    edges: list[DataFrame] = []
    deep: list[DataFrame] = []
    small: list[DataFrame] = []
    for level in range(DEPTH, DEEPEST + 1):
        counts = keys.groupBy(F.col("path").alias("c_path")).agg(F.count("*").alias("n")).where("n > 1")
        shared = stage(keys.join(counts, F.col("path") == F.col("c_path")).select("rid", "run", "node", "path", "n"), f"shared-{level}")
        small.append(shared.where(F.col("n") <= SMALL).select("path", "rid"))
        large = shared.where(F.col("n") > SMALL)
        if large.isEmpty():
            break
        if level == DEEPEST:
            deep.append(_edges_within(_block_pairs(large).join(reps, "rid")))
            break
        near = large.join(reps, "rid").join(_pivots(large, reps), F.col("path") == F.col("p_path"))
        same = lambda p: F.aggregate(F.zip_with("sketch", p["sketch"], lambda x, y: (x == y).cast("int")), F.lit(0), lambda n, x: n + x)
        alike = F.transform("pivots", lambda p: F.struct(p["rid"].alias("pivot"), same(p).alias("same")))
        child = [F.col("node") * BRANCHES + b for b in range(BRANCHES)]
        parts = F.array(*(F.struct(c.alias("node"), F.xxhash64("path", c, F.get("sketch", _branch_order(F.col("run").cast("long"), c))).alias("path")) for c in child))
        met = stage(near.select("rid", "run", alike.alias("alike"), parts.alias("parts")), f"pivots-{level}")
        linked = met.select("rid", F.explode(F.filter("alike", lambda p: p["same"] >= LOOSE * SKETCH)).alias("p")).select(F.col("rid").alias("a"), F.col("p.pivot").alias("b"))
        edges.append(linked.where("a <> b"))
        keys = met.where(~F.exists("alike", lambda p: p["same"] >= NEAR * SKETCH)).select("rid", "run", F.explode("parts").alias("k")).select("rid", "run", "k.node", "k.path")
    # All levels share one grouping and one distinct: the plan that the driver holds gains only a scan with each level.
    # Small buckets: the same few sets meet in most runs; each list of sets is compared once. At most SMALL ids in a list.
    lists = reduce(DataFrame.union, small).groupBy("path").agg(F.sort_array(F.collect_list("rid")).alias("rids")).select("rids")
    buckets = lists.distinct().select(F.xxhash64("rids").alias("bucket"), F.explode("rids").alias("rid"))
    found = [_edges_within(buckets.join(reps, "rid")), *deep]
    if edges:
        found.append(reduce(DataFrame.union, edges).distinct())
    return reduce(DataFrame.union, found)


def _sets(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(id, text_hash, k1, k2, n, sketch): the set's 128-bit key, its size and its sketch."""
    kind = docs.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingler = Shingler()
        for b in batches:
            for at in range(0, b.num_rows, 128):
                part = b.slice(at, 128)
                sets = shingler.sets(part.column(1).to_pylist())
                key = np.array([(s.sum(dtype=np.uint64), np.bitwise_xor.reduce(s * np.uint64(_K)) if len(s) else 0) for s in sets], np.uint64).view(np.int64).reshape(-1, 2)
                sk = pa.array(np.concatenate([sketch(s) for s in sets]), pa.int32())
                lists = pa.ListArray.from_arrays(pa.array(np.arange(0, SKETCH * len(sets) + 1, SKETCH), pa.int32()), sk)
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), pa.array(key[:, 0]), pa.array(key[:, 1]), pa.array([len(s) for s in sets], pa.int64()), lists], names=[id_col, "text_hash", "k1", "k2", "n", "sketch"])

    return docs.select(id_col, text_col, F.xxhash64(text_col).alias("text_hash")).mapInArrow(run, f"`{id_col}` {kind}, text_hash long, k1 long, k2 long, n long, sketch array<int>")


def _exact(members: DataFrame) -> DataFrame:
    """members: g, side (0, 1 or 2: both), rid, weight, grams. Per group the links between its two sides: rows (rid, links) and forest edges (rid, other)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for g in grouped(batches):
            side = g.column(1).to_numpy(zero_copy_only=False)
            rid = g.column(2).to_numpy(zero_copy_only=False)
            weight = g.column(3).to_numpy(zero_copy_only=False).astype(np.float64)
            sets = [np.frombuffer(x.as_buffer(), np.uint64) for x in g.column(4)]
            alone = bool((side == 2).all())
            x, y = (np.arange(len(side)),) * 2 if alone else (np.flatnonzero(side == 0), np.flatnonzero(side == 1))
            if not len(x) or not len(y) or alone and len(x) < 2:
                continue
            links, forest = links_between(sets, x, y, weight)
            got = np.flatnonzero(links)
            rows = [(int(rid[i]), int(links[i]), None) for i in got] + [(int(rid[i]), None, int(rid[j])) for i, j in forest]
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows)], names=["rid", "links", "other"])

    return members.select("g", "side", "rid", "weight", "grams").repartition("g").sortWithinPartitions("g").mapInArrow(run, "rid long, links long, other long")


def links_between(sets: list[np.ndarray], x: np.ndarray, y: np.ndarray, weight: np.ndarray) -> tuple[np.ndarray, list[tuple[int, int]]]:
    """Weight of every set's links between x and y (the same sets or disjoint ones) and forest edges, tile by tile."""
    links, alone = np.zeros(len(sets)), np.array_equal(x, y)

    def edges() -> Iterator[tuple[int, int]]:
        for i in range(0, len(x), TILE):
            for j in range(i if alone else 0, len(y), TILE):
                left, right, square = x[i : i + TILE], y[j : j + TILE], alone and i == j
                hit = similar(sets, left, right)
                if square:
                    np.fill_diagonal(hit, False)
                links[left] += hit @ weight[right]
                if not square:
                    links[right] += hit.T @ weight[left]
                yield from ((int(left[a]), int(right[b])) for a, b in _dense_forest(hit, square))

    return links, _forest(len(sets), edges())


def similar(sets: list[np.ndarray], x: np.ndarray, y: np.ndarray, threshold: float = THRESHOLD) -> np.ndarray:
    """Boolean len(x) by len(y): Jaccard similarity of at least threshold, exactly, from products of incidence matrices over shared tokens."""
    use = np.unique(np.concatenate([x, y]))
    sizes = np.array([len(s) for s in sets], np.float64)
    tokens = np.concatenate([sets[i] for i in use])
    row = np.repeat(use, [len(sets[i]) for i in use])
    order = np.argsort(tokens, kind="stable")
    tokens, row = tokens[order], row[order]
    new = np.concatenate(([True], tokens[1:] != tokens[:-1]))
    column = np.cumsum(new) - 1
    held = np.bincount(column)[column]
    at_x, at_y = np.full(len(sets), -1), np.full(len(sets), -1)
    at_x[x], at_y[y] = np.arange(len(x)), np.arange(len(y))
    both = np.zeros((len(x), len(y)), np.float32)
    rare = (held > 1) & (held <= RARE)
    c, r = column[rare], row[rare]
    for step in range(1, RARE):  # tokens of few sets: pairs one by one
        a, b = r[:-step][c[:-step] == c[step:]], r[step:][c[:-step] == c[step:]]
        for a, b in ((a, b), (b, a)):
            ok = (at_x[a] >= 0) & (at_y[b] >= 0)
            np.add.at(both, (at_x[a[ok]], at_y[b[ok]]), 1)
    column, row = np.unique(column[held > RARE], return_inverse=True)[1], row[held > RARE]
    columns = int(column[-1]) + 1 if len(column) else 0
    width = min(1024, columns)
    for lo in range(0, columns, max(width, 1)):
        a, z = np.searchsorted(column, [lo, lo + width])
        c, r = column[a:z] - lo, row[a:z]
        left, right = np.zeros((len(x), width), np.float32), np.zeros((len(y), width), np.float32)
        in_x, in_y = at_x[r] >= 0, at_y[r] >= 0
        left[at_x[r[in_x]], c[in_x]] = 1
        right[at_y[r[in_y]], c[in_y]] = 1
        both += left @ right.T
    hit = np.zeros(both.shape, bool)
    for at in range(0, len(x), 256):  # a few rows at a time in double precision
        common = both[at : at + 256].astype(np.float64)
        hit[at : at + 256] = common >= threshold * (sizes[x[at : at + 256]][:, None] + sizes[y] - common) - 1e-9
    return hit


def similarity_classes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", recall: float = RECALL) -> DataFrame:
    """(id, class_id, n_links, _row) of every row; _row numbers the rows of the staged input."""
    ship(docs.sparkSession)
    docs = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"))
    sets = stage(_sets(docs, "doc_id", "text").withColumn("rid", F.monotonically_increasing_id()), "sets")
    classes = stage(sets.where("n > 0").groupBy("k1", "k2").agg(F.min("rid").alias("rep"), F.count("*").alias("size"), F.min("doc_id").alias("least"), F.min("n").alias("n")), "classes")
    reps = stage(sets.select("rid", "doc_id", "text_hash", "sketch").join(classes.select(F.col("rep").alias("rid"), "size", "k1", "k2", "n"), "rid"), "representatives")
    edges = stage(candidate_edges(reps.select("rid", "sketch"), recall), "edges")  # on its own: no task needs two Python workers
    likely = components(edges)
    likely = stage(likely.join(reps.select(F.col("rid").alias("node"), "doc_id", "text_hash", "k1", "k2", "n", "size"), "node"), "likely")
    # Exact comparison inside candidate components: blocks of about BLOCK_TOKENS tokens and BLOCK_SETS sets, all pairs of blocks.
    blocks = likely.groupBy(F.col("component").alias("c")).agg(F.greatest(F.ceil(F.sum("n") / BLOCK_TOKENS), F.ceil(F.count("*") / BLOCK_SETS)).cast("int").alias("blocks"))
    wanted = likely.join(blocks, F.col("component") == F.col("c")).select(F.col("doc_id").alias("w_doc"), F.col("text_hash").alias("w_hash"), F.col("k1").alias("w1"), F.col("k2").alias("w2"), F.col("node").alias("rid"), "component", "blocks", F.col("size").alias("weight"))
    # A text is met by its id and hash: rows that share an id (null, say) do not multiply.
    texts = docs.withColumn("text_hash", F.xxhash64("text")).join(wanted.hint("merge"), F.col("doc_id").eqNullSafe(F.col("w_doc")) & (F.col("text_hash") == F.col("w_hash"))).select("text", "w1", "w2", "rid", "component", "blocks", "weight")

    def regram(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingler = Shingler()
        for b in batches:
            for at in range(0, b.num_rows, 256):
                part = b.slice(at, 256)
                found = shingler.sets(part.column(0).to_pylist())
                keys = list(zip(part.column(1).to_pylist(), part.column(2).to_pylist()))
                ok = [len(s) > 0 and (int(s.sum(dtype=np.uint64).view(np.int64)), int(np.bitwise_xor.reduce(s * np.uint64(_K)).view(np.int64))) == k for s, k in zip(found, keys)]  # another text with the same id and hash drops out
                pick = pa.array(np.flatnonzero(ok))
                yield pa.RecordBatch.from_arrays([*(part.column(i).take(pick) for i in (3, 4, 5, 6)), pa.array([s.tobytes() for s, o in zip(found, ok) if o], pa.binary())], names=["rid", "component", "blocks", "weight", "grams"])

    grams = texts.mapInArrow(regram, "rid long, component long, blocks int, weight long, grams binary").dropDuplicates(["rid"])
    own = F.pmod(F.xxhash64("rid"), F.col("blocks")).cast("int")
    pairs = grams.withColumn("own", own).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    lo, hi = F.least("own", "other"), F.greatest("own", "other")
    side = F.when(F.col("own") == F.col("other"), 2).when(F.col("own") < F.col("other"), 0).otherwise(1)
    exact = stage(_exact(pairs.select(F.xxhash64("component", lo, hi).alias("g"), side.alias("side"), "rid", "weight", "grams")), "links")
    links = exact.where("other is null").groupBy("rid").agg(F.sum("links").alias("links"))
    joined = components(exact.where("other is not null").select(F.col("rid").alias("a"), F.col("other").alias("b")), "linked")
    named = classes.select("rep", "least").join(joined, F.col("rep") == F.col("node")).groupBy("component").agg(F.min("least").alias("class_id")).select(F.col("component").alias("m"), "class_id")
    where = joined.join(named, F.col("component") == F.col("m")).select("node", "class_id").join(links.withColumnRenamed("rid", "l_rid"), F.col("node") == F.col("l_rid"), "left").select("node", "class_id", "links")
    told = classes.join(where, F.col("rep") == F.col("node"), "left").select(F.col("k1").alias("t1"), F.col("k2").alias("t2"), F.coalesce("class_id", "least").alias("class_id"), (F.coalesce("links", F.lit(0)) + F.col("size") - 1).alias("n_links"))
    rows = sets.select("rid", "doc_id", "k1", "k2", "n")
    with_class = rows.where("n > 0").join(told, (F.col("k1") == F.col("t1")) & (F.col("k2") == F.col("t2")), "left").select(F.col("doc_id").alias(id_col), "class_id", "n_links", F.col("rid").alias("_row"))
    empty = rows.where("n = 0").select(F.col("doc_id").alias(id_col), F.col("doc_id").alias("class_id"), F.lit(0).cast("long").alias("n_links"), F.col("rid").alias("_row"))
    return with_class.union(empty)


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row of each class, with all columns: the one with the smallest id, nulls last. Empty texts all stay."""
    numbered = stage(docs.select(F.monotonically_increasing_id().alias("n"), F.struct("*").alias("doc")), "numbered")  # a struct: no column can clash
    field = F.col("doc").getField
    classes = similarity_classes(numbered.select("n", field(text_col).alias("text")), "n", "text").select(F.col("n").alias("c_n"), "class_id")
    ids = numbered.select("n", field(id_col).alias("id"))
    first = F.min(F.struct(F.col("id").isNull(), F.col("id"), F.col("n")).alias("f"))
    kept = classes.join(ids, F.col("c_n") == F.col("n")).groupBy("class_id").agg(first.alias("first")).select(F.col("first.n").alias("k_n"))
    return numbered.join(kept, F.col("n") == F.col("k_n"), "left_semi").select("doc.*")
