"""Operator registry, dependency classes, the detector tree and its fusion rules.

An operator says whether a row's result needs other rows (sample dependency) and whether a feature's needs other features. Without one of the
two it is batched along that axis automatically; with both, its author gives a splitter for pairs of row splits. A detector is a
small tree of operator nodes; before anything is planned, rules replace neighbouring nodes by fused ones.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from farpoint.model import FeatureFrame
from farpoint.plans.arrow import grouped, matrix
from farpoint.plans.blocks import Block, MemoryBudgetExceeded, blocks_for, run_owners
from farpoint.quantize.bounds import eligible
from farpoint.session import ship, stage


@dataclass(frozen=True)
class OpSpec:
    """raw_floats: the output is full-precision numbers. gain and check_cost: seconds (or any common unit) of low precision and of its check."""

    name: str
    sample_dep: bool
    feature_dep: bool
    raw_floats: bool = False
    gain: float = 0.0
    check_cost: float = 1.0

    @property
    def strategy(self) -> str:
        if self.sample_dep and self.feature_dep:
            return "pairs"
        return "features" if self.sample_dep else "rows"

    @property
    def quantizable(self) -> bool:
        return eligible(self.raw_floats, self.gain, self.check_cost)


#: Bytes of one feature (ids and values) that a task takes for an operator that needs it whole.
FEATURE_BUDGET = 1 << 30
OPERATORS: dict[str, OpSpec] = {}
IMPLEMENTATIONS: dict[str, Callable] = {}
DETECTORS: dict[str, Callable[..., DataFrame]] = {}
RULES: list[tuple[tuple[str, ...], Callable]] = []

for spec in (
    OpSpec("pairwise_distance", True, True, raw_floats=True),
    OpSpec("topk", False, True, gain=2, check_cost=1),
    OpSpec("intersection", True, False),
    OpSpec("histogram", True, False, gain=1, check_cost=0.5),
    OpSpec("feature_sample", False, True),
    OpSpec("ecdf", True, False, gain=1, check_cost=0.5),
    OpSpec("linear_map", False, True, raw_floats=True),
    OpSpec("moments", True, False, raw_floats=True),
    OpSpec("knn", True, True, gain=4, check_cost=1),
    OpSpec("neighbours_in_range", True, True, gain=4, check_cost=1),
    OpSpec("cosine", False, True, raw_floats=True),
    OpSpec("tails", True, False, raw_floats=True),
    OpSpec("axes", True, True, raw_floats=True),
    OpSpec("reach_density", True, False, raw_floats=True),
):
    OPERATORS[spec.name] = spec


def register_operator(spec: OpSpec, fn: Callable, splitter: Callable | None = None) -> None:
    """fn: rows strategy, matrix to matrix with as many rows; features strategy, one whole column to one column (refused beyond FEATURE_BUDGET); pairs strategy, unused.
    splitter (pairs only, mandatory there): (own ids, own rows, other ids, other rows) to (ids i, ids j, values)."""
    if spec.strategy == "pairs" and splitter is None:
        raise ValueError(f"{spec.name} depends on other rows and other features: it needs a splitter")
    OPERATORS[spec.name] = spec
    IMPLEMENTATIONS[spec.name] = splitter if spec.strategy == "pairs" else fn


def run_operator(name: str, x: FeatureFrame, batch: int = 4096, blocks: int | None = None) -> DataFrame:
    """A registered operator over a frame, batched by its class. rows and features: (id, x array); pairs: (i, j, value)."""
    spec, fn, d = OPERATORS[name], IMPLEMENTATIONS[name], x.d
    ship(x.df.sparkSession)
    if spec.strategy == "pairs":

        def kernel(own: Block, partners: Iterator[Block]) -> Iterator[pa.RecordBatch]:
            mine = own.tiles()
            for other in partners:
                for theirs in other.tiles():
                    for u in mine:
                        i, j, v = fn(u.ids, u.stored, theirs.ids, theirs.stored)
                        yield pa.RecordBatch.from_arrays([pa.array(i, pa.int64()), pa.array(j, pa.int64()), pa.array(v, pa.float64())], names=["i", "j", "value"])

        return run_owners(x, blocks or blocks_for(x), kernel, "i long, j long, value double")
    if spec.strategy == "rows":

        def by_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                for at in range(0, b.num_rows, batch):
                    part = b.slice(at, batch)
                    out = np.asarray(fn(matrix(part.column(1), d)), float).reshape(part.num_rows, -1)
                    yield pa.RecordBatch.from_arrays([part.column(0), pa.array(out.tolist(), pa.list_(pa.float64()))], names=["id", "x"])

        return x.pack().df.select("id", "x").mapInArrow(by_rows, "id long, x array<double>")

    def by_feature(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for g in grouped(batches):
            out = np.asarray(fn(g.column(2).to_numpy(zero_copy_only=False)), float)
            yield pa.RecordBatch.from_arrays([g.column(0), g.column(1), pa.array(out)], names=["at", "id", "v"])

    if (need := x.count() * 16) > FEATURE_BUDGET:  # the function asks for a whole feature at once
        raise MemoryBudgetExceeded(f"a feature of {need >> 20} MB does not fit a task of {FEATURE_BUDGET >> 20} MB; use ranked values, histograms or moments")
    cells = x.pack().df.select("id", F.posexplode("x").alias("at", "v")).select(F.col("at").cast("long").alias("at"), "id", "v")
    columns = cells.repartition("at").sortWithinPartitions("at", "id").mapInArrow(by_feature, "at long, id long, v double")
    return columns.groupBy("id").agg(F.transform(F.array_sort(F.collect_list(F.struct("at", "v"))), lambda c: c["v"]).alias("x"))


@dataclass(frozen=True)
class OpNode:
    op: str
    inputs: tuple = ()
    params: dict = field(default_factory=dict)


def register_fusion(pattern: tuple[str, ...], build: Callable[..., OpNode]) -> None:
    """pattern: operator names from the outer node down its first inputs. build gets the matched nodes, outermost first. Later rules go first."""
    RULES.insert(0, (pattern, build))


def fuse(node: OpNode) -> OpNode:
    node = OpNode(node.op, tuple(fuse(i) if isinstance(i, OpNode) else i for i in node.inputs), node.params)
    for pattern, build in RULES:
        chain: list[OpNode] = [node]
        while len(chain) < len(pattern) and chain[-1].inputs and isinstance(chain[-1].inputs[0], OpNode):
            chain.append(chain[-1].inputs[0])
        if tuple(c.op for c in chain) == pattern:
            return build(*chain)
    return node


def _merged(op: str) -> Callable[..., OpNode]:
    return lambda *chain: OpNode(op, chain[-1].inputs, {k: v for c in reversed(chain) for k, v in c.params.items()})


register_fusion(("topk_smallest", "pairwise_distance"), _merged("knn_fused"))
register_fusion(("within", "pairwise_distance"), _merged("range_fused"))
register_fusion(("count", "within", "pairwise_distance"), _merged("range_count_fused"))
register_fusion(("count", "range_fused"), _merged("range_count_fused"))
register_fusion(("log", "ecdf"), _merged("tails_fused"))
register_fusion(("lookup", "histogram"), _merged("histogram_score_fused"))
register_fusion(("square", "project"), _merged("component_score_fused"))


def lower(node: OpNode, fused: bool = True) -> DataFrame | FeatureFrame:
    """Plan a tree. Without fusion every operator's result is made whole and read by the next; a top-k takes distances as they come, tile by tile, since
    all of them are too many to be written out. Operators of a user's own run by their class."""
    from farpoint.composite import neighbours as N
    from farpoint.detectors import statistical as S
    from farpoint.operators import basic as O
    from farpoint.operators.ecdf import ecdf

    if fused:
        node = fuse(node)
    p = node.params

    def src():
        return lower(node.inputs[0], False) if isinstance(node.inputs[0], OpNode) else node.inputs[0]

    def leaf(n: OpNode = node) -> FeatureFrame:
        return leaf(n.inputs[0]) if isinstance(n.inputs[0], OpNode) else n.inputs[0]

    def log() -> DataFrame:
        x = leaf()
        skew = F.element_at(F.create_map(*(F.lit(v) for f, s in O.skews(x).items() for v in (f, s))), F.col("feature"))
        left, right = F.log("f_left") * -1.0, F.log("f_right") * -1.0
        return stage(src(), "ecdf").select(*x.ids, "feature", left.alias("u_left"), right.alias("u_right"), F.when(skew < 0, left).otherwise(right).alias("u_skew"))

    def lookup() -> DataFrame:
        x, d = leaf(), S.HistogramDetector(node.inputs[0].params.get("bins", 10))
        return d.model(O.edges_of(x, d.bins), stage(src(), "histogram")).score(x)

    def project() -> FeatureFrame:
        x = src()
        m = S.PcaDetector().fit(x)
        at = {f: k for k, f in enumerate(m.features)}
        z = x.select(list(m.features)).map(lambda f, c: (c - m.mean[at[f]]) / m.sd[at[f]])
        return O.project(z, m.vectors[:, list(m.chosen)] / np.sqrt(m.values[list(m.chosen)]))

    def square() -> DataFrame:
        x = src().staged("projected")
        return x.df.select(*x.ids, sum((F.col(f) * F.col(f) for f in x.features), F.lit(0.0)).alias("score"))

    def topk() -> DataFrame:
        below = node.inputs[0]
        if isinstance(below, OpNode) and below.op == "pairwise_distance" and isinstance(below.inputs[0], FeatureFrame):
            return N.knn(below.inputs[0], p["k"], mode="concat", blocks=below.params.get("blocks"), metric=below.params.get("metric", "euclidean"))
        return N._ranked(src(), p["k"])

    blocks = p.get("blocks")
    table = {
        "pairwise_distance": lambda: (lambda x: N.pairwise_distance(x, p.get("metric", "euclidean"), blocks=blocks or blocks_for(x)))(src()),
        "topk_smallest": topk,
        "within": lambda: src().where(F.col("dist") <= p["phi"]).select("i", "j"),
        "count": lambda: src().groupBy("i").agg(F.count("*").alias("n")),
        "ecdf": lambda: ecdf(src()),
        "log": log,
        "histogram": lambda: O.histogram(src(), p.get("bins", 10)),
        "lookup": lookup,
        "project": project,
        "square": square,
        "knn_fused": lambda: N.knn(src(), p["k"], blocks=blocks, metric=p.get("metric", "euclidean"), precision=p.get("precision", 64)),
        "range_fused": lambda: N.nwr(src(), p["phi"], blocks=blocks, precision=p.get("precision", 64)),
        "range_count_fused": lambda: N.nwr_counts(src(), [p["phi"]], blocks).where("n > 0").select("i", "n"),
        "tails_fused": lambda: S.tail_scores(src()),
        "histogram_score_fused": lambda: S.HistogramDetector(p.get("bins", 10)).fit_score(src()),
        "component_score_fused": lambda: S.PcaDetector().fit_score(src()),
    }
    if node.op in table:
        return table[node.op]()
    if node.op in IMPLEMENTATIONS:
        x = src()
        return run_operator(node.op, x if isinstance(x, FeatureFrame) else FeatureFrame(x, ("id",), leaf().features, True), blocks=blocks)
    raise ValueError(f"no plan for {node.op}")


def detector(name: str) -> Callable:
    """Decorator: f(x, **parameters) gives ids and score."""

    def keep(f: Callable[..., DataFrame]) -> Callable[..., DataFrame]:
        DETECTORS[name] = f
        return f

    return keep
