"""Toxicity by a weighted finite-state pattern grammar over clauses.

A lexicon maps words to symbols: insult, threat, target, negation, report; commas and colons are pauses. Four small transducers rewrite the
symbol sequence of a clause and are composed into one machine: negation weakens an insult within three words and up to the next pause,
reported speech weakens what follows it up to the clause's end, whatever pauses or quotes are between, a target beside an insult or after a threat
strengthens it, and the last one turns symbols into weights. A text is scored by its matched clauses (total, strongest and number), never by words
alone; a logistic curve turns these three into a score from 0 to 1.

The lexicon starts from general word lists and takes more insult words, and four-letter word beginnings, from labelled
texts by a likelihood-ratio test. The machine's arc weights (``Arcs``) start from general values; each is changed where the labelled texts speak
clearly for another one. Fitting reads a bounded sample: the ``SAMPLE`` labelled training rows with the smallest hashes.

Defined results: null and empty texts have no clause and get the curve's base score; words of any length and texts of
any length are learned from and scanned whole; repeated rows get equal scores; without usable labels the general word lists, arcs and
curve hold; an empty table gives an empty result; further columns are ignored.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from farpoint.session import ship, stage

#: At most so many labelled rows are used for fitting.
SAMPLE = 12_000
#: Likelihood-ratio statistic and share of toxic texts that a learned word needs, and the fall of the loss that a changed arc weight needs.
EVIDENCE, PRECISION, CLEARLY = 20.0, 0.7, 3.0
#: Letters of a learned word beginning.
BEGINNING = 4

INSULTS = "idiot idiots stupid moron morons loser losers scum trash garbage clown clowns pathetic worthless disgusting dumb fool jerk imbecile vermin filth dummkopf trottel abschaum idiota imbécil estúpido basura crétin abruti ordure".split()
THREATS = "kill hurt destroy beat burn smash shoot stab hang crush töten umbringen schlagen erschießen verbrennen tuer frapper brûler détruire écraser matar golpear quemar destruir disparar".split()
TARGETS = "you your yours you're he she him her they them this these those du dich ihr euch sie tu te vous toi usted ustedes tú ellos".split()
NEGATIONS = "not no never isn't aren't wasn't don't doesn't nobody nicht kein keine nie pas jamais aucun nunca jamás".split()
REPORTS = "said says quoted reported claims claimed wrote called sagte schrieb behauptet dit écrit affirme dijo escribió".split()

_ROLES = {*TARGETS, *NEGATIONS, *REPORTS}
_WORD = re.compile(r"[^\W\d_]+(?:'[^\W\d_]+)?")
_TOKEN = re.compile(r"[,:]|" + _WORD.pattern)
_CLAUSE = re.compile(r"[.!?;|\n\r]+")


def _plain(text: str | None) -> str:
    """Lower case, with straight apostrophes."""
    return (text or "").lower().replace("\u2019", "'")


@dataclass(frozen=True)
class Transducer:
    """Deterministic: step(state, symbol) gives (next state, output symbol, added weight); states and steps are tabulated."""

    start: object
    steps: dict

    def run(self, symbols: list[str]) -> float:
        state, total = self.start, 0.0
        for s in symbols:
            state, _, w = self.steps[state, s]
            total += w
        return total


def build(start: object, symbols: list[str], step) -> Transducer:
    steps, todo = {}, [start]
    while todo:
        state = todo.pop()
        for s in symbols:
            if (state, s) not in steps:
                steps[state, s] = step(state, s)
                todo.append(steps[state, s][0])
    return Transducer(start, steps)


def compose(a: Transducer, b: Transducer, symbols: list[str]) -> Transducer:
    """Feeds what a writes to b; weights add."""

    def step(state, s):
        x, mid, w = a.steps[state[0], s]
        y, out, v = b.steps[state[1], mid]
        return (x, y), out, w + v

    return build((a.start, b.start), symbols, step)


SYMBOLS = ["other", "pause", "insult", "threat", "target", "negation", "report"]
#: An insult or threat with marks: n negated, r reported, t beside a target.
_MARKED = [b + m for b in ("insult", "threat") for m in ("", "n", "r", "nr", "t", "nt", "rt", "nrt")]
_ALL = [s for s in SYMBOLS if s not in ("insult", "threat")] + _MARKED


class Arcs(NamedTuple):
    """Weights of the machine's arcs: of a threat (an insult weighs 1), factors of the marks, and what a target after an insult or threat adds."""

    threat: float = 0.4
    negated: float = 0.35
    reported: float = 0.6
    targeted: float = 1.5
    followed: float = 0.5

    def others(self) -> list[Arcs]:
        """Arcs that differ in one weight."""
        grid = {"threat": (0.0, 0.2, 0.8, 1.5), "negated": (0.0, 0.15, 0.7, 1.0), "reported": (0.0, 0.3, 0.8, 1.0), "targeted": (1.0, 2.0, 3.0), "followed": (0.0, 0.25, 1.0)}
        return [self._replace(**{k: v}) for k, vs in grid.items() for v in vs if v != getattr(self, k)]


#: Arcs that make the machine a plain sum over words: for measuring what the grammar is worth.
FLAT = Arcs(1.0, 1.0, 1.0, 1.0, 0.0)


def grammar(arcs: Arcs = Arcs()) -> Transducer:
    def negation(left: int, s: str):
        if s == "negation":
            return 3, s, 0.0
        if s == "pause":
            return 0, s, 0.0
        mark = "n" if left and s in ("insult", "threat") else ""
        return max(0, left - 1), s + mark, 0.0

    def reported(on: bool, s: str):
        if s == "report":
            return True, s, 0.0
        return on, (s + "r" if on and s.startswith(("insult", "threat")) else s), 0.0

    def targeted(state: tuple[int, int], s: str):
        """(words left in which a target was seen, words left in which an insult or threat waits for one); pauses are no words."""
        near, waits = state
        if s == "pause":
            return state, s, 0.0
        if s == "target":
            return (4, 0), s, arcs.followed if waits else 0.0
        if s.startswith(("insult", "threat")):
            return (max(0, near - 1), 4), (s + "t" if near else s), 0.0
        return (max(0, near - 1), max(0, waits - 1)), s, 0.0

    def weighed(_: int, s: str):
        base = 1.0 if s.startswith("insult") else arcs.threat if s.startswith("threat") else 0.0
        marks = s[6:] if base else ""
        return 0, s, base * (arcs.negated if "n" in marks else 1) * (arcs.reported if "r" in marks else 1) * (arcs.targeted if "t" in marks else 1)

    machine = build(0, SYMBOLS, negation)
    machine = compose(machine, build(False, _ALL, reported), SYMBOLS)
    machine = compose(machine, build((0, 0), _ALL, targeted), SYMBOLS)
    return compose(machine, build(0, _ALL, weighed), SYMBOLS)


@dataclass
class ToxicityModel:
    words: dict[str, float] = field(default_factory=dict)
    beginnings: dict[str, float] = field(default_factory=dict)
    #: Base, then for log1p(total weight), strongest clause, log1p(matched clauses).
    curve: tuple[float, ...] = (-3.0, 2.0, 1.5, 0.5)
    arcs: Arcs = Arcs()

    def __post_init__(self):
        self.symbol = {w: s for s, ws in (("target", TARGETS), ("negation", NEGATIONS), ("report", REPORTS), ("threat", THREATS), ("insult", INSULTS)) for w in ws} | dict.fromkeys(self.words, "insult")
        self.hot = {w for w, s in self.symbol.items() if s in ("insult", "threat")}
        self.machine = grammar(self.arcs)

    def _symbol(self, word: str) -> str:
        return self.symbol.get(word) or ("insult" if word[:BEGINNING] in self.beginnings else "other")

    def matched(self, text: str | None) -> list[tuple[str, list[str], float]]:
        """Clauses with an insult or threat: text, symbols, and how sure the strongest learned word is."""
        low = _plain(text)
        seen = set(_WORD.findall(low))
        if self.hot.isdisjoint(seen) and not any(w[:BEGINNING] in self.beginnings for w in seen):
            return []
        out = []
        for clause in _CLAUSE.split(low):
            words = _TOKEN.findall(clause)
            symbols = ["pause" if w in ",:" else self._symbol(w) for w in words]
            if "insult" in symbols or "threat" in symbols:
                sure = max([self.words.get(w) or self.beginnings.get(w[:BEGINNING]) or 1.0 for w, s in zip(words, symbols) if s == "insult"], default=1.0)
                out.append((clause, symbols, sure))
        return out

    def clauses(self, text: str | None) -> list[tuple[str, float]]:
        """The matched clauses and their weights."""
        return [(clause, self.machine.run(symbols) * sure) for clause, symbols, sure in self.matched(text)]

    def features(self, text: str | None) -> tuple[float, float, float]:
        return _features([x for _, x in self.clauses(text)])

    def score(self, text: str | None) -> float:
        z = self.curve[0] + sum(a * b for a, b in zip(self.curve[1:], self.features(text)))
        return 1 / (1 + math.exp(-max(-30.0, min(30.0, z))))


def _features(weights: list[float]) -> tuple[float, float, float]:
    return (math.log1p(sum(weights)), max(weights), math.log1p(sum(x > 0 for x in weights))) if weights else (0.0, 0.0, 0.0)


def _curve(x: np.ndarray, y: np.ndarray, prior: tuple[float, ...]) -> tuple[tuple[float, ...], float]:
    """Logistic regression by Newton steps, with a light pull towards the default curve; and its loss."""
    x = np.c_[np.ones(len(x)), x]
    prior = np.array(prior)
    w, pull = prior.copy(), np.array([0.1, 0.5, 0.5, 0.5])
    loss = lambda w: np.logaddexp(0, np.where(y > 0.5, -1, 1) * (x @ w)).sum() + 0.5 * (pull * (w - prior) ** 2).sum()
    for _ in range(100):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + np.diag(pull), x.T @ (y - p) - pull * (w - prior))
        size, before = 1.0, loss(w)
        while size > 1e-6 and loss(w + size * step) > before:
            size /= 2
        w = w + size * step
        if np.abs(size * step).max() < 1e-8:
            break
    return tuple(map(float, w)), float(loss(w))


def fit(docs: DataFrame, labels: DataFrame, held_out_fifth: bool = True, sample: int = SAMPLE) -> ToxicityModel:
    """Fit on at most ``sample`` labelled rows; with held_out_fifth, rows whose crc32(doc_id as text) mod 5 is 0 take no part."""
    ship(docs.sparkSession)
    usable = labels.where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull())
    if held_out_fifth:
        usable = usable.where(F.crc32(F.col("doc_id").cast("string")) % 5 != 0)
    ids = usable.groupBy("doc_id").agg(F.max("toxic").alias("toxic")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample)
    rows = stage(docs.select("doc_id", "text").join(F.broadcast(ids), "doc_id").select("text", (F.col("toxic") > 0).alias("toxic")), "toxic-sample")  # the small side has at most `sample` rows
    totals = {r["toxic"]: r["n"] for r in rows.groupBy("toxic").agg(F.count("*").alias("n")).collect()}
    n_pos, n_neg = totals.get(True, 0), totals.get(False, 0)
    if not n_pos or not n_neg:
        return ToxicityModel()

    def terms(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pos, neg = Counter(), Counter()
        for b in batches:
            for text, toxic in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                words = set(_WORD.findall(_plain(text)))
                (pos if toxic else neg).update(words | {w[:BEGINNING] + "*" for w in words if len(w) >= BEGINNING})
        keys = list(pos.keys() | neg.keys())
        yield pa.RecordBatch.from_arrays([pa.array(keys, pa.string()), pa.array([pos[k] for k in keys], pa.int64()), pa.array([neg[k] for k in keys], pa.int64())], names=["term", "pos", "neg"])

    counted = rows.mapInArrow(terms, "term string, pos long, neg long").groupBy("term").agg(F.sum("pos").alias("pos"), F.sum("neg").alias("neg"))
    # Likelihood-ratio statistic of a term's share of toxic texts against the base share.
    share, base = F.col("pos") / (F.col("pos") + F.col("neg")), n_pos / (n_pos + n_neg)
    statistic = 2 * (F.col("pos") * F.log(share / base) + F.when(F.col("neg") > 0, F.col("neg") * F.log((1 - share) / (1 - base))).otherwise(0.0))
    clear = (F.col("pos") >= 4) & (F.col("pos") * (1 - PRECISION) * n_neg >= F.col("neg") * PRECISION * n_pos) & (statistic >= EVIDENCE)
    words, beginnings = {}, {}
    for term, pos, neg in counted.where(clear).collect():  # terms of at most `sample` texts
        if term in _ROLES:  # these speak through the machine
            continue
        weight = min(2.0, 0.5 * math.log((pos + 0.5) / (n_pos + 1) * (n_neg + 1) / (neg + 0.5)))
        (beginnings if term.endswith("*") else words)[term.rstrip("*")] = weight

    def measured(candidates: list[Arcs]) -> list[tuple[float, tuple[float, ...]]]:
        """(loss, curve) of every candidate: the features of each text under each of them."""

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            m, machines = ToxicityModel(words, beginnings), [grammar(a) for a in candidates]
            for b in batches:
                out = []
                for text in b.column(0).to_pylist():
                    found = m.matched(text)
                    out.append([v for machine in machines for v in _features([machine.run(symbols) * sure for _, symbols, sure in found])])
                yield pa.RecordBatch.from_arrays([pa.array(out, pa.list_(pa.float64())), b.column(1)], names=["x", "toxic"])

        seen = sorted((r["toxic"], *r["x"]) for r in rows.mapInArrow(run, "x array<double>, toxic boolean").collect())  # at most `sample` rows
        x, y = np.array([r[1:] for r in seen], float), np.array([r[0] for r in seen], float)
        return [(loss, curve) for curve, loss in (_curve(x[:, 3 * k : 3 * k + 3], y, ToxicityModel.curve) for k in range(len(candidates)))]

    arcs, (least, curve) = Arcs(), (math.inf, ())
    for _ in range(4):
        candidates = [arcs, *arcs.others()]
        results = measured(candidates)
        least, curve = results[0]
        best = min(range(len(candidates)), key=lambda k: results[k][0])
        if results[best][0] > least - CLEARLY:
            break
        arcs, curve = candidates[best], results[best][1]
    return ToxicityModel(words, beginnings, curve, arcs)


def score(docs: DataFrame, model: ToxicityModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, score) of every row; map-only. The model is bounded by the sample that it was fitted on."""
    spark = ship(docs.sparkSession)
    sent = spark.sparkContext.broadcast((model.words, model.beginnings, model.curve, model.arcs))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = ToxicityModel(*sent.value)
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(_scores(m, b.column(1)), pa.float64())], names=[id_col, "score"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, text_col).mapInArrow(run, f"`{id_col}` {kind}, score double")


def keep_clean(docs: DataFrame, model: ToxicityModel, reject_from: float = 0.5) -> DataFrame:
    """The rows whose score is below the cut, with all their columns. Only texts go to the Python workers and only scores come back."""
    spark = ship(docs.sparkSession)
    sent = spark.sparkContext.broadcast((model.words, model.beginnings, model.curve, model.arcs))

    @F.arrow_udf("double")
    def toxic(texts: Iterator[pa.Array]) -> Iterator[pa.Array]:
        m = ToxicityModel(*sent.value)
        for t in texts:
            yield pa.array(_scores(m, t), pa.float64())

    return docs.where(toxic(F.col("text")) < reject_from)


def _scores(m: ToxicityModel, texts: pa.Array) -> list[float]:
    """Few texts at a time become Python strings."""
    return [m.score(t) for at in range(0, len(texts), 256) for t in texts.slice(at, 256).to_pylist()]
