"""License scans: an Aho-Corasick automaton finds identifier tags and notice phrases, a shunting-yard parser evaluates licence expressions.

A text is lower-cased in A-Z only and seen as words ``[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+`` joined by single spaces.
Since every byte of a character beyond ASCII is a word byte, this is one byte translation and one split.
Notice phrases are matched on whole words. An identifier tag's expression is parsed from the original text into a tree;
its labels are the identifiers in it, so a tag before other words, or before NONE or NOASSERTION, gives none.

Defined results: null text counts as empty (0 words, no labels, score 0); repeated rows give repeated results; a text
of any length is scanned whole; an empty table gives an empty result; further columns are ignored.
"""

from __future__ import annotations

import functools
import itertools
import re
from bisect import bisect_left
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame

from farpoint.session import ship

#: The base phrases and their labels.
BASE = {"gnu general public license": "gpl", "apache license": "apache", "cc by": "cc-by", "mit license": "mit"}
#: Notice phrases of the method itself, as words, with their labels and how sure they are.
NOTICES = {
    "gnu lesser general public license": ("lgpl", 0.9),
    "gnu affero general public license": ("agpl", 0.9),
    "mozilla public license": ("mpl", 0.9),
    "eclipse public license": ("epl", 0.9),
    "bsd 2 clause": ("bsd-2-clause", 0.8),
    "bsd 3 clause": ("bsd-3-clause", 0.8),
    "redistribution and use in source and binary forms": ("bsd", 0.9),
    "permission is hereby granted free of charge to any person obtaining a copy": ("mit", 1.0),
    "permission to use copy modify and or distribute this software for any purpose": ("isc", 1.0),
    "creative commons attribution": ("cc-by", 0.8),
    "creative commons zero": ("cc0", 0.8),
    "released into the public domain": ("public-domain", 0.8),
    "this is free and unencumbered software": ("unlicense", 1.0),
    "boost software license": ("bsl", 0.9),
    "all rights reserved": ("all-rights-reserved", 0.5),
    "licensed under the apache license": ("apache", 1.0),
    "released under the mit license": ("mit", 1.0),
    "licensed under cc by": ("cc-by", 1.0),
    "terms of the gnu general public license": ("gpl", 1.0),
}
#: The tag before a licence expression, as words.
TAG = "spdx license identifier"
_TAG = re.compile(r"spdx-license-identifier[ \t]*:[ \t]*([^\r\n]*)", re.I | re.A)
_LEX = re.compile(r"\(|\)|[A-Za-z0-9.+:-]+")
#: Binding strength of the expression's operators.
STRENGTH = {"or": 1, "and": 2, "with": 3}
_DELIMITERS = bytes(b for b in range(128) if not (48 <= b <= 57 or 97 <= b <= 122 or 65 <= b <= 90))
_TABLE = bytes.maketrans(_DELIMITERS + bytes(range(65, 91)), b" " * len(_DELIMITERS) + bytes(range(97, 123)))


#: Identifiers without a version number, and the words that say there is none.
NAMED = set("mit isc x11 zlib unlicense wtfpl 0bsd beerware blessing bsd curl fair fsfap ftl hpnd ijg info-zip intel json libpng libtiff naist-2003 ncsa ntp openssl php postgresql psf python-2.0 ruby sleepycat sissl tcl tosl unicode-tou vim w3c xnet zed zpl zend mit-0 mit-cmu gpl lgpl agpl apache mpl epl cc0 cc-by cc-by-sa cc-by-nc cc-by-nd public-domain proprietary".split())
NONE = {"none", "noassertion"}


def is_identifier(word: str) -> bool:
    """A known name, a reference, or anything of the shape of a versioned identifier: parts joined by hyphens, with a digit."""
    low = word.lower().rstrip("+")
    return low in NAMED or low.startswith(("licenseref-", "documentref-")) or ("-" in low and low[0].isalpha() and low[-1].isalnum() and any(c.isdigit() for c in low))


@dataclass(frozen=True)
class Choice:
    """An evaluated expression as a tree: a licence, or 'and' / 'or' over parts. It is never multiplied out, so its size is that of the text."""

    op: str
    licence: str = ""
    parts: tuple[Choice, ...] = ()

    @property
    def licences(self) -> set[str]:
        return {self.licence} if self.op == "one" else {x for p in self.parts for x in p.licences}

    def allows(self, accepted: set[str]) -> bool:
        """Whether somebody who accepts these licences may use the work."""
        return self.licence in accepted if self.op == "one" else (all if self.op == "and" else any)(p.allows(accepted) for p in self.parts)

    def alternatives(self) -> Iterator[frozenset[str]]:
        """The sets of licences to choose from, one by one; there can be exponentially many."""
        if self.op == "one":
            yield frozenset([self.licence])
        elif self.op == "or":
            for p in self.parts:
                yield from p.alternatives()
        else:
            for sets in itertools.product(*(list(p.alternatives()) for p in self.parts)):
                yield frozenset().union(*sets)

    def text(self) -> str:
        """Alternatives by | and joint licences by &, parts in order and once each."""
        if self.op == "one":
            return self.licence
        inner = sorted({f"({p.text()})" if self.op == "and" and p.op == "or" else p.text() for p in self.parts})
        return ("&" if self.op == "and" else "|").join(inner)

    def with_exception(self, name: str) -> Choice:
        return Choice("one", f"{self.licence} with {name}") if self.op == "one" else Choice(self.op, "", tuple(p.with_exception(name) for p in self.parts))


def _joined(op: str, a: Choice, b: Choice) -> Choice:
    parts = [q for p in (a, b) for q in (p.parts if p.op == op else (p,))]
    once = tuple(dict.fromkeys(parts))
    return once[0] if len(once) == 1 else Choice(op, "", once)


def parse_expression(text: str) -> Choice | None:
    """Shunting-yard over or / and / with and parentheses; stops at the first word that does not fit, such as one that is no identifier. None if nothing parses or the text says that there is no licence."""
    values: list[Choice] = []
    pending: list[str] = []

    def reduce() -> None:
        op = pending.pop()
        b, a = values.pop(), values.pop()
        values.append(a.with_exception("+".join(sorted(b.licences))) if op == "with" else _joined(op, a, b))

    operand_next, depth = True, 0
    for m in _LEX.finditer(text):
        t = m[0]
        low = t.lower().rstrip(".,:;")
        if operand_next:
            if t == "(":
                pending.append(t)
                depth += 1
                continue
            if t == ")" or low in STRENGTH or low in NONE or not low:
                break
            if not (is_identifier(low) or pending and pending[-1] == "with" and "-" in low):
                break
            values.append(Choice("one", low))
            operand_next = False
        elif low in STRENGTH:
            while pending and pending[-1] != "(" and STRENGTH[pending[-1]] >= STRENGTH[low]:
                reduce()
            pending.append(low)
            operand_next = True
        elif t == ")" and depth:
            while pending[-1] != "(":
                reduce()
            pending.pop()
            depth -= 1
        else:
            break
    if operand_next:  # an operator without its right side is dropped
        while pending and (pending[-1] == "(" or len(values) < 1 + sum(p in STRENGTH for p in pending)):
            pending.pop()
    while pending:
        if pending[-1] == "(":
            pending.pop()
        elif len(values) >= 2:
            reduce()
        else:
            pending.pop()
    return values[-1] if values else None


def words_of(text: str) -> list[bytes]:
    return text.encode().translate(_TABLE).split()


@functools.lru_cache(maxsize=1)
def _automaton():
    import ahocorasick

    a = ahocorasick.Automaton()
    found: dict[str, list] = {}
    for p, label in BASE.items():
        found.setdefault(p, []).append(("base", label, 1.0))
    for p, (label, sure) in NOTICES.items():
        found.setdefault(p, []).append(("notice", label, sure))
    found[TAG] = [("tag", "", 1.0)]
    for p, hits in found.items():
        a.add_word(f" {p} ", (p.count(" ") + 1, hits))
    a.make_automaton()
    return a


@dataclass
class Scan:
    n_words: int
    n_base: int
    first_word: int | None
    last_word: int | None
    base_labels: list[str]
    labels: list[str]
    score: float
    choices: list[Choice]


def scan(text: str | None) -> Scan:
    text = text or ""
    words = words_of(text)
    joined = b" " + b" ".join(words) + b" "
    line = joined.decode("latin-1")  # one character for each byte; phrases are ASCII
    places, base, own, sure, tagged = [], set(), set(), 0.0, False
    starts: list[int] | None = None
    for end, (n, hits) in _automaton().iter(line):
        for kind, label, weight in hits:
            if kind == "tag":
                tagged = True
                continue
            sure = max(sure, weight)
            if kind == "base":
                base.add(label)
                if starts is None:
                    starts, at = [], 0
                    for w in words:
                        starts.append(at)
                        at += len(w) + 1
                places.append(bisect_left(starts, end) - n)
            else:
                own.add(label)
    choices = []
    if tagged:
        for m in _TAG.finditer(text):
            if c := parse_expression(m[1]):
                choices.append(c)
                own |= c.licences
                sure = 1.0
    return Scan(len(words), len(places), min(places, default=None), max(places, default=None), sorted(base), sorted(base | own), sure, choices)


def scan_licenses(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Every row's scan; map-only. expression is the tags' licence choices, alternatives by | and joint licences by &, never multiplied out."""
    ship(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            s = [scan(t) for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays(
                [
                    b.column(0),
                    *(pa.array([getattr(x, f) for x in s], pa.int64()) for f in ("n_words", "n_base", "first_word", "last_word")),
                    *(pa.array([",".join(getattr(x, f)) for x in s], pa.string()) for f in ("base_labels", "labels")),
                    pa.array([x.score for x in s], pa.float64()),
                    pa.array([";".join(c.text() for c in x.choices) for x in s], pa.string()),
                ],
                names=[id_col, "n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score", "expression"],
            )

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, text_col).mapInArrow(run, f"`{id_col}` {kind}, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double, expression string")
