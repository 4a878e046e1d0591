"""Token counts and token ids of whole texts.

Counting takes a shortcut: a vocabulary string that the tokenizer itself turns into one token when it
stands alone is counted by one set lookup, because merges never cross the borders of pre-tokens. Which
strings these are is proved once per worker by encoding the vocabulary. All other pre-tokens are merged by the
library, once per worker and distinct string. Texts with characters or strings for which the shortcut's
splitting rule is not proved equal to the library's (see ``PLAIN``) go to the library whole.

Defined results: null text counts as empty (0 bytes, 0 tokens); repeated rows give repeated results; an empty
table gives an empty result; further columns of the input are ignored.
"""

from __future__ import annotations

import functools
import json
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from farpoint.session import ship

#: Texts made of these characters only are split alike by both regular-expression engines and are not changed by NFC: ASCII and Latin letters without digits-like superscripts, fractions, no-break space or dotted capital i, and general punctuation.
PLAIN = re.compile(r"[\t\n\r\x20-\x7e¡-±´-¸º»¿-įı-ɏ‐-‧]*")
#: Fixed value: how the word-level vocabulary's library file splits lower-cased text.
WORDS = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[^\W\d_]+|\d|(?:[^\w\s]|_)+")
#: Entries that a worker remembers.
REMEMBERED = 400_000


class WordCounter:
    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        spec = json.load(open(path, encoding="utf-8"))
        self.special = [t["content"] for t in spec["added_tokens"]]
        end = spec["model"]["end_of_word_suffix"]
        whole = [w[: -len(end)] for w in spec["model"]["vocab"] if w.endswith(end)]
        whole = [w for w in whole if WORDS.fullmatch(w) and PLAIN.fullmatch(w)]
        single = self._library_counts(whole)
        self.proved = {w: 1 for w, n in zip(whole, single) if n == 1}
        self.known = dict(self.proved)

    def _library_counts(self, texts: list[str]) -> list[int]:
        return [len(e.ids) for e in self.library.encode_batch(texts, add_special_tokens=False)]

    def count(self, texts: list[str]) -> list[int]:
        counts = [0] * len(texts)
        rest: list[int] = []
        for start in range(0, len(texts), 256):
            split = []
            for i in range(start, min(start + 256, len(texts))):
                t = texts[i]
                if PLAIN.fullmatch(t) and not any(s in t for s in self.special):
                    split.append((i, WORDS.findall(t.lower())))
                else:
                    rest.append(i)
            known = self.known
            missing = list({w for _, ws in split for w in ws if w not in known})
            if missing:
                if len(known) + len(missing) > REMEMBERED + len(self.proved):
                    known = self.known = dict(self.proved)
                    missing = list({w for _, ws in split for w in ws if w not in known})
                known.update(zip(missing, self._library_counts(missing)))
            get = known.__getitem__
            for i, ws in split:
                counts[i] = sum(map(get, ws))
        for i in rest:
            counts[i] = len(self.library.encode(texts[i], add_special_tokens=False).ids)
        return counts


@functools.lru_cache(maxsize=4)
def word_counter(path: str) -> WordCounter:
    return WordCounter(path)


def count_tokens(docs: DataFrame, tokenizer: str, limit: int = 2048, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, n_bytes, n_tokens, over_limit) of every row; map-only, one Arrow pass."""
    ship(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = word_counter(tokenizer)
        for b in batches:
            texts = [t or "" for t in b.column(1).to_pylist()]
            n = counter.count(texts)
            yield pa.RecordBatch.from_arrays(
                [b.column(0), pa.array([len(t.encode()) for t in texts], pa.int64()), pa.array(n, pa.int64()), pa.array([x > limit for x in n], pa.bool_())],
                names=[id_col, "n_bytes", "n_tokens", "over_limit"],
            )

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, text_col).mapInArrow(run, f"`{id_col}` {kind}, n_bytes long, n_tokens long, over_limit boolean")


class ByteEncoder:
    """Ids of the byte-level vocabulary. A second library with the same ranks is several times faster; texts beyond PLAIN go to the first."""

    def __init__(self, path: str, ranks_path: str | None):
        self.path, self._library = path, None
        self.special = {t["content"]: t["id"] for t in json.load(open(path, encoding="utf-8"))["added_tokens"]}
        self.fast = None
        if ranks_path:
            import base64

            import public_tokenizers
            import tiktoken

            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(ranks_path, "rb"))}
            self.fast = tiktoken.Encoding("byte_level", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})

    @property
    def library(self):
        """Loaded when the first text needs it."""
        if self._library is None:
            from tokenizers import Tokenizer

            self._library = Tokenizer.from_file(self.path)
        return self._library

    def ids(self, text: str) -> list[int]:
        if self.fast and PLAIN.fullmatch(text) and not any(s in text for s in self.special):
            return self.fast.encode_ordinary(text)
        return self.library.encode(text, add_special_tokens=False).ids


@functools.lru_cache(maxsize=4)
def byte_encoder(path: str, ranks_path: str | None) -> ByteEncoder:
    return ByteEncoder(path, ranks_path)
