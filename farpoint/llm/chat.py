"""Chat formatting with DataFrame expressions only.

Turn structs of a conversation are collected and sorted by (turn, role, text); adjacent turns of one role become one
block; blocks are concatenated. The markers are control strings: inside a text, every control string (the template's
own and common ones of other templates) gets one more backslash after its first character, and reading takes one
away, so any text comes back unchanged and a text can never close its block.

    <|turn|>role<|text|>first text<|next|>second text<|end|>

The loss mask is an array of (start, length) in code points of the formatted string: each assistant text, without markers.

Defined results: null text or role counts as empty; null conversation ids form one conversation; rows with equal turn
are ordered by role and text; repeated rows stay repeated; an empty table gives an empty result; further columns are
ignored. A conversation is one output value, so its turns must fit one string.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Template:
    turn: str = "<|turn|>"
    text: str = "<|text|>"
    next: str = "<|next|>"
    end: str = "<|end|>"
    #: Control strings of other templates, escaped as well.
    others: tuple[str, ...] = ("[INST]", "[/INST]", "<s>", "</s>", "<<SYS>>", "<</SYS>>", "<|im_start|>", "<|im_end|>", "<|endoftext|>", "<|startoftext|>")
    learned: tuple[str, ...] = ("assistant",)

    @property
    def control(self) -> list[str]:
        return [self.turn, self.text, self.next, self.end, *self.others]

    def by_first(self) -> list[tuple[str, str]]:
        """(first character, what may follow it and a run of backslashes), both as patterns."""
        rests: dict[str, list[str]] = {}
        for c in self.control:
            rests.setdefault(c[0], []).append(quoted(c[1:]))
        return [(quoted(f), f"(?=\\\\*(?:{'|'.join(r)}))") for f, r in rests.items()]


def quoted(s: str) -> str:
    return "".join(c if c.isalnum() else "\\" + c for c in s)


def escape(text: Column, t: Template = Template()) -> Column:
    """One backslash more in the run (possibly empty) after a control string's first character."""
    return F.regexp_replace(text, "|".join(first + then for first, then in t.by_first()), r"$0\\")


def unescape(text: Column, t: Template = Template()) -> Column:
    """One backslash less in such a run."""
    parts = t.by_first()
    return F.regexp_replace(text, "|".join(rf"({first})\\{then}" for first, then in parts), "".join(f"${i + 1}" for i in range(len(parts))))


def format_chats(turns: DataFrame, template: Template = Template(), conv: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text") -> DataFrame:
    """(conv_id, formatted, n_blocks, loss_spans array<struct<start,length>>), one row for each conversation."""
    t = template
    esc = lambda c: escape(c, t)
    rows = turns.select(F.col(conv).alias("conv_id"), F.struct(F.col(turn).alias("turn"), F.coalesce(F.col(role).cast("string"), F.lit("")).alias("role"), F.coalesce(F.col(text), F.lit("")).alias("text")).alias("t"))
    grouped = rows.groupBy("conv_id").agg(F.sort_array(F.collect_list("t")).alias("turns")).withColumn("turns", F.transform("turns", lambda x: F.struct(x["role"].alias("role"), esc(x["text"]).alias("text"))))
    starts = F.filter(F.sequence(F.lit(0), F.size("turns") - 1), lambda i: (i == 0) | (F.col("turns")[i]["role"] != F.col("turns")[F.greatest(i - 1, F.lit(0))]["role"]))
    grouped = grouped.withColumn("starts", starts)
    last = F.size("starts") - 1
    blocks = F.transform("starts", lambda s, k: F.slice("turns", s + 1, F.when(k < last, F.col("starts")[F.least(k + 1, last)]).otherwise(F.size("turns")) - s))
    grouped = grouped.withColumn("blocks", F.transform(blocks, lambda b: F.struct(b[0]["role"].alias("role"), F.transform(b, lambda x: x["text"]).alias("texts"))))
    written = F.transform("blocks", lambda b: F.concat(F.lit(t.turn), esc(b["role"]), F.lit(t.text), F.array_join(b["texts"], t.next), F.lit(t.end)))
    # Positions: each block adds its length; each text of a learned block adds one span.
    learned = lambda r: r.isin(*t.learned)
    span = lambda at, n: F.struct(at.cast("long").alias("start"), n.cast("long").alias("length"))
    none = F.expr("cast(array() as array<struct<start:bigint,length:bigint>>)")
    state = lambda at, spans: F.struct(at.cast("long").alias("at"), spans.alias("spans"))

    def add_block(acc: Column, b: Column) -> Column:
        head = acc["at"] + len(t.turn) + F.length(esc(b["role"])) + len(t.text)
        inside = F.aggregate(b["texts"], state(head, none), lambda a, x: state(a["at"] + F.length(x) + len(t.next), F.concat(a["spans"], F.array(span(a["at"], F.length(x))))))
        return state(inside["at"] - len(t.next) + len(t.end), F.when(learned(b["role"]), F.concat(acc["spans"], inside["spans"])).otherwise(acc["spans"]))

    mask = F.aggregate("blocks", state(F.lit(0), none), add_block)["spans"]
    return grouped.select("conv_id", F.array_join(written, "").alias("formatted"), F.size("blocks").alias("n_blocks"), mask.alias("loss_spans"))


def read_chats(formatted: DataFrame, template: Template = Template()) -> DataFrame:
    """Back from the formatted string: turns array<struct<role,text>> and loss_text, the unescaped text under the mask."""
    t = template
    bodies = F.transform(F.split(F.regexp_replace("formatted", quoted(t.end) + "$", ""), quoted(t.end), -1), lambda b: F.substring(b, len(t.turn) + 1, 2147483647))
    turns = F.flatten(F.transform(bodies, lambda b: F.transform(F.split(F.split(b, quoted(t.text), 2)[1], quoted(t.next), -1), lambda x: F.struct(unescape(F.split(b, quoted(t.text), 2)[0], t).alias("role"), unescape(x, t).alias("text")))))
    loss = F.array_join(F.transform("loss_spans", lambda s: unescape(F.substring(F.col("formatted"), (s["start"] + 1).cast("int"), s["length"].cast("int")), t)), "")
    return formatted.withColumn("turns", turns).withColumn("loss_text", loss)
