"""Feature frames over the given tables, and generated points."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from farpoint.model import FeatureFrame
from farpoint.session import table

LINE_IDS = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice"]


def vectors(spark: SparkSession, sf_dir: str) -> FeatureFrame:
    return FeatureFrame.packed(table(spark, sf_dir, "embeddings", "vec_id", "embedding"), "vec_id", "embedding", 64, "trust")


def line_measures(spark: SparkSession, sf_dir: str) -> FeatureFrame:
    df = table(spark, sf_dir, "lineitem", *LINE_IDS, "l_quantity", "l_discount", "l_tax").withColumn("price", F.col("l_extendedprice"))
    df = df.withColumnsRenamed({"l_quantity": "quantity", "l_discount": "discount", "l_tax": "tax"})
    return FeatureFrame.wide(df, LINE_IDS, ["quantity", "price", "discount", "tax"], "trust")


def line_subset(spark: SparkSession, sf_dir: str) -> FeatureFrame:
    """The lines of orders below 500: small enough for all pairs at every scale."""
    x = line_measures(spark, sf_dir)
    return FeatureFrame(x.df.where(F.col("l_orderkey") < 500), x.ids, x.features)


def customer_behaviour(spark: SparkSession, sf_dir: str) -> FeatureFrame:
    price = F.col("o_totalprice").cast("decimal(18,2)")
    per = table(spark, sf_dir, "orders", "o_custkey", "o_totalprice", "o_orderpriority").groupBy("o_custkey").agg(F.count("*").alias("n"), F.sum(price).cast("double").alias("s"), F.max(price).cast("double").alias("m"), F.count_if(F.col("o_orderpriority") == "1-URGENT").alias("u"))
    df = table(spark, sf_dir, "customer", "c_custkey", "c_acctbal").join(per, F.col("c_custkey") == F.col("o_custkey"), "left")
    zero = lambda c: F.coalesce(c.cast("double"), F.lit(0.0))
    df = df.select("c_custkey", F.col("c_acctbal").alias("acctbal"), zero(F.col("n")).alias("n_orders"), zero(F.col("s")).alias("sum_price"), zero(F.col("s") / F.col("n")).alias("avg_price"), zero(F.col("m")).alias("max_price"), zero(F.col("u") / F.col("n")).alias("urgent_share"))
    return FeatureFrame.wide(df, ["c_custkey"], ["acctbal", "n_orders", "sum_price", "avg_price", "max_price", "urgent_share"], "trust")


def user_activity(spark: SparkSession, sf_dir: str) -> FeatureFrame:
    e = table(spark, sf_dir, "events", "user_id", "event_type", "value")
    share = lambda t: F.count_if(F.col("event_type") == t) / F.count("*")
    df = e.groupBy("user_id").agg(F.count("*").cast("double").alias("n"), F.avg("value").alias("mean_value"), F.coalesce(F.stddev_pop("value"), F.lit(0.0)).alias("sd_value"), F.max("value").alias("max_value"), *(share(t).alias(f"share_{t}") for t in EVENT_TYPES))
    return FeatureFrame.wide(df, ["user_id"], ["n", "mean_value", "sd_value", "max_value", *(f"share_{t}" for t in EVENT_TYPES)], "trust")


#: Four of the event types; the fifth share follows from these.
EVENT_TYPES = ["click", "view", "purchase", "signup"]


#: Words are runs of other characters than these.
BLANKS = bytes.maketrans(b"\t\n\r", b"   ")
TEXT_MARKS = {"digit_share": b"0123456789", "upper_share": b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", "punct_share": b".,;:!?"}


def document_stats(spark: SparkSession, sf_dir: str) -> FeatureFrame:
    """All marks are single bytes of UTF-8, so they are counted in bytes, one pass each; only words are taken apart."""
    t = F.coalesce(F.col("text"), F.lit(""))
    df = table(spark, sf_dir, "documents", "doc_id", "text").select("doc_id", F.length(t).alias("chars"), t.cast("binary").alias("t"))
    names = ["chars", "words", "mean_word", *TEXT_MARKS, "distinct_share", "lines"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = np.zeros((batch.num_rows, len(names)))
            out[:, 0] = chars = batch.column(1).to_numpy(zero_copy_only=False)
            for row, text in enumerate(batch.column(2)):
                text = text.as_py()
                words = text.translate(BLANKS).split(b" ")
                n, distinct = len(words) - words.count(b""), len(set(words) - {b""})
                marks = (len(text) - len(text.translate(None, m)) for m in TEXT_MARKS.values())
                out[row, 1:] = n, 0, *marks, distinct, text.count(b"\n") + 1
            each = np.maximum(out[:, 1], 1)
            out[:, 2] = chars / each
            out[:, 3:6] /= np.maximum(chars, 1)[:, None]
            out[:, 6] /= each
            yield pa.RecordBatch.from_arrays([batch.column(0), *map(pa.array, out.T)], names=["doc_id", *names])

    schema = f"doc_id {df.schema['doc_id'].dataType.simpleString()}, " + ", ".join(f"{n} double" for n in names)
    return FeatureFrame.wide(df.mapInArrow(run, schema), ["doc_id"], names, "trust")


def page_stats(spark: SparkSession, sf_dir: str) -> FeatureFrame:
    t = F.coalesce(F.col("html"), F.lit(""))
    count = lambda p: F.regexp_count(t, F.lit(p))
    text = F.length(F.regexp_replace(t, "<[^>]*>", ""))
    df = table(spark, sf_dir, "pages", "page_id", "url", "html").select("page_id", F.length(t).alias("html_len"), count("<[a-z]").alias("tags"), count("<a ").alias("links"), count("<script").alias("scripts"), (text / F.greatest(F.length(t), F.lit(1))).alias("text_share"), F.regexp_count(F.coalesce(F.col("url"), F.lit("")), F.lit("/")).alias("url_depth"))
    return FeatureFrame.wide(df, ["page_id"], df.columns[1:], "trust")


def conversation_stats(spark: SparkSession, sf_dir: str) -> FeatureFrame:
    n = F.length(F.coalesce(F.col("text"), F.lit("")))
    df = table(spark, sf_dir, "conversations", "conv_id", "role", "text").groupBy("conv_id").agg(F.count("*").alias("turns"), F.avg(n).alias("mean_len"), F.max(n).alias("max_len"), F.stddev_pop(n).alias("sd_len"), (F.count_if(F.col("role") == "user") / F.count("*")).alias("user_share"))
    return FeatureFrame.wide(df, ["conv_id"], df.columns[1:], "trust")


def order_prices(spark: SparkSession, sf_dir: str) -> FeatureFrame:
    df = table(spark, sf_dir, "orders", "o_orderkey", "o_totalprice", "o_orderdate").select("o_orderkey", F.col("o_totalprice").alias("price"), F.datediff(F.col("o_orderdate").cast("date"), F.lit("1995-01-01").cast("date")).alias("days"))
    return FeatureFrame.wide(df, ["o_orderkey"], ["price", "days"], "trust")


def event_values(spark: SparkSession, sf_dir: str) -> FeatureFrame:
    df = table(spark, sf_dir, "events", "event_id", "ts", "value", "props").select("event_id", "value", F.hour("ts").alias("hour"), F.get_json_object("props", "$.k").cast("int").alias("k"))
    return FeatureFrame.wide(df, ["event_id"], ["value", "hour", "k"], "trust")


def part_dims(spark: SparkSession, sf_dir: str) -> FeatureFrame:
    df = table(spark, sf_dir, "part", "p_partkey", "p_size", "p_retailprice").withColumnsRenamed({"p_size": "size", "p_retailprice": "price"})
    return FeatureFrame.wide(df, ["p_partkey"], ["size", "price"], "trust")


def synthetic(spark: SparkSession, n: int, d: int, outlier_share: float = 0.01, clusters: int = 4, seed: int = 1) -> FeatureFrame:
    """points_of the numbers from 0 to n - 1."""
    return points_of(spark.range(n), d, outlier_share, clusters, seed)


def points_of(ids: DataFrame, d: int, outlier_share: float = 0.01, clusters: int = 4, seed: int = 1) -> FeatureFrame:
    """A point for each row of ids (one column, id): inliers around cluster centres, planted outliers in a wider box. Integer arithmetic only until the last
    division, so any SQL engine makes the very same rows. ``planted(id)`` tells the outliers."""
    i = F.col("id")
    noise = lambda k: ((i * (1103515 + 2 * k) + (seed * 7919 + k * 104729)) * 69069 + k * 15485863) % 1000003 / 1000003.0
    out = planted(outlier_share, seed)
    df = ids.select("id", *(F.when(out, noise(k) * 8 - 4).otherwise((i % clusters * (k + 3) % 5 - 2) * 0.5 + (noise(k) + noise(k + d) - 1) * 0.5).alias(f"x{k}") for k in range(d)))
    return FeatureFrame.wide(df, ["id"], [f"x{k}" for k in range(d)], "trust")


def planted(outlier_share: float = 0.01, seed: int = 1):
    return (F.col("id") * 7717 + seed) % 10007 < int(outlier_share * 10007)


def scale_unit(spark: SparkSession, n: int, d: int = 20) -> FeatureFrame:
    """Generated points, packed, scaled to the unit box by a fixed factor."""
    return synthetic(spark, n, d).map(lambda f, c: (c + 4) / 8).pack()
