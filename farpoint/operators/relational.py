"""Relational operators around the detectors: as-of and interval joins, rolling statistics, features in windows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from farpoint.composite.neighbours import near_band
from farpoint.functions.sql import register_sql_functions
from farpoint.model import FeatureFrame


def previous_event(events: DataFrame, by: str = "user_id", at: str = "ts", ids: str = "event_id", value: str = "value") -> DataFrame:
    """As-of: each event with the last earlier one of its user."""
    w = Window.partitionBy(by).orderBy(at, ids)
    return events.select(ids, by, value, F.lag(ids).over(w).alias("previous_id"), F.lag(value).over(w).alias("previous_value"), (F.unix_timestamp(F.col(at).cast("timestamp")) - F.unix_timestamp(F.lag(at).over(w).cast("timestamp"))).alias("gap"))


def near_in_time(events: DataFrame, seconds: int = 3600, by: str = "user_id", at: str = "ts", ids: str = "event_id") -> DataFrame:
    """Pairs (earlier, later) of one user's events at most so far apart: an equi-join on user and time bucket, each later event looking into two buckets."""
    t = F.unix_timestamp(F.col(at).cast("timestamp"))
    left = events.select(F.col(by).alias("u"), F.col(ids).alias("earlier"), t.alias("ta"), F.floor(t / seconds).alias("bucket"))
    right = events.select(F.col(by).alias("u"), F.col(ids).alias("later"), t.alias("tb")).withColumn("bucket", F.explode(F.array(F.floor(F.col("tb") / seconds), F.floor(F.col("tb") / seconds) - 1)))
    return left.join(right, ["u", "bucket"]).where((F.col("tb") - F.col("ta")).between(0, seconds) & ((F.col("ta") < F.col("tb")) | (F.col("earlier") < F.col("later")))).select("u", "earlier", "later")


def rolling_zscore(events: DataFrame, rows: int = 20, by: str = "user_id", at: str = "ts", ids: str = "event_id", value: str = "value") -> DataFrame:
    """Each value against the mean and deviation of the user's preceding rows; null without two of them or without deviation."""
    w = Window.partitionBy(by).orderBy(at, ids).rowsBetween(-rows, -1)
    m, s, n = F.avg(value).over(w), F.stddev_pop(value).over(w), F.count(value).over(w)
    return events.select(ids, by, F.when((n >= 2) & (s > 0), (F.col(value) - m) / s).alias("z"))


def rolling_median_deviation(events: DataFrame, rows: int = 10, by: str = "user_id", at: str = "ts", ids: str = "event_id", value: str = "value") -> DataFrame:
    """Distance from the median of the user's preceding rows."""
    w = Window.partitionBy(by).orderBy(at, ids).rowsBetween(-rows, -1)
    return events.select(ids, by, F.abs(F.col(value) - F.percentile(value, F.lit(0.5)).over(w)).alias("deviation"))


def trailing_day(events: DataFrame, by: str = "user_id", at: str = "ts", ids: str = "event_id", value: str = "value") -> DataFrame:
    """Count and mean over the 24 hours up to each event: a range frame on seconds."""
    t = F.unix_timestamp(F.col(at).cast("timestamp"))
    w = Window.partitionBy(by).orderBy("t").rangeBetween(-86400, 0)
    return events.withColumn("t", t).select(ids, by, F.count("*").over(w).alias("n_day"), F.avg(value).over(w).alias("mean_day"))


def top_outliers(scores: DataFrame, n: int, ids: list[str], by: list[str] | None = None, offset: int = 0) -> DataFrame:
    """The n largest scores (after offset), overall or of each group."""
    if not by:
        return scores.orderBy(F.desc("score"), *ids).offset(offset).limit(n)
    w = Window.partitionBy(*by).orderBy(F.desc("score"), *ids)
    return scores.withColumn("rank", F.row_number().over(w)).where(F.col("rank").between(offset + 1, offset + n))


def nearest_by_sql(x: FeatureFrame, k: int) -> DataFrame:
    """(i, j, rank, dist): the k nearest other rows by a self join, fp_distance and row_number in SQL.

    The join's rows would be all pairs. Tasks that hold two blocks compare them in 32 bit, and of the pairs only those whose error bounds leave them a place among the k
    nearest go on to SQL, which alone decides. Rows with components that have no finite number are paired with all."""
    spark, p = x.df.sparkSession, x.pack().df
    register_sql_functions(spark)
    usable = ~F.exists("x", lambda v: v.isNull() | F.isnan(v) | (F.abs(v) == float("inf")))
    p.createOrReplaceTempView("fp_vectors")
    near_band(FeatureFrame(p.where(usable), ("id",), x.features, True), k).createOrReplaceTempView("fp_near")
    pairs, odd = "select i, j from fp_near", p.where(~usable).select("id")
    if not odd.isEmpty():
        odd.createOrReplaceTempView("fp_unusable")
        pairs += " union select u.id, v.id from fp_unusable u cross join fp_vectors v union select v.id, u.id from fp_unusable u cross join fp_vectors v"
    return spark.sql(
        "select i, j, rank, dist from (select i, j, dist, row_number() over (partition by i order by dist, j) as rank from ("
        f"select a.id as i, b.id as j, fp_distance(a.x, b.x) as dist from fp_vectors a join ({pairs}) p on a.id = p.i join fp_vectors b on p.j = b.id and a.id <> b.id"
        f")) where rank <= {k}"
    )
