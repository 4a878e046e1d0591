"""SQL functions, an Arrow UDF and a table function over vectors."""

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from farpoint.session import ship


def register_sql_functions(spark: SparkSession) -> None:
    """fp_sq_distance, fp_distance, fp_cosine of two arrays, as SQL bodies that Catalyst inlines."""
    sums = "aggregate(zip_with(a, b, (x, y) -> {}), 0D, (s, v) -> s + v)"
    size = "sqrt(aggregate({0}, 0D, (s, v) -> s + v * v))"
    for name, body in (
        ("fp_sq_distance", sums.format("(x - y) * (x - y)")),
        ("fp_distance", f"sqrt({sums.format('(x - y) * (x - y)')})"),
        ("fp_cosine", f"try_divide({sums.format('x * y')}, {size.format('a')} * {size.format('b')})"),
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN {body}")


@F.arrow_udf(T.DoubleType())
def norm_udf(v: pa.Array) -> pa.Array:
    """Euclidean norm of arrays, a batch at a time; null for null."""
    return pa.array([None if x is None else float(np.sqrt(sum(c * c for c in x))) for x in v.to_pylist()], pa.float64())


@F.udtf(returnType=T.StructType().add("i", T.LongType()).add("rank", T.IntegerType()).add("id", T.LongType()).add("dist", T.DoubleType()))
class nearest_of:
    """Table function: for each of some (id, vector) the k nearest of others, ties to the smaller id; one call for a block of both."""

    def eval(self, own: list, queries: list, ids: list, vectors: list, k: int):
        from farpoint.composite.neighbours import _Nearest, canonical, centred_squares

        q, v, names = np.array(queries, float), np.array(vectors, float), np.array(ids, np.int64)
        best = _Nearest(len(q), k)
        near, slack = centred_squares(q, v)
        a, b = best.candidates(near, slack, True)
        best.add(a, names[b], canonical(q, v, a, b))
        place = np.arange(len(best.row)) - np.searchsorted(best.row, best.row) + 1
        for at, rank, i, dist in zip(best.row.tolist(), place.tolist(), best.id.tolist(), best.dist.tolist()):
            yield own[at], rank, i, dist


def median_of(df: DataFrame, by: str, value: str) -> DataFrame:
    """Grouped median in pandas: shows the grouped-aggregate UDF; use percentile for the built-in form."""
    ship(df.sparkSession)

    @F.pandas_udf("double")
    def median(v: pd.Series) -> float:
        return float(v.median())

    return df.groupBy(by).agg(median(value).alias("median"))
