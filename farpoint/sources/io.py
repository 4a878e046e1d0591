"""Reading and writing: pruned scans, other formats, generated points as a data source, score tables and models."""

from __future__ import annotations

import json

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from farpoint.detectors.statistical import HistogramModel, PcaModel


def scan(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None, where: Column | str | None = None) -> DataFrame:
    """One table; filters and columns reach the Parquet reader."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    df = df.where(where) if where is not None else df
    return df.select(*columns) if columns else df


def read_any(spark: SparkSession, path: str, fmt: str, schema=None, **options) -> DataFrame:
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema is not None else reader).load(path)


def write_any(df: DataFrame, path: str, fmt: str = "parquet", partition_by: list[str] | None = None, **options) -> None:
    w = df.write.format(fmt).options(**options).mode("overwrite")
    (w.partitionBy(*partition_by) if partition_by else w).save(path)


def write_scores(df: DataFrame, path: str, partition_by: list[str] | None = None) -> None:
    write_any(df, path, "parquet", partition_by)


def save_model(spark: SparkSession, model, path: str) -> None:
    """A fitted model as one line of JSON, written by Spark so that any file system works."""
    body = {k: v.tolist() if hasattr(v, "tolist") else v for k, v in vars(model).items()}
    line = json.dumps({"kind": type(model).__name__, "body": body})
    spark.range(1).selectExpr(f"'{line.replace(chr(92), chr(92) * 2).replace(chr(39), chr(92) + chr(39))}' as value").coalesce(1).write.mode("overwrite").text(path)


def load_model(spark: SparkSession, path: str):
    import numpy as np

    said = json.loads(spark.read.text(path).first()[0])
    body = said["body"]
    if said["kind"] == "HistogramModel":
        return HistogramModel(**body)
    arrays = {k: np.array(body[k]) for k in ("values", "vectors")}
    return PcaModel(**{k: tuple(v) if isinstance(v, list) else v for k, v in body.items() if k not in arrays}, **arrays)


class SyntheticPoints(DataSource):
    """spark.read.format("synthetic_points").option("rows", n).option("features", d).option("partitions", p)"""

    @classmethod
    def name(cls) -> str:
        return "synthetic_points"

    def schema(self) -> str:
        d = int(self.options.get("features", 4))
        return "id long, " + ", ".join(f"x{k} double" for k in range(d))

    def reader(self, schema) -> DataSourceReader:
        return _SyntheticReader(dict(self.options))


class _Range(InputPartition):
    def __init__(self, lo: int, hi: int):
        self.lo, self.hi = lo, hi


class _SyntheticReader(DataSourceReader):
    def __init__(self, options: dict):
        self.n, self.d, self.p = (int(options.get(k, v)) for k, v in (("rows", 1000), ("features", 4), ("partitions", 4)))

    def partitions(self) -> list[InputPartition]:
        return [_Range(self.n * k // self.p, self.n * (k + 1) // self.p) for k in range(self.p)]

    def read(self, part: _Range):
        import pyarrow as pa

        for lo in range(part.lo, part.hi, 10_000):
            ids = range(lo, min(lo + 10_000, part.hi))
            cols = [pa.array(list(ids), pa.int64())] + [pa.array([(i * (31 + 2 * k) + 17 * k) % 1009 / 1009.0 for i in ids]) for k in range(self.d)]
            yield pa.RecordBatch.from_arrays(cols, names=["id", *(f"x{k}" for k in range(self.d))])


def register_sources(spark: SparkSession) -> None:
    spark.dataSource.register(SyntheticPoints)
