"""The input matrix as a DataFrame: rows are points, columns are features, no labels."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class FeatureFrame:
    """Wide form: one double column for each feature. Packed form: one array column ``x`` and a bigint ``id``.

    Feature-independent operators read the wide form (a feature is a column that Spark can prune); all-pairs operators read the packed one.
    """

    df: DataFrame
    ids: tuple[str, ...]
    features: tuple[str, ...]
    is_packed: bool = False
    #: Number of rows where it is known.
    rows: int | None = None

    @staticmethod
    def wide(df: DataFrame, ids: list[str], features: list[str], nulls: str = "error") -> FeatureFrame:
        """nulls: 'error' raises when a cell is null, NaN or infinite (one aggregate), 'drop' leaves such rows out, 'impute_mean' fills finite means in, 'trust' checks nothing."""
        x = df.select(*ids, *(F.col(f).cast("double").alias(f) for f in features))
        return FeatureFrame(_clean(x, features, nulls), tuple(ids), tuple(features))

    @staticmethod
    def packed(df: DataFrame, id_col: str, vector_col: str, d: int, nulls: str = "error") -> FeatureFrame:
        """Rows whose array has another length than d are an error at run time."""
        x = F.transform(vector_col, lambda v: v.cast("double"))
        right = F.when(F.size(x) == d, x).otherwise(F.raise_error(F.lit(f"a vector does not have {d} components")).cast("array<double>"))
        out = df.select(F.col(id_col).cast("long").alias("id"), right.alias("x"))
        bad = F.exists("x", _unusable)
        if nulls == "drop":
            out = out.where(~bad)
        elif nulls == "error" and not out.where(bad).isEmpty():
            raise ValueError("null, NaN or infinite components")
        return FeatureFrame(out, ("id",), tuple(f"x{i}" for i in range(d)), True)

    @property
    def d(self) -> int:
        return len(self.features)

    def count(self) -> int:
        return self.df.count() if self.rows is None else self.rows

    def pack(self) -> FeatureFrame:
        if self.is_packed:
            return self
        if len(self.ids) != 1:
            raise ValueError("packing needs one id column")
        return FeatureFrame(self.df.select(F.col(self.ids[0]).cast("long").alias("id"), F.array(*self.features).alias("x")), ("id",), self.features, True, self.rows)

    def unpack(self) -> FeatureFrame:
        if not self.is_packed:
            return self
        return FeatureFrame(self.df.select("id", *(F.col("x")[i].alias(f) for i, f in enumerate(self.features))), ("id",), self.features, rows=self.rows)

    def long(self) -> DataFrame:
        """(ids..., feature, value)."""
        return self.unpack().df.unpivot(list(self.ids), list(self.features), "feature", "value")

    def staged(self, name: str = "features") -> FeatureFrame:
        """Written once to the shared folder: for frames that are costly to assemble and read by several aggregates."""
        from farpoint.session import stage

        df = stage(self.df, name)
        return replace(self, df=df, rows=df.count())

    def select(self, features: list[str]) -> FeatureFrame:
        if self.is_packed:
            at = [self.features.index(f) for f in features]
            return replace(self, df=self.df.select("id", F.array(*(F.col("x")[i] for i in at)).alias("x")), features=tuple(features))
        return replace(self, df=self.df.select(*self.ids, *features), features=tuple(features))

    def map(self, f) -> FeatureFrame:
        """Each feature column by f(name, column)."""
        w = self.unpack()
        return replace(w, df=w.df.select(*w.ids, *(f(n, F.col(n)).alias(n) for n in w.features)))


def _unusable(v: Column) -> Column:
    return v.isNull() | F.isnan(v) | (F.abs(v) == float("inf"))


def _clean(x: DataFrame, features: list[str], nulls: str) -> DataFrame:
    bad = F.lit(False)
    for f in features:
        bad = bad | F.coalesce(_unusable(F.col(f)), F.lit(True))
    if nulls == "trust":
        return x
    if nulls == "drop":
        return x.where(~bad)
    if nulls == "error":
        if not x.where(bad).isEmpty():
            raise ValueError("null, NaN or infinite cells")
        return x
    if nulls == "impute_mean":
        finite = lambda f: F.when(~_unusable(F.col(f)), F.col(f))
        means = x.agg(*(F.avg(finite(f)).alias(f) for f in features)).first()
        return x.withColumns({f: F.coalesce(finite(f), F.lit(means[f])) for f in features})
    raise ValueError(nulls)
