"""The matrix: distinct (i, j) rows with a value, a shape, and thin methods over the operators."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass(frozen=True)
class SparseMatrix:
    """``df`` has columns i, j (0-based longs) and v; a stored entry counts as present whatever its value."""

    df: DataFrame
    n_rows: int
    n_cols: int

    @property
    def shape(self) -> tuple[int, int]:
        return self.n_rows, self.n_cols

    def with_df(self, df: DataFrame) -> SparseMatrix:
        return SparseMatrix(df.select("i", "j", "v"), self.n_rows, self.n_cols)

    def transpose(self) -> SparseMatrix:
        """Swap the indices: a projection, nothing moves."""
        return SparseMatrix(self.df.select(F.col("j").alias("i"), F.col("i").alias("j"), "v"), self.n_cols, self.n_rows)

    def pattern(self) -> SparseMatrix:
        return self.with_df(self.df.withColumn("v", F.lit(True)))

    def apply(self, f) -> SparseMatrix:
        return self.with_df(self.df.withColumn("v", f(F.col("v"))))

    def prune(self, keep=None) -> SparseMatrix:
        """Drop stored zeros, or all entries whose value fails ``keep``."""
        return self.with_df(self.df.where(F.col("v") != 0 if keep is None else keep(F.col("v"))))

    def cast(self, kind: str) -> SparseMatrix:
        return self.apply(lambda v: v.cast(kind))

    def multiply(self, other: SparseMatrix, **options) -> SparseMatrix:
        from gridsparse.operators.product import multiply

        return multiply(self, other, **options)

    def register(self, name: str) -> SparseMatrix:
        """A temporary view, for ``spark.sql``."""
        self.df.createOrReplaceTempView(name)
        return self

    def validate(self) -> SparseMatrix:
        """Raise unless indices are in range, distinct and not null (an action)."""
        bad = F.col("i").isNull() | F.col("j").isNull() | (F.col("i") < 0) | (F.col("j") < 0) | (F.col("i") >= self.n_rows) | (F.col("j") >= self.n_cols)
        if self.df.where(bad).head(1):
            raise IndexError("an index is null or out of range")
        if self.df.groupBy("i", "j").count().where("count > 1").head(1):
            raise ValueError("an entry is stored twice")
        return self


def from_triples(df: DataFrame, i: str, j: str, v: str | None, shape: tuple[int, int], on_duplicate: str = "add", base: int = 0, order: str | None = None) -> SparseMatrix:
    """Build from any table: duplicates are added, refused, or the last by ``order`` wins; null keys are refused on ``validate``."""
    value = F.lit(1).cast("long") if v is None else F.col(v)
    cells = df.select((F.col(i).cast("long") - base).alias("i"), (F.col(j).cast("long") - base).alias("j"), value.alias("v"), *([F.col(order).alias("at")] if order else []))
    if on_duplicate == "add":
        cells = cells.groupBy("i", "j").agg(F.sum("v").alias("v"))
    elif on_duplicate == "last":
        cells = cells.groupBy("i", "j").agg(F.max_by("v", "at").alias("v"))
    elif on_duplicate == "error":
        made = SparseMatrix(cells.select("i", "j", "v"), *shape)
        return made.validate()
    else:
        raise ValueError(f"unknown policy {on_duplicate}")
    return SparseMatrix(cells, *shape)


def from_arrays(spark: SparkSession, i, j, v, shape: tuple[int, int], base: int = 0, kind: str = "double") -> SparseMatrix:
    """A small literal matrix."""
    rows = [(int(a) - base, int(b) - base, c) for a, b, c in zip(i, j, v, strict=True)]
    return SparseMatrix(spark.createDataFrame(rows, f"i long, j long, v {kind}"), *shape)
