"""Element-wise algebra: union, intersection, implicit negation, scaling, reduction."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridsparse.matrix import SparseMatrix
from gridsparse.semiring import Semiring


def _same_shape(a: SparseMatrix, b: SparseMatrix) -> None:
    if a.shape != b.shape:
        raise ValueError(f"shapes differ: {a.shape} and {b.shape}")


def ewise_add(a: SparseMatrix, b: SparseMatrix, semiring: Semiring | None = None, disjoint: bool = False) -> SparseMatrix:
    """Pointwise sum over the union of the patterns; known disjoint patterns need no shuffle."""
    _same_shape(a, b)
    both = a.df.unionByName(b.df)
    if disjoint:
        return a.with_df(both)
    add = (semiring or Semiring.plus_times()).add
    return a.with_df(both.groupBy("i", "j").agg(add("v").alias("v")))


def ewise_mult(a: SparseMatrix, b: SparseMatrix, semiring: Semiring | None = None, negate_b: bool = False) -> SparseMatrix:
    """Pointwise product over the common pattern, or ``a`` where ``b`` has no entry (the complement is never formed)."""
    _same_shape(a, b)
    if negate_b:
        return a.with_df(a.df.join(b.df.select("i", "j"), ["i", "j"], "left_anti"))
    mul = (semiring or Semiring.plus_times()).mul
    joined = a.df.join(b.df.withColumnRenamed("v", "w"), ["i", "j"])
    return a.with_df(joined.withColumn("v", mul(F.col("v"), F.col("w"), F.col("j"))))


def ewise_sub(a: SparseMatrix, b: SparseMatrix) -> SparseMatrix:
    """Difference in a ring; entries that cancel are pruned."""
    return ewise_add(a, b.apply(lambda v: -v)).prune()


def reduce(a: SparseMatrix, axis: str = "rows", semiring: Semiring | None = None) -> DataFrame:
    """(i, v): the sum of each row (or column) that has entries."""
    add = (semiring or Semiring.plus_times()).add
    key = "i" if axis == "rows" else "j"
    return a.df.groupBy(F.col(key).alias("i")).agg(add("v").alias("v"))


def degrees(a: SparseMatrix, axis: str = "rows") -> DataFrame:
    """(i, n): the number of entries of each row or column that has any."""
    return a.df.groupBy(F.col("i" if axis == "rows" else "j").alias("i")).agg(F.count("*").alias("n"))


def scale(a: SparseMatrix, diagonal: DataFrame, axis: str = "cols") -> SparseMatrix:
    """Multiply by a diagonal (i, v), on the right for columns, on the left for rows: one join, no sum."""
    key = "j" if axis == "cols" else "i"
    d = diagonal.select(F.col("i").alias(key), F.col("v").alias("w"))
    return a.with_df(a.df.join(d, key).withColumn("v", F.col("v") * F.col("w")))


def diff(a: SparseMatrix, b: SparseMatrix) -> DataFrame:
    """Cells (i, j, v, w) whose presence or value differs."""
    right = b.df.withColumnRenamed("v", "w").withColumn("in_b", F.lit(True))
    joined = a.df.withColumn("in_a", F.lit(True)).join(right, ["i", "j"], "full")
    return joined.where(F.col("in_a").isNull() | F.col("in_b").isNull() | ~F.col("v").eqNullSafe(F.col("w"))).select("i", "j", "v", "w")


def equals(a: SparseMatrix, b: SparseMatrix) -> bool:
    return a.shape == b.shape and not diff(a, b).head(1)
