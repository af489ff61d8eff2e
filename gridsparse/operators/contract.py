"""Contraction by restriction operators: one coarse id per fine id."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridsparse.matrix import SparseMatrix
from gridsparse.operators import elementwise
from gridsparse.operators.product import multiply, multiply_chain, multiply_split
from gridsparse.storage import small


def restrict_right(a: SparseMatrix, s: SparseMatrix) -> SparseMatrix:
    """A times S transposed: one product per entry of A whatever the order."""
    return multiply(a, s.transpose(), strategy="broadcast")


def contract(a: SparseMatrix, s: SparseMatrix, order: str = "fused", drop_loops: bool = False) -> SparseMatrix:
    """S A S-transposed.  'fused' looks both ids up and sums once; 'left' and 'right' are the two products."""
    if order == "fused":
        fine = small(s.df.select("i", F.col("j").alias("fine"), F.col("v").alias("w")))
        rows = fine.select(F.col("i").alias("ci"), F.col("fine").alias("i"), F.col("w").alias("wi"))
        cols = fine.select(F.col("i").alias("cj"), F.col("fine").alias("j"), F.col("w").alias("wj"))
        cells = a.df.join(rows, "i").join(cols, "j").select(F.col("ci").alias("i"), F.col("cj").alias("j"), (F.col("wi") * F.col("v") * F.col("wj")).alias("v"))
        out = SparseMatrix(cells.groupBy("i", "j").agg(F.sum("v").alias("v")), s.n_rows, s.n_rows)
    else:
        out = multiply_chain([s, a, s.transpose()], order)
    return out.with_df(out.df.where("i <> j")) if drop_loops else out


def galerkin(a: SparseMatrix, s: SparseMatrix, split_diag: bool = True) -> SparseMatrix:
    """The triple product with A's diagonal taken apart first, which balances diagonal cells."""
    left = multiply_split(s, a) if split_diag else multiply(s, a)
    return multiply(left, s.transpose())


def weighted_restriction(s: SparseMatrix, weights: DataFrame) -> SparseMatrix:
    """S with fine id j weighted by (i, v)."""
    return elementwise.scale(s, weights, "cols")


def interpolate(s: SparseMatrix, coarse: SparseMatrix) -> SparseMatrix:
    """S-transposed times Y: coarse values carried to their fine ids.

    Where each fine id has one coarse id, every entry of the result is one
    product: a look-up without a sum, so the result is never shuffled.
    """
    if s.df.groupBy("j").count().where("count > 1").head(1):
        return multiply(s.transpose(), coarse)
    fine = small(s.df.select(F.col("i").alias("c"), F.col("j").alias("fine"), F.col("v").alias("w")))
    made = coarse.df.withColumnRenamed("i", "c").join(fine, "c")
    return SparseMatrix(made.select(F.col("fine").alias("i"), "j", (F.col("w") * F.col("v")).alias("v")), s.n_cols, coarse.n_cols)
