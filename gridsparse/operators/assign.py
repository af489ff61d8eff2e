"""Replacing a window of a matrix, adding into one, clearing one."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridsparse.matrix import SparseMatrix
from gridsparse.operators import build, elementwise
from gridsparse.operators.indexing import check_range
from gridsparse.operators.product import multiply
from gridsparse.semiring import Semiring
from gridsparse.storage import small


def check(a: SparseMatrix, rows: DataFrame, cols: DataFrame, b: SparseMatrix) -> None:
    """Raise if an index repeats or is out of range, or if there are not as many as B has rows or columns."""
    for index, n, length in ((rows, a.n_rows, b.n_rows), (cols, a.n_cols, b.n_cols)):
        check_range(index, n)
        if index.groupBy("idx").count().where("count > 1").head(1):
            raise ValueError("an index repeats; use extend_add")
        if index.count() != length:
            raise ValueError("the index vectors' lengths are not the block's shape")


def embed(a: SparseMatrix, rows: DataFrame, cols: DataFrame, b: SparseMatrix, via: str = "join") -> SparseMatrix:
    """B moved into its window in a matrix of A's shape; entries at repeated targets add up."""
    if via == "product":
        left = multiply(build.embed_rows(rows, b.n_rows, a.n_rows), b, semiring=Semiring.select_second())
        return multiply(left, build.embed_cols(cols, b.n_cols, a.n_cols), semiring=Semiring.select_first())
    r = small(rows.select(F.col("pos").alias("i"), F.col("idx").alias("to_i")))
    c = small(cols.select(F.col("pos").alias("j"), F.col("idx").alias("to_j")))
    return a.with_df(b.df.join(r, "i").join(c, "j").select(F.col("to_i").alias("i"), F.col("to_j").alias("j"), "v"))


def window_of(a: SparseMatrix, rows: DataFrame, cols: DataFrame, via: str = "join") -> SparseMatrix:
    """The entries of A inside the window, at their places."""
    if via == "product":
        left = multiply(build.diag_selector(rows, a.n_rows), a, semiring=Semiring.select_second())
        return multiply(left, build.diag_selector(cols, a.n_cols), semiring=Semiring.select_first())
    inside = a.df.join(small(rows.select(F.col("idx").alias("i")).distinct()), "i", "left_semi")
    return a.with_df(inside.join(small(cols.select(F.col("idx").alias("j")).distinct()), "j", "left_semi"))


def clear_window(a: SparseMatrix, rows: DataFrame, cols: DataFrame) -> SparseMatrix:
    """A without the window: one scan with two lookups."""
    r = small(rows.select(F.col("idx").alias("i")).distinct().withColumn("in_i", F.lit(True)))
    c = small(cols.select(F.col("idx").alias("j")).distinct().withColumn("in_j", F.lit(True)))
    flagged = a.df.join(r, "i", "left").join(c, "j", "left")
    return a.with_df(flagged.where(F.col("in_i").isNull() | F.col("in_j").isNull()))


def assign(a: SparseMatrix, rows: DataFrame, cols: DataFrame, b: SparseMatrix, clear: str = "mask", via: str = "join", validate: bool = True) -> SparseMatrix:
    """A with A(I, J) = B.

    'mask' drops the window by its pattern, which needs no additive inverse and
    is right for NaN and infinity; 'subtract' is the form for rings.
    """
    if validate:
        check(a, rows, cols, b)
    placed = embed(a, rows, cols, b, via)
    if clear == "subtract":
        cleared = elementwise.ewise_sub(a, window_of(a, rows, cols, via))
    elif via == "product":
        cleared = elementwise.ewise_mult(a, window_of(a, rows, cols, via), negate_b=True)
    else:
        cleared = clear_window(a, rows, cols)
    return elementwise.ewise_add(cleared, placed, disjoint=True)


def extend_add(a: SparseMatrix, rows: DataFrame, cols: DataFrame, b: SparseMatrix, via: str = "join") -> SparseMatrix:
    """A with B added into the window; repeated indices accumulate."""
    return elementwise.ewise_add(a, embed(a, rows, cols, b, via))
