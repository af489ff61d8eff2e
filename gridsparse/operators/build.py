"""Structured matrices: identities, selectors, embeddings, restrictions."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridsparse.matrix import SparseMatrix


def _one():
    return F.lit(1).cast("long").alias("v")


def identity(spark: SparkSession, n: int) -> SparseMatrix:
    return SparseMatrix(spark.range(n).select(F.col("id").alias("i"), F.col("id").alias("j"), _one()), n, n)


def diagonal(vector: DataFrame, n: int) -> SparseMatrix:
    """(i, v) on the diagonal."""
    return SparseMatrix(vector.select("i", F.col("i").alias("j"), "v"), n, n)


def row_selector(index: DataFrame, length: int, m: int) -> SparseMatrix:
    """length x m, one entry per row: row pos picks row idx."""
    return SparseMatrix(index.select(F.col("pos").alias("i"), F.col("idx").alias("j"), _one()), length, m)


def col_selector(index: DataFrame, length: int, n: int) -> SparseMatrix:
    """n x length: the transpose of an identically built row selector."""
    return row_selector(index, length, n).transpose()


def embed_rows(index: DataFrame, length: int, m: int) -> SparseMatrix:
    """m x length: puts row pos of a block at row idx."""
    return row_selector(index, length, m).transpose()


def embed_cols(index: DataFrame, length: int, n: int) -> SparseMatrix:
    """length x n: puts column pos of a block at column idx."""
    return row_selector(index, length, n)


def diag_selector(index: DataFrame, n: int) -> SparseMatrix:
    """n x n with ones where the index vector points."""
    return SparseMatrix(index.select(F.col("idx").alias("i"), F.col("idx").alias("j"), _one()).distinct(), n, n)


def restriction(spark: SparkSession, n: int, order: int) -> SparseMatrix:
    """ceil(n / order) x n: runs of ``order`` fine ids form a coarse one."""
    fine = spark.range(n).select(F.floor(F.col("id") / order).alias("i"), F.col("id").alias("j"), _one())
    return SparseMatrix(fine, -(-n // order), n)


def restriction_from(table: DataFrame, fine: str, coarse: str, shape: tuple[int, int]) -> SparseMatrix:
    """A restriction from a foreign key: each fine id has one coarse id."""
    return SparseMatrix(table.select(F.col(coarse).cast("long").alias("i"), F.col(fine).cast("long").alias("j"), _one()), *shape)
