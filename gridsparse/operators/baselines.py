"""Comparison methods: dense, one processor, and the block matrix of Spark's machine-learning library."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from gridsparse.matrix import SparseMatrix
from gridsparse.operators.layout import Grid
from gridsparse.semiring import Semiring


def dense(a: SparseMatrix, b: SparseMatrix, most: int = 4_000_000) -> np.ndarray:
    """The product in numpy on the driver; refused unless both operands are small."""
    if a.n_rows * a.n_cols > most or b.n_rows * b.n_cols > most:
        raise ValueError("too large for the dense baseline")
    return to_dense(a) @ to_dense(b)


def to_dense(a: SparseMatrix) -> np.ndarray:
    if a.n_rows * a.n_cols > 4_000_000:
        raise ValueError("too large for the dense baseline")
    out = np.zeros(a.shape)
    for r in a.df.collect():
        out[r["i"], r["j"]] = r["v"]
    return out


def one_processor(a: SparseMatrix, b: SparseMatrix, semiring: Semiring | None = None) -> SparseMatrix:
    """The hypersparse kernel over whole operands in one task: the run that speed-ups refer to."""
    return a.multiply(b, semiring=semiring, strategy="grid", grid=Grid(1, 1), kernel="outer")


#: Blocks of a result, and products of two blocks, that a task of the library's product holds at once, about; a block of 1024 x 1024 doubles takes 8 MB.
TASK_BLOCKS, TASK_PRODUCTS = 4, 32


def library_tasks(a: SparseMatrix, b: SparseMatrix, block: int) -> tuple[int, int]:
    """Partitions of the library's result, and splits of its inner range: a task lists all products of blocks that meet in its part of both before it sums them."""
    rows, cols = -(-a.n_rows // block), -(-b.n_cols // block)
    parts = max(a.df.sparkSession.sparkContext.defaultParallelism, -(-rows * cols // TASK_BLOCKS))
    high, wide = (max(1, round(n / parts**0.5)) for n in (rows, cols))  # the library's own rule
    tile = lambda x: F.floor(F.col(x) / block)
    left = a.df.select(tile("i").alias("bi"), tile("j").alias("k")).distinct().groupBy(F.floor(F.col("bi") / high).alias("bi"), "k").agg(F.count("*").alias("na"))
    right = b.df.select(tile("i").alias("k"), tile("j").alias("bj")).distinct().groupBy("k", F.floor(F.col("bj") / wide).alias("bj")).agg(F.count("*").alias("nb"))
    most = left.join(right, "k").groupBy("bi", "bj").agg(F.sum(F.col("na") * F.col("nb")).alias("n")).agg(F.coalesce(F.max("n"), F.lit(0))).first()[0]
    return parts, max(1, -(-most // TASK_PRODUCTS))


def mllib_block(a: SparseMatrix, b: SparseMatrix, block: int = 1024) -> SparseMatrix:
    """Dense blocks on an RDD grid: stands in for a general distributed library.

    The library deals the result to as many tasks as its operands have partitions; ``library_tasks`` says how many keep a
    task's blocks few.  Entries go in and out as DataFrames, not through Python.
    """
    from pyspark.mllib.common import callMLlibFunc
    from pyspark.mllib.linalg.distributed import CoordinateMatrix

    parts, splits = library_tasks(a, b, block)

    def blocks(m: SparseMatrix):
        rows = m.df.select("i", "j", F.col("v").cast("double").alias("value")).repartition(parts)
        return CoordinateMatrix(callMLlibFunc("createCoordinateMatrix", rows, m.n_rows, m.n_cols)).toBlockMatrix(block, block)

    left, right = blocks(a)._java_matrix_wrapper, blocks(b)._java_matrix_wrapper._java_model
    made = left.call("multiply", right, splits).toCoordinateMatrix()
    entries = callMLlibFunc("getMatrixEntries", made).where("value <> 0")
    return SparseMatrix(entries.select("i", "j", F.col("value").alias("v")), a.n_rows, b.n_cols)
