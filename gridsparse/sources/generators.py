"""Random matrices as expressions over a range of draws: no state, any partitioning gives the same draw."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from gridsparse.functions.permutations import feistel
from gridsparse.matrix import SparseMatrix

#: Quadrant probabilities of the recursive generator.
QUADRANTS = (0.6, 0.4 / 3, 0.4 / 3, 0.4 / 3)


def uniform(*parts: Column) -> Column:
    return (F.shiftrightunsigned(F.xxhash64(*parts), 11).cast("double") + 0.5) / F.lit(float(1 << 53))


def rmat(spark: SparkSession, scale: int, degree: int = 8, seed: int = 1, relabel: str = "independent", quadrants=QUADRANTS) -> SparseMatrix:
    """degree * 2**scale draws by recursive quadrants, equal draws merged.

    'independent' relabels rows and columns by permutations of this seed;
    'shared' uses one permutation for all seeds, so hubs coincide; 'none'
    leaves hubs at the low ids.
    """
    n = 1 << scale
    a, b, c, _ = quadrants
    draws = spark.range(degree * n)
    zero = F.struct(F.lit(0).cast("long").alias("i"), F.lit(0).cast("long").alias("j"))

    def descend(state, level):
        u = uniform(F.lit(seed), F.col("id"), level)
        down = (u >= a + b).cast("long")
        right = ((u >= a) & (u < a + b) | (u >= a + b + c)).cast("long")
        return F.struct((state["i"] * 2 + down).alias("i"), (state["j"] * 2 + right).alias("j"))

    cells = draws.select(F.aggregate(F.sequence(F.lit(1), F.lit(scale)), zero, descend).alias("e")).select("e.i", "e.j").distinct()
    if relabel != "none":
        keys = (seed * 2 + 1, seed * 2 + 2) if relabel == "independent" else (0, 0)
        cells = cells.select(feistel(F.col("i"), n, keys[0]).alias("i"), feistel(F.col("j"), n, keys[1]).alias("j"))
    return SparseMatrix(cells.withColumn("v", F.lit(1).cast("long")), n, n)


def erdos_renyi(spark: SparkSession, n: int, k: int, per_column: int, seed: int = 2) -> SparseMatrix:
    """n x k with ``per_column`` flat random draws a column, equal draws merged."""
    draws = spark.range(k * per_column).select(F.floor(uniform(F.lit(seed), F.col("id")) * n).alias("i"), F.expr(f"id div {per_column}").alias("j"))
    return SparseMatrix(draws.distinct().withColumn("v", F.lit(1).cast("long")), n, k)


def random_sources(spark: SparkSession, n: int, k: int, seed: int = 3) -> DataFrame:
    """k distinct vertices (vertex), the first k of a permutation."""
    return spark.range(k).select(feistel(F.col("id"), n, seed).alias("vertex"))
