"""Permutations and index vectors; an index vector is a table (pos, idx) whose order is the data in pos."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def affine(x: Column, n: int, factor: int = 1103, shift: int = 17) -> Column:
    """A closed-form bijection of [0, n); no sort, no join."""
    if math.gcd(factor, n) != 1:
        raise ValueError("the factor must be coprime to n")
    return F.pmod(x * F.lit(factor) + F.lit(shift), F.lit(n))


def affine_inverse(y: Column, n: int, factor: int = 1103, shift: int = 17) -> Column:
    return F.pmod((y - F.lit(shift)) * F.lit(pow(factor, -1, n)), F.lit(n))


def feistel(x: Column, n: int, seed: int, rounds: int = 4, walks: int = 96) -> Column:
    """A keyed pseudo-random bijection of [0, n) as one expression.

    A balanced network permutes [0, 4**h), at most four times n; a value that
    leaves the range walks on until it returns.  One that has not after
    ``walks`` steps (a chance under 1e-12) raises an error.
    """
    half = max(1, math.ceil(math.log2(max(2, n)) / 2))
    low = F.lit((1 << half) - 1)

    def once(v: Column) -> Column:
        left, right = F.shiftright(v, half), v.bitwiseAND(low)
        for r in range(rounds):
            left, right = right, left.bitwiseXOR(F.xxhash64(F.lit(seed), F.lit(r), right).bitwiseAND(low))
        return F.shiftleft(left, half).bitwiseOR(right)

    start = F.struct(once(x.cast("long")).alias("v"))
    walked = F.aggregate(F.sequence(F.lit(1), F.lit(walks)), start, lambda s, _: F.struct(F.when(s["v"] >= n, once(s["v"])).otherwise(s["v"]).alias("v")))
    return F.when(walked["v"] < n, walked["v"]).otherwise(F.raise_error(F.lit("the walk did not return")).cast("long"))


def md5_rank(keys: DataFrame, key: str = "idx", salt: str = "7:") -> DataFrame:
    """(pos, idx): keys in the order of md5(salt || key).

    Keys are range-partitioned by hash and numbered inside each range; the
    ranges' offsets are a small table, so no task sees all keys.
    """
    hashed = keys.select(F.col(key).cast("long").alias("idx")).withColumn("h", F.md5(F.concat(F.lit(salt), F.col("idx").cast("string"))))
    prefixed = hashed.withColumn("b", F.substring("h", 1, 3))
    counts = prefixed.groupBy("b").count()
    offsets = counts.select("b", (F.sum("count").over(Window.orderBy("b")) - F.col("count")).alias("off"))  # at most 4096 rows
    inner = F.row_number().over(Window.partitionBy("b").orderBy("h", "idx"))
    return prefixed.withColumn("r", inner).join(F.broadcast(offsets), "b").select((F.col("off") + F.col("r") - 1).alias("pos"), "idx")


def random_permutation(spark: SparkSession, n: int, seed: int = 7, method: str = "hash") -> DataFrame:
    """(pos, idx) over [0, n); 'hash' sorts in ranges, 'affine' and 'feistel' are projections."""
    ids = spark.range(n).select(F.col("id").alias("pos"))
    if method == "affine":
        return ids.withColumn("idx", affine(F.col("pos"), n))
    if method == "feistel":
        return ids.withColumn("idx", feistel(F.col("pos"), n, seed))
    return md5_rank(ids.withColumnRenamed("pos", "idx"), salt=f"{seed}:")


def chunks(perm: DataFrame, n: int, k: int) -> DataFrame:
    """(chunk, pos, idx): the vector cut into k runs, each numbered from 0."""
    size = -(-n // k)
    return perm.select(F.floor(F.col("pos") / size).cast("int").alias("chunk"), (F.col("pos") % size).alias("pos"), "idx")


def head(perm: DataFrame, length: int) -> DataFrame:
    """The first ``length`` places: a duplicate-free subset."""
    return perm.where(F.col("pos") < length)


def index_vector(spark: SparkSession, values) -> DataFrame:
    return spark.createDataFrame([(p, int(x)) for p, x in enumerate(values)], "pos long, idx long")
