"""Join and window forms that the engine's users need beyond plain SQL."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def asof_join(left: DataFrame, right: DataFrame, by: list[str], time: str, values: list[str]) -> DataFrame:
    """For each left row the last right row of the same key at or before its time, by one sort of both sides."""
    marked = left.withColumn("_side", F.lit(1))
    other = right.select(*by, time, F.struct(*values).alias("_last"), F.lit(0).alias("_side"))
    both = marked.unionByName(other, allowMissingColumns=True)
    order = Window.partitionBy(*by).orderBy(time, "_side").rowsBetween(Window.unboundedPreceding, 0)
    filled = both.withColumn("_last", F.last("_last", ignorenulls=True).over(order)).where("_side = 1")
    return filled.select(*left.columns, *(F.col(f"_last.{v}").alias(f"last_{v}") for v in values))


def range_join(points: DataFrame, intervals: DataFrame, at: str, low: str, high: str, width: int) -> DataFrame:
    """Points inside closed integer intervals: both sides meet in buckets of ``width``, so it is an equi-join."""
    bucketed = points.withColumn("_b", F.floor(F.col(at) / width))
    spread = intervals.withColumn("_b", F.explode(F.sequence(F.floor(F.col(low) / width), F.floor(F.col(high) / width))))
    return bucketed.join(spread, "_b").where(F.col(at).between(F.col(low), F.col(high))).drop("_b")


def interval_pairs(events: DataFrame, key: str, time: str, ident: str, seconds: int) -> DataFrame:
    """(first, second): events of one key at most ``seconds`` apart, by time buckets; a row sees its own and the next bucket."""
    at = F.unix_timestamp(F.col(time).cast("timestamp"))
    rows = events.select(key, ident, at.alias("_t"), F.floor(at / seconds).alias("_b"))
    second = rows.select(key, F.col(ident).alias("second"), F.col("_t").alias("_u"), F.explode(F.array(F.col("_b"), F.col("_b") - 1)).alias("_b"))
    joined = rows.withColumnRenamed(ident, "first").join(second, [key, "_b"])
    near = (F.col("_u") - F.col("_t")).between(0, seconds) & (F.col("first") != F.col("second"))
    return joined.where(near).select("first", "second").distinct()


def salted_sum(df: DataFrame, keys: list[str], value: Column, salts: int = 16) -> DataFrame:
    """A sum that first aggregates per salt, for keys whose rows an aggregate can't combine before the shuffle."""
    salt = F.pmod(F.xxhash64(value), F.lit(salts))
    return df.groupBy(*keys, salt.alias("_s")).agg(F.sum(value).alias("v")).groupBy(*keys).agg(F.sum("v").alias("v"))


def row_as_map(df: DataFrame, key: str, column: str, value: str) -> DataFrame:
    """One map per row of a matrix-like table."""
    return df.groupBy(key).agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct(column, value)))).alias("cells"))


def bernoulli_sample(df: DataFrame, fraction: float, seed: int) -> DataFrame:
    """Each row with probability ``fraction``, independently; the same seed over the same files and partitions gives the same rows."""
    return df.sample(withReplacement=False, fraction=fraction, seed=seed)
