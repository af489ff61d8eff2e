"""Connected components of a distributed edge list by alternating star contractions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridsparse.llm import common


def connected_components(edges: DataFrame, most_rounds: int = 60) -> DataFrame:
    """``edges`` (a, b) to ``node, component``: each node with the least node of its component.

    A round hangs every node's larger neighbours, then its smaller ones, under
    the least node it sees; edges end as stars around the least nodes.  All
    steps are aggregations and joins on written tables, so nothing is gathered
    and a lost executor costs a re-read; edges of a hub are joined where they
    are.  Nodes without edges do not appear.
    """
    now = common.materialize(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "stars")
    before = None
    for _ in range(most_rounds):
        both = now.unionAll(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"), F.count("*").alias("members"))
        least = common.materialize(least, "least")
        edges_now = now.count()
        large = common.join_hot(both, least, ["a"], 2 * edges_now).where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        large = common.materialize(large, "large")
        down = common.materialize(large.groupBy("a").agg(F.min("b").alias("m"), F.count("*").alias("members")), "down")
        small = common.join_hot(large, down, ["a"], edges_now).select(F.explode(F.array(F.struct(F.col("b").alias("a"), F.col("m").alias("b")), F.struct("a", F.col("m").alias("b")))).alias("e")).select("e.a", "e.b")
        now = common.materialize(small.where("a <> b").distinct(), "stars")
        mark = now.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if mark == before or not mark[0]:
            break
        before = mark
    else:
        raise RuntimeError("components did not settle")
    roots = now.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct()
    return now.select(F.col("a").alias("node"), F.col("b").alias("component")).unionAll(roots)
