"""Graph methods as repeated products; loops write their state each round."""

from __future__ import annotations

import itertools

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from gridsparse.matrix import SparseMatrix
from gridsparse.operators import elementwise
from gridsparse.operators.product import multiply, power, top_per_row
from gridsparse.semiring import Semiring
from gridsparse.storage import settle


def _bounded(rounds: int, most: int | None) -> None:
    if most is not None and rounds > most:
        raise RuntimeError(f"not done after {most} rounds")


def bfs_multi(a: SparseMatrix, sources: DataFrame, most_levels: int | None = None, depth: int | None = None) -> DataFrame:
    """(source, vertex, level): level-synchronous search from all ``sources`` (vertex) at once.

    Each level is the frontier (a tall, thin matrix, one column per source)
    times the graph, less what has been visited.  The search ends with an empty
    frontier; one still going after ``most_levels`` is an error.  ``depth`` asks
    for the vertices at most so many levels away only.
    """
    visited = settle(sources.select(F.col("vertex").alias("source"), "vertex", F.lit(0).alias("level")), "bfs")
    frontier = visited.select("source", "vertex")
    edges = a.df.select(F.col("i").alias("vertex"), F.col("j").alias("to"))
    for level in itertools.count(1) if depth is None else range(1, depth + 1):
        reached = frontier.join(edges, "vertex").select("source", F.col("to").alias("vertex")).distinct()
        fresh = settle(reached.join(visited.select("source", "vertex"), ["source", "vertex"], "left_anti"), "bfs")
        if not fresh.head(1):
            break
        _bounded(level, most_levels)
        visited = visited.unionByName(fresh.withColumn("level", F.lit(level)))
        frontier = fresh
    return visited


def betweenness(a: SparseMatrix, sources: DataFrame, most_levels: int | None = None) -> DataFrame:
    """(vertex, score) of all vertices reached: dependencies summed over the sources, by path counts forward and shares backward.

    All levels are searched; more than ``most_levels`` are an error.
    """
    edges = a.df.select(F.col("i").alias("vertex"), F.col("j").alias("to"))
    levels = [settle(sources.select(F.col("vertex").alias("source"), "vertex", F.lit(1.0).alias("paths")), "paths")]
    seen = levels[0].select("source", "vertex")
    for level in itertools.count(1):
        step = levels[-1].join(edges, "vertex").groupBy("source", F.col("to").alias("vertex")).agg(F.sum("paths").alias("paths"))
        step = settle(step.join(seen, ["source", "vertex"], "left_anti"), "paths")
        if not step.head(1):
            break
        _bounded(level, most_levels)
        levels.append(step)
        seen = seen.unionByName(step.select("source", "vertex"))
    share = levels[-1].select("source", "vertex", F.lit(0.0).alias("share"))
    total = share
    for depth in range(len(levels) - 1, 0, -1):
        ready = levels[depth].join(share, ["source", "vertex"], "left").select("source", F.col("vertex").alias("to"), F.col("paths").alias("to_paths"), F.coalesce("share", F.lit(0.0)).alias("rest"))
        back = levels[depth - 1].join(edges, "vertex").join(ready, ["source", "to"])
        back = back.groupBy("source", "vertex").agg(F.sum(F.col("paths") / F.col("to_paths") * (1 + F.col("rest"))).alias("share"))
        share = settle(levels[depth - 1].select("source", "vertex").join(back, ["source", "vertex"], "left").select("source", "vertex", F.coalesce("share", F.lit(0.0)).alias("share")), "share")
        total = total.unionByName(share)
    return total.join(sources.select(F.col("vertex").alias("source"), "vertex"), ["source", "vertex"], "left_anti").groupBy("vertex").agg(F.sum("share").alias("score"))


def peer_pressure(a: SparseMatrix, rounds: int = 3) -> DataFrame:
    """(vertex, cluster): each vertex takes its neighbours' most voted cluster, ties to the least."""
    votes_from = a.df.select(F.col("i").alias("vertex"), F.col("j").alias("to"), "v")
    vertices = a.df.select(F.col("i").alias("vertex")).union(a.df.select("j")).distinct()
    now = vertices.withColumn("cluster", F.col("vertex"))
    for _ in range(rounds):
        votes = votes_from.join(now, "vertex").groupBy("to", "cluster").agg(F.sum("v").alias("n"))
        won = votes.groupBy(F.col("to").alias("vertex")).agg(F.max_by("cluster", F.struct("n", -F.col("cluster"))).alias("won"))
        now = settle(now.join(won, "vertex", "left").select("vertex", F.coalesce("won", "cluster").alias("cluster")), "clusters")
    return now


def markov_cluster_step(a: SparseMatrix, inflate: float = 2.0, keep: int = 10) -> SparseMatrix:
    """Square, keep the largest entries of each row, raise to a power and normalise the rows."""
    big = top_per_row(power(a, 2), keep).apply(lambda v: F.pow(v, F.lit(inflate)))
    total = F.sum("v").over(Window.partitionBy("i"))
    return big.with_df(big.df.withColumn("v", F.col("v") / total))


def apsp(a: SparseMatrix, rounds: int | None = None) -> SparseMatrix:
    """All shortest distances by repeated squaring over (min, +); vertices reach themselves at 0."""
    ids = a.df.select("i").union(a.df.select("j")).distinct()
    own = ids.select("i", F.col("i").alias("j"), F.lit(0).cast(dict(a.df.dtypes)["v"]).alias("v"))
    ring = Semiring.min_plus()
    now = elementwise.ewise_add(a, SparseMatrix(own, *a.shape), ring)
    for _ in range(rounds or max(1, (a.n_rows - 1).bit_length())):
        step = now.with_df(settle(multiply(now, now, semiring=ring).df, "apsp"))
        if elementwise.equals(step, now):
            break
        now = step
    return now


def triangles(a: SparseMatrix) -> int:
    """Triangles of a symmetric pattern without loops, by the product masked by the lower part."""
    low = a.with_df(a.df.where("i > j"))
    closed = multiply(low, low, semiring=Semiring.count_pairs(), mask=low)
    return closed.df.agg(F.coalesce(F.sum("v"), F.lit(0))).first()[0]


def cycles_through(a: SparseMatrix, length: int) -> DataFrame:
    """(i, v): closed walks of ``length`` steps through each vertex."""
    return power(a, length).df.where("i = j").select("i", "v")


def matching_round(a: SparseMatrix) -> DataFrame:
    """(i, j): proposals along each row's heaviest edge that are each column's heaviest proposal."""
    offers = a.df.groupBy("i").agg(F.max_by(F.struct("j", "v"), F.struct("v", -F.col("j"))).alias("o")).select("i", "o.j", "o.v")
    return offers.groupBy("j").agg(F.max_by("i", F.struct("v", -F.col("i"))).alias("i")).select("i", "j")


def schur_update(d: SparseMatrix, c: SparseMatrix, inverse: SparseMatrix, b: SparseMatrix) -> SparseMatrix:
    """D - C inverse B."""
    return elementwise.ewise_sub(d, multiply(multiply(c, inverse), b))


def cfg_reach(rules: list[tuple[str, str, str]], edges: DataFrame, most_rounds: int | None = None) -> DataFrame:
    """(label, i, j) derivable by rules label -> left right, from labelled edges, to the fixpoint; one not met in ``most_rounds`` is an error.

    Each round joins only what the round before it found.  A grammar of one rule
    S -> S E, where no rule makes E, doubles the reach of S in a round as long as
    the pairs that so many E-steps link don't grow beyond twice the E-edges.
    """
    spark = edges.sparkSession
    grammar = F.broadcast(spark.createDataFrame(rules, "label string, l string, r string"))
    now = settle(edges.select("label", "i", "j").distinct(), "cfg")
    done = 0
    fresh = now
    if len(rules) == 1 and rules[0][0] == rules[0][1] != rules[0][2]:
        now, done = _doubled(now, *rules[0][1:], most_rounds)
        if done is None:
            return now
        fresh = now
    for count in itertools.count(done + 1):
        with_rule = lambda part: part.withColumnRenamed("label", "l").join(grammar, "l").select("label", "r", "i", F.col("j").alias("k"))
        right = lambda part: part.select(F.col("label").alias("r"), F.col("i").alias("k"), "j")
        made = with_rule(fresh).join(right(now), ["r", "k"]).unionByName(with_rule(now).join(right(fresh), ["r", "k"])).select("label", "i", "j").distinct()
        fresh = settle(made.join(now, ["label", "i", "j"], "left_anti"), "cfg")
        if not fresh.head(1):
            break
        _bounded(count, most_rounds)
        now = now.unionByName(fresh) if count % 8 else settle(now.unionByName(fresh), "cfg")
    return now


def _doubled(now: DataFrame, label: str, step: str, most_rounds: int | None) -> tuple[DataFrame, int | None]:
    """S of at most 2 ** r further steps after r rounds; the rounds made, or none if the fixpoint is met."""
    other = now.where(F.col("label") != label)
    reach = now.where(F.col("label") == label).select("i", "j")
    hops = now.where(F.col("label") == step).select(F.col("i").alias("k"), "j")
    most = 2 * hops.count()
    for count in itertools.count(1):
        more = reach.withColumnRenamed("j", "k").join(hops, "k").select("i", "j").distinct()
        fresh = settle(more.join(reach, ["i", "j"], "left_anti"), "cfg")
        whole = lambda r: other.unionByName(r.select(F.lit(label).alias("label"), "i", "j"))
        if not fresh.head(1):
            return whole(reach), None
        _bounded(count, most_rounds)
        reach = reach.unionByName(fresh)
        twice = settle(hops.select(F.col("k").alias("from"), F.col("j").alias("k")).join(hops, "k").select(F.col("from").alias("k"), "j").distinct(), "hops")
        if twice.count() > most:
            return settle(whole(reach), "cfg"), count
        hops = twice


def colored_intersection(m: SparseMatrix) -> SparseMatrix:
    """For each pair of sets the number of shared colours."""
    return multiply(m, m.transpose(), semiring=Semiring.count_pairs())
