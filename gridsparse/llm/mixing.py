"""Mixing sources to target weights by a hypergeometric splitting tree, and op1.

All steps are DataFrame expressions.  A hash of the id permutes a source's
documents and cuts them into blocks.  A source's target turns into an exact
quota of blocks: whole passes over it, then a run of blocks of one more pass.
From the first block that does not fit on, documents are taken one by one:
those larger than the words left are skipped, so what a source misses in the end
is less than each of its documents that could have been taken once more.
The quotas are dealt to output shards by a binary tree: at each node a
multivariate hypergeometric draw (source after source, by inversion around the
mode) says how many of each source's blocks go left.  A leaf takes a run of
each source's permuted blocks, disjoint from all others, and orders its
documents by another hash.

A null source is a source of its own, after all others; null texts have size 0.
Sources' totals (a row each) meet in one task, and each node of the tree holds
a number per source: meant for up to some 100 000 sources, of any size.
Rows that agree in id, source and size share one decision.  Empty tables give
empty results.  Draws depend on ids and the seed only, so reruns agree.
"""

from __future__ import annotations

import math
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from gridsparse.llm import common

WEIGHTS = (5.0, 2.0, 1.0)
SHARE = 1.5
MOST_PASSES = 2.0
BLOCK_DOCUMENTS = 64
MOST_BLOCK_BITS = 16
SHARD_WORDS = 1 << 22
MOST_SHARD_BITS = 12


def uniform(*parts) -> Column:
    """A number in (0, 1) from a hash of the parts."""
    bits = F.shiftrightunsigned(F.xxhash64(*parts), 11)
    return (bits.cast("double") + 0.5) / F.lit(float(1 << 53))


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(common.WORD)), F.lit(0)).cast("long")


def targets(sources: DataFrame, weights=WEIGHTS, share: float = SHARE, most: float = MOST_PASSES) -> DataFrame:
    """Targets of ``sources`` (source, source_size): shares by cycled weights, stopped at ``most`` times the size.

    With sources by ascending limit over weight, one is at its limit iff the
    level that the rest would share exceeds that quotient; one pass finds all.
    """
    whole = Window.orderBy(F.col("source").asc_nulls_last())
    ranked = sources.withColumn("source_rank", F.row_number().over(whole) - 1)
    cycle = F.array(*map(F.lit, weights))
    ranked = ranked.withColumn("weight", F.element_at(cycle, (F.col("source_rank") % len(weights) + 1).cast("int")))
    ranked = ranked.withColumn("limit", F.lit(most) * F.col("source_size"))
    by_quotient = Window.orderBy(F.col("limit") / F.col("weight"), "source_rank")
    before, onward = by_quotient.rowsBetween(Window.unboundedPreceding, -1), by_quotient.rowsBetween(0, Window.unboundedFollowing)
    everything = by_quotient.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    total = F.lit(share) * F.sum("source_size").over(everything)
    level = (total - F.coalesce(F.sum("limit").over(before), F.lit(0.0))) / F.sum("weight").over(onward)
    ranked = ranked.withColumn("level", level)
    open_level = F.when(F.col("level") * F.col("weight") < F.col("limit"), F.col("level"))
    shared = F.first(open_level, ignorenulls=True).over(everything)
    target = F.coalesce(F.least(F.col("limit"), shared * F.col("weight")), F.col("limit"))
    return ranked.select("source", "source_rank", "source_size", "documents", "weight", target.alias("target"))


def bind(value: Column, body) -> Column:
    """``body`` of ``value``, which is evaluated once."""
    return F.element_at(F.transform(F.array(value), body), 1)


def _ratio(s: Column, k: Column) -> Column:
    """P(k + 1) over P(k) for the draw in the struct ``s`` of doubles."""
    return (s["marked"] - k) * (s["drawn"] - k) / ((k + 1.0) * (s["rest"] - s["drawn"] + k + 1.0))


def _walk(s: Column, up: bool, wanted: Column | None) -> Column:
    """Go from the mode to the end of one side, adding probabilities; stop counting once ``wanted`` is reached.

    Gives a struct of the relative probability p, the mass added and the value ``at`` which it was reached.
    """
    steps = F.when(s["top"] > s["mode"], F.sequence(s["mode"].cast("long"), s["top"].cast("long") - 1)) if up else F.when(s["mode"] > s["bottom"], F.sequence(s["mode"].cast("long") - 1, s["bottom"].cast("long")))
    start = F.struct(F.lit(1.0).alias("p"), F.lit(0.0).alias("mass"), s["mode"].alias("at"))

    def step(state, k):
        ratio = _ratio(s, k.cast("double"))
        p = state["p"] * (ratio if up else 1.0 / ratio)
        if wanted is None:
            return F.struct(p.alias("p"), (state["mass"] + p).alias("mass"), state["at"].alias("at"))
        on = (state["mass"] < wanted).cast("double")
        return F.struct(p.alias("p"), (state["mass"] + p * on).alias("mass"), F.when(on > 0, k.cast("double") + (1.0 if up else 0.0)).otherwise(state["at"]).alias("at"))

    return F.aggregate(F.coalesce(steps, F.array().cast("array<long>")), start, step)


def hypergeometric(total: Column, marked: Column, drawn: Column, chance: Column) -> Column:
    """How many of ``drawn`` out of ``total`` are among the ``marked`` ones, by inversion of ``chance``.

    Probabilities relative to the mode's follow from their ratios; only values
    within 12 deviations of the mode are walked, the rest being under 1e-30.
    Values are taken in this order: the mode, those above it, those below it.
    """
    d = lambda c: c.cast("double")
    given = F.struct(d(total).alias("total"), d(marked).alias("marked"), d(drawn).alias("drawn"), (d(total) - d(marked)).alias("rest"), chance.alias("chance"))

    def with_mode(g):
        low, high = F.greatest(F.lit(0.0), g["drawn"] - g["rest"]), F.least(g["marked"], g["drawn"])
        mode = F.least(F.greatest(d(F.floor((g["drawn"] + 1) * (g["marked"] + 1) / (g["total"] + 2))), low), high)
        spread = F.sqrt(g["drawn"] * g["marked"] * g["rest"] * (g["total"] - g["drawn"]) / F.greatest(g["total"] * g["total"] * (g["total"] - 1), F.lit(1.0)))
        reach = d(F.ceil(12 * spread + 12))
        return bind(F.struct(g["marked"].alias("marked"), g["drawn"].alias("drawn"), g["rest"].alias("rest"), g["chance"].alias("chance"), mode.alias("mode"), low.alias("low"), high.alias("high"), reach.alias("reach")), with_ends)

    def with_ends(g):
        top, bottom = F.least(g["high"], g["mode"] + g["reach"]), F.greatest(g["low"], g["mode"] - g["reach"])
        ends = F.struct(*(g[c].alias(c) for c in ("marked", "drawn", "rest", "chance", "mode")), top.alias("top"), bottom.alias("bottom"))
        return bind(ends, lambda s: bind(F.struct(_walk(s, True, None)["mass"].alias("above"), _walk(s, False, None)["mass"].alias("below")), lambda m: choose(s, m)))

    def choose(s, m):
        wanted = s["chance"] * (1.0 + m["above"] + m["below"])
        return F.when(wanted <= 1.0, s["mode"]).when(wanted <= 1.0 + m["above"], _walk(s, True, wanted - 1.0)["at"]).otherwise(_walk(s, False, wanted - 1.0 - m["above"])["at"])

    return bind(given, with_mode).cast("long")


def _left_counts(seed: int, level: int) -> Column:
    """A node's draw of half of its blocks, source after source: how many of each go left."""
    begin = F.struct(F.col("all").alias("total"), F.expr("`all` div 2").alias("drawn"), F.array().cast("array<long>").alias("left"))

    def draw(state, pair):
        count = pair["count"]
        chance = uniform(F.lit(seed), F.lit(level), F.col("node"), pair["rank"])
        part = F.when(count == 0, F.lit(0).cast("long")).otherwise(hypergeometric(state["total"], count, state["drawn"], chance))
        return bind(part, lambda p: F.struct((state["total"] - count).alias("total"), (state["drawn"] - p).alias("drawn"), F.concat(state["left"], F.array(p)).alias("left")))

    pairs = F.zip_with("counts", "ranks", lambda c, r: F.struct(c.alias("count"), r.alias("rank")))
    return F.aggregate(pairs, begin, draw, lambda s: s["left"])


def split_quotas(quotas: DataFrame, bits: int, seed: int) -> DataFrame:
    """``quotas`` (source_rank, quota) dealt to ``2**bits`` shards: shard, source_rank, blocks."""
    counts = F.transform(F.array_sort(F.collect_list(F.struct("source_rank", "quota"))), lambda x: x["quota"])
    nodes = quotas.agg(counts.alias("counts"), F.array_sort(F.collect_list("source_rank")).alias("ranks")).select(F.lit(0).cast("long").alias("node"), "counts", "ranks")
    for level in range(bits):
        total = F.aggregate("counts", F.lit(0).cast("long"), lambda a, x: a + x)
        nodes = nodes.withColumn("all", total).withColumn("left", _left_counts(seed, level))
        right = F.zip_with("counts", "left", lambda c, x: c - x)
        sides = F.array(F.struct((F.col("node") * 2).alias("node"), F.col("left").alias("counts")), F.struct((F.col("node") * 2 + 1).alias("node"), right.alias("counts")))
        nodes = nodes.select("ranks", F.explode(sides).alias("side")).select("side.node", "side.counts", "ranks")
    return nodes.select("node", F.explode(F.arrays_zip("ranks", "counts")).alias("x")).select(F.col("node").cast("int").alias("shard"), F.col("x.ranks").alias("source_rank"), F.col("x.counts").alias("blocks"))


class Plan:
    """The decisions for a table: its sources' targets, block shards, and the documents taken from last blocks."""

    def __init__(self, docs: DataFrame, weights=WEIGHTS, share: float = SHARE, most: float = MOST_PASSES, seed: int = 1, shard_words: int = SHARD_WORDS):
        self.seed = seed
        slim = docs.select("doc_id", "source", word_count(F.col("text")).alias("size"))
        self.slim = common.materialize(slim, "mix-sizes")
        stats = self.slim.groupBy("source").agg(F.sum("size").alias("source_size"), F.count("*").alias("documents"))
        found = targets(stats, weights, share, most)
        bits = F.least(F.lit(MOST_BLOCK_BITS), F.greatest(F.lit(0), F.ceil(F.log2(F.col("documents") / F.lit(float(BLOCK_DOCUMENTS)))).cast("int")))
        passes = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0).cast("long")
        found = found.withColumn("block_bits", bits).withColumn("passes", passes)
        self.sources = common.materialize(found.withColumn("room", F.col("target") - F.col("passes") * F.col("source_size")), "mix-sources")
        keyed = self._keyed(self.slim)
        sums = keyed.groupBy("source_rank", "block").agg(F.sum("size").alias("words"))
        sums = sums.join(self.sources.select("source_rank", "room", "passes", "block_bits"), "source_rank")
        before = F.coalesce(F.sum("words").over(Window.partitionBy("source_rank").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
        sums = sums.withColumn("before", before)
        state = F.when((F.col("words") > 0) & (F.col("before") + F.col("words") <= F.col("room")), 2).when((F.col("words") > 0) & (F.col("before") < F.col("room")), 1).otherwise(0)
        blocks = common.materialize(sums.select("source_rank", "block", "passes", "before", "room", state.alias("state")), "mix-blocks")
        self.last = self._last_documents(keyed, blocks)
        touched = self.last.select("source_rank", "block").distinct().withColumn("touched", F.lit(1))
        state = F.when((F.col("state") == 0) & F.col("touched").isNotNull(), 1).otherwise(F.col("state"))
        self.blocks = common.materialize(blocks.join(touched, ["source_rank", "block"], "left").select("source_rank", "block", "passes", state.alias("state")), "mix-states")
        words = self.sources.agg(F.sum("target")).first()[0] or 0.0
        self.bits = min(MOST_SHARD_BITS, max(3, math.ceil(math.log2(max(1.0, words / shard_words)))))
        self.shards = self._shards()

    def _keyed(self, rows: DataFrame) -> DataFrame:
        """Rows with their source's rank, permutation key and block; a null-safe join to the small sources table."""
        small = self.sources.select(F.col("source").alias("of_source"), "source_rank", "source_size", "target", "passes", "block_bits")
        key = F.xxhash64(F.lit(self.seed), F.col("doc_id"))
        joined = rows.join(small, F.col("source").eqNullSafe(F.col("of_source"))).drop("of_source").withColumn("mix_key", key)
        block = F.when(F.col("block_bits") == 0, F.lit(0)).otherwise(F.expr("shiftrightunsigned(mix_key, 64 - block_bits)"))
        return joined.withColumn("block", block.cast("long")).drop("block_bits")

    def _last_documents(self, keyed: DataFrame, blocks: DataFrame) -> DataFrame:
        """The documents taken one more time from each source's first block that does not fit, and from those after it.

        Each round fills one block a source.  Between two such blocks all
        documents that fit the words left are taken whole blocks at a time, by
        the blocks' sums; the next one to fill is where these sums exceed the
        words left.  Rounds end when no later document fits.
        """
        place = ["source_rank", "block"]
        edge = blocks.where("state = 1").select(*place, (F.col("room") - F.col("before")).cast("double").alias("space"))
        rows = keyed.select(*place, "mix_key", "doc_id", "size").where("size > 0")
        taken = None
        while True:
            chosen = common.materialize(self._fill(rows.join(edge, place)), "mix-last")
            taken = chosen if taken is None else taken.unionByName(chosen)
            used = chosen.groupBy("source_rank").agg(F.sum("words").alias("used"))
            left = edge.join(used, "source_rank", "left").select("source_rank", F.col("block").alias("done"), (F.col("space") - F.coalesce("used", F.lit(0))).alias("space"))
            later = rows.join(F.broadcast(left), "source_rank").where("block > done and size <= space")
            small = later.groupBy(*place, "space", "mix_key", "doc_id", "size").agg((F.col("size") * F.count("*")).alias("words")).where("words <= space")
            small = common.materialize(small, "mix-small")
            if not small.head(1):
                break
            order = Window.partitionBy("source_rank").orderBy("block")
            sums = small.groupBy(*place, "space").agg(F.sum("words").alias("words")).withColumn("upto", F.sum("words").over(order))
            sums = common.materialize(sums, "mix-small-sums")
            whole = small.join(sums.where("upto <= space").select(*place), place).select(*place, "mix_key", "doc_id", "size", "words")
            taken = taken.unionByName(common.materialize(whole, "mix-last"))
            beyond = F.struct("block", (F.col("space") - F.col("upto") + F.col("words")).alias("space"))
            edge = common.materialize(sums.where("upto > space").groupBy("source_rank").agg(F.min(beyond).alias("e")).select("source_rank", "e.block", "e.space"), "mix-edge")
            if not edge.head(1):
                break
            rows = small.join(F.broadcast(edge.select("source_rank", F.col("block").alias("from"))), "source_rank").where("block >= from").select(rows.columns)
        return common.materialize(taken.drop("words").withColumn("one_more", F.lit(True)), "mix-last")

    def _fill(self, rows: DataFrame) -> DataFrame:
        """What is taken of ``rows`` of one block a source: in key order while it fits, then the largest that still fit."""
        rows = rows.groupBy("source_rank", "block", "space", "mix_key", "doc_id", "size").agg(F.count("*").alias("times"))
        words = F.col("size") * F.col("times")
        order = Window.partitionBy("source_rank").orderBy("mix_key", "doc_id", "size")
        rows = rows.withColumn("words", words).withColumn("upto", F.sum("words").over(order)).withColumn("nth", F.row_number().over(order))
        whole = Window.partitionBy("source_rank")
        fits = F.col("upto") <= F.col("space")
        rows = rows.withColumn("fit_words", F.coalesce(F.max(F.when(fits, F.col("upto"))).over(whole), F.lit(0)))
        item = F.struct((-F.col("words")).alias("less"), F.col("mix_key"), F.col("doc_id"), F.col("size"))
        waiting = F.array_sort(F.collect_list(F.when(~fits & (F.col("words") <= F.col("space") - F.col("fit_words")), item)).over(whole))
        rows = rows.withColumn("waiting", F.when(F.col("nth") == 1, waiting))
        begin = F.struct((F.col("space") - F.col("fit_words")).cast("double").alias("left"), F.array().cast("array<struct<less:long,mix_key:long,doc_id:long,size:long>>").alias("chosen"))

        def fill(state, x):
            ok = -x["less"] <= state["left"]
            return F.struct(F.when(ok, state["left"] + x["less"]).otherwise(state["left"]).alias("left"), F.when(ok, F.concat(state["chosen"], F.array(x))).otherwise(state["chosen"]).alias("chosen"))

        extra = rows.where("nth = 1").select("source_rank", "block", F.explode(F.aggregate("waiting", begin, fill, lambda s: s["chosen"])).alias("c"))
        extra = extra.select("source_rank", "block", "c.mix_key", "c.doc_id", "c.size", (-F.col("c.less")).alias("words"))
        return rows.where(fits).select("source_rank", "block", "mix_key", "doc_id", "size", "words").unionByName(extra)

    def _shards(self) -> DataFrame:
        """For each block the shard of each pass over it, in order."""
        passed = F.sum(F.when(F.col("state") > 0, 1).otherwise(0)).cast("long")
        quotas = self.blocks.groupBy("source_rank").agg((F.first("passes") * F.count("*") + passed).alias("quota"))
        numbered = self.blocks.withColumn("nth", F.row_number().over(Window.partitionBy("source_rank").orderBy(F.desc(F.col("state") > 0), "block")) - 1)
        size = F.count("*").over(Window.partitionBy("source_rank"))
        numbered = numbered.withColumn("n_blocks", size).select("source_rank", "block", "state", "nth", "n_blocks")
        dealt = split_quotas(quotas, self.bits, self.seed)
        until = F.sum("blocks").over(Window.partitionBy("source_rank").orderBy("shard"))
        runs = dealt.withColumn("until", until).where("blocks > 0")
        places = runs.select("source_rank", "shard", F.explode(F.expr("sequence(until - blocks, until - 1)")).alias("place"))
        sized = numbered.select("source_rank", "n_blocks").distinct()
        places = places.join(sized, "source_rank").withColumn("nth", F.col("place") % F.col("n_blocks"))
        shards = F.transform(F.array_sort(F.collect_list(F.struct("place", "shard"))), lambda x: x["shard"])
        placed = places.groupBy("source_rank", "nth").agg(shards.alias("shards"))
        result = numbered.join(placed, ["source_rank", "nth"], "left").select("source_rank", "block", "state", "shards")
        return common.materialize(result, "mix-shards")

    def apply(self, rows: DataFrame) -> DataFrame:
        """``rows`` (doc_id, source, size, and any others) with source_size, target, copies and shards."""
        last = self.last.select("source_rank", "mix_key", "size", F.col("doc_id").alias("last_id"), "one_more")
        out = self._keyed(rows).join(self.shards, ["source_rank", "block"], "left").alias("row")
        same = [F.col(f"row.{c}") == F.col(f"last.{c}") for c in ("source_rank", "mix_key", "size")]
        out = out.join(last.alias("last"), reduce(Column.__and__, same) & F.col("row.doc_id").eqNullSafe(F.col("last_id")), "left").select("row.*", "one_more")
        partial = F.when(F.col("state") == 2, 1).when((F.col("state") == 1) & F.coalesce("one_more", F.lit(False)), 1).otherwise(0)
        copies = F.when(F.col("size") > 0, F.col("passes") + partial).otherwise(0).cast("long")
        shards = F.when(copies > 0, F.slice("shards", F.lit(1), copies.cast("int"))).otherwise(F.array().cast("array<int>"))
        return out.withColumn("copies", copies).withColumn("mix_shards", shards).drop("source_rank", "block", "passes", "state", "one_more", "shards")


def assign(docs: DataFrame, **options) -> DataFrame:
    """For each row: doc_id, source, size, source_size, target, copies, taken, shards."""
    plan = Plan(docs, **options)
    done = plan.apply(plan.slim)
    return done.select("doc_id", "source", "size", "source_size", "target", "copies", (F.col("copies") * F.col("size")).alias("taken"), F.col("mix_shards").alias("shards"))


def mix(docs: DataFrame, **options) -> DataFrame:
    """The mix itself: a row of ``docs`` for each copy taken, with its shard and its place's order key there.

    Each partition is one shard, in its order.  The two added columns are
    ``mix_shard`` and ``mix_order``, with underscores before where ``docs`` has these.
    """
    plan = Plan(docs, **options)
    own = [F.col(c) for c in docs.columns]
    wide = docs.select(F.struct(*own).alias("mix_row"), "doc_id", "source", word_count(F.col("text")).alias("size"))
    copies = plan.apply(wide).select("mix_row", "mix_key", F.posexplode("mix_shards").alias("mix_pass", "mix_shard"))
    shard, order = (_free(c, docs.columns) for c in ("mix_shard", "mix_order"))
    copies = copies.select("mix_row.*", F.col("mix_shard").alias(shard), F.xxhash64(F.lit(plan.seed + 1), "mix_key", "mix_pass").alias(order))
    return copies.repartitionById(1 << plan.bits, F.col(shard)).sortWithinPartitions(shard, order)


def _free(name: str, taken: list[str]) -> str:
    """``name``, with underscores before until no column of ``taken`` has it (letter case aside)."""
    while name.lower() in {c.lower() for c in taken}:
        name = "_" + name
    return name


def op1_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents mixed to weights 5, 2, 1 over their sources, at one and a half times their words."""
    mixed = assign(common.read_table(spark, sf_dir, "documents"))
    return mixed.select("doc_id", "size", "source_size", "target", "taken", "shards")
