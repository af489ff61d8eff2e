"""Quality by importance resampling over hashed n-grams, and op10.

Two bag-of-n-grams models, of target text (documents labelled good) and of all
text, are counted over every document: words and word pairs, hashed into
``BUCKETS``.  A document's log weight is the sum over its n-grams of the log
ratio of the two models.  Adding Gumbel noise, a function of the id, and taking
the k largest draws k documents without replacement in proportion to their
weights.  The k-th largest key is found exactly by counting keys in ever finer
bins, so no sort and no task sees all rows.

No text is shuffled to learn its label: labelled ids are broadcast where they
are at most ``BROADCAST_IDS``; beyond that a bitmap of fixed size drops most
other texts in the scan and only the rest is joined.  The counts are the same.

Null and empty texts have weight 0 (log).  With no target text all weights are
equal and the draw is uniform.  Keys tie only for rows of equal id and text;
rows tied at the last place are all selected.
"""

from __future__ import annotations

import struct

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from gridsparse.llm import common

BUCKETS = 1 << 16
SHARE = 0.5
SMOOTHING = 1.0
LEVEL_BITS = 16
BROADCAST_IDS = 1_000_000
FILTER_BITS = 26


def gram_buckets(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bucket of each word and each adjacent pair of words, and the row of each."""
    data, offsets = common.utf8(column)
    starts, ends, word_offsets = common.word_bounds(data, offsets)
    words, row = common.word_hashes(data, starts, ends), common.row_of(word_offsets)
    pairs = common.mix64(words[:-1] * np.uint64(3) + words[1:])
    same = row[:-1] == row[1:]
    shift = np.uint64(64 - BUCKETS.bit_length() + 1)
    grams = np.concatenate((words, pairs[same])) >> shift
    return grams.astype(np.int64), np.concatenate((row, row[:-1][same]))


def count_grams(docs: DataFrame) -> DataFrame:
    """``bucket, whole, target``: n-gram counts of all rows and of targets; a row per task and bucket before the sum.

    ``is_target`` is 0 for other rows, 1 for targets and 2 for rows that count as target only.
    """

    def run(batches):
        whole, target = np.zeros(BUCKETS, np.int64), np.zeros(BUCKETS, np.int64)
        for batch in batches:
            for part in common.slices(batch):
                grams, rows = gram_buckets(part.column("text"))
                kind = part.column("is_target").to_numpy(zero_copy_only=False)[rows]
                whole += np.bincount(grams[kind < 2], minlength=BUCKETS)
                target += np.bincount(grams[kind > 0], minlength=BUCKETS)
        some = np.flatnonzero(whole + target)
        yield pa.RecordBatch.from_arrays([pa.array(some), pa.array(whole[some]), pa.array(target[some])], names=["bucket", "whole", "target"])

    counts = docs.mapInArrow(run, "bucket long, whole long, target long")
    return counts.groupBy("bucket").agg(F.sum("whole").alias("whole"), F.sum("target").alias("target"))


def label(docs: DataFrame, good: DataFrame) -> DataFrame:
    """``text, is_target`` of every row; beyond ``BROADCAST_IDS`` ids, rows of targets come twice, once as the whole's and once as target's (``is_target`` 2)."""
    rows = docs.select("doc_id", "text")
    if good.limit(BROADCAST_IDS + 1).count() <= BROADCAST_IDS:
        marked = rows.join(F.broadcast(good.withColumn("found", F.lit(1))), "doc_id", "left")
        return marked.select("text", F.coalesce("found", F.lit(0)).alias("is_target"))
    targets = likely(rows, good).join(good, "doc_id", "left_semi")
    return rows.select("text", F.lit(0).alias("is_target")).unionAll(targets.select("text", F.lit(2).alias("is_target")))


def likely(rows: DataFrame, good: DataFrame) -> DataFrame:
    """``rows`` without most of those whose id is not in ``good``, by a bitmap of ``2**FILTER_BITS`` hashes."""
    place = F.shiftrightunsigned(F.xxhash64("doc_id"), 64 - FILTER_BITS)
    run = F.bitmap_bucket_number(place + 1) - 1
    maps = good.groupBy(run.alias("run")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(place + 1)).alias("bits")).collect()
    bits = np.zeros((max(1, (1 << FILTER_BITS) >> 15), 1 << 12), np.uint8)
    for r in maps:
        bits[r["run"]] = np.frombuffer(r["bits"], np.uint8)
    shared = rows.sparkSession.sparkContext.broadcast(bits.ravel())

    def run_filter(batches):
        for batch in batches:
            at = batch.column("place").to_numpy(zero_copy_only=False).astype(np.int64)
            yield batch.filter(pa.array((shared.value[at >> 3] >> (at & 7)) & 1 == 1)).select(["doc_id", "text"])

    return rows.where(F.col("doc_id").isNotNull()).select("doc_id", "text", place.alias("place")).mapInArrow(run_filter, "doc_id long, text string")


def log_ratios(counts: DataFrame) -> np.ndarray:
    """The log ratio of the models per bucket (at most ``BUCKETS`` rows come to the driver)."""
    whole, target = np.zeros(BUCKETS), np.zeros(BUCKETS)
    for r in counts.collect():
        whole[r["bucket"]], target[r["bucket"]] = r["whole"], r["target"]
    if not target.any():
        return np.zeros(BUCKETS)
    p, q = ((c + SMOOTHING) / (c.sum() + SMOOTHING * BUCKETS) for c in (target, whole))
    return np.log(p) - np.log(q)


def weigh(docs: DataFrame, ratios: np.ndarray) -> DataFrame:
    """``doc_id, n_grams, log_weight`` for every row."""
    shared = docs.sparkSession.sparkContext.broadcast(ratios)

    def kernel(part: pa.RecordBatch) -> pa.RecordBatch:
        grams, rows = gram_buckets(part.column("text"))
        n = part.num_rows
        columns = [part.column("doc_id"), pa.array(np.bincount(rows, minlength=n)), pa.array(np.bincount(rows, shared.value[grams], n))]
        return pa.RecordBatch.from_arrays(columns, names=["doc_id", "n_grams", "log_weight"])

    return common.map_slices(docs.select("doc_id", "text"), kernel, "doc_id long, n_grams long, log_weight double")


def largest(rows: DataFrame, key: str, k: int) -> int | None:
    """The ``k``-th largest value of the long column ``key``; None if there are no more than ``k`` rows.

    Four counts of 2**16 bins each narrow the 64 bits down.
    """
    if rows.count() <= k:
        return None
    # order-preserving unsigned form: the sign bit flipped
    base = F.col(key).bitwiseXOR(F.lit(-(1 << 63)))
    prefix, left = 0, k
    for level in range(4):
        shift = 64 - LEVEL_BITS * (level + 1)
        part = F.shiftrightunsigned(base, shift)
        here = rows if level == 0 else rows.where(F.shiftrightunsigned(base, shift + LEVEL_BITS) == F.lit(prefix))
        found = here.groupBy(part.bitwiseAND(F.lit((1 << LEVEL_BITS) - 1)).alias("bin")).count().collect()
        for r in sorted(found, key=lambda r: -r["bin"]):
            if left <= r["count"]:
                prefix = prefix << LEVEL_BITS | r["bin"]
                break
            left -= r["count"]
    value = prefix ^ (1 << 63)
    return struct.unpack(">q", value.to_bytes(8, "big"))[0]


def resample(docs: DataFrame, targets: DataFrame, share: float = SHARE, seed: int = 10) -> DataFrame:
    """``doc_id, n_grams, log_weight, sample_key, selected`` for every row of ``docs``; ``targets`` has the ids of good ones."""
    good = common.materialize(targets.where(F.col("doc_id").isNotNull()).select("doc_id").distinct(), "targets")
    ratios = log_ratios(count_grams(label(docs, good)))
    u = (F.shiftrightunsigned(F.xxhash64(F.lit(seed), F.coalesce("doc_id", F.lit(-1))), 11).cast("double") + 0.5) / F.lit(float(1 << 53))
    keyed = weigh(docs, ratios).withColumn("sample_key", F.col("log_weight") - F.log(-F.log(u)))
    keyed = common.materialize(keyed, "weights").withColumn("place", F.round(F.col("sample_key") * 1e9).cast("long"))
    k = int(share * keyed.count())
    least = largest(keyed, "place", k) if k else None
    selected = F.lit(k > 0) if least is None else F.col("place") >= F.lit(least)
    return keyed.withColumn("selected", selected).drop("place")


def op10_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document's weight towards text labelled good, and whether it is among the drawn half."""
    docs, labels = (common.read_table(spark, sf_dir, t) for t in ("documents", "labels"))
    return resample(docs, labels.where("quality = 1"))
