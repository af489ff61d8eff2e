"""MinHash near-duplicates with odd-sketch verification, and op6.

A document's set holds the 64-bit hashes of its distinct shingles.  Documents
of equal sets form a class and only its least id goes on.  MinHash samples
(``BANDS`` x ``ROWS``) give band keys; the same samples, folded into a parity
bitmap, give the odd sketch, from whose XOR population count a pair's
similarity is estimated.  Pairs that share a band and whose estimate is not
hopeless are confirmed on their full sets.

No bucket is expanded into all pairs: each document is first confirmed against
the least document it shares a band with; components of confirmed links are
found; only buckets that still hold several components are compared further,
in blocks of bounded size, by sketches, across components: first on narrow rows,
and texts go only to those blocks in which their sketch is close to another's.
So every pair of candidates is confirmed, excluded by its sketch, or connected
already.  Rows of a hot key (a large group of copies) stay where they are.

Two documents at the threshold share no band with a probability of
(1 - 0.85 ** ROWS) ** BANDS = 2.4e-7; the sketch drops one at the threshold
with a probability under 1e-7 (``SLACK`` deviations).

Null and empty texts have an empty set and link with nothing.  Rows that
repeat an id count as one document.  Rows without an id link with nothing, have
no component and are kept.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridsparse.llm import common
from gridsparse.llm.components import connected_components

BANDS, ROWS = 26, 5
SKETCH_BITS = 512
SLACK = 5.5
CHUNK = 256  # partners of one document in a run that confirms them
RUN = 1024  # members of one band key in a chunk of a run that compares them
BROADCAST_ROWS = 500_000  # narrow rows: ids and a few numbers

_draw = np.random.default_rng(20240601)
MULTIPLIERS = (_draw.integers(0, 1 << 32, BANDS * ROWS, dtype=np.uint32) | np.uint32(1))[:, None]
_SHIFTS = _draw.integers(0, 1 << 32, BANDS * ROWS, dtype=np.uint32)[:, None]
_WORD_KEYS = _draw.integers(1 << 62, 1 << 63, 16, dtype=np.uint64) | np.uint64(1)
_SAMPLE = (np.arange(BANDS * ROWS, dtype=np.uint64) + np.uint64(1)) << np.uint64(32)


def shingle_sets(column: pa.Array, width: int) -> list[np.ndarray]:
    """The sorted distinct shingle hashes of each text; a text of fewer words is one shingle."""
    data, offsets = common.utf8(column)
    starts, ends, word_offsets = common.word_bounds(data, offsets)
    words = common.word_hashes(data, starts, ends)
    rolled = np.zeros(max(0, len(words) - width + 1), np.uint64)
    for k in range(width):
        rolled += words[k : k + len(rolled)] * _WORD_KEYS[k]
    rolled = common.mix64(rolled)
    out = []
    for a, b in zip(word_offsets[:-1].tolist(), word_offsets[1:].tolist(), strict=True):
        if b - a >= width:
            out.append(np.unique(rolled[a : b - width + 1]))
        elif b > a:
            short = (words[a:b] * _WORD_KEYS[: b - a]).sum(dtype=np.uint64) + np.uint64(b - a)
            out.append(common.mix64(np.array([short], np.uint64)))
        else:
            out.append(np.empty(0, np.uint64))
    return out


def minhashes(values: np.ndarray) -> np.ndarray:
    """``BANDS * ROWS`` samples: the least of each permuted copy of the set's 32-bit hashes."""
    low = (values >> np.uint64(32)).astype(np.uint32)
    best = np.full(BANDS * ROWS, 0xFFFFFFFF, np.uint32)
    for a in range(0, len(low), 4096):
        np.minimum(best, (low[None, a : a + 4096] * MULTIPLIERS + _SHIFTS).min(axis=1), out=best)
    return best


def odd_sketches(samples: np.ndarray) -> np.ndarray:
    """Parity bitmaps (a row of 64-bit words each) of the sample matrix."""
    n = len(samples)
    place = common.mix64(samples.astype(np.uint64) + _SAMPLE) >> np.uint64(64 - int(math.log2(SKETCH_BITS)))
    flat = place.astype(np.int64) + np.arange(n)[:, None] * SKETCH_BITS
    odd = (np.bincount(flat.ravel(), minlength=n * SKETCH_BITS) & 1).astype(np.uint8)
    return np.packbits(odd).view(np.int64).reshape(n, SKETCH_BITS // 64)


def band_keys(samples: np.ndarray) -> np.ndarray:
    shaped = samples.reshape(-1, BANDS, ROWS).astype(np.uint64)
    key = np.broadcast_to(np.arange(BANDS, dtype=np.uint64), shaped.shape[:2]).copy()
    for k in range(ROWS):
        key = common.mix64(key + shaped[:, :, k])
    return key.view(np.int64)


def sketch_limit(similarity: float) -> int:
    """The XOR population count that a pair at ``similarity`` exceeds with negligible probability."""
    samples = BANDS * ROWS
    apart = samples * (1 - similarity) + SLACK * math.sqrt(samples * similarity * (1 - similarity))
    flips = 2 * apart
    mean = SKETCH_BITS / 2 * (1 - (1 - 2 / SKETCH_BITS) ** flips)
    return math.ceil(mean + 0.5 * SLACK * math.sqrt(mean))


def signatures(docs: DataFrame, width: int) -> DataFrame:
    """Per row: doc_id, n_shingles, two set digests, band keys and the sketch (both null for an empty set)."""

    def kernel(part: pa.RecordBatch) -> pa.RecordBatch:
        sets = shingle_sets(part.column("text"), width)
        n = len(sets)
        count = np.array([len(s) for s in sets], np.int64)
        samples = np.stack([minhashes(s) for s in sets]) if n else np.empty((0, BANDS * ROWS), np.uint32)
        first = np.array([s.sum(dtype=np.uint64) for s in sets], np.uint64).view(np.int64)
        second = np.array([np.bitwise_xor.reduce(common.mix64(s)) if len(s) else 0 for s in sets], np.uint64).view(np.int64)
        none = count == 0

        def lists(matrix):
            width = matrix.shape[1]
            return pa.ListArray.from_arrays(pa.array(np.arange(n + 1) * width, pa.int32()), pa.array(matrix.ravel(), pa.int64()), mask=pa.array(none))

        columns = [part.column("doc_id"), pa.array(count), pa.array(first), pa.array(second), lists(band_keys(samples)), lists(odd_sketches(samples))]
        return pa.RecordBatch.from_arrays(columns, names=["doc_id", "n_shingles", "set_a", "set_b", "bands", "sketch"])

    return common.map_slices(docs.select("doc_id", "text"), kernel, "doc_id long, n_shingles long, set_a long, set_b long, bands array<long>, sketch array<long>")


def bounded(df: DataFrame, rows: int | None = None) -> DataFrame:
    """A broadcast hint if the written table ``df`` has few enough rows, else ``df`` as it is."""
    return F.broadcast(df) if (df.count() if rows is None else rows) <= BROADCAST_ROWS else df


def sketches_apart(a, b):
    """Population count of the XOR of two sketches (arrays of longs)."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: F.bit_count(x.bitwiseXOR(y))), F.lit(0), lambda s, x: s + x)


def confirm(pairs: DataFrame, docs: DataFrame, width: int, percent: int) -> DataFrame:
    """Those ``pairs`` (a, b) of doc ids whose full sets have ``100 * |both| >= percent * |either|``.

    The texts of all b that share an a meet a's text in one sorted run; a with
    many partners is split into runs of some ``CHUNK`` of them.
    """
    rows = pairs.count()
    runs = pairs.groupBy("a").agg(F.ceil(F.count("*") / CHUNK).cast("int").alias("runs"), F.count("*").alias("members"))
    split = common.materialize(common.join_hot(pairs, common.materialize(runs, "heads"), ["a"], rows).select("a", "b", F.pmod(F.xxhash64("b"), F.col("runs")).cast("int").alias("run")), "pairs")
    wanted = split.select(F.col("b").alias("doc_id"), "a", "run", F.lit(1).alias("role"))
    heads = split.select("a", "run").distinct().select(F.col("a").alias("doc_id"), "a", "run", F.lit(0).alias("role"))
    wanted = bounded(wanted.unionAll(heads), 2 * rows)
    texts = docs.select("doc_id", "text").join(wanted, "doc_id")
    texts = texts.repartition("a", "run").sortWithinPartitions("a", "run", "role")

    def run(batches):
        head, key = [], None
        for batch in batches:
            for part in common.slices(batch):
                sets = shingle_sets(part.column("text"), width)
                left, right = [], []
                for s, d, a, r, role in zip(sets, *(part.column(c).to_pylist() for c in ("doc_id", "a", "run", "role")), strict=True):
                    if key != (a, r):
                        head, key = [], (a, r)
                    if role == 0:
                        head.append(s)
                    elif any(alike(h, s, percent) for h in head):
                        left.append(a)
                        right.append(d)
                yield pa.RecordBatch.from_arrays([pa.array(left, pa.int64()), pa.array(right, pa.int64())], names=["a", "b"])

    return texts.select("doc_id", "a", "run", "role", "text").mapInArrow(run, "a long, b long")


def across_components(members: DataFrame, docs: DataFrame, width: int, percent: int, limit: int) -> DataFrame:
    """Links (a, b) among ``members`` (band, key, component, node, bands, sketch) of one key but different components.

    A key's members are dealt to chunks; a run compares two chunks, so its size
    is bounded whatever the key's.  Runs of narrow rows name the members with a
    partner within the sketch limit, in the first band that the two share; texts
    are then carried for these only, and confirmed on full sets where they meet.
    Only links leave a run, at most one for each two components that it joins.
    """
    rows = members.count()
    sizes = common.materialize(members.groupBy("key").agg(F.ceil(F.count("*") / RUN).cast("int").alias("chunks"), F.count("*").alias("members")), "sizes")
    placed = common.join_hot(members, sizes, ["key"], rows).withColumn("chunk", F.pmod(F.xxhash64("node"), F.col("chunks")).cast("int"))
    other = F.explode(F.sequence(F.lit(0), F.col("chunks") - 1))
    placed = placed.withColumn("other", other).withColumn("lo", F.least("chunk", "other")).withColumn("hi", F.greatest("chunk", "other"))
    placed = placed.select(F.col("node").alias("doc_id"), "key", "lo", "hi", "chunk", "band", "component", "bands", "sketch")
    in_runs = lambda df: df.repartition("key", "lo", "hi").sortWithinPartitions("key", "lo", "hi", "chunk", "doc_id")
    close = in_runs(placed).mapInArrow(_over_runs(lambda rows: _close(rows, limit)), placed.schema)
    close = common.materialize(close, "close")
    nodes = bounded(common.materialize(close.select("doc_id").distinct(), "close-nodes"))
    texts = common.materialize(docs.select("doc_id", "text").join(nodes, "doc_id", "left_semi"), "run-texts").join(close, "doc_id")

    def confirmed(rows: list[dict]) -> list[dict]:
        node, component = (np.array([r[k] for r in rows], np.int64) for k in ("doc_id", "component"))
        sets: dict[int, np.ndarray] = {}

        def set_of(k):
            if k not in sets:
                sets[k] = shingle_sets(pa.array([rows[k]["text"]], pa.string()), width)[0]
            return sets[k]

        out = []
        for i, partners in _near(rows, limit):
            for j in partners.tolist():
                if component[i] != component[j] and alike(set_of(i), set_of(j), percent):
                    out.append({"a": min(node[i], node[j]), "b": max(node[i], node[j])})
                    component[component == component[j]] = component[i]
        return out

    return in_runs(texts.select(*placed.columns, "text")).mapInArrow(_over_runs(confirmed), "a long, b long").distinct()


def _near(rows: list[dict], limit: int):
    """For the rows of a run: each member with those after it, of the other chunk and component, that are close in the first band they share."""
    chunk, component = (np.array([r[k] for r in rows], np.int64) for k in ("chunk", "component"))
    whole = rows[0]["lo"] == rows[0]["hi"]
    if len(rows) < 2 or (not whole and chunk[0] == chunk[-1]):
        return
    bits, bands = (np.array([r[k] for r in rows], np.int64).view(np.uint64) for k in ("sketch", "bands"))
    earlier = bands[:, : rows[0]["band"]]
    first, second = (np.flatnonzero(chunk == c) for c in (rows[0]["lo"], rows[0]["hi"]))
    for i in first.tolist():
        later = second[second > i] if whole else second
        good = later[(np.bitwise_count(bits[later] ^ bits[i]).sum(axis=1) <= limit) & (component[later] != component[i])]
        good = good[~(earlier[good] == earlier[i]).any(axis=1)]
        if len(good):
            yield i, good


def _close(rows: list[dict], limit: int) -> list[dict]:
    """The rows of a run that are close to another."""
    kept = np.zeros(len(rows), bool)
    for i, partners in _near(rows, limit):
        kept[i] = True
        kept[partners] = True
    return [rows[k] for k in np.flatnonzero(kept).tolist()]


def _over_runs(of_run):
    """A map over sorted rows that gives ``of_run`` of the rows of each run (key, lo, hi)."""

    def run(batches):
        key, rows = None, []
        for batch in batches:
            for part in common.slices(batch) if "text" in batch.schema.names else (batch.slice(a, 4096) for a in range(0, batch.num_rows, 4096)):
                found = []
                for row in part.to_pylist():
                    if key != (row["key"], row["lo"], row["hi"]):
                        found += of_run(rows) if len(rows) > 1 else []
                        key, rows = (row["key"], row["lo"], row["hi"]), []
                    rows.append(row)
                if found:
                    yield pa.RecordBatch.from_pylist(found, schema=_schema(found[0]))
        found = of_run(rows) if len(rows) > 1 else []
        if found:
            yield pa.RecordBatch.from_pylist(found, schema=_schema(found[0]))

    return run


def _schema(row: dict) -> pa.Schema:
    kinds = {"lo": pa.int32(), "hi": pa.int32(), "chunk": pa.int32(), "band": pa.int32(), "bands": pa.list_(pa.int64()), "sketch": pa.list_(pa.int64())}
    return pa.schema([(k, kinds.get(k, pa.int64())) for k in row])


def alike(x: np.ndarray, y: np.ndarray, percent: int) -> bool:
    """Whether two sorted sets have ``100 * |both| >= percent * |either|``."""
    if not len(x) or not len(y) or 100 * min(len(x), len(y)) < percent * max(len(x), len(y)):
        return False
    shared = np.count_nonzero(x[np.minimum(np.searchsorted(x, y), len(x) - 1)] == y)
    return 100 * shared >= percent * (len(x) + len(y) - shared)


def link(docs: DataFrame, width: int = 5, percent: int = 80) -> DataFrame:
    """For each row: doc_id, n_shingles, component_id (the least id reachable), kept."""
    signed = common.materialize(signatures(docs, width), "signatures")
    limit = sketch_limit(percent / 100)
    known = signed.where(F.col("doc_id").isNotNull() & (F.col("n_shingles") > 0))
    classes = common.materialize(known.groupBy("set_a", "set_b", "n_shingles").agg(F.min("doc_id").alias("node"), F.min_by("bands", "doc_id").alias("bands"), F.min_by("sketch", "doc_id").alias("sketch"), F.count("*").alias("copies")), "classes")
    keyed = classes.select("node", F.posexplode("bands").alias("band", "key"))
    buckets = keyed.groupBy("key").agg(F.min("node").alias("leader"), F.count("*").alias("members")).where("members > 1")
    shared = common.materialize(common.join_hot(keyed, common.materialize(buckets, "buckets"), ["key"], BANDS * classes.count()), "shared-bands")
    least = shared.where("node <> leader").groupBy(F.col("node").alias("b")).agg(F.min("leader").alias("a"))
    drawn = classes.select("node", "sketch")
    pairs = least.join(drawn.select(F.col("node").alias("b"), F.col("sketch").alias("sketch_b")), "b").join(drawn.select(F.col("node").alias("a"), F.col("sketch").alias("sketch_a")), "a")
    pairs = common.materialize(pairs.where(sketches_apart("sketch_a", "sketch_b") <= limit).select("a", "b").distinct(), "first-pairs")
    links = common.materialize(confirm(pairs, docs, width, percent), "links")
    labels = common.materialize(connected_components(links), "components")

    placed = common.materialize(shared.join(labels, "node", "left").select("band", "key", "node", F.coalesce("component", "node").alias("component")), "placed")
    mixed = placed.groupBy("key").agg(F.min("component").alias("low"), F.max("component").alias("high"), F.count("*").alias("members")).where("low <> high").select("key", "members")
    members = common.materialize(common.join_hot(placed, common.materialize(mixed, "mixed"), ["key"], placed.count()).join(classes.select("node", "bands", "sketch"), "node"), "mixed-bands")
    more = common.materialize(across_components(members, docs, width, percent, limit), "more-links")
    if more.head(1):
        labels = common.materialize(connected_components(links.unionAll(more)), "components")
    key = ["set_a", "set_b", "n_shingles"]
    of_class = classes.join(labels, "node", "left").select(*key, F.coalesce("component", "node").alias("component"), F.col("copies").alias("members"))
    of_class = common.materialize(of_class, "class-components")
    with_set = F.col("doc_id").isNotNull() & (F.col("n_shingles") > 0)
    rows = signed.select("doc_id", *key)
    linked = common.join_hot(rows.where(with_set), of_class, key, signed.count()).select("doc_id", "n_shingles", "component")
    alone = rows.where(~with_set).select("doc_id", "n_shingles", F.col("doc_id").alias("component"))
    out = linked.unionByName(alone).withColumnRenamed("component", "component_id")
    return out.withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def op6_neardup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents, three-word shingles, links at 85 per cent."""
    return link(common.read_table(spark, sf_dir, "documents"), width=3, percent=85)


def deduplicate(docs: DataFrame, width: int = 5, percent: int = 80) -> DataFrame:
    """``docs`` with one document of each component: that of the least id, once."""
    links = common.materialize(link(docs, width, percent), "linked")
    gone = common.materialize(links.where(~F.col("kept")).select("doc_id").distinct(), "gone")
    out = docs.join(bounded(gone), "doc_id", "left_anti").select(docs.columns)
    repeated = links.where("kept AND doc_id IS NOT NULL").groupBy("doc_id").count().where("count > 1").select("doc_id")
    repeated = common.materialize(repeated, "repeated")
    if repeated.head(1):
        again = out.join(bounded(repeated), "doc_id", "left_semi").select(docs.columns).dropDuplicates(["doc_id"])
        out = out.join(bounded(repeated), "doc_id", "left_anti").select(docs.columns).unionByName(again)
    return out


#: Shingles and links by a plain self-join, components by recursion.
ORACLE_SQL = r"""
WITH RECURSIVE t AS (
    SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents
), g AS MATERIALIZED (
    SELECT doc_id, CASE WHEN len(w) >= 3 THEN list_distinct(list_transform(range(1, len(w) - 1), lambda k: w[k] || ' ' || w[k + 1] || ' ' || w[k + 2])) WHEN len(w) > 0 THEN [array_to_string(w, ' ')] ELSE [] END AS s FROM t
), x AS MATERIALIZED (
    SELECT doc_id, unnest(s) AS h FROM g
), pair AS (
    SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS n FROM x a JOIN x b ON a.h = b.h AND a.doc_id < b.doc_id GROUP BY ALL
), link AS MATERIALIZED (
    SELECT a, b FROM pair JOIN g ga ON ga.doc_id = a JOIN g gb ON gb.doc_id = b WHERE 100 * n >= 85 * (len(ga.s) + len(gb.s) - n)
), side AS MATERIALIZED (
    SELECT a, b FROM link UNION ALL SELECT b, a FROM link
), reach AS (
    SELECT doc_id, doc_id AS other FROM g UNION SELECT reach.doc_id, side.b FROM reach JOIN side ON side.a = reach.other
), least AS (
    SELECT doc_id, min(other) AS component_id FROM reach GROUP BY doc_id
)
SELECT doc_id, CAST(len(s) AS BIGINT) AS n_shingles, component_id, doc_id = component_id AS kept FROM g JOIN least USING (doc_id)
"""
