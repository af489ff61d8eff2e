"""Exact BM25 top-k over sharded inverted indexes with block-max WAND pruning, and op4.

Each task turns runs of its documents into shards: a sorted term array, and
per term the postings (document, count) in document order.  Document
frequencies, the number of documents and their mean length are global, so
scores of different shards compare.  Documents of equal terms and counts are
one entry of a shard with several ids: they share their score.

Every common list carries, for aligned blocks of ``BLOCK`` documents, its
largest impact there; the blocks of the other lists are single documents, since
such a list seldom has two in a block, so their maxima are the impacts.  The
lists' cursors move over the documents together: one whose maxima, summed over
the query's lists, stay under the query's threshold is skipped before any
posting of a common list is read; what is left is scored in full.  The maxima
of the common lists stand in a matrix, and a batch of queries is tested at once.

The threshold is the k-th best score that the query has met anywhere: shards
have levels (a level has four times the shards of the next), the few shards of
the highest levels go first, and each level starts from the thresholds of those
before it.  A task merges its shards' hits and gives at most k a query, so all
levels together give some k a level, whatever the number of shards.

Terms are words, A-Z lower-cased; a query's distinct terms count once each.
Scores are rounded to 6 digits and ties go to the lesser id.  Null and empty
texts match nothing, as query or as document; null ids are not queries and are
not returned.  A query's results may hold the query's own document.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from gridsparse.llm import common

K1, B = 1.2, 0.75
TOP = 10
SHARD_DOCUMENTS = 4096
SHARD_BYTES = 24 << 20
BLOCK = 4
COMMON_SHARE = 1 / 24  # lists in more than this share of a shard's documents keep their maxima in a matrix; work differs, results don't
FIRST_SHARDS = 8
MOST_LEVEL = 15
QUERY_BLOCK = 4096
BLOCK_TERMS = 4_000_000
BATCH_ENTRIES = 600_000
BATCH_QUERIES = 256
RUN_POSTINGS = 100_000  # postings of the lists that are not common, read at once: their arrays should fit a core's cache
MATRIX_DOCUMENTS = 128  # a query with more open documents in a shard gets the common lists' part of all by a matrix product
INDEX_SCHEMA = "shard long, n_docs int, words long, ids binary, id_starts binary, lengths binary, terms binary, starts binary, docs binary, counts binary, frequencies binary, level int"


def document_terms(column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Distinct (row, term) pairs of a text column sorted by term, their counts, and each row's length in words."""
    data, offsets = common.utf8(column)
    starts, ends, word_offsets = common.word_bounds(data, offsets)
    terms, rows = common.word_hashes(data, starts, ends), common.row_of(word_offsets)
    order = np.argsort(terms, kind="stable")
    terms, rows = terms[order], rows[order]
    first = np.ones(len(terms), bool)
    first[1:] = (terms[1:] != terms[:-1]) | (rows[1:] != rows[:-1])
    at = np.flatnonzero(first)
    return rows[at].astype(np.int32), terms[at], np.diff(np.append(at, len(terms))).astype(np.int32), np.diff(word_offsets)


def _runs(starts: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The members of the ranges ``starts[k] + 0 .. sizes[k] - 1``, and the range of each."""
    which = np.repeat(np.arange(len(sizes)), sizes)
    ends = np.cumsum(sizes)
    return np.arange(ends[-1] if len(ends) else 0) + np.repeat(starts - ends + sizes, sizes), which


def _same(rows: np.ndarray, terms: np.ndarray, counts: np.ndarray, n: int) -> np.ndarray:
    """A group number for each of ``n`` documents; documents of equal terms and counts (by 128 bits of digests) share one, numbered by their first."""
    digests = np.zeros((2, n), np.uint64)
    order = np.argsort(rows, kind="stable")
    by_row, codes = rows[order], common.mix64(terms[order] ^ common.mix64(counts[order].astype(np.uint64)))
    begin = np.flatnonzero(np.concatenate(([True], by_row[1:] != by_row[:-1]))) if len(by_row) else np.empty(0, np.int64)
    if len(begin):
        digests[0, by_row[begin]] = np.add.reduceat(codes, begin)
        digests[1, by_row[begin]] = np.add.reduceat(common.mix64(codes), begin)
    order = np.lexsort((np.arange(n), digests[1], digests[0]))
    new = np.ones(n, bool)
    new[1:] = (digests[:, order[1:]] != digests[:, order[:-1]]).any(axis=0)
    head = order[np.flatnonzero(new)][np.cumsum(new) - 1]
    leader = np.empty(n, np.int64)
    leader[order] = head
    return np.unique(leader, return_inverse=True)[1]


def _shard(parts, number: int) -> dict:
    """One shard from the parts (ids, rows, terms, counts, lengths) of its slices."""
    base = np.cumsum([0] + [len(p[0]) for p in parts[:-1]]).astype(np.int32)
    rows = np.concatenate([p[1] + b for p, b in zip(parts, base, strict=True)])
    terms, counts = (np.concatenate([p[i] for p in parts]) for i in (2, 3))
    order = np.argsort(terms, kind="stable")
    rows, terms, counts = rows[order], terms[order], counts[order]
    lengths, ids = (np.concatenate([p[i] for p in parts]) for i in (4, 0))
    group = _same(rows, terms, counts, len(ids))
    _, first_row, times = np.unique(group, return_index=True, return_counts=True)
    kept = np.zeros(len(ids), bool)
    kept[first_row] = True
    held = kept[rows]
    docs, terms, counts = group[rows[held]], terms[held], counts[held]
    first = np.flatnonzero(np.concatenate(([True], terms[1:] != terms[:-1]))) if len(terms) else np.empty(0, np.int64)
    bits = int(common.mix64(np.array([number + 1], np.uint64))[0]) | 1 << 2 * MOST_LEVEL
    return {
        "shard": number, "n_docs": len(ids), "words": int(lengths.sum()), "ids": ids[np.lexsort((ids, group))].astype(np.int64).tobytes(),
        "id_starts": np.concatenate(([0], np.cumsum(times))).astype(np.int32).tobytes(), "lengths": lengths[first_row].astype(np.int32).tobytes(),
        "terms": terms[first].tobytes(), "starts": np.append(first, len(terms)).astype(np.int32).tobytes(), "docs": docs.astype(np.uint16).tobytes(),
        "counts": counts.astype(np.int32).tobytes(), "frequencies": (np.add.reduceat(times[docs], first) if len(first) else first).astype(np.int32).tobytes(),
        "level": ((bits & -bits).bit_length() - 1) // 2,
    }


def build_index(docs: DataFrame) -> DataFrame:
    """A row per shard; shards are runs of an input partition, so no text is shuffled."""
    fields = [f.split() for f in INDEX_SCHEMA.split(", ")]
    kinds = {"long": pa.int64(), "int": pa.int32(), "binary": pa.binary()}

    def batch(row):
        return pa.RecordBatch.from_arrays([pa.array([row[n]], kinds[k]) for n, k in fields], names=[n for n, _ in fields])

    def run(batches):
        number = TaskContext.get().partitionId() << 20
        parts, held, size = [], 0, 0
        for source in batches:
            for cut in common.slices(source):
                for a in range(0, cut.num_rows, SHARD_DOCUMENTS):
                    part = cut.slice(a, SHARD_DOCUMENTS)
                    if parts and (held + part.num_rows > SHARD_DOCUMENTS or size > SHARD_BYTES):
                        yield batch(_shard(parts, number))
                        number, parts, held, size = number + 1, [], 0, 0
                    rows, terms, counts, lengths = document_terms(part.column("text"))
                    parts.append((part.column("doc_id").to_numpy(zero_copy_only=False), rows, terms, counts, lengths))
                    held += part.num_rows
                    size += part.nbytes
        if parts:
            yield batch(_shard(parts, number))

    return docs.where(F.col("doc_id").isNotNull()).select("doc_id", "text").mapInArrow(run, INDEX_SCHEMA)


def query_terms(queries: DataFrame) -> DataFrame:
    """Rows (query, term) of the distinct terms of ``queries`` (doc_id, text)."""

    def kernel(part: pa.RecordBatch) -> pa.RecordBatch:
        rows, terms, _, _ = document_terms(part.column("text"))
        return pa.RecordBatch.from_arrays([part.column("doc_id").take(pa.array(rows)), pa.array(terms.view(np.int64))], names=["query", "term"])

    return common.map_slices(queries.select("doc_id", "text"), kernel, "query long, term long").distinct()


def frequencies(index: DataFrame) -> DataFrame:
    """Number of documents of each term over all shards: rows (term, df), summed before anything is joined to them."""

    def run(batches):
        for batch in batches:
            for terms, counts in zip(batch.column("terms"), batch.column("frequencies"), strict=True):
                found = np.frombuffer(terms.as_py(), np.int64)
                times = np.frombuffer(counts.as_py(), np.int32).astype(np.int64)
                for a in range(0, len(found), 50_000):
                    yield pa.RecordBatch.from_arrays([pa.array(found[a : a + 50_000]), pa.array(times[a : a + 50_000])], names=["term", "n"])

    return index.select("terms", "frequencies").mapInArrow(run, "term long, n long").groupBy("term").agg(F.sum("n").alias("df"))


class QueryBlock:
    """Queries with their weighted terms, and the best ``top`` hits met so far."""

    def __init__(self, ids: np.ndarray, ends: np.ndarray, terms: np.ndarray, weights: np.ndarray, top: int):
        self.ids, self.ends, self.weights, self.top = ids, ends, weights, top
        self.vocabulary, self.slots = np.unique(terms, return_inverse=True)
        self.floor = np.full(len(ids), -np.inf)  # a hit must beat this score, or equal it with an id of at most last
        self.last = np.full(len(ids), np.iinfo(np.int64).max)

    def start(self) -> None:
        """A task's own state: hits (scores, ids) of each query, and its thresholds."""
        self.hits: list[tuple[np.ndarray, np.ndarray] | None] = [None] * len(self.ids)
        self.bar = self.floor.copy()

    def offer(self, query: int, scores: np.ndarray, ids: np.ndarray) -> None:
        good = (scores > self.floor[query]) | ((scores == self.floor[query]) & (ids <= self.last[query]))
        scores, ids = scores[good], ids[good]
        if not len(scores):
            return
        if self.hits[query] is not None:
            scores, ids = np.concatenate((self.hits[query][0], scores)), np.concatenate((self.hits[query][1], ids))
        order = np.lexsort((ids, -scores))[: self.top]
        self.hits[query] = scores[order], ids[order]
        if len(order) == self.top:
            self.bar[query] = max(self.bar[query], scores[order[-1]])

    def found(self) -> pa.RecordBatch:
        some = [q for q, h in enumerate(self.hits) if h is not None]
        scores, ids = (np.concatenate([self.hits[q][k] for q in some]) if some else np.empty(0) for k in (0, 1))
        names = np.repeat(self.ids[some], [len(self.hits[q][0]) for q in some]) if some else np.empty(0)
        return pa.RecordBatch.from_arrays([pa.array(names.astype(np.int64)), pa.array(ids.astype(np.int64)), pa.array(scores.astype(float))], names=["query", "doc_id", "score"])


class Shard:
    """A shard's lists with impacts and block maxima, ready for queries."""

    def __init__(self, row: dict[str, pa.Buffer], mean_length: float):
        read = lambda name, kind: np.frombuffer(row[name], kind)
        self.ids, self.id_starts = read("ids", np.int64), read("id_starts", np.int32).astype(np.int64)
        self.terms, self.starts = read("terms", np.uint64), read("starts", np.int32).astype(np.int64)
        self.docs, self.counts = read("docs", np.uint16).astype(np.int32), read("counts", np.int32)
        self.n = len(self.id_starts) - 1
        self.blocks = -(-self.n // BLOCK)
        self.norm = K1 * (1 - B + B * read("lengths", np.int32) / max(mean_length, 1e-9))
        self.impacts = (self.counts * (K1 + 1) / (self.counts + self.norm[self.docs])).astype(np.float32)
        size = np.diff(self.starts)
        self.common = np.full(len(self.terms), -1)
        many = np.flatnonzero(size > max(16, self.n * COMMON_SHARE))
        self.common[many] = np.arange(len(many))
        place, which = _runs(self.starts[many], size[many])
        self.dense = np.zeros((self.blocks * BLOCK, len(many)), np.float32)
        self.dense[self.docs[place], which] = self.impacts[place]
        self.maxima = np.ascontiguousarray(self.dense.reshape(self.blocks, BLOCK, len(many)).max(axis=1).T)
        # postings by document, for exact scores
        self.by_doc = np.argsort(self.docs.astype(np.uint16), kind="stable").astype(np.int32)
        self.doc_starts = np.concatenate(([0], np.cumsum(np.bincount(self.docs, minlength=self.n))))
        self.term_of = np.repeat(np.arange(len(self.terms), dtype=np.int32), size)
        self.rare_size = np.append(np.where(self.common < 0, size, 0), 0)  # the last one for terms that the shard lacks

    def search(self, queries: QueryBlock) -> int:
        """Offer this shard's hits of all queries; gives the number of documents that were scored."""
        if not len(self.terms) or not len(queries.vocabulary):
            return 0
        at = np.minimum(np.searchsorted(self.terms, queries.vocabulary), len(self.terms) - 1)
        place = np.where(self.terms[at] == queries.vocabulary, at, -1)[queries.slots]
        cost = np.concatenate(([0], np.cumsum(self.rare_size[place])))[queries.ends]
        scored, number = 0, len(queries.ids)
        most = max(1, min(BATCH_QUERIES, BATCH_QUERIES * SHARD_DOCUMENTS // max(1, self.n)))
        for first in range(0, number, most):
            scored += self._batch(queries, place, cost, first, min(first + most, number))
        return scored

    def _rare(self, queries: QueryBlock, place: np.ndarray, cost: np.ndarray, first: int, stop: int) -> np.ndarray:
        """The part of the lists that are not common in the scores of all documents, in 32 bits; runs of some ``RUN_POSTINGS`` postings."""
        width = self.blocks * BLOCK
        out = np.zeros((stop - first, width), np.float32)
        low = first
        while low < stop:
            high = min(stop, max(low + 1, int(np.searchsorted(cost, cost[low] + RUN_POSTINGS, side="right")) - 1))
            if cost[high] > cost[low]:
                a, b = queries.ends[low], queries.ends[high]
                lists, size = place[a:b], self.rare_size[place[a:b]]
                some = np.flatnonzero(size)
                lists, size = lists[some], size[some]
                begin = np.repeat(np.arange(high - low) * width, np.diff(queries.ends[low : high + 1]))[some]
                at = np.repeat(self.starts[lists] - np.cumsum(size) + size, size)
                at += np.arange(len(at))
                cell = self.docs[at]
                cell = cell + np.repeat(begin, size)
                load = np.repeat(queries.weights[a:b][some], size)
                load *= self.impacts[at]
                out[low - first : high - first] = np.bincount(cell, load, (high - low) * width).reshape(high - low, width)
            low = high
        return out

    def _batch(self, queries: QueryBlock, place: np.ndarray, cost: np.ndarray, first: int, stop: int) -> int:
        """The queries from ``first`` up to ``stop``: test all their documents, then score what is open."""
        a, b = queries.ends[first], queries.ends[stop]
        number = stop - first
        owner = np.repeat(np.arange(number), np.diff(queries.ends[first : stop + 1]))
        known = place[a:b] >= 0
        owner, lists, weights = owner[known], place[a:b][known], queries.weights[a:b][known]
        slot = self.common[lists]
        often = slot >= 0
        share = np.zeros((number, self.dense.shape[1]), np.float32)
        share[owner[often], slot[often]] = weights[often]
        rare = self._rare(queries, place, cost, first, stop)
        bound = share @ self.maxima
        slack = 1e-4 * (bound.max(initial=0) + rare.max(initial=0)) + 1e-3  # far above the rounding of 32-bit sums
        bar = queries.bar[first:stop].copy()
        scored = 0

        def scores(open_documents):
            """Query, document and score (in 32 bits) of the open (query, document) cells."""
            q, doc = np.nonzero(open_documents)
            total = rare[q, doc]
            edges = np.searchsorted(q, np.arange(number + 1))
            size = np.diff(edges)
            many = np.flatnonzero(size > MATRIX_DOCUMENTS)
            part = share[many] @ self.dense.T if len(many) else ()
            for k, row in zip(many, part, strict=True):
                total[edges[k] : edges[k + 1]] += row[doc[edges[k] : edges[k + 1]]]
            for k in np.flatnonzero((size > 0) & (size <= MATRIX_DOCUMENTS)):
                run = slice(edges[k], edges[k + 1])
                total[run] += self.dense[doc[run]] @ share[k]
            return q, doc, total, edges

        fresh = np.flatnonzero(np.isneginf(bar))
        if len(fresh):  # no threshold yet: the documents of the highest bounds give one
            ahead = np.zeros(rare.shape, bool)
            most = min(self.n, 8 * queries.top)
            upper = (rare[fresh] + np.repeat(bound[fresh], BLOCK, axis=1))[:, : self.n]
            ahead[fresh[:, None], np.argpartition(-upper, most - 1, axis=1)[:, :most]] = True
            q, _, total, edges = scores(ahead)
            scored += len(q)
            for k in fresh:
                own = total[edges[k] : edges[k + 1]]
                if len(own) >= queries.top:
                    bar[k] = np.partition(own, -queries.top)[-queries.top]
        least = np.maximum(bar - slack, 1e-6).astype(np.float32)[:, None]
        q, doc, total, edges = scores(rare >= np.repeat(least - bound, BLOCK, axis=1))
        scored += len(q)
        total[doc >= self.n] = 0
        for k in np.flatnonzero(np.diff(edges) > queries.top):
            own = total[edges[k] : edges[k + 1]]
            least[k] = max(least[k, 0], np.partition(own, -queries.top)[-queries.top] - slack)
        good = total >= least[q, 0]
        q, doc = q[good], doc[good]
        exact = self._exact(q, doc, owner, lists, weights)
        edges = np.searchsorted(q, np.arange(number + 1))
        for k in np.flatnonzero(np.diff(edges)):
            run = slice(edges[k], edges[k + 1])
            copies = self.id_starts[doc[run] + 1] - self.id_starts[doc[run]]
            ids, which = _runs(self.id_starts[doc[run]], np.minimum(copies, queries.top))
            queries.offer(first + k, exact[run][which], self.ids[ids])
        return scored

    def _exact(self, q, doc, owner, lists, weights) -> np.ndarray:
        """Rounded 64-bit scores of (query, document) pairs, sorted by query; a query's weights stand in an array over the lists, for some ``RUN_POSTINGS`` postings at once."""
        weight, out = np.zeros(len(self.terms)), np.zeros(len(q))
        size = self.doc_starts[doc + 1] - self.doc_starts[doc]
        upto = np.concatenate(([0], np.cumsum(size)))
        edges, own = (np.searchsorted(x, np.arange((q[-1] if len(q) else -1) + 2)) for x in (q, owner))
        for k in np.flatnonzero(np.diff(edges)):
            mine = slice(own[k], own[k + 1])
            weight[lists[mine]] = weights[mine]
            a = edges[k]
            while a < edges[k + 1]:
                b = min(edges[k + 1], max(a + 1, int(np.searchsorted(upto, upto[a] + RUN_POSTINGS, side="right")) - 1))
                posting, pair = _runs(self.doc_starts[doc[a:b]], size[a:b])
                posting = self.by_doc[posting]
                load = weight[self.term_of[posting]]
                hit = np.flatnonzero(load)
                posting = posting[hit]
                count = self.counts[posting]
                out[a:b] = np.bincount(pair[hit], count * (K1 + 1) / (count + self.norm[self.docs[posting]]) * load[hit], b - a)
                a = b
            weight[lists[mine]] = 0
        return np.round(out, 6)


def search(docs: DataFrame, queries: DataFrame, top: int = TOP) -> DataFrame:
    """``query, doc_id, score, rank`` of the best ``top`` of ``docs`` for each row of ``queries`` (doc_id, text)."""
    spark = docs.sparkSession
    index = common.materialize(build_index(docs), "index", by="level")
    levels = sorted(index.groupBy("level").agg(F.count("*").alias("shards"), F.sum("n_docs").alias("n"), F.sum("words").alias("words")).collect(), key=lambda r: -r["level"])
    n = sum(r["n"] for r in levels)
    mean = sum(r["words"] for r in levels) / max(1, n)
    wanted = query_terms(queries.where(F.col("doc_id").isNotNull()))
    counted = frequencies(index)
    idf = F.log(1 + (F.lit(float(n)) - F.col("df") + 0.5) / (F.col("df") + 0.5))
    weighted = wanted.join(counted, "term").groupBy("query").agg(F.array_sort(F.collect_list(F.struct("term", idf.alias("idf")))).alias("terms"))
    weighted = common.materialize(weighted, "queries")
    size = weighted.agg(F.count("*"), F.sum(F.size("terms"))).first()
    blocks = max(1, -(-size[0] // QUERY_BLOCK), -(-(size[1] or 0) // BLOCK_TERMS))
    rounds: list[list[int]] = [[]]
    held = 0
    for r in levels:
        if held >= FIRST_SHARDS:
            rounds.append([])
        rounds[-1].append(r["level"])
        held += r["shards"]
    out = []
    for b in range(blocks):
        here = weighted.where(F.pmod(F.xxhash64("query"), F.lit(blocks)) == b) if blocks > 1 else weighted
        out.append(_search_block(index, rounds, here, mean, top))
    return spark.read.schema(HITS).parquet(*out)


HITS = "query long, doc_id long, score double, rank int"


def _search_block(index: DataFrame, rounds: list[list[int]], queries: DataFrame, mean: float, top: int) -> str:
    """The folder of the best hits of a block of queries (bounded in queries and terms), found level after level.

    The block and its thresholds are broadcast; the index stays where it is.
    """
    block = queries.select("query", "terms").toArrow()
    lists = block.column("terms").combine_chunks()
    ends = np.concatenate(([0], np.cumsum(lists.value_lengths().to_numpy(zero_copy_only=False)))).astype(np.int64)
    terms = lists.flatten().field("term").to_numpy(zero_copy_only=False).view(np.uint64)
    state = QueryBlock(block.column("query").to_numpy(), ends, terms, lists.flatten().field("idf").to_numpy(zero_copy_only=False), top)
    order = np.argsort(state.ids)
    best, folder = None, ""
    for levels in rounds:
        if best is not None:
            last = best.where(F.col("rank") == top).select("query", "doc_id", "score").toArrow()
            at = order[np.searchsorted(state.ids, last.column("query").to_numpy(), sorter=order)]
            state.floor[at], state.last[at] = last.column("score").to_numpy(), last.column("doc_id").to_numpy()
        shared = index.sparkSession.sparkContext.broadcast(state)
        hits = index.where(F.col("level").isin(levels)).drop("level", "frequencies").mapInArrow(_scorer(shared, mean), "query long, doc_id long, score double")
        folder = common.write(_best(hits if best is None else hits.unionByName(best.drop("rank")), top), "hits")
        best = index.sparkSession.read.schema(HITS).parquet(folder)
        shared.destroy()
    return folder


def _scorer(shared, mean: float):
    def run(batches):
        queries: QueryBlock = shared.value
        queries.start()
        for batch in batches:
            for k in range(batch.num_rows):
                Shard({name: batch.column(name)[k].as_buffer() for name in batch.schema.names if pa.types.is_binary(batch.schema.field(name).type)}, mean).search(queries)
        yield queries.found()

    return run


def _best(hits: DataFrame, top: int) -> DataFrame:
    rank = F.row_number().over(Window.partitionBy("query").orderBy(F.desc("score"), "doc_id"))
    return hits.withColumn("rank", rank).where(F.col("rank") <= top)


def op4_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The best ten documents for the whole text of each document whose id is divisible by 100."""
    docs = common.read_table(spark, sf_dir, "documents")
    return search(docs, docs.where(F.col("doc_id") % 100 == 0))


ORACLE_SQL = r"""
WITH w AS (SELECT doc_id, unnest(regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+')) AS term FROM documents),
tf AS (SELECT doc_id, term, count(*) AS tf FROM w GROUP BY ALL),
len AS (SELECT d.doc_id, count(w.term) AS dl FROM documents d LEFT JOIN w ON w.doc_id = d.doc_id GROUP BY d.doc_id),
stat AS (SELECT count(*) AS n, avg(dl) AS mean FROM len),
df AS (SELECT term, count(*) AS df FROM tf GROUP BY term),
s AS (SELECT q.doc_id AS query, d.doc_id, round(sum(ln(1 + (n - df + 0.5) / (df + 0.5)) * d.tf * 2.2 / (d.tf + 1.2 * (0.25 + 0.75 * dl / mean))), 6) AS score
      FROM tf q JOIN tf d ON d.term = q.term JOIN df ON df.term = q.term JOIN len ON len.doc_id = d.doc_id CROSS JOIN stat
      WHERE q.doc_id % 100 = 0 GROUP BY q.doc_id, d.doc_id),
r AS (SELECT *, CAST(row_number() OVER (PARTITION BY query ORDER BY score DESC, doc_id) AS INTEGER) AS rank FROM s)
SELECT query, doc_id, score, rank FROM r WHERE rank <= 10
"""
