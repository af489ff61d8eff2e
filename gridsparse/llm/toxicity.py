"""Toxic spans by a linear-chain conditional random field, and its op7 query.

Tokens are white-space words; a token's features are the hashed prefixes of its
lower-cased bytes.  Token labels come from document labels: a prefix is
telling if it is much denser in toxic training texts than in the others; tokens
with a telling prefix are tagged in toxic documents.  The field (two states,
learned transitions and prefix weights) is fitted to windows of those tags.  At
scoring time tokens without a telling prefix all share one potential, so a run
of them is one matrix power and exact forward-backward visits the others only.
A document's score is a logistic function of its marginals' sum, density and
maximum.

Fitting reads at most ``PER_CLASS`` labelled training documents (those of least
id hash) and uses all their windows; scoring reads every text whole.  Null and empty texts
have no tokens and get the score of zero evidence; without labelled training
rows of both classes every score is the share of toxic training labels (0 if
none).  Rows repeat as in the input.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridsparse.llm import common

PER_CLASS = (2000, 1000)  # documents without and with the label
PREFIXES = (3, 4, 5, 6, 7, 8)
BUCKETS = 1 << 20
WINDOW = 24
BATCH = 20_000  # windows whose marginals are in memory at once
THRESHOLD = 0.3


def prefix_buckets(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """For each token the bucket of each of its prefixes, 0 where the token is shorter."""
    out = np.zeros((len(starts), len(PREFIXES)), np.int32)
    state = np.zeros(len(starts), np.uint64)
    room = ends - starts
    for length in range(1, max(PREFIXES) + 1):
        code = common.LOWER[data[np.minimum(starts + length - 1, len(data) - 1)]].astype(np.uint64)
        state = (state ^ (code + np.uint64(length << 8))) * np.uint64(0x9E3779B97F4A7C15)
        state ^= state >> np.uint64(29)
        if length in PREFIXES:
            bucket = (common.mix64(state) >> np.uint64(44)).astype(np.int32)
            out[:, PREFIXES.index(length)] = np.where(room >= length, np.maximum(bucket, 1), 0)
    return out


@dataclass
class Field:
    """A fitted field and its document link; ``weights`` is dense by prefix bucket."""

    weights: np.ndarray
    bias: float
    trans: np.ndarray
    link: np.ndarray
    base: float | None = None

    def evidence(self, buckets: np.ndarray) -> np.ndarray:
        return self.weights[buckets].sum(axis=1)

    def run_power(self, gaps: np.ndarray) -> np.ndarray:
        """Products of ``gap`` plain tokens' step matrices, each scaled by the leading eigenvalue."""
        step = np.exp(self.trans + np.array([0.0, self.bias])[None, :])
        values, vectors = np.linalg.eig(step)
        order = np.argsort(-values.real)
        values, vectors = values.real[order], vectors.real[:, order]
        inverse = np.linalg.inv(vectors)
        lead, other = (np.outer(vectors[:, i], inverse[i]) for i in (0, 1))
        ratio = values[1] / values[0]
        return lead + (ratio ** gaps.astype(float))[:, None, None] * other

    def marginals(self, at: np.ndarray, score: np.ndarray, rows: np.ndarray, lengths: np.ndarray) -> np.ndarray:
        """P(toxic) at the listed tokens (place in their row, evidence, row), rows of ``lengths`` tokens."""
        n = len(at)
        if n == 0:
            return np.empty(0)
        first = np.concatenate(([True], rows[1:] != rows[:-1]))
        begin = np.flatnonzero(first)
        rank = np.arange(n) - np.repeat(begin, np.diff(np.append(begin, n)))
        gap_before = np.where(first, at, at - np.concatenate(([0], at[:-1])) - 1)
        last = np.concatenate((first[1:], [True]))
        gap_after = np.where(last, lengths[rows] - at - 1, 0)
        into = self.run_power(gap_before)
        emit = np.stack((np.ones(n), np.exp(np.clip(self.bias + score, -30, 30))), axis=1)
        move = np.exp(self.trans)
        order = np.argsort(rank, kind="stable")
        cuts = np.searchsorted(rank[order], np.arange(rank.max() + 2))
        ahead, back = np.empty((n, 2)), np.empty((n, 2))
        for k in range(len(cuts) - 1):
            i = order[cuts[k] : cuts[k + 1]]
            came = np.tile([[1.0, 0.0]], (len(i), 1)) if k == 0 else ahead[i - 1]
            came = np.einsum("ij,ijk->ik", came, into[i]) @ move * emit[i]
            ahead[i] = came / came.sum(axis=1, keepdims=True)
        tail = np.einsum("ijk->ij", self.run_power(gap_after))
        for k in range(len(cuts) - 2, -1, -1):
            i = order[cuts[k] : cuts[k + 1]]
            ended = last[i]
            back[i[ended]] = tail[i[ended]]
            j = i[~ended]
            went = np.einsum("ijk,ik->ij", into[j + 1], (back[j + 1] * emit[j + 1]) @ move.T)
            back[j] = went
            back[i] /= back[i].sum(axis=1, keepdims=True)
        both = ahead * back
        return both[:, 1] / both.sum(axis=1)

    def spans(self, data: np.ndarray, offsets: np.ndarray):
        """Telling tokens of a buffer of texts: row, byte start, byte end, marginal; and each row's score."""
        starts, ends, word_offsets = common.word_bounds(data, offsets)
        lengths = np.diff(word_offsets)
        if self.base is not None:
            z = np.empty(0, np.int64)
            return z, z, z, np.empty(0), np.full(len(lengths), self.base)
        keep, score = [], []
        for a in range(0, len(starts), 1 << 18):
            part = self.evidence(prefix_buckets(data, starts[a : a + (1 << 18)], ends[a : a + (1 << 18)]))
            hit = np.flatnonzero(part)
            keep.append(hit + a)
            score.append(part[hit])
        keep = np.concatenate(keep) if keep else np.empty(0, np.int64)
        score = np.concatenate(score) if score else np.empty(0)
        rows = np.searchsorted(word_offsets, keep, side="right") - 1
        chance = self.marginals(keep - word_offsets[rows], score, rows, lengths)
        return rows, starts[keep], ends[keep], chance, self.rate(features(rows, chance, lengths))

    def rate(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(x @ self.link, -30, 30)))


def features(rows: np.ndarray, chance: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """What the document link sees: 1, mass of the marginals (log), their density (root, log) and their maximum."""
    n = len(lengths)
    mass = np.bincount(rows, chance, n)
    most = np.zeros(n)
    np.maximum.at(most, rows, chance)
    density = 100 * mass / (lengths + 5)
    return np.stack((np.ones(n), np.log1p(mass), np.sqrt(density), np.log1p(density), most), axis=1)


def fit(texts: list[str | None], toxic: list[int], share: float) -> Field:
    """A field from labelled texts; ``share`` is the toxic share among all training labels."""
    empty = Field(np.zeros(BUCKETS, np.float32), 0.0, np.zeros((2, 2)), np.zeros(5), base=share)
    y = np.array(toxic, bool)
    if not len(y) or y.all() or not y.any():
        return empty
    data, offsets = common.utf8(pa.array(texts, pa.string()))
    starts, ends, word_offsets = common.word_bounds(data, offsets)
    lengths = np.diff(word_offsets)
    if not len(starts):
        return empty
    row = common.row_of(word_offsets)
    buckets = prefix_buckets(data, starts, ends)
    bad = y[row]
    inside, outside = (np.bincount(buckets[side].ravel(), minlength=BUCKETS) for side in (bad, ~bad))
    seen = np.zeros(BUCKETS, np.int32)  # toxic documents with the prefix
    for r in np.flatnonzero(y):
        seen[np.unique(buckets[word_offsets[r] : word_offsets[r + 1]])] += 1
    odds = np.log((inside + 0.5) / (bad.sum() + 1)) - np.log((outside + 0.5) / ((~bad).sum() + 1))
    telling = (odds > 1.5) & (seen >= max(3, 0.002 * y.sum()))
    telling[0] = False
    ids = np.full(BUCKETS, -1, np.int32)
    ids[np.flatnonzero(telling)] = np.arange(telling.sum())
    strong = telling & (odds > 2.0)
    local, tag = ids[buckets], bad.copy()
    active = (local >= 0).any(axis=1)
    if not active.any():
        return empty
    tag[tag] = strong[buckets[tag]].any(axis=1)
    weights, bias, trans = _fit_chain(local, active, tag, word_offsets, row, int(telling.sum()))
    dense = np.zeros(BUCKETS, np.float32)
    dense[np.flatnonzero(telling)] = weights
    field = Field(dense, bias, trans, np.zeros(5))
    at = np.flatnonzero(active)
    chance = field.marginals(at - word_offsets[row[at]], field.evidence(buckets[at]), row[at], lengths)
    weight = np.where(y, share / y.mean(), (1 - share) / (1 - y.mean()))
    field.link = _fit_logistic(features(row[at], chance, lengths), y.astype(float), weight)
    return field


def _fit_chain(local, active, tag, word_offsets, row, n_features, rounds: int = 60):
    """Maximum likelihood with a small ridge, over all windows around the active tokens, ``BATCH`` of them at a time."""
    centre = np.flatnonzero(active)
    centre = centre[np.concatenate(([True], (np.diff(centre) > WINDOW // 2) | (np.diff(row[centre]) > 0)))]
    batches = []
    gold_t, gold_b, gold_w = np.zeros((2, 2)), 0, np.zeros(n_features)
    for first in range(0, len(centre), BATCH):
        part = centre[first : first + BATCH]
        place = part[:, None] + np.arange(-(WINDOW // 3), WINDOW - WINDOW // 3)[None, :]
        real = (place >= word_offsets[row[part]][:, None]) & (place < word_offsets[row[part] + 1][:, None])
        place = np.where(real, place, 0)
        labels = (tag[place] & real).ravel()
        at = np.flatnonzero(active[place] & real)
        which = local[place.ravel()[at]]
        flat, cell = which[which >= 0], at[np.nonzero(which >= 0)[0]].astype(np.int32)
        marks, pairs = labels.reshape(real.shape), real[:, 1:] & real[:, :-1]
        gold_t += [[(pairs & (marks[:, :-1] == i) & (marks[:, 1:] == j)).sum() for j in (0, 1)] for i in (0, 1)]
        gold_b += labels.sum()
        gold_w += np.bincount(flat, labels[cell], n_features)
        batches.append((real, flat, cell))
    theta = np.concatenate((np.zeros(n_features), [-4.0], np.zeros(4)))
    m, v = np.zeros_like(theta), np.zeros_like(theta)
    for step in range(1, rounds + 1):
        w, bias, trans = theta[:n_features], theta[n_features], theta[n_features + 1 :].reshape(2, 2)
        grad_w, grad_b, grad_t = gold_w - 0.5 * w, float(gold_b), gold_t - 0.5 * trans
        for real, flat, cell in batches:
            score = np.bincount(cell, w[flat], real.size).reshape(real.shape)
            one, two = _window_marginals(bias + score, trans, real)
            grad_w -= np.bincount(flat, one.ravel()[cell], n_features)
            grad_b -= one[real].sum()
            grad_t -= two
        grad = np.concatenate((grad_w, [grad_b], grad_t.ravel())) / len(centre)
        m, v = 0.9 * m + 0.1 * grad, 0.99 * v + 0.01 * grad**2
        theta = theta + 0.25 * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-8)
    return theta[:n_features], float(theta[n_features]), theta[n_features + 1 :].reshape(2, 2)


def _window_marginals(score, trans, real):
    """P(toxic) per cell and expected transition counts; cells off the text pass probability on untouched."""
    n, width = score.shape
    emit = np.stack((np.ones_like(score), np.exp(np.clip(score, -30, 30))), axis=2)
    emit[~real] = 1.0
    move = np.exp(trans)
    ahead, back = np.empty((n, width, 2)), np.ones((n, width, 2))
    ahead[:, 0] = emit[:, 0] / emit[:, 0].sum(axis=1, keepdims=True)
    joined = real[:, 1:] & real[:, :-1]
    for t in range(1, width):
        came = np.where(joined[:, t - 1, None], ahead[:, t - 1] @ move, 1.0) * emit[:, t]
        ahead[:, t] = came / came.sum(axis=1, keepdims=True)
    expected = np.zeros((2, 2))
    for t in range(width - 2, -1, -1):
        after = emit[:, t + 1] * back[:, t + 1]
        pair = ahead[:, t, :, None] * move * after[:, None, :]
        pair /= pair.sum(axis=(1, 2), keepdims=True)
        expected += pair[joined[:, t]].sum(axis=0)
        went = np.where(joined[:, t, None], after @ move.T, 1.0)
        back[:, t] = went / went.sum(axis=1, keepdims=True)
    both = ahead * back
    return both[:, :, 1] / both.sum(axis=2), expected


def _fit_logistic(x: np.ndarray, y: np.ndarray, weight: np.ndarray, rounds: int = 30) -> np.ndarray:
    beta = np.zeros(x.shape[1])
    ridge = np.diag([1e-3] + [0.05] * (x.shape[1] - 1))
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ beta, -30, 30)))
        hessian = (x * (weight * p * (1 - p))[:, None]).T @ x + ridge
        step = np.linalg.solve(hessian, x.T @ (weight * (y - p)) - ridge @ beta)
        beta += np.clip(step, -5, 5)
    return beta


def fit_from_labels(docs: DataFrame, labels: DataFrame, per_class: tuple[int, int] = PER_CLASS) -> Field:
    """Fit on up to ``per_class`` documents of either class among the rows that may be learned from."""
    known = labels.where(F.col("toxic").isin(0, 1) & F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    known = known.where(common.crc_bucket("doc_id", 4) != 2)
    counts = {int(r["toxic"]): r["n"] for r in known.groupBy("toxic").agg(F.count("*").alias("n")).collect()}
    share = counts.get(1, 0) / max(1, sum(counts.values()))
    chosen = None
    for side in (0, 1):
        part = known.where(F.col("toxic") == side).orderBy(F.xxhash64("doc_id"), "doc_id").limit(per_class[side])
        chosen = part if chosen is None else chosen.unionAll(part)
    texts = docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").dropDuplicates(["doc_id"])
    return common.fit_remotely(texts.where(F.col("text").isNotNull()).select("doc_id", "text", "toxic"), lambda rows: _fit_rows(rows, share))


def _fit_rows(rows: list[dict], share: float) -> Field:
    rows = sorted((r["doc_id"], r["text"], r["toxic"]) for r in rows)
    return fit([r[1] for r in rows], [r[2] for r in rows], share)


def score_documents(docs: DataFrame, field: Field) -> DataFrame:
    """``doc_id, score, n_toxic, spans`` for every row; spans are code-point offsets of tokens of marginal >= 0.5."""
    shared = docs.sparkSession.sparkContext.broadcast(field)

    def kernel(part: pa.RecordBatch) -> pa.RecordBatch:
        data, offsets = common.utf8(part.column("text"))
        rows, begin, end, chance, score = shared.value.spans(data, offsets)
        sure = np.flatnonzero(chance >= 0.5)
        spans: list[list[dict]] = [[] for _ in range(part.num_rows)]
        for r in np.unique(rows[sure]):
            here = sure[rows[sure] == r] if len(sure) < 64 else sure[slice(*np.searchsorted(rows[sure], [r, r + 1]))]
            lead = np.concatenate(([0], np.cumsum((data[offsets[r] : offsets[r + 1]] & 0xC0) != 0x80)))
            spans[r] = [{"start": int(lead[begin[i] - offsets[r]]), "end": int(lead[end[i] - offsets[r]]), "p": float(chance[i])} for i in here]
        kind = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64()), ("p", pa.float64())]))
        columns = [part.column("doc_id"), pa.array(score), pa.array([len(s) for s in spans], pa.int64()), pa.array(spans, kind)]
        return pa.RecordBatch.from_arrays(columns, names=["doc_id", "score", "n_toxic", "spans"])

    return common.map_slices(docs.select("doc_id", "text"), kernel, "doc_id long, score double, n_toxic long, spans array<struct<start:long,end:long,p:double>>")


def op7_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document's toxicity by the field, fitted on rows whose id's crc32 is not 2 modulo 4."""
    docs, labels = (common.read_table(spark, sf_dir, t) for t in ("documents", "labels"))
    scored = score_documents(docs, fit_from_labels(docs, labels))
    return scored.select("doc_id", (common.crc_bucket("doc_id", 4) == 2).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"), "n_toxic")


def keep_clean(docs: DataFrame, field: Field, threshold: float = THRESHOLD) -> DataFrame:
    """The rows of ``docs``, all columns, whose score is under ``threshold``."""
    shared = docs.sparkSession.sparkContext.broadcast(field)

    def kernel(part: pa.RecordBatch) -> pa.RecordBatch:
        score = shared.value.spans(*common.utf8(part.column("text")))[4]
        return part.filter(pa.array(score < threshold))

    return common.map_slices(docs, kernel, docs.schema)
