"""Language identification by error-correcting output codes, and its op9 query.

Each language has a codeword; each bit has a binary naive Bayes classifier over
hashed byte trigrams of the lower-cased text.  A bit's mean log-ratio is
calibrated by a logistic curve; decoding takes the codeword of least
reliability-weighted log loss and flags texts whose runner-up is close.

Training reads about ``PER_LANGUAGE`` documents of each language (those of
least id hash); prediction reads every text whole.  Null texts and texts
without a letter are ``und`` with score 0; with no training rows all are.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridsparse.llm import common

PER_LANGUAGE = 1000
BUCKETS = 1 << 16
UNDETERMINED = "und"
LETTER = np.zeros(256, bool)
LETTER[65:91] = LETTER[97:123] = True


def codewords(classes: int, seed: int = 11) -> np.ndarray:
    """A 0/1 matrix, a row per class: exhaustive codes up to 5 classes, else the best-spread of random ones."""
    if classes < 2:
        return np.ones((classes, 1), np.int8)
    if classes <= 5:
        columns = np.arange(1, 1 << (classes - 1))
        rest = (columns[None, :] >> np.arange(classes - 1)[:, None]) & 1
        return np.vstack((np.zeros(len(columns), int), rest)).astype(np.int8)
    bits, best, spread = int(np.ceil(10 * np.log2(classes))), None, -1
    for draw in np.random.default_rng(seed).integers(0, 2, (50, classes, bits), dtype=np.int8):
        apart = (draw[:, None, :] != draw[None, :, :]).sum(axis=2)[np.triu_indices(classes, 1)].min()
        if apart > spread and (draw.min(axis=0) != draw.max(axis=0)).all():
            best, spread = draw, apart
    return best


def trigrams(data: np.ndarray) -> np.ndarray:
    """The bucket of the trigram that starts at each byte but the last two."""
    low = common.LOWER[data].astype(np.uint32)
    code = (low[:-2] << np.uint32(16)) | (low[1:-1] << np.uint32(8)) | low[2:]
    return (code * np.uint32(2654435761)) >> np.uint32(16)


@dataclass
class Codebook:
    languages: list[str]
    codes: np.ndarray
    weights: np.ndarray
    scale: np.ndarray
    reliability: np.ndarray

    def means(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        """Each row's mean trigram weight per bit; rows under three bytes are padded with a space on both sides."""
        out = np.zeros((len(offsets) - 1, self.weights.shape[0]))
        sizes = np.diff(offsets)
        for r in np.flatnonzero((sizes > 0) & (sizes < 3)):
            grams = trigrams(np.concatenate(([32], data[offsets[r] : offsets[r + 1]], [32, 32])).astype(np.uint8))
            out[r] = self.weights[:, grams].mean(axis=1)
        long = np.flatnonzero(sizes >= 3)
        if len(long):
            edges = np.empty(2 * len(long), np.int64)
            edges[::2], edges[1::2] = offsets[long], offsets[long + 1] - 2
            grams = np.append(trigrams(data), np.uint32(0))
            for bit, weights in enumerate(self.weights):
                out[long, bit] = np.add.reduceat(weights[grams], edges, dtype=np.float64)[::2] / (sizes[long] - 2)
        return out

    def chances(self, means: np.ndarray) -> np.ndarray:
        z = np.clip(means * self.scale[0] + self.scale[1], -30, 30)
        return 1 / (1 + np.exp(-z))

    def decode(self, chances: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Best class, its share among all codewords by loss, and whether the runner-up is close."""
        p = np.clip(chances, 1e-6, 1 - 1e-6)
        gain = (np.log(p) * self.reliability) @ self.codes.T + (np.log(1 - p) * self.reliability) @ (1 - self.codes).T
        share = np.exp(gain - gain.max(axis=1, keepdims=True))
        share /= share.sum(axis=1, keepdims=True)
        best = share.argmax(axis=1)
        top = share[np.arange(len(best)), best]
        return best, top, top < 0.75


def fit(texts: list[str], languages: list[str]) -> Codebook | None:
    names = sorted(set(languages))
    if not names:
        return None
    codes = codewords(len(names))
    y = np.array([names.index(v) for v in languages])
    data, offsets = common.utf8(pa.array(texts, pa.string()))
    counts = np.zeros((len(names), BUCKETS))
    for r, cls in enumerate(y):
        part = data[offsets[r] : offsets[r + 1]]
        if len(part) >= 3:
            counts[cls] += np.bincount(trigrams(part), minlength=BUCKETS) / (len(part) - 2)
    shares = (counts + 0.02 / BUCKETS * np.maximum(1, counts.sum(axis=1, keepdims=True))) / (1.02 * np.maximum(1, counts.sum(axis=1, keepdims=True)))
    bits = codes.shape[1]
    weights = np.empty((bits, BUCKETS), np.float32)
    for b in range(bits):
        ones, zeros = shares[codes[:, b] == 1], shares[codes[:, b] == 0]
        none = np.full((1, BUCKETS), 1 / BUCKETS)
        weights[b] = np.log((ones if len(ones) else none).mean(axis=0)) - np.log((zeros if len(zeros) else none).mean(axis=0))
    book = Codebook(names, codes, weights, np.vstack((np.ones(bits), np.zeros(bits))), np.ones(bits))
    means = book.means(data, offsets)
    for b in range(bits):
        target = codes[y, b].astype(float)
        x, beta = np.stack((means[:, b], np.ones(len(y))), axis=1), np.array([1.0, 0.0])
        for _ in range(25):
            p = 1 / (1 + np.exp(-np.clip(x @ beta, -30, 30)))
            hessian = (x * (p * (1 - p))[:, None]).T @ x + 1e-2 * np.eye(2)
            beta += np.clip(np.linalg.solve(hessian, x.T @ (target - p) - 1e-2 * beta), -3, 3)
        book.scale[:, b] = beta
    right = (book.chances(means) >= 0.5) == (codes[y] == 1)
    book.reliability = np.maximum(0.1, 2 * right.mean(axis=0) - 1)
    return book


def fit_from_documents(docs: DataFrame, per_language: int = PER_LANGUAGE) -> Codebook | None:
    """Fit on about ``per_language`` learnable documents of each language, drawn by id hash."""
    known = docs.select("doc_id", "lang").where(F.col("lang").isNotNull() & F.col("doc_id").isNotNull() & (common.crc_bucket("doc_id", 3) != 1))
    counts = known.groupBy("lang").agg(F.count("*").alias("n"))
    counts = counts.select(F.col("lang").alias("of_lang"), (F.lit(per_language) / F.col("n")).alias("rate"))
    draw = F.pmod(F.xxhash64(F.col("doc_id"), F.lit(9)), F.lit(1 << 30)) / F.lit(float(1 << 30))
    chosen = known.join(counts, F.col("lang") == F.col("of_lang")).where(draw < F.col("rate")).select("doc_id", "lang").distinct()
    rows = docs.select("doc_id", "text", "lang").where(F.col("text").isNotNull()).join(F.broadcast(chosen), ["doc_id", "lang"])
    return common.fit_remotely(rows, _fit_rows)


def _fit_rows(rows: list[dict]) -> Codebook | None:
    rows = sorted((r["doc_id"], r["lang"], r["text"]) for r in rows)
    return fit([r[2] for r in rows], [r[1] for r in rows])


def identify(docs: DataFrame, book: Codebook | None) -> DataFrame:
    """``doc_id, lang_pred, score, ambiguous`` for every row."""
    shared = docs.sparkSession.sparkContext.broadcast(book)

    def kernel(part: pa.RecordBatch) -> pa.RecordBatch:
        known: Codebook | None = shared.value
        data, offsets = common.utf8(part.column("text"))
        n = part.num_rows
        found = np.concatenate(([0], np.cumsum(LETTER[data])))
        lettered = found[offsets[1:]] > found[offsets[:-1]]
        for r in np.flatnonzero(~lettered & (np.diff(offsets) > 0)):
            lettered[r] = any(map(str.isalpha, data[offsets[r] : offsets[r + 1]].tobytes().decode()))
        if known is None:
            lettered[:] = False
            names, score, close = np.full(n, UNDETERMINED, object), np.zeros(n), np.zeros(n, bool)
        else:
            best, score, close = known.decode(known.chances(known.means(data, offsets)))
            names = np.array(known.languages, object)[best]
        names = np.where(lettered, names, UNDETERMINED)
        columns = [part.column("doc_id"), pa.array(names.tolist(), pa.string()), pa.array(np.where(lettered, score, 0.0)), pa.array(close & lettered)]
        return pa.RecordBatch.from_arrays(columns, names=["doc_id", "lang_pred", "score", "ambiguous"])

    return common.map_slices(docs.select("doc_id", "text"), kernel, "doc_id long, lang_pred string, score double, ambiguous boolean")


def op9_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document's language, learned from rows whose id's crc32 is not 1 modulo 3."""
    docs = common.read_table(spark, sf_dir, "documents")
    found = identify(docs, fit_from_documents(docs))
    return found.select("doc_id", (common.crc_bucket("doc_id", 3) == 1).alias("held_out"), "lang_pred", "score", "ambiguous")
