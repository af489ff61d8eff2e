"""Token counts of sections by offset-mapped attribution, and op5.

A document is encoded once, whole, so its tokens are those of the whole text.
Each token has a span of characters: from the character of its first byte to
that of its last.  The spans are joined to the sections' intervals; a token that
crosses a boundary goes, whole, to the section that the rule names: ``most``
(the section with most of its characters, the earlier one on a tie), ``first``
or ``last`` (that of its first or last character).

Sections are lines, each with its line feed; or fields, columns that are written
one after another, each but the last followed by a line feed that counts as its
own; or those that begin at given offsets (of characters, in any order; the
first section begins at 0).  Null and empty texts have no section and no token;
a null field is empty.  The counts of a document's sections add up to its tokens.
"""

from __future__ import annotations

import functools

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridsparse.llm import bpe, common

RULES = ("most", "first", "last")


@functools.lru_cache(maxsize=2)
def token_sizes(vocabulary: str | None = None) -> np.ndarray:
    return np.array([len(raw) for raw in bpe.encoder(vocabulary).token_bytes], np.int64)


def character_spans(raw: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """First and last character of each token, given a text's bytes and the tokens' sizes in bytes, in order."""
    number = np.cumsum((raw & 0xC0) != 0x80) - 1
    end = np.cumsum(sizes)
    return number[end - sizes], number[end - 1]


def line_starts(raw: np.ndarray) -> np.ndarray:
    """Offsets of characters at which lines begin; an empty last line does not count."""
    at = np.concatenate(([0], np.flatnonzero(raw == 10) + 1))
    number = np.cumsum((raw & 0xC0) != 0x80) - 1
    return number[at[at < len(raw)]]


def attribute(first: np.ndarray, last: np.ndarray, starts: np.ndarray, rule: str = "most") -> tuple[np.ndarray, int]:
    """Tokens of each section, given the tokens' first and last characters in order, and how many tokens cross a boundary."""
    if rule not in RULES:
        raise ValueError(f"unknown rule {rule}")
    if not len(starts):
        return np.zeros(0, np.int64), 0
    low = np.searchsorted(starts, first, side="right") - 1
    high = np.searchsorted(starts, last, side="right") - 1
    crossing = np.flatnonzero(low != high)
    owner = (high if rule == "last" else low).copy()
    if rule == "most":
        for i in crossing:
            edges = np.concatenate(([first[i]], starts[low[i] + 1 : high[i] + 1], [last[i] + 1]))
            owner[i] = low[i] + int(np.diff(edges).argmax())
    return np.bincount(owner, minlength=len(starts)), len(crossing)


def token_spans(docs: DataFrame, vocabulary: str | None = None) -> DataFrame:
    """``doc_id, ids, first, last``: every token of each text with its first and last character."""

    def kernel(part: pa.RecordBatch) -> pa.RecordBatch:
        coder, size_of = bpe.encoder(vocabulary), token_sizes(vocabulary)
        data, offsets = common.utf8(part.column("text"))
        found = []
        for a, b in zip(offsets[:-1], offsets[1:], strict=True):
            ids = np.frombuffer(coder.encode_packed(data[a:b].tobytes().decode()), "<u4")
            found.append((ids.astype(np.int32), *character_spans(data[a:b], size_of[ids])))
        columns = [part.column("doc_id"), pa.array([f[0] for f in found], pa.list_(pa.int32())), *(pa.array([f[k] for f in found], pa.list_(pa.int64())) for k in (1, 2))]
        return pa.RecordBatch.from_arrays(columns, names=["doc_id", "ids", "first", "last"])

    return common.map_slices(docs.select("doc_id", "text"), kernel, "doc_id long, ids array<int>, first array<long>, last array<long>")


def count_sections(docs: DataFrame, rule: str = "most", vocabulary: str | None = None, starts: str | None = None) -> DataFrame:
    """Per row: doc_id, n_tokens, n_sections, crossing, section_tokens; ``starts`` names a column of offsets (default: lines)."""

    def kernel(part: pa.RecordBatch) -> pa.RecordBatch:
        coder, size_of = bpe.encoder(vocabulary), token_sizes(vocabulary)
        data, offsets = common.utf8(part.column("text"))
        given = part.column("starts").to_pylist() if starts else None
        total, number, cross, tokens = [], [], [], []
        for k, (a, b) in enumerate(zip(offsets[:-1], offsets[1:], strict=True)):
            raw = data[a:b]
            sizes = size_of[np.frombuffer(coder.encode_packed(raw.tobytes().decode()), "<u4")]
            first, last = character_spans(raw, sizes)
            begin = line_starts(raw) if given is None else np.unique([0, *(x for x in given[k] or [] if x is not None and 0 < x <= last[-1])]) if len(raw) else np.empty(0, np.int64)
            counts, crossing = attribute(first, last, begin, rule)
            total.append(len(sizes))
            number.append(len(counts))
            cross.append(crossing)
            tokens.append(counts)
        columns = [part.column("doc_id"), *(pa.array(v, pa.int64()) for v in (total, number, cross)), pa.array(tokens, pa.list_(pa.int64()))]
        return pa.RecordBatch.from_arrays(columns, names=["doc_id", "n_tokens", "n_sections", "crossing", "section_tokens"])

    wanted = docs.select("doc_id", "text", *([F.col(starts).alias("starts")] if starts else []))
    return common.map_slices(wanted, kernel, "doc_id long, n_tokens long, n_sections long, crossing long, section_tokens array<long>")


def count_fields(docs: DataFrame, fields: list[str], rule: str = "most", vocabulary: str | None = None) -> DataFrame:
    """``doc_id, n_tokens, crossing`` and ``field_tokens``, a map of each of ``fields`` to its tokens, all written into one text."""
    parts = [F.concat(F.coalesce(F.col(f).cast("string"), F.lit("")), F.lit("\n" if k < len(fields) - 1 else "")) for k, f in enumerate(fields)]
    sizes = F.array(*(F.length(p).cast("long") for p in parts))
    at = F.array(*(F.aggregate(F.slice(sizes, 1, k), F.lit(0).cast("long"), lambda x, y: x + y) for k in range(1, len(fields))))
    counted = count_sections(docs.select("doc_id", F.concat(*parts).alias("text"), at.alias("at")), rule, vocabulary, "at")
    # an empty last field begins at the end, where no token is
    named = F.map_from_arrays(F.array(*map(F.lit, fields)), F.transform(F.sequence(F.lit(1), F.lit(len(fields))), lambda k: F.coalesce(F.try_element_at("section_tokens", k), F.lit(0).cast("long"))))
    return counted.select("doc_id", "n_tokens", "crossing", named.alias("field_tokens"))


def op5_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tokens of every line of every document."""
    return count_sections(common.read_table(spark, sf_dir, "documents"))
