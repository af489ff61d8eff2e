"""Shared plumbing of the text operators: slim inputs, bounded batches, word hashes.

Words are maximal runs of bytes other than ``0x20`` and ``0x09``-``0x0D``; the
hash kernel works on the UTF-8 buffer of an Arrow column, so no Python string
is made for a word.
"""

from __future__ import annotations

import pickle
import uuid
import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SLICE_BYTES = 1 << 20
ARROW_ROWS = 2000  # rows of texts that go to a worker at once
WORD = r"[^\x20\x09-\x0D]+"

SEPARATOR = np.zeros(256, dtype=bool)
SEPARATOR[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32

_GOLD = np.uint64(0x9E3779B97F4A7C15)
_MIX = np.uint64(0xD6E8FEB86659FD93)
_S32 = np.uint64(32)


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The cluster's shared folder (``spark.checkpoint.dir``); one of our own only where unset."""
    return (spark.sparkContext.getConf().get("spark.checkpoint.dir") or "file:///tmp/checkpoints").rstrip("/")


def write(df: DataFrame, label: str, by: str | None = None) -> str:
    """Write ``df`` to a new folder of the shared one as Parquet (in a folder for each value of ``by``); the files go when the driver's JVM ends."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
    (df.write.partitionBy(by) if by else df.write).parquet(path)
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(target)
    return path


def materialize(df: DataFrame, label: str, by: str | None = None) -> DataFrame:
    """Write ``df`` to the shared folder and read it back.

    Cuts lineage so that a lost executor costs a file read rather than a
    recomputation.
    """
    return df.sparkSession.read.schema(df.schema).parquet(write(df, label, by))


HOT_KEYS = 10_000  # at most so many keys are broadcast by join_hot


def join_hot(left: DataFrame, right: DataFrame, keys: list[str], rows: int, how: str = "inner", least: int = 1000) -> DataFrame:
    """``left.join(right, keys, how)`` that never gathers a hot key's rows in one task.

    ``right`` has a row per key with ``members``, the number of its rows in
    ``left`` (of ``rows`` in all).  Keys with more than ``rows / HOT_KEYS`` of
    them, so fewer than ``HOT_KEYS``, are broadcast; their rows don't move.
    """
    most = max(least, rows // HOT_KEYS)
    hot = F.broadcast(right.where(F.col("members") > most))
    warm = left.join(hot, keys)
    cold = left.join(hot.select(*keys), keys, "left_anti").join(right.where(F.col("members") <= most), keys, how)
    return warm.unionByName(cold.select(warm.columns)).drop("members")


def fit_remotely(sample: DataFrame, fit: Callable[[list[dict]], object]):
    """``fit`` of the rows of a bounded ``sample``, in one task; only the pickled model comes to the driver."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = [row for batch in batches for row in batch.to_pylist()]
        yield pa.RecordBatch.from_arrays([pa.array([zlib.compress(pickle.dumps(fit(rows)), 1)], pa.binary())], names=["model"])

    made = sample.repartition(1).mapInArrow(run, "model binary").collect()
    return pickle.loads(zlib.decompress(made[0]["model"])) if made else fit([])


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser, vectorised."""
    x = x * _GOLD
    x ^= x >> _S32
    x *= _MIX
    x ^= x >> _S32
    return x


def utf8(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of a string column (nulls as empty) and its ``len + 1`` offsets from 0."""
    if column.null_count:
        column = pc.fill_null(column, "")
    column = column.cast(pa.large_string()) if not pa.types.is_large_string(column.type) else column
    n = len(column)
    if n == 0:
        return np.empty(0, np.uint8), np.zeros(1, np.int64)
    offsets = np.frombuffer(column.buffers()[1], np.int64, n + 1, column.offset * 8)
    raw = column.buffers()[2]
    data = np.frombuffer(raw, np.uint8) if raw is not None else np.empty(0, np.uint8)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def slices(batch: pa.RecordBatch, text: str = "text", most: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Cuts of a batch that hold about ``most`` bytes of text each (one row at least)."""
    n = batch.num_rows
    if n == 0:
        return
    lengths = pc.fill_null(pc.binary_length(batch.column(text)), 0).to_numpy(zero_copy_only=False).astype(np.int64)
    ends, start = np.cumsum(lengths), 0
    while start < n:
        base = ends[start - 1] if start else 0
        stop = max(start + 1, int(np.searchsorted(ends, base + most, side="right")))
        yield batch.slice(start, stop - start)
        start = stop


def map_slices(df: DataFrame, kernel: Callable[[pa.RecordBatch], pa.RecordBatch], schema: str, text: str = "text") -> DataFrame:
    """``kernel`` over bounded cuts of every batch; ``df`` holds just the columns it needs.

    The running session's batches for Python workers are lowered to
    ``ARROW_ROWS`` rows where they are larger: whole texts are wide rows.
    """
    setting = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(df.sparkSession.conf.get(setting)) <= ARROW_ROWS:
        df.sparkSession.conf.set(setting, str(ARROW_ROWS))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, text):
                yield kernel(part)

    return df.mapInArrow(run, schema)


def word_bounds(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of all words, and the offsets of each row's words among them."""
    if len(data) == 0:
        z = np.empty(0, np.int64)
        return z, z, np.zeros(len(offsets), np.int64)
    gap = SEPARATOR[data]
    edge = np.zeros(len(data) + 1, bool)
    edge[offsets] = True
    before = np.empty(len(data), bool)
    before[0] = True
    before[1:] = gap[:-1]
    after = np.empty(len(data), bool)
    after[-1] = True
    after[:-1] = gap[1:]
    starts = np.flatnonzero(~gap & (before | edge[:-1]))
    ends = np.flatnonzero(~gap & (after | edge[1:])) + 1
    return starts, ends, np.searchsorted(starts, offsets)


def word_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, slab: int = 1 << 19) -> np.ndarray:
    """64-bit hashes of the words, A-Z lower-cased.

    The hash is the sum over a word's bytes of a mixed (position, byte) code,
    mixed again; slabs bound the memory for any text length.
    """
    out = np.empty(len(starts), np.uint64)
    sizes = ends - starts
    total = np.concatenate(([0], np.cumsum(sizes)))
    first = 0
    while first < len(starts):
        last = max(first + 1, int(np.searchsorted(total, total[first] + slab, side="right")) - 1)
        lens = sizes[first:last]
        at = total[first:last] - total[first]
        place = np.arange(total[last] - total[first]) - np.repeat(at, lens)
        code = LOWER[data[place + np.repeat(starts[first:last], lens)]].astype(np.uint64)
        code += (place.astype(np.uint64) + np.uint64(1)) << np.uint64(8)
        out[first:last] = mix64(np.add.reduceat(mix64(code), at))
        first = last
    return out


def row_of(word_offsets: np.ndarray) -> np.ndarray:
    """The row number of each word."""
    return np.repeat(np.arange(len(word_offsets) - 1), np.diff(word_offsets))


def hash_one(word: str) -> int:
    raw = np.frombuffer(word.encode(), np.uint8)
    return int(word_hashes(raw, np.array([0]), np.array([len(raw)]))[0])


def crc_bucket(column: str, modulus: int):
    """crc32 of the id's decimal text, modulo; null ids fall in bucket -1 (never held out)."""
    return F.coalesce(F.pmod(F.crc32(F.col(column).cast("string").cast("binary")), F.lit(modulus)), F.lit(-1))
