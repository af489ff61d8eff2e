"""Coordinate text, delimited, JSON and ORC edge lists, blocked Parquet, a generator data source and table functions."""

from __future__ import annotations

import uuid
from dataclasses import dataclass

import pyarrow as pa
import pyarrow.parquet as pq
from pyarrow.fs import FileSystem
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceArrowWriter, DataSourceReader, InputPartition, WriterCommitMessage

from gridsparse.matrix import SparseMatrix
from gridsparse.operators.layout import Grid, to_blocks


def write_coordinate(a: SparseMatrix, path: str) -> None:
    """Text triples, 1-based, under a comment and a line of sizes (the header is a file of its own)."""
    spark = a.df.sparkSession
    header = spark.createDataFrame([("%%coordinate general",), (f"% {a.n_rows} {a.n_cols}",)], "value string").coalesce(1)
    header.write.mode("overwrite").text(f"{path}/header")
    a.df.select(F.concat_ws(" ", F.col("i") + 1, F.col("j") + 1, "v").alias("value")).write.mode("overwrite").text(f"{path}/entries")


def read_coordinate(spark: SparkSession, path: str, kind: str = "double") -> SparseMatrix:
    sizes = spark.read.text(f"{path}/header").where("value LIKE '% %' AND value NOT LIKE '%%\\%coord%'").where(~F.col("value").startswith("%%")).first()["value"].split()
    parts = F.split("value", " ")
    cells = spark.read.text(f"{path}/entries").select((parts[0].cast("long") - 1).alias("i"), (parts[1].cast("long") - 1).alias("j"), parts[2].cast(kind).alias("v"))
    return SparseMatrix(cells, int(sizes[1]), int(sizes[2]))


def write_edges(df: DataFrame, path: str, form: str) -> None:
    """'csv', 'json', 'orc' or 'parquet'."""
    writer = df.write.mode("overwrite")
    (writer.option("header", True) if form == "csv" else writer).format(form).save(path)


def read_edges(spark: SparkSession, path: str, form: str, schema: str) -> DataFrame:
    reader = spark.read.schema(schema)
    return (reader.option("header", True) if form == "csv" else reader).format(form).load(path)


def write_blocks(a: SparseMatrix, path: str, grid: Grid, mode: str = "overwrite") -> None:
    """Parquet partitioned by block, so that a window reads its blocks only."""
    to_blocks(a, grid).drop("cell").write.mode(mode).partitionBy("br", "bc").parquet(path)


def read_window(spark: SparkSession, path: str, shape: tuple[int, int], grid: Grid, i0: int, i1: int) -> DataFrame:
    """Rows i0 to i1 - 1 of a blocked matrix, with the block predicate derived from the range."""
    height = max(1, -(-shape[0] // grid.pr))
    return spark.read.parquet(path).where(F.col("br").between(i0 // height, (i1 - 1) // height) & F.col("i").between(i0, i1 - 1)).select("i", "j", "v")


class _Draws(InputPartition):
    def __init__(self, low: int, high: int):
        self.low, self.high = low, high


class _DrawReader(DataSourceReader):
    def __init__(self, options):
        self.scale, self.degree, self.seed = (int(options.get(k, d)) for k, d in (("scale", 8), ("degree", 8), ("seed", 1)))

    def partitions(self):
        total = self.degree << self.scale
        step = max(1, total // 16)
        return [_Draws(a, min(total, a + step)) for a in range(0, total, step)]

    def read(self, partition):
        yield from draw_edges(partition.low, partition.high, self.scale, self.seed)


class RecursiveEdges(DataSource):
    """Format ``recursive_edges``: raw recursive-quadrant draws (i, j); options scale, degree, seed."""

    @classmethod
    def name(cls):
        return "recursive_edges"

    def schema(self):
        return "i long, j long"

    def reader(self, schema):
        return _DrawReader(self.options)


def draw_edges(low: int, high: int, scale: int, seed: int):
    """Draws low to high - 1, each from its own counter-based stream."""
    import numpy as np

    for d in range(low, high):
        u = np.random.Generator(np.random.Philox(key=seed, counter=d)).random(scale)
        side = np.searchsorted(np.cumsum([0.6, 0.4 / 3, 0.4 / 3]), u, side="right")
        weight = 1 << np.arange(scale - 1, -1, -1)
        yield int((side // 2) @ weight), int((side % 2) @ weight)


@dataclass
class _Written(WriterCommitMessage):
    file: str


class _EdgeWriter(DataSourceArrowWriter):
    def __init__(self, path: str):
        self.path = path

    def write(self, iterator):
        store, at = FileSystem.from_uri(self.path)
        store.create_dir(at, recursive=True)
        file = f"{at}/{uuid.uuid4().hex}.parquet"
        schema = pa.schema([("i", pa.int64()), ("j", pa.int64())])
        with pq.ParquetWriter(file, schema, filesystem=store) as out:
            for batch in iterator:
                out.write_batch(pa.RecordBatch.from_arrays([batch.column(c).cast(pa.int64()) for c in ("i", "j")], schema=schema))
        return _Written(file)

    def commit(self, messages):
        """The list of the tasks' files makes them the table: what a failed attempt left is not read."""
        store, at = FileSystem.from_uri(self.path)
        store.create_dir(at, recursive=True)
        with store.open_output_stream(f"{at}/files") as out:
            out.write("\n".join(m.file for m in messages if m is not None).encode())


class _EdgeReader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path

    def partitions(self):
        store, at = FileSystem.from_uri(self.path)
        with store.open_input_stream(f"{at}/files") as listed:
            return [InputPartition(f) for f in listed.read().decode().split("\n") if f] or [InputPartition(None)]

    def read(self, partition):
        if partition.value is None:
            return
        store, _ = FileSystem.from_uri(self.path)
        with store.open_input_file(partition.value) as source:
            yield from pq.ParquetFile(source).iter_batches(batch_size=10_000)


class EdgeFiles(DataSource):
    """Format ``edge_files``: edges (i, j) written and read by Arrow batches, a file per task, in a folder that all executors share."""

    @classmethod
    def name(cls):
        return "edge_files"

    def schema(self):
        return "i long, j long"

    def reader(self, schema):
        return _EdgeReader(self.options["path"])

    def writer(self, schema, overwrite):
        return _EdgeWriter(self.options["path"])


def register_table_functions(spark: SparkSession) -> None:
    """SQL table functions ``recursive_edges(lo, hi, scale, seed)`` and ``set_edges(members)``: the ordered pairs of distinct members."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="i bigint, j bigint")
    class Edges:
        def eval(self, lo: int, hi: int, scale: int, seed: int):
            yield from draw_edges(lo, hi, scale, seed)

    @udtf(returnType="i bigint, j bigint")
    class SetEdges:
        def eval(self, members: list):
            for i in members:
                for j in members:
                    if i != j:
                        yield i, j

    spark.udtf.register("recursive_edges", Edges)
    spark.udtf.register("set_edges", SetEdges)
