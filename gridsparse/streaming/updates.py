"""Graph updates as streams: additive assembly, last-write-wins assignment, windows."""

from __future__ import annotations

import json
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from gridsparse.storage import shared_dir

EVENT_SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def replay(spark: SparkSession, events: DataFrame, schema: str = EVENT_SCHEMA, files: int = 4) -> DataFrame:
    """A stream over ``events`` written out as files; timestamps with a zone, as watermarks need."""
    path = f"{shared_dir(spark)}/replay-{uuid.uuid4().hex}"
    events.repartition(files, "event_id").write.parquet(path)
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 2).parquet(path)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


class VersionedStore:
    """A matrix as blocks of rows, each in numbered Parquet versions.

    A batch writes a new version of the blocks that it touches and of no other;
    one that was applied before is not applied again.  A block's files are
    dealt by cell, so a hub's row is not one task.  After a batch's blocks a
    manifest is written that names the version of every block (one line, at most
    ``blocks`` numbers); a store made anew over the same path goes on from the
    newest complete one, so a batch cut off before it counts as never applied.
    """

    def __init__(self, spark: SparkSession, path: str | None = None, blocks: int = 64, spread: int = 4):
        self.spark = spark
        self.path = path or f"{shared_dir(spark)}/store-{uuid.uuid4().hex}"
        self.blocks, self.spread = blocks, spread
        self.version: int | None = None
        self.current: dict[int, int] = {}
        self.schema = None
        self._resume()

    def _folder(self, name: str = ""):
        """The Hadoop file system and path of a folder of the store."""
        path = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{self.path}/{name}")
        return path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()), path

    def _listed(self, name: str) -> list[str]:
        files, path = self._folder(name)
        return [status.getPath().getName() for status in files.listStatus(path)] if files.exists(path) else []

    def _resume(self) -> None:
        """Take up the newest manifest whose write was completed."""
        versions = sorted((int(name[1:]) for name in self._listed("manifest") if name[1:].isdigit()), reverse=True)
        done = next((v for v in versions if "_SUCCESS" in self._listed(f"manifest/v{v}")), None)
        if done is None:
            return
        kept = json.loads(self.spark.read.text(f"{self.path}/manifest/v{done}").first()[0])
        if kept["blocks"] != self.blocks:
            raise ValueError(f"the store at {self.path} has {kept['blocks']} blocks, not {self.blocks}")
        self.version, self.schema = done, StructType.fromJson(kept["schema"])
        self.current = {int(block): version for block, version in kept["current"].items()}

    def _commit(self, version: int, current: dict[int, int], schema: StructType) -> None:
        line = json.dumps({"blocks": self.blocks, "current": current, "schema": schema.jsonValue()})
        self.spark.createDataFrame([(line,)], "value string").coalesce(1).write.mode("overwrite").text(f"{self.path}/manifest/v{version}")
        self.version, self.current, self.schema = version, current, schema

    def vacuum(self) -> int:
        """Remove block files and manifests that the present version doesn't use; gives the number of folders removed.

        Frames that ``read`` gave before a later batch may need them: call it when those are done.
        """
        gone = [f"manifest/{name}" for name in self._listed("manifest") if name != f"v{self.version}"]
        for version in [name for name in self._listed("") if name[:1] == "v" and name[1:].isdigit()]:
            stale = [name for name in self._listed(version) if name.startswith("block=") and self.current.get(int(name[6:])) != int(version[1:])]
            gone += [f"{version}/{name}" for name in stale]
        for name in gone:
            files, path = self._folder(name)
            files.delete(path, True)
        return len(gone)

    def read(self, blocks: set[int] | None = None) -> DataFrame | None:
        """The matrix as it stands, or its given blocks; None before the first batch."""
        if self.version is None:
            return None
        paths = [f"{self.path}/v{v}/block={b}" for b, v in sorted(self.current.items()) if blocks is None or b in blocks]
        return self.spark.read.schema(self.schema).parquet(*paths) if paths else self.spark.createDataFrame([], self.schema)

    def apply(self, batch: DataFrame, batch_id: int, mode: str) -> None:
        """``batch`` (i, j, v, and at for 'assign'): added, or the latest of equal cells wins."""
        if self.version is not None and batch_id <= self.version:
            return
        columns = ["i", "j", "v"] if mode == "extend_add" else ["i", "j", "v", "at"]

        def merged(cells: DataFrame, *place: str) -> DataFrame:
            if mode == "extend_add":
                return cells.groupBy(*place, "i", "j").agg(F.sum("v").alias("v"))
            return cells.groupBy(*place, "i", "j").agg(F.max(F.struct("at", "v")).alias("m")).select(*place, "i", "j", "m.v", "m.at")

        fresh = merged(batch.select(*columns))
        block = F.pmod(F.xxhash64("i"), F.lit(self.blocks)).cast("int")
        fresh.persist()
        try:
            touched = {r[0] for r in fresh.select(block).distinct().collect()}  # at most self.blocks
            old = self.read(touched)
            both = (fresh if old is None else old.unionByName(fresh)).withColumn("block", block).withColumn("part", F.pmod(F.xxhash64("i", "j"), F.lit(self.spread)))
            new = merged(both.repartition("block", "part"), "block", "part").drop("part")
            if touched:
                new.write.mode("overwrite").partitionBy("block").parquet(f"{self.path}/v{batch_id}")
        finally:
            fresh.unpersist()
        self._commit(batch_id, self.current | dict.fromkeys(touched, batch_id), self.schema or fresh.schema)


def apply_updates(updates: DataFrame, mode: str = "extend_add", store: VersionedStore | None = None) -> VersionedStore:
    """Run the stream of cells to its end and return the store with the last version."""
    spark = updates.sparkSession
    store = store or VersionedStore(spark)
    query = updates.writeStream.foreachBatch(lambda df, n: store.apply(df, n, mode)).option("checkpointLocation", f"{store.path}/checkpoint").trigger(availableNow=True).start()
    query.awaitTermination()
    return store


def run_to_table(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream to its end into files (append) or memory (complete) and read the result."""
    spark = stream.sparkSession
    name = f"s{uuid.uuid4().hex}"
    path = f"{shared_dir(spark)}/{name}"
    if mode == "append":
        query = stream.writeStream.format("parquet").option("path", f"{path}/data").option("checkpointLocation", f"{path}/checkpoint").trigger(availableNow=True).start()
        query.awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{path}/data")
    query = stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", f"{path}/checkpoint").trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.table(name)


def windowed_counts(stream: DataFrame, width: str = "1 day", late: str = "40 days") -> DataFrame:
    """(start, event_type, n) of tumbling windows."""
    return stream.withWatermark("ts", late).groupBy(F.window("ts", width).alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def deduplicated(stream: DataFrame, key: str = "event_id", late: str = "40 days") -> DataFrame:
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark([key])
