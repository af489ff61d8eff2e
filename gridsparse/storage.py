"""Written tables in the cluster's shared folder, for iterations and checked broadcasts."""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Rows up to which a side may be broadcast; beyond it plans shuffle.
BROADCAST_ROWS = 1_000_000


def shared_dir(spark) -> str:
    """``spark.checkpoint.dir`` of the session; one of our own only where it is unset."""
    return (spark.sparkContext.getConf().get("spark.checkpoint.dir") or "file:///tmp/checkpoints").rstrip("/")


_open: list[list[str]] = []


def _files(spark, path: str):
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), target


def settle(df: DataFrame, label: str = "matrix", by: str | None = None, **options) -> DataFrame:
    """Write ``df`` (in a folder per value of ``by``) and read it back: lineage ends at files that every executor can read."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
    for made in _open:
        made.append(path)
    (df.write.partitionBy(by) if by else df.write).options(**options).parquet(path)
    files, target = _files(spark, path)
    files.deleteOnExit(target)
    return spark.read.schema(df.schema).parquet(path)


@contextmanager
def scratch(spark) -> Iterator[None]:
    """Tables that ``settle`` writes inside are removed at the end: plans over them must have run by then."""
    _open.append(made := [])
    try:
        yield
    finally:
        _open.pop()
        for path in made:
            files, target = _files(spark, path)
            files.delete(target, True)
            files.cancelDeleteOnExit(target)


def is_small(df: DataFrame, rows: int = BROADCAST_ROWS) -> bool:
    """Whether ``df`` has at most ``rows`` rows, by one bounded count; rows here are a few numbers wide."""
    return df.limit(rows + 1).count() <= rows


def small(df: DataFrame, rows: int = BROADCAST_ROWS) -> DataFrame:
    """A broadcast hint if ``df`` has at most ``rows`` rows, else ``df``."""
    return F.broadcast(df) if is_small(df, rows) else df
