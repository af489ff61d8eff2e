"""A matrix held row by row in the state of a stream; the latest value of a cell wins."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridsparse.streaming.updates import run_to_table

STATE = "js array<long>, vs array<long>, ats array<long>"
CHANGES = "i long, part long, j long, v long, at long"


def _keep_latest(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
    """Merge a key's new cells into its row; yields the cells whose value is new."""
    js, vs, ats = state.get if state.exists else ([], [], [])
    rows = [pd.DataFrame({"j": list(js), "v": list(vs), "at": list(ats), "held": 1}, dtype="int64")]
    rows += [f[["j", "v", "at"]].assign(held=0) for f in frames]
    # of equal times the larger value wins; what is held wins over its own repeat
    row = pd.concat(rows).sort_values(["at", "v", "held"]).drop_duplicates("j", keep="last")
    state.update((row["j"].tolist(), row["v"].tolist(), row["at"].tolist()))
    fresh = row[row["held"] == 0]
    yield pd.DataFrame({"i": key[0], "part": key[1], "j": fresh["j"], "v": fresh["v"], "at": fresh["at"]})


def row_changes(cells: DataFrame, width: int = 1 << 16) -> DataFrame:
    """A stream of the cells (i, j, v, at) that changed, from a stream of updates (i, j, v, at).

    The state of a key is a run of ``width`` columns of one row, so that a row
    of any length is held in bounded pieces.  Updates with a null are dropped.
    """
    whole = cells.select(*(F.col(c).cast("long").alias(c) for c in ("i", "j", "v")), F.unix_micros(F.col("at").cast("timestamp")).alias("at")).dropna()
    keyed = whole.withColumn("part", F.floor(F.col("j") / width)).groupBy("i", "part")
    found = keyed.applyInPandasWithState(_keep_latest, CHANGES, STATE, "append", "NoTimeout")
    return found.select("i", "j", "v", F.timestamp_micros("at").alias("at"))


def row_store(cells: DataFrame, width: int = 1 << 16) -> DataFrame:
    """The matrix (i, j, v, at) after all updates of the stream: the last change of each cell."""
    changes = run_to_table(row_changes(cells, width))
    return changes.groupBy("i", "j").agg(F.max(F.struct("at", "v")).alias("m")).select("i", "j", "m.v", "m.at")
