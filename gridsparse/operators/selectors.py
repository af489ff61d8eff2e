"""Selectors formed on a grid from index vectors that its cells hold, and the words that this moves."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridsparse.operators import build
from gridsparse.operators.layout import Grid, place_by_id


def located(index: DataFrame, length: int, m: int, grid: Grid, source: str = "diagonal") -> DataFrame:
    """A row selector's entries (i, j, v) with home, the cell that holds this index, and cell, which wants the entry.

    'diagonal': run k of the vector is held by cell (k, k), and a scatter along
    row k of the cells forms the selector; the grid must be square.  'all':
    every cell holds an equal run, and the cells exchange all-to-all.
    """
    if source not in ("diagonal", "all"):
        raise ValueError(f"no such source: {source}")
    if source == "diagonal" and grid.pr != grid.pc:
        raise ValueError("a diagonal needs a square grid")
    row, col = grid.row_block(F.col("i"), length), grid.col_block(F.col("j"), m)
    home = row * grid.pc + row if source == "diagonal" else F.floor(F.col("i") / max(1, -(-length // grid.cells)))
    return build.row_selector(index, length, m).df.select("i", "j", "v", home.cast("int").alias("home"), (row * grid.pc + col).cast("int").alias("cell"))


def scatter(index: DataFrame, length: int, m: int, grid: Grid, source: str = "diagonal") -> DataFrame:
    """The row selector, placed by cell: one shuffle of the index vector, whichever cells hold it."""
    return place_by_id(located(index, length, m, grid, source), grid.cells, "cell")


def exchanged(index: DataFrame, length: int, n: int, grid: Grid, source: str = "diagonal") -> DataFrame:
    """A column selector's entries (n x length): the row selector of the same vector, each cell (r, c) sent to (c, r).

    home is here the cell of the row selector and cell the one across the diagonal.
    """
    if grid.pr != grid.pc:
        raise ValueError("an exchange across the diagonal needs a square grid")
    over = F.col("cell") % grid.pc * grid.pc + F.floor(F.col("cell") / grid.pc)
    return located(index, length, n, grid, source).select(F.col("j").alias("i"), F.col("i").alias("j"), "v", F.col("cell").alias("home"), over.cast("int").alias("cell"))


def exchange(index: DataFrame, length: int, n: int, grid: Grid, source: str = "diagonal") -> DataFrame:
    """The column selector, placed by cell."""
    return place_by_id(exchanged(index, length, n, grid, source), grid.cells, "cell")


def words(entries: DataFrame) -> DataFrame:
    """Per receiving cell its entries and those that came from another cell."""
    return entries.groupBy("cell").agg(F.count("*").alias("received"), F.count_if(F.col("home") != F.col("cell")).alias("moved"))
