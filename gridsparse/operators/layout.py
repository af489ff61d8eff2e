"""Block grids, packed storage and its sizes."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gridsparse.matrix import SparseMatrix
from gridsparse.storage import is_small


@dataclass(frozen=True)
class Grid:
    """A pr x pc grid, with ``inner`` splits of the inner index for products in three dimensions.

    'range' blocks are runs of indices; 'hash' cells deal indices out by a hash
    (other salts for rows and columns, so a heavy diagonal spreads).
    """

    pr: int
    pc: int
    inner: int = 1
    layout: str = "range"

    def row_block(self, i: Column, m: int) -> Column:
        return self._block(i, m, self.pr, 1)

    def col_block(self, j: Column, n: int) -> Column:
        return self._block(j, n, self.pc, 2)

    def inner_block(self, k: Column, size: int) -> Column:
        return self._block(k, size, self.inner, 3)

    def _block(self, x: Column, size: int, parts: int, salt: int) -> Column:
        if self.layout == "hash":
            return F.pmod(F.xxhash64(x, F.lit(salt)), F.lit(parts)).cast("int")
        return F.floor(x / F.lit(max(1, -(-size // parts)))).cast("int")

    @property
    def cells(self) -> int:
        return self.pr * self.pc


def stage_owner(stage: int, block: int, inner: int, parts: int) -> int:
    """The grid column (or row) that owns the first index of a stage, for ``parts`` blocks of the inner range."""
    return (stage * block) // -(-inner // parts)


def stages(inner: int, block: int) -> int:
    return -(-inner // block)


def place_by_id(df: DataFrame, parts: int, cell: str) -> DataFrame:
    """One partition per cell: by partition id where the session has it, else by hash."""
    if hasattr(df, "repartitionById"):
        return df.repartitionById(parts, F.col(cell))
    return df.repartition(parts, cell)


def to_blocks(a: SparseMatrix, grid: Grid) -> DataFrame:
    """Entries with br, bc and cell, partitioned by cell: one shuffle."""
    df = a.df.withColumn("br", grid.row_block(F.col("i"), a.n_rows)).withColumn("bc", grid.col_block(F.col("j"), a.n_cols))
    df = df.withColumn("cell", F.col("br") * grid.pc + F.col("bc"))
    return place_by_id(df, grid.cells, "cell")


def row_blocks(a: SparseMatrix, parts: int) -> DataFrame:
    """Entries with their row block rb, partitioned by it."""
    return a.df.withColumn("rb", F.floor(F.col("i") / max(1, -(-a.n_rows // parts))).cast("int")).repartition(parts, "rb")


PACKED = "br int, bc int, jc array<long>, cp array<long>, ir array<long>, num array<double>, aux array<long>"


def pack_dcsc(a: SparseMatrix, grid: Grid, aux: bool = False) -> DataFrame:
    """One row per non-empty block: nonempty columns, their pointers, row ids and values, global ids.

    ``aux`` adds, for equal ranges of the block's columns, the first pointer at or after each range.
    """
    width = max(1, -(-a.n_cols // grid.pc))

    def pack(table: pa.Table) -> pa.Table:
        i, j, v = (table.column(c).to_numpy() for c in ("i", "j", "v"))
        order = np.lexsort((i, j))
        i, j, v = i[order], j[order], v[order]
        jc, first = np.unique(j, return_index=True)
        cp = np.append(first, len(j))
        look = np.searchsorted(jc, jc[0] // width * width + np.arange(0, width + 1, max(1, width // max(1, len(jc))))) if aux else None
        one = lambda x, t: pa.array([x], pa.list_(t))
        return pa.table({"br": table.column("br").slice(0, 1), "bc": table.column("bc").slice(0, 1), "jc": one(jc, pa.int64()), "cp": one(cp, pa.int64()), "ir": one(i, pa.int64()), "num": one(v.astype(float), pa.float64()), "aux": one(look, pa.int64())})

    return to_blocks(a, grid).groupBy("br", "bc").applyInArrow(pack, PACKED)


def unpack_dcsc(packed: DataFrame, shape: tuple[int, int]) -> SparseMatrix:
    """Back to triples, with array functions only."""
    columns = packed.select("cp", "ir", "num", F.posexplode("jc").alias("at", "j"))
    runs = columns.select("j", F.expr("slice(ir, cast(cp[at] as int) + 1, cast(cp[at + 1] - cp[at] as int))").alias("ir"), F.expr("slice(num, cast(cp[at] as int) + 1, cast(cp[at + 1] - cp[at] as int))").alias("num"))
    cells = runs.select("j", F.explode(F.arrays_zip("ir", "num")).alias("e"))
    return SparseMatrix(cells.select(F.col("e.ir").alias("i"), "j", F.col("e.num").alias("v")), *shape)


def pack_csc(a: SparseMatrix, base: int = 0) -> tuple[list[int], list[int], list]:
    """Dense column pointers, row ids and values of a small matrix (driver side, for baselines and fixtures)."""
    if a.n_cols > 1_000_000 or not is_small(a.df):
        raise ValueError("column pointers are for small matrices")
    rows = sorted((r["j"], r["i"], r["v"]) for r in a.df.collect())
    counts = np.bincount([r[0] for r in rows], minlength=a.n_cols) if rows else np.zeros(a.n_cols, int)
    return (np.concatenate(([0], np.cumsum(counts))) + base).tolist(), [r[1] + base for r in rows], [r[2] for r in rows]


def dcsc_column(block: dict, j: int) -> list[tuple[int, float]]:
    """Entries of a column of a packed block, by binary search among the nonempty columns."""
    at = int(np.searchsorted(block["jc"], j))
    if at == len(block["jc"]) or block["jc"][at] != j:
        return []
    a, b = block["cp"][at], block["cp"][at + 1]
    return list(zip(block["ir"][a:b], block["num"][a:b], strict=True))


def dcsc_column_range(block: dict, low: int, high: int) -> list[tuple[int, int, float]]:
    """Entries (i, j, v) of columns low to high - 1: two searches and a slice."""
    first, last = (int(x) for x in np.searchsorted(block["jc"], [low, high]))
    return [(block["ir"][e], block["jc"][c], block["num"][e]) for c in range(first, last) for e in range(block["cp"][c], block["cp"][c + 1])]


def block_counts(a: SparseMatrix, grid: Grid) -> DataFrame:
    """(br, bc, nnz, nzc) of the non-empty blocks, by two aggregations of partial counts."""
    cells = a.df.select(grid.row_block(F.col("i"), a.n_rows).alias("br"), grid.col_block(F.col("j"), a.n_cols).alias("bc"), "j")
    columns = cells.groupBy("br", "bc", "j").agg(F.count("*").alias("n"))
    return columns.groupBy("br", "bc").agg(F.sum("n").alias("nnz"), F.count("*").alias("nzc"))


def storage_words(a: SparseMatrix, grid: Grid) -> DataFrame:
    """One row: words of column pointers over all blocks, of doubly compressed blocks, and of triples."""
    width = -(-a.n_cols // grid.pc)
    total = block_counts(a, grid).agg(F.coalesce(F.sum("nnz"), F.lit(0)).alias("nnz"), F.coalesce(F.sum("nzc"), F.lit(0)).alias("nzc"), F.count("*").alias("blocks"))
    csc = F.lit(grid.cells * (width + 1)) + 2 * F.col("nnz")
    return total.select(csc.cast("long").alias("csc_words"), (2 * F.col("nzc") + F.col("blocks") + 2 * F.col("nnz")).cast("long").alias("dcsc_words"), (3 * F.col("nnz")).cast("long").alias("triples_words"))


def hypersparsity(a: SparseMatrix, grid: Grid) -> DataFrame:
    """Per non-empty block its entries over its number of columns, in thousandths, rounded down."""
    width = -(-a.n_cols // grid.pc)
    return block_counts(a, grid).select("br", "bc", "nnz", F.expr(f"nnz * 1000 div {width}").alias("per_mille"))
