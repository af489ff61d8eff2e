"""Sub-matrix extraction, relabelling and the special cases; index vectors are tables (pos, idx)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridsparse.matrix import SparseMatrix
from gridsparse.operators import build, elementwise
from gridsparse.operators.layout import Grid, place_by_id
from gridsparse.operators.product import multiply
from gridsparse.semiring import Semiring
from gridsparse.storage import settle, small


def check_range(index: DataFrame, n: int) -> None:
    """Raise if an index lies outside [0, n) or is null."""
    if index.where(F.col("idx").isNull() | (F.col("idx") < 0) | (F.col("idx") >= n)).head(1):
        raise IndexError("an index is out of range")


def extract(a: SparseMatrix, rows: DataFrame | None, cols: DataFrame | None, lengths: tuple[int, int], via: str = "join", order: str = "auto", validate: bool = False) -> SparseMatrix:
    """A(I, J): row pos of the result is row I(pos), in the index vectors' order; repeats are allowed.

    ``None`` stands for all rows or columns.  'product' multiplies by selector
    matrices; 'join' is the same without the sums, since each result entry has
    one product.
    """
    if validate:
        for index, n in ((rows, a.n_rows), (cols, a.n_cols)):
            if index is not None:
                check_range(index, n)
    if order == "auto" and rows is not None and cols is not None:
        order = left_or_right(a, rows, cols)
    steps = ["rows", "cols"] if order != "right" else ["cols", "rows"]
    out = a
    for step in steps:
        index = rows if step == "rows" else cols
        if index is None:
            continue
        if via == "product":
            ring = Semiring.select_second() if step == "rows" else Semiring.select_first()
            length = lengths[0] if step == "rows" else lengths[1]
            out = multiply(build.row_selector(index, length, a.n_rows), out, semiring=ring) if step == "rows" else multiply(out, build.col_selector(index, length, a.n_cols), semiring=ring)
        else:
            out = _pick(out, index, "i" if step == "rows" else "j")
    return SparseMatrix(out.df.select("i", "j", "v"), lengths[0] if rows is not None else a.n_rows, lengths[1] if cols is not None else a.n_cols)


def _pick(a: SparseMatrix, index: DataFrame, axis: str) -> SparseMatrix:
    side = small(index.select(F.col("idx").alias(axis), "pos"))
    return a.with_df(a.df.join(side, axis).drop(axis).withColumnRenamed("pos", axis))


def left_or_right(a: SparseMatrix, rows: DataFrame, cols: DataFrame) -> str:
    """The association whose intermediate has fewer entries."""
    def reach(axis, index):
        d = elementwise.degrees(a, axis).withColumnRenamed("i", "idx")
        return index.join(d, "idx").agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]

    return "left" if reach("rows", rows) <= reach("cols", cols) else "right"


def row(a: SparseMatrix, i: int) -> DataFrame:
    return a.df.where(F.col("i") == i).select("j", "v")


def column(a: SparseMatrix, j: int) -> DataFrame:
    return a.df.where(F.col("j") == j).select("i", "v")


def element(a: SparseMatrix, i: int, j: int) -> DataFrame:
    return a.df.where((F.col("i") == i) & (F.col("j") == j)).select("v")


def window(a: SparseMatrix, i0: int, i1: int, j0: int, j1: int) -> SparseMatrix:
    """Rows i0 to i1 - 1 and columns j0 to j1 - 1, re-based: a pushed-down filter."""
    inside = a.df.where(F.col("i").between(i0, i1 - 1) & F.col("j").between(j0, j1 - 1))
    return SparseMatrix(inside.select((F.col("i") - i0).alias("i"), (F.col("j") - j0).alias("j"), "v"), i1 - i0, j1 - j0)


def induced_subgraph(a: SparseMatrix, index: DataFrame, length: int, **options) -> SparseMatrix:
    return extract(a, index, index, (length, length), **options)


def permute(a: SparseMatrix, row_perm: DataFrame, col_perm: DataFrame, **options) -> SparseMatrix:
    """Relabel rows and columns by permutations."""
    return extract(a, row_perm, col_perm, a.shape, order=options.pop("order", "left"), **options)


def permute_closed(a: SparseMatrix, new_row, new_col) -> SparseMatrix:
    """Relabel by expressions old id -> new id: a projection, no join."""
    return a.with_df(a.df.select(new_row(F.col("i")).alias("i"), new_col(F.col("j")).alias("j"), "v"))


def permute_by_map(a: SparseMatrix, perm: DataFrame) -> SparseMatrix:
    """Baseline: build the position map and export every entry through it, two full shuffles."""
    where = perm.select(F.col("idx").alias("old"), F.col("pos").alias("new"))
    rows = a.df.hint("shuffle_hash").join(where, F.col("i") == F.col("old")).select(F.col("new").alias("i"), "j", "v")
    return a.with_df(rows.hint("shuffle_hash").join(where, F.col("j") == F.col("old")).select("i", F.col("new").alias("j"), "v"))


def extract_many(a: SparseMatrix, chunked: DataFrame, k: int, sequential: bool = False) -> DataFrame:
    """The subgraphs of k disjoint index vectors (chunk, pos, idx): rows (chunk, i, j, v).

    One after another reads the matrix k times, each result written before the
    next begins; together it is one scan and two lookups.
    """
    if sequential:
        out = None
        for c in range(k):
            index = chunked.where(F.col("chunk") == c).select("pos", "idx")
            part = settle(extract(a, index, index, a.shape, order="left").df.select(F.lit(c).alias("chunk"), "i", "j", "v"), "subgraph")
            out = part if out is None else out.unionByName(part)
        return out
    side = small(chunked)
    rows = side.select(F.col("idx").alias("i"), F.col("chunk"), F.col("pos").alias("new_i"))
    cols = side.select(F.col("idx").alias("j"), F.col("chunk").alias("chunk_j"), F.col("pos").alias("new_j"))
    both = a.df.join(rows, "i").join(cols, "j").where("chunk = chunk_j")
    return both.select("chunk", F.col("new_i").alias("i"), F.col("new_j").alias("j"), "v")


def scatter_index(index: DataFrame, length: int, m: int, grid: Grid) -> DataFrame:
    """A row selector's entries with their cell, placed there: one small shuffle."""
    selector = build.row_selector(index, length, m)
    cell = grid.row_block(F.col("i"), length) * grid.pc + grid.col_block(F.col("j"), m)
    return place_by_id(selector.df.withColumn("cell", cell.cast("int")), grid.cells, "cell")
