"""Choosing strategies and association orders from exact product counts and entry counts."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from gridsparse.matrix import SparseMatrix
from gridsparse.operators import measures
from gridsparse.operators.layout import Grid

#: Entries up to which an operand counts as small enough to broadcast.
BROADCAST_ENTRIES = 200_000
#: Products of one cell of the grid, summed in one task.
CELL_PRODUCTS = 50_000_000


def grid_for(made: int, partitions: int) -> Grid:
    """A square grid with a cell at least for each of ``partitions`` tasks and for each ``CELL_PRODUCTS`` products."""
    side = math.ceil(math.sqrt(max(partitions, made / CELL_PRODUCTS)))
    return Grid(side, side)


def choose(a: SparseMatrix, b: SparseMatrix, grid: Grid | None = None) -> tuple[str, Grid | None]:
    """Compare rows moved: a small operand, left or right, is broadcast; else the inner join's N + F against the grid's copies."""
    na, nb = measures.nnz(a), measures.nnz(b)
    if min(na, nb) <= BROADCAST_ENTRIES:
        return ("broadcast" if nb <= na else "broadcast_left"), None
    made = measures.products(a, b)
    side = grid or grid_for(made, int(a.df.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    moved_inner = na + nb + made
    moved_grid = side.pc * na + side.pr * nb
    return ("grid", side) if moved_grid < moved_inner else ("inner", None)


def predict_structure(a: SparseMatrix, b: SparseMatrix, how: str = "exact_flops", share: float = 0.1) -> float:
    """Products (exact), or entries of the product by a distinct sketch, or by the uniform model d*d*n.

    The sketch forms the products of a ``share`` of A's rows only: rows of the
    product are disjoint, so entries grow with the rows' products, whose total is exact.
    """
    if how == "exact_flops":
        return float(measures.products(a, b))
    if how == "uniform":
        return measures.nnz(a) * measures.nnz(b) / max(1, a.n_cols)
    if how != "sketch":
        raise ValueError(f"unknown method {how}")
    rows = a.df.where(F.pmod(F.xxhash64("i"), F.lit(1000)) < int(1000 * share)).select("i", F.col("j").alias("k"))
    cells = rows.join(b.df.select(F.col("i").alias("k"), "j"), "k")
    entries, made = cells.agg(F.approx_count_distinct(F.struct("i", "j"), 0.02), F.count("*")).first()
    return entries * measures.products(a, b) / made if made else 0.0


def chain_order(matrices: list[SparseMatrix]):
    """The association of least estimated work: intermediate sizes by the uniform model, exact where both are leaves."""
    n = len(matrices)
    size = {(k, k): float(measures.nnz(m)) for k, m in enumerate(matrices)}
    cost: dict[tuple[int, int], float] = {(k, k): 0.0 for k in range(n)}
    tree: dict[tuple[int, int], object] = {(k, k): k for k in range(n)}
    for span in range(1, n):
        for i in range(n - span):
            j = i + span
            best = None
            for m in range(i, j):
                inner = max(1, matrices[m].n_cols)
                work = float(measures.products(matrices[m], matrices[j])) if i == m and m + 1 == j else size[i, m] * size[m + 1, j] / inner
                total = cost[i, m] + cost[m + 1, j] + work
                if best is None or total < best[0]:
                    best = total, work, (tree[i, m], tree[m + 1, j])
            cost[i, j], work, tree[i, j] = best
            size[i, j] = min(work, float(matrices[i].n_rows) * matrices[j].n_cols)
    return tree[0, n - 1]
