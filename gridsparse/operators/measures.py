"""Cost measures: entries, products, words moved, balance, and the paper-style closed forms."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridsparse.matrix import SparseMatrix
from gridsparse.operators.elementwise import degrees
from gridsparse.operators.layout import Grid


def nnz(a: SparseMatrix) -> int:
    return a.df.count()


def inner_degrees(a: SparseMatrix, b: SparseMatrix) -> DataFrame:
    """(k, na, nb) of the inner indices present on both sides."""
    cols = degrees(a, "cols").select(F.col("i").alias("k"), F.col("n").alias("na"))
    return cols.join(degrees(b, "rows").select(F.col("i").alias("k"), F.col("n").alias("nb")), "k")


def product_stats(a: SparseMatrix, b: SparseMatrix) -> DataFrame:
    """One row: products (multiplies), flops2 (multiply and add), ni (inner indices on both sides)."""
    made = F.coalesce(F.sum(F.col("na") * F.col("nb")), F.lit(0)).cast("long")
    return inner_degrees(a, b).agg(made.alias("products"), (2 * made).alias("flops2"), F.count("*").alias("ni"))


def products(a: SparseMatrix, b: SparseMatrix) -> int:
    return product_stats(a, b).first()["products"]


def flops2(a: SparseMatrix, b: SparseMatrix) -> int:
    return 2 * products(a, b)


def chain_products(a: SparseMatrix, b: SparseMatrix, c: SparseMatrix) -> dict[str, int]:
    """Products of (AB)C and of A(BC), intermediates by their patterns."""
    from gridsparse.operators.product import multiply
    from gridsparse.semiring import Semiring

    pair = Semiring.any_pair()
    left, right = multiply(a, b, semiring=pair), multiply(b, c, semiring=pair)
    return {"left": products(a, b) + products(left, c), "right": products(b, c) + products(a, right)}


def nzc_nzr(a: SparseMatrix) -> DataFrame:
    """One row: nonempty columns and rows."""
    return a.df.agg(F.count_distinct("j").alias("nzc"), F.count_distinct("i").alias("nzr"))


def compression(a: SparseMatrix, b: SparseMatrix, c: SparseMatrix | None = None) -> float:
    """Products over entries of the product."""
    from gridsparse.operators.product import multiply

    return products(a, b) / max(1, nnz(c or multiply(a, b)))


def comm_words(a: SparseMatrix, b: SparseMatrix, grid: Grid) -> DataFrame:
    """(cell, words): entries that each cell of the grid product receives."""
    left = a.df.groupBy(grid.row_block(F.col("i"), a.n_rows).alias("br")).count().withColumn("bc", F.explode(F.sequence(F.lit(0), F.lit(grid.pc - 1))))
    right = b.df.groupBy(grid.col_block(F.col("j"), b.n_cols).alias("bc")).count().withColumn("br", F.explode(F.sequence(F.lit(0), F.lit(grid.pr - 1))))
    both = left.select("br", "bc", "count").unionByName(right.select("br", "bc", "count"))
    return both.groupBy((F.col("br") * grid.pc + F.col("bc")).cast("int").alias("cell")).agg(F.sum("count").alias("words"))


def stage_cells(a: SparseMatrix, b: SparseMatrix, grid: Grid, block: int) -> DataFrame:
    """(br, bc, stage, nzc, nzr, products, ni) of each cell and stage with work."""
    stage = lambda k: F.floor(F.col(k) / block).cast("int").alias("stage")
    left = a.df.groupBy(grid.row_block(F.col("i"), a.n_rows).alias("br"), F.col("j").alias("k")).agg(F.count("*").alias("na"))
    right = b.df.groupBy(grid.col_block(F.col("j"), b.n_cols).alias("bc"), F.col("i").alias("k")).agg(F.count("*").alias("nb"))
    nzc = left.groupBy("br", stage("k")).agg(F.count("*").alias("nzc"))
    nzr = right.groupBy("bc", stage("k")).agg(F.count("*").alias("nzr"))
    work = left.join(right, "k").groupBy("br", "bc", stage("k")).agg(F.sum(F.col("na") * F.col("nb")).alias("products"), F.count("*").alias("ni"))
    return work.join(nzc, ["br", "stage"]).join(nzr, ["bc", "stage"])


def stage_cost(a: SparseMatrix, b: SparseMatrix, grid: Grid, block: int) -> DataFrame:
    """(br, bc, cost): the hypersparse kernel's cost summed over stages, nzc + nzr + products * lg(ni)."""
    cost = F.col("nzc") + F.col("nzr") + F.col("products") * F.log2(F.greatest(F.col("ni"), F.lit(2)))
    return stage_cells(a, b, grid, block).groupBy("br", "bc").agg(F.sum(cost).alias("cost"))


def imbalance(a: SparseMatrix, grid: Grid) -> DataFrame:
    """One row: the fullest cell and the total; their quotient times the cells is the imbalance."""
    cells = a.df.groupBy(grid.row_block(F.col("i"), a.n_rows).alias("br"), grid.col_block(F.col("j"), a.n_cols).alias("bc")).agg(F.count("*").alias("n"))
    return cells.agg(F.max("n").alias("most"), F.sum("n").alias("total"), F.lit(grid.cells).cast("long").alias("cells"))


def window_share(a: SparseMatrix, index: DataFrame) -> DataFrame:
    """One row: vertices and entries of the window that the index vector selects on both sides."""
    ids = index.select("idx").distinct()
    inside = a.df.join(ids.withColumnRenamed("idx", "i"), "i", "left_semi").join(ids.withColumnRenamed("idx", "j"), "j", "left_semi")
    return inside.agg(F.count("*").alias("entries")).crossJoin(ids.agg(F.count("*").alias("vertices")))


def nnz_shrink(a: SparseMatrix, coarse: SparseMatrix) -> float:
    return nnz(coarse) / max(1, nnz(a))


def degree_stats(a: SparseMatrix, axis: str = "rows") -> DataFrame:
    """One row: nonempty lines, the largest and the total degree, and quantiles."""
    d = degrees(a, axis)
    return d.agg(F.count("*").alias("lines"), F.max("n").alias("most"), F.sum("n").alias("total"), F.expr("percentile_approx(n, array(0.5, 0.9, 0.99), 1000)").alias("quantiles"))


def structure_error(estimate: float, exact: float) -> float:
    return abs(estimate / exact - 1)


# -- closed forms, in units of one flop ------------------------------------------
def comm_model(p: int, nnz_a: float, nnz_b: float, alpha: float, beta: float) -> float:
    """Grid product: sqrt(p) stages of two messages and the cell's share of both operands."""
    return math.sqrt(p) * (2 * alpha + beta * (nnz_a + nnz_b) / p)


def comp_model(p: int, n: float, d: float) -> float:
    """Grid product: reading the slabs, and merging d*d*n/p products."""
    share = max(2.0, d * d * n / p)
    return d * n / math.sqrt(p) + share * math.log2(share)


def extract_model(p: int, n_entries: float, rows: float, cols: float, alpha: float, beta: float) -> dict[str, float]:
    side = math.sqrt(p)
    merge = math.log2(max(2.0, (rows + cols) / p + side))
    return {"comp": (rows + cols + n_entries) / side + n_entries / p * merge, "comm": alpha * side + beta * (n_entries + rows + cols) / side}


def scatter_model(p: int, length: float, alpha: float, beta: float) -> float:
    """Dealing an index vector along the diagonal."""
    return alpha * math.log2(max(2, p)) + beta * length / math.sqrt(p)


def row_select_model(p: int, n_entries: float, rows: float, alpha: float, beta: float) -> dict[str, float]:
    """Taking whole rows by a selector product: one side of ``extract_model``."""
    side = math.sqrt(p)
    return {"comp": (rows + n_entries) / side + n_entries / p * math.log2(max(2.0, rows / p + side)), "comm": alpha * side + beta * (n_entries + rows) / side}


def assign_model(nnz_a: float, nnz_b: float, rows: float, cols: float) -> float:
    return nnz_a + nnz_b + rows + cols


def dense_flops(m: int, k: int, n: int) -> int:
    return 2 * m * k * n


def useful_rate(flops: float, seconds: float) -> float:
    return flops / max(seconds, 1e-9)


def speedup(t1: float, tp: float) -> float:
    return t1 / tp


def efficiency(t1: float, tp: float, p: int) -> float:
    return t1 / tp / p


def loglog_slope(cores: list[int], speedups: list[float]) -> float:
    """Least-squares slope of log speedup over log cores."""
    x, y = [math.log(c) for c in cores], [math.log(s) for s in speedups]
    mx, my = sum(x) / len(x), sum(y) / len(y)
    return sum((a - mx) * (b - my) for a, b in zip(x, y, strict=True)) / sum((a - mx) ** 2 for a in x)


def weak_scaling_row(d1: float, d2: float, n: int, k: int, p: int) -> dict[str, float]:
    """Work, memory and bandwidth of the tall-skinny experiment at p tasks."""
    memory = d1 * n + d2 * k
    return {"work": d1 * d2 * k, "memory": memory, "bandwidth": memory * math.sqrt(p)}


# -- measured phases ---------------------------------------------------------------
def _stages(spark, after: int) -> list:
    """The status store's stages of an id above ``after``."""
    sc = spark.sparkContext
    jvm = sc._jvm
    sc._jsc.sc().listenerBus().waitUntilEmpty()
    found = sc._jsc.sc().statusStore().stageList(None, False, False, sc._gateway.new_array(jvm.double, 0), jvm.java.util.ArrayList())
    return [s for k in range(found.size()) if (s := found.apply(k)).stageId() > after]


def phase_breakdown(spark, action) -> dict[str, float]:
    """Run ``action`` and split its tasks' seconds: computing, waiting for and writing shuffled data, collecting garbage; also megabytes moved and spilled, the most memory that a stage's tasks held, and whether it ran out of memory."""
    last = max((s.stageId() for s in _stages(spark, -1)), default=-1)
    short = False
    try:
        action()
    except Exception as error:
        if "OutOfMemory" not in str(error) and "MEMORY" not in str(error):
            raise
        short = True
    done = _stages(spark, last)
    run, wait, write, gc = (sum(f(s) for s in done) / u for f, u in ((lambda s: s.executorRunTime(), 1e3), (lambda s: s.shuffleFetchWaitTime(), 1e3), (lambda s: s.shuffleWriteTime(), 1e9), (lambda s: s.jvmGcTime(), 1e3)))
    moved, spilled = sum(s.shuffleWriteBytes() for s in done) / 1e6, sum(s.diskBytesSpilled() for s in done) / 1e6
    return {"compute_s": max(0.0, run - wait - write - gc), "wait_s": wait, "write_s": write, "gc_s": gc, "moved_mb": moved, "spilled_mb": spilled, "peak_mb": max((s.peakExecutionMemory() for s in done), default=0) / 1e6, "out_of_memory": float(short)}
