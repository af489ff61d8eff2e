"""The experiment workloads on the given tables and on generated graphs.

``run(spark, sf_dir, wid)`` gives (metric, value) rows: counts that must not
depend on the method, and seconds where methods are compared.  Each timed plan
is written to the no-op sink.  ``counts(spark, sf_dir, wid)`` runs the counts of
a workload only, without timing a plan.
"""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridsparse.functions import permutations as perms
from gridsparse.matrix import SparseMatrix
from gridsparse.operators import assign, baselines, contract, graph, indexing, layout, measures, product
from gridsparse.operators.layout import Grid
from gridsparse.sources import generators
from gridsparse.sources.tables import Tables
from gridsparse.storage import scratch, settle


TIMED = True


def seconds(plan: DataFrame | Callable[[], DataFrame]) -> float:
    """Seconds to run a plan; a function that makes it is timed as well, where making it runs jobs (loops)."""
    if not TIMED:
        return 0.0
    start = time.time()
    df = plan() if callable(plan) else plan
    df.write.format("noop").mode("overwrite").save()
    return time.time() - start


def kept(m: SparseMatrix) -> SparseMatrix:
    return m.with_df(settle(m.df))


def _md5(t: Tables) -> DataFrame:
    return settle(perms.md5_rank(t.table("part").select(F.col("p_partkey").alias("idx"))))


def relabel(t: Tables) -> dict:
    """Random symmetric relabelling of the table graph and of a generated one: by joins, by expression, by map."""
    h, p = kept(t.co_purchase()), _md5(t)
    new = lambda x: perms.affine_inverse(x, t.parts)
    g = kept(generators.rmat(t.spark, 12))
    q = settle(perms.random_permutation(t.spark, g.n_rows))
    moved = indexing.permute(h, p, p)
    return {"nnz": measures.nnz(moved), "s_join": seconds(moved.df), "s_map": seconds(indexing.permute_by_map(h, p).df), "s_closed": seconds(indexing.permute_closed(h, new, new).df), "rmat_nnz": measures.nnz(indexing.permute(g, q, q)), "rmat_s_join": seconds(indexing.permute(g, q, q).df), "rmat_s_map": seconds(indexing.permute_by_map(g, q).df)}


def subgraphs(t: Tables) -> dict:
    """Ten disjoint induced subgraphs, one after another and together."""
    h, c = kept(t.co_purchase()), perms.chunks(_md5(t), t.parts, 10)
    many = indexing.extract_many(h, c, 10)
    return {"nnz": many.count(), "expected": measures.nnz(h) / 10, "s_sequential": seconds(lambda: indexing.extract_many(h, c, 10, True)), "s_batched": seconds(many)}


def replace_window(t: Tables) -> dict:
    """Windows of a half, a quarter and an eighth of the vertices replaced by blocks of like density."""
    out, n = {}, t.parts
    h, p = kept(t.co_purchase()), _md5(t)
    new = lambda x: perms.affine_inverse(x, n)
    other = indexing.permute_closed(h, new, new)
    for share in (2, 4, 8):
        w = settle(perms.head(p, n // share))
        block = kept(indexing.induced_subgraph(other, w, n // share))
        done = assign.assign(h, w, w, block)
        inside = measures.window_share(h, w).first()
        out |= {f"edge_share_1_{share}": inside["entries"] / measures.nnz(h), f"nnz_balance_1_{share}": measures.nnz(done) - (measures.nnz(h) - inside["entries"] + measures.nnz(block)), f"s_join_1_{share}": seconds(done.df), f"s_product_1_{share}": seconds(assign.assign(h, w, w, block, via="product").df)}
    return out


def square(t: Tables) -> dict:
    """Squares: entries, products, compression; table graph, user hops, and generated graphs under both relabellings."""
    out = {}
    cases = {"parts": (h := kept(t.co_purchase()), h), "users": (u := kept(t.user_hop()), u)}
    for scale in (10, 12, 14):
        for how in ("independent", "shared"):
            a, b = (kept(generators.rmat(t.spark, scale, seed=s, relabel=how)) for s in (1, 2))
            cases[f"rmat{scale}_{how}"] = a, b
    for name, (a, b) in cases.items():
        c = kept(a.multiply(b))
        made, entries = measures.products(a, b), measures.nnz(c)
        out |= {f"{name}_nnz": measures.nnz(a), f"{name}_products": made, f"{name}_nnz_c": entries, f"{name}_flops2_per_entry": 2 * made / max(1, entries), f"{name}_uniform": measures.nnz(a) * measures.nnz(b) / a.n_cols}
    return out


def _scratched(t: Tables, action):
    """``action()``, after which the slabs that it wrote are removed."""
    with scratch(t.spark):
        return action()


def stage_sizes(t: Tables) -> dict:
    """Whole- and half-block stages on a 4 x 4 grid, with the phases of each: the table graph's square, customers by suppliers times its transpose."""
    out = {}
    h, c = kept(t.co_purchase()), kept(t.cust_supp())
    for name, (a, b) in {"parts": (h, h), "customers": (c, c.transpose())}.items():
        width = -(-a.n_cols // 4)
        out[f"{name}_products"] = measures.products(a, b)
        for size, block in (("whole", width), ("half", -(-width // 2))):
            cost = measures.stage_cost(a, b, Grid(4, 4), block).agg(F.sum("cost"), F.max("cost")).first()
            out |= {f"{name}_model_{size}": cost[0], f"{name}_most_{size}": cost[1], f"s_{name}_{size}": _scratched(t, lambda: seconds(lambda: a.multiply(b, mode="loop", block=block, kernel="tiled").df))}  # noqa: B023
            if TIMED:
                phases = measures.phase_breakdown(t.spark, lambda: _scratched(t, lambda: seconds(lambda: a.multiply(b, mode="loop", strategy="grid", grid=Grid(4, 4), block=block, kernel="tiled").df)))  # noqa: B023
                out |= {f"s_{name}_{size}_{k}": v for k, v in phases.items()}
    return out


def restrict(t: Tables) -> dict:
    """The right restriction of orders 2, 4, 8: as many products as entries, whatever the order."""
    out = {}
    for name, m in {"parts": t.co_purchase(), "orders": t.order_part()}.items():
        h = kept(m)
        out[f"{name}_nnz"] = measures.nnz(h)
        for order in (2, 4, 8):
            s = t.restriction(order)
            out |= {f"{name}_products_{order}": measures.products(h, s.transpose()), f"{name}_nnz_{order}": measures.nnz(contract.restrict_right(h, s)), f"s_{name}_{order}": seconds(contract.restrict_right(h, s).df)}
    return out


def triple(t: Tables) -> dict:
    """The full restriction of order 8 in both associations and fused, of the sparse and the full co-purchase graph."""
    out, s = {}, t.restriction(8)
    for name, returned in (("parts", True), ("all", False)):
        h = kept(t.co_purchase(returned))
        out |= {f"{name}_nnz": measures.nnz(contract.contract(h, s))} | {f"s_{name}_{o}": seconds(contract.contract(h, s, o).df) for o in ("left", "right", "fused")}
        out |= {f"{name}_products_{k}": v for k, v in measures.chain_products(s, h, s.transpose()).items()}
    return out


def diagonal_split(t: Tables) -> dict:
    """The order-2 triple product of a full-diagonal matrix, with and without the split; cell balance and shrinking."""
    a, s = kept(t.part_diag()), t.restriction(2)
    _, rest = product.split_diagonal(a)
    balance = lambda m: (lambda r: r["most"] * r["cells"] / r["total"])(measures.imbalance(m, Grid(4, 4)).first())
    coarse = contract.galerkin(a, s)
    return {"shrink": measures.nnz_shrink(a, coarse), "imbalance": balance(a), "imbalance_split": balance(rest), "s_split": seconds(coarse.df), "s_plain": seconds(contract.galerkin(a, s, False).df)}


def tall_skinny(t: Tables) -> dict:
    """Graphs times tall operands of growing density and an n-th of 128 as wide; then weak scaling at n / p and k / p fixed, times over the first."""
    out = {}
    for name, a in {"parts": kept(t.co_purchase()), "rmat13": kept(generators.rmat(t.spark, 13))}.items():
        wide = max(2, a.n_cols // 128)
        for d in (1, 10, 100, 1000):
            if d > a.n_cols:
                continue
            b = kept(generators.erdos_renyi(t.spark, a.n_cols, wide, d))
            out |= {f"s_nnz_{name}_{d}": measures.nnz(b), f"s_products_{name}_{d}": measures.products(a, b), f"s_{name}_{d}": seconds(a.multiply(b).df)}
    first = None
    for p in (1, 2, 4, 8):
        scale, wide, d = 11 + p.bit_length() - 1, 16 * p, 10
        a = kept(generators.rmat(t.spark, scale))
        b = kept(generators.erdos_renyi(t.spark, a.n_cols, wide, d))
        a, b = (m.with_df(settle(m.df.repartition(p))) for m in (a, b))
        took = _with_tasks(t.spark, p, lambda: seconds(a.multiply(b).df))  # noqa: B023
        first = first or took
        model = measures.weak_scaling_row(8, d, a.n_cols, wide, p)
        out |= {f"s_weak_{p}": took, f"s_weak_over_first_{p}": took / max(first, 1e-9), f"weak_bandwidth_{p}": model["bandwidth"], f"weak_work_{p}": model["work"]}
    return out


def _with_tasks(spark: SparkSession, tasks: int, action):
    """``action()`` with ``tasks`` shuffle partitions (a setting of the running session, put back after)."""
    before = {k: spark.conf.get(k) for k in ("spark.sql.shuffle.partitions", "spark.sql.adaptive.coalescePartitions.enabled")}
    spark.conf.set("spark.sql.shuffle.partitions", str(tasks))
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")
    try:
        return action()
    finally:
        for k, v in before.items():
            spark.conf.set(k, v)


def strong_scaling(t: Tables) -> dict:
    """The table graph's square with 1, 2, 4 and 8 tasks: seconds, speed-ups over one processor's kernel, efficiencies, log-log slope; as many cores must be free."""
    h = kept(t.co_purchase())
    out = {"products": measures.products(h, h), "s_one_kernel": seconds(baselines.one_processor(h, h).df)}
    cores, ups = [1, 2, 4, 8], []
    for p in cores:
        m = h.with_df(settle(h.df.repartition(p)))
        out[f"s_{p}"] = _with_tasks(t.spark, p, lambda: min(seconds(m.multiply(m).df) for _ in range(2)))  # noqa: B023
        ups.append(measures.speedup(out["s_1"], max(out[f"s_{p}"], 1e-9)) if TIMED else 1.0)
        out |= {f"s_speedup_{p}": ups[-1], f"s_efficiency_{p}": ups[-1] / p}
    out["s_slope"] = measures.loglog_slope(cores, ups)
    out["s_useful_rate"] = measures.useful_rate(2 * out["products"], out["s_8"]) if TIMED else 0.0
    return out


def methods(t: Tables) -> dict:
    """One square by every strategy, kernel and merge; speed-ups over the row-distributed baseline."""
    h = kept(t.co_purchase())
    plans = {
        "inner": {}, "grid": {"strategy": "grid", "grid": Grid(4, 4)}, "rowwise_1d": {"strategy": "rowwise_1d"}, "broadcast": {"strategy": "broadcast"}, "loop": {"mode": "loop", "grid": Grid(4, 4)},
        "loop_eager": {"mode": "loop", "grid": Grid(4, 4), "merge": "eager"}, "outer_kernel": {"strategy": "grid", "grid": Grid(4, 4), "kernel": "outer"}, "columnwise_kernel": {"strategy": "grid", "grid": Grid(4, 4), "kernel": "columnwise"},
    }
    plans |= {"loop_threshold": {"mode": "loop", "grid": Grid(4, 4), "merge": "threshold", "every": 2}, "loop_half_blocks": {"mode": "loop", "block": max(1, h.n_cols // 8)}, "loop_on_grid": {"mode": "loop", "strategy": "grid", "grid": Grid(4, 4)}, "grid_hash": {"strategy": "grid", "grid": Grid(4, 4, layout="hash")}}
    out = {f"s_{n}": seconds(lambda: h.multiply(h, **o).df) for n, o in plans.items()}  # noqa: B023
    out["s_library_square"] = seconds(lambda: baselines.mllib_block(h, h).df)
    s = t.restriction(8)
    wide = s.transpose()
    out |= {"s_restrict": seconds(contract.restrict_right(h, s).df), "s_restrict_rowwise_1d": seconds(h.multiply(wide, strategy="rowwise_1d").df), "s_library_restrict": seconds(lambda: baselines.mllib_block(h, wide).df)}
    out |= {"s_triple": seconds(contract.contract(h, s, "fused").df), "s_triple_rowwise_1d": seconds(s.multiply(h, strategy="rowwise_1d").multiply(wide, strategy="rowwise_1d").df), "s_library_triple": seconds(lambda: baselines.mllib_block(baselines.mllib_block(s, h), wide).df)}
    if h.n_rows * h.n_cols <= 4_000_000 and TIMED:
        start = time.time()
        baselines.dense(h, h)
        out["s_dense"] = time.time() - start
    over = {f"s_speedup_{k}": out[slow] / max(out[fast], 1e-9) for k, slow, fast in (("inner", "s_rowwise_1d", "s_inner"), ("grid", "s_rowwise_1d", "s_grid"), ("restrict", "s_restrict_rowwise_1d", "s_restrict"), ("triple", "s_triple_rowwise_1d", "s_triple"), ("square_library", "s_library_square", "s_inner"), ("restrict_library", "s_library_restrict", "s_restrict"), ("triple_library", "s_library_triple", "s_triple"))}
    words = measures.comm_words(h, h, Grid(4, 4)).agg(F.sum("words")).first()[0]
    return out | over | {"words_grid": words, "words_rowwise": 9 * measures.nnz(h), "dense_flops": measures.dense_flops(*h.shape, h.n_cols)}


def search(t: Tables) -> dict:
    """Breadth-first search from eight sources."""
    h, p = kept(t.co_purchase()), _md5(t)
    found = graph.bfs_multi(h, perms.head(p, 8).select(F.col("idx").alias("vertex")))
    return {"reached": found.count(), "levels": found.agg(F.max("level")).first()[0]}


def storage(t: Tables) -> dict:
    """Words of both column formats over growing grids for hashed terms and links."""
    out = {}
    for name, m in {"terms": kept(t.doc_term()), "links": kept(t.page_link())}.items():
        for side in (1, 2, 4, 8):
            r = layout.storage_words(m, Grid(side, side)).first()
            out |= {f"{name}_csc_{side}": r["csc_words"], f"{name}_dcsc_{side}": r["dcsc_words"]}
    return out


WORKLOADS = {
    "w01_relabel": relabel, "w02_subgraphs": subgraphs, "w03_replace_window": replace_window, "w04_square": square, "w05_stage_sizes": stage_sizes, "w06_restrict": restrict,
    "w07_triple": triple, "w08_diagonal_split": diagonal_split, "w09_tall_skinny": tall_skinny, "w10_methods": methods, "w12_search": search, "w15_storage": storage, "w20_strong_scaling": strong_scaling,
}


def run(spark: SparkSession, sf_dir: str, wid: str) -> DataFrame:
    found = WORKLOADS[wid](Tables(spark, sf_dir))
    return spark.createDataFrame([(k, float(v)) for k, v in found.items()], "metric string, value double")


def counts(spark: SparkSession, sf_dir: str, wid: str) -> DataFrame:
    """The counts of a workload: its metrics that are no seconds and nothing made of them."""
    global TIMED
    TIMED = False
    try:
        found = WORKLOADS[wid](Tables(spark, sf_dir))
    finally:
        TIMED = True
    return spark.createDataFrame([(k, float(v)) for k, v in found.items() if not k.startswith("s_")], "metric string, value double")
