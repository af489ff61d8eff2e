"""Queries over the surrounding operators: scans, joins, aggregates, windows, functions, files."""

from __future__ import annotations

import uuid

import numpy as np
import pandas as pd
from pyspark.sql import Window
from pyspark.sql import functions as F

from gridsparse.matrix import SparseMatrix
from gridsparse.operators import relational
from gridsparse.operators.layout import Grid
from gridsparse.queries.catalog import ORACLE_SQL, QUERIES, register, sql
from gridsparse.sources import files
from gridsparse.sources.tables import Tables, read_table
from gridsparse.storage import settle, shared_dir, small

CENTS_SQL = "CAST(round(l_extendedprice * 100) AS BIGINT)"


def cents():
    return F.round(F.col("l_extendedprice") * 100).cast("long")


def _over(table: str, body):
    return lambda spark, sf_dir: body(read_table(spark, sf_dir, table))


def add(name: str, table: str, text: str, body) -> None:
    register(name, text)(_over(table, body))


add("r01_scan", "region", "SELECT r_regionkey, r_name FROM region", lambda d: d.select("r_regionkey", "r_name"))
add("r07_block_of_index", "lineitem", "SELECT l_orderkey // 1000 AS block, count(*) AS n FROM lineitem GROUP BY 1", lambda d: d.groupBy(F.expr("l_orderkey div 1000").alias("block")).agg(F.count("*").alias("n")))
add("r08_predicates", "lineitem", "SELECT l_orderkey, l_partkey FROM lineitem WHERE l_returnflag IN ('R', 'A') AND l_quantity BETWEEN 10 AND 12 AND l_partkey < 500 AND l_shipdate IS NOT NULL", lambda d: d.where(F.col("l_returnflag").isin("R", "A") & F.col("l_quantity").between(10, 12) & (F.col("l_partkey") < 500) & F.col("l_shipdate").isNotNull()).select("l_orderkey", "l_partkey"))
add("r20_hash_aggregate", "lineitem", f"SELECT l_returnflag, count(*) AS n, CAST(sum({CENTS_SQL}) AS BIGINT) AS cents FROM lineitem GROUP BY 1", lambda d: d.groupBy("l_returnflag").agg(F.count("*").alias("n"), F.sum(cents()).alias("cents")))
add("r21_sort_aggregate", "lineitem", "SELECT l_suppkey, min(l_partkey) AS part, arg_min(l_orderkey, l_partkey * 100000000 + l_orderkey) AS first_order FROM lineitem GROUP BY 1", lambda d: d.groupBy("l_suppkey").agg(F.min(F.struct("l_partkey", "l_orderkey")).alias("m")).select("l_suppkey", F.col("m.l_partkey").alias("part"), F.col("m.l_orderkey").alias("first_order")))
add("r22_distinct", "lineitem", "SELECT count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem", lambda d: d.agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers")))
add("r25_cube", "orders", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)", lambda d: d.cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n")))
add("r26_pivot", "events", "SELECT user_id, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'view') AS view FROM events GROUP BY 1", lambda d: d.groupBy("user_id").pivot("event_type", ["click", "view"]).agg(F.count("event_id")).select("user_id", F.coalesce("click", F.lit(0)).cast("long").alias("click"), F.coalesce("view", F.lit(0)).cast("long").alias("view")))
add("r27_ranking", "part", "SELECT p_partkey, CAST(row_number() OVER w AS INTEGER) AS rn, CAST(rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS INTEGER) AS rk, CAST(dense_rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS INTEGER) AS dr, CAST(ntile(4) OVER w AS INTEGER) AS quarter FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size, p_partkey)", lambda d: d.select("p_partkey", F.row_number().over(Window.partitionBy("p_brand").orderBy("p_size", "p_partkey")).alias("rn"), F.rank().over(Window.partitionBy("p_brand").orderBy("p_size")).alias("rk"), F.dense_rank().over(Window.partitionBy("p_brand").orderBy("p_size")).alias("dr"), F.ntile(4).over(Window.partitionBy("p_brand").orderBy("p_size", "p_partkey")).alias("quarter")))
add("r28_lead_lag", "conversations", "SELECT conv_id, turn, lag(role) OVER w AS before, lead(role) OVER w AS after FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)", lambda d: d.select("conv_id", "turn", F.lag("role").over(Window.partitionBy("conv_id").orderBy("turn")).alias("before"), F.lead("role").over(Window.partitionBy("conv_id").orderBy("turn")).alias("after")))
add("r29_running_sum", "lineitem", "SELECT j, CAST(sum(n) OVER (PARTITION BY j // 100 ORDER BY j) - n AS BIGINT) AS pointer FROM (SELECT l_partkey AS j, count(*) AS n FROM lineitem GROUP BY 1)", lambda d: d.groupBy(F.col("l_partkey").alias("j")).agg(F.count("*").alias("n")).select("j", (F.sum("n").over(Window.partitionBy(F.expr("j div 100")).orderBy("j").rowsBetween(Window.unboundedPreceding, 0)) - F.col("n")).alias("pointer")))
add("r30_last_value", "events", "SELECT user_id, arg_max(event_type, ts) AS last_type, arg_min(event_type, ts) AS first_type FROM events GROUP BY 1", lambda d: d.groupBy("user_id").agg(F.max_by("event_type", "ts").alias("last_type"), F.min_by("event_type", "ts").alias("first_type")))
add("r31_sort_limit_offset", "orders", "SELECT o_orderkey, o_custkey FROM orders ORDER BY o_custkey DESC, o_orderkey LIMIT 20 OFFSET 5", lambda d: d.select("o_orderkey", "o_custkey").orderBy(F.desc("o_custkey"), "o_orderkey").offset(5).limit(20))
add("r37_math", "lineitem", "SELECT l_orderkey % 7 AS m, CAST(max(greatest(l_partkey, l_suppkey)) AS BIGINT) AS g, CAST(min(least(l_partkey, l_suppkey)) AS BIGINT) AS l, CAST(sum(l_partkey >> 2) AS BIGINT) AS s FROM lineitem GROUP BY 1", lambda d: d.groupBy(F.pmod("l_orderkey", F.lit(7)).alias("m")).agg(F.max(F.greatest("l_partkey", "l_suppkey")).alias("g"), F.min(F.least("l_partkey", "l_suppkey")).alias("l"), F.sum(F.shiftright("l_partkey", 2)).alias("s")))
add("r38_md5", "part", "SELECT p_partkey, md5('7:' || p_partkey) AS h FROM part", lambda d: d.select("p_partkey", F.md5(F.concat(F.lit("7:"), F.col("p_partkey").cast("string"))).alias("h")))
add("r39_strings", "pages", "SELECT page_id, len(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS links, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host FROM pages", lambda d: d.select("page_id", F.size(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).cast("long").alias("links"), F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("host")))
add("r40_dates", "orders", "SELECT CAST(date_part('year', o_orderdate) AS INTEGER) AS y, CAST(date_part('month', o_orderdate) AS INTEGER) AS m, count(*) AS n, CAST(max(date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE))) AS INTEGER) AS days FROM orders GROUP BY 1, 2", lambda d: d.groupBy(F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m")).agg(F.count("*").alias("n"), F.max(F.datediff(F.to_date("o_orderdate"), F.lit("1992-01-01").cast("date"))).alias("days")))
add("r41_arrays", "embeddings", "SELECT vec_id, CAST(list_sum(list_transform(embedding, lambda x: CAST(round(CAST(x AS DOUBLE) * 1000) AS BIGINT))) AS BIGINT) AS total, len(list_filter(embedding, lambda x: x > 0)) AS positive FROM embeddings", lambda d: d.select("vec_id", F.aggregate(F.transform("embedding", lambda x: F.round(x.cast("double") * 1000).cast("long")), F.lit(0).cast("long"), lambda a, x: a + x).alias("total"), F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("positive")))
add("r43_json", "events", "SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1", lambda d: d.groupBy(F.get_json_object("props", "$.k").cast("long").alias("k")).agg(F.count("*").alias("n")))
add("r44_decimal", "lineitem", "SELECT l_suppkey, CAST(sum(CAST(round(l_extendedprice * 100) AS DECIMAL(20, 0))) AS BIGINT) AS cents FROM lineitem GROUP BY 1", lambda d: d.groupBy("l_suppkey").agg(F.sum(F.round(F.col("l_extendedprice") * 100).cast("decimal(20,0)")).cast("long").alias("cents")))
add("r56_hash_sample", "lineitem", "SELECT l_orderkey, l_partkey, l_linenumber FROM lineitem WHERE substr(md5(CAST(l_orderkey AS VARCHAR)), 1, 1) = '0'", lambda d: d.where(F.substring(F.md5(F.col("l_orderkey").cast("string")), 1, 1) == "0").select("l_orderkey", "l_partkey", "l_linenumber"))
add("r56_bernoulli_sample", "lineitem", None, lambda d: relational.bernoulli_sample(d, 0.1, 11).select("l_orderkey", "l_partkey", "l_linenumber"))
add("r52_salted_sum", "lineitem", f"SELECT l_linestatus, CAST(sum({CENTS_SQL}) AS BIGINT) AS v FROM lineitem GROUP BY 1", lambda d: relational.salted_sum(d, ["l_linestatus"], cents()))


def _join(name: str, how: str, hint: str | None, left: str, right: str, on: tuple[str, str], columns: list[str], text: str) -> None:
    def run(spark, sf_dir):
        a, b = read_table(spark, sf_dir, left), read_table(spark, sf_dir, right)
        b = b.hint(hint) if hint else b
        return a.join(b, F.col(on[0]) == F.col(on[1]), how).select(*columns)

    register(name, text)(run)


_join("r09_broadcast_join", "inner", "broadcast", "customer", "nation", ("c_nationkey", "n_nationkey"), ["c_custkey", "n_name"], "SELECT c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey")
_join("r10_merge_join", "inner", "merge", "lineitem", "orders", ("l_orderkey", "o_orderkey"), ["l_orderkey", "l_partkey", "o_custkey"], "SELECT l_orderkey, l_partkey, o_custkey FROM lineitem JOIN orders ON l_orderkey = o_orderkey")
_join("r11_shuffle_hash_join", "inner", "shuffle_hash", "lineitem", "part", ("l_partkey", "p_partkey"), ["l_orderkey", "p_brand"], "SELECT l_orderkey, p_brand FROM lineitem JOIN part ON l_partkey = p_partkey")
_join("r12_semi_join", "left_semi", None, "part", "lineitem", ("p_partkey", "l_partkey"), ["p_partkey"], "SELECT p_partkey FROM part WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_partkey = p_partkey)")
_join("r13_anti_join", "left_anti", None, "orders", "lineitem", ("o_orderkey", "l_orderkey"), ["o_orderkey"], "SELECT o_orderkey FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")
_join("r14_left_outer", "left", None, "customer", "orders", ("c_custkey", "o_custkey"), ["c_custkey", "o_orderkey"], "SELECT c_custkey, o_orderkey FROM customer LEFT JOIN orders ON c_custkey = o_custkey")
_join("r14_right_outer", "right", None, "orders", "customer", ("o_custkey", "c_custkey"), ["c_custkey", "o_orderkey"], "SELECT c_custkey, o_orderkey FROM orders RIGHT JOIN customer ON c_custkey = o_custkey")
_join("r14_full_outer", "full", None, "customer", "supplier", ("c_custkey", "s_suppkey"), ["c_custkey", "s_suppkey"], "SELECT c_custkey, s_suppkey FROM customer FULL JOIN supplier ON c_custkey = s_suppkey")


@register("r15_theta_join", "SELECT r_name, n_name FROM region, nation WHERE n_regionkey < r_regionkey")
def r15_theta_join(spark, sf_dir):
    """Two fixed tables of 5 and 25 rows."""
    t = Tables(spark, sf_dir)
    return t.table("region").join(t.table("nation").hint("broadcast"), F.col("n_regionkey") < F.col("r_regionkey")).select("r_name", "n_name")


@register("r16_range_join", "SELECT p_partkey, lo FROM part JOIN (SELECT b * 130 AS lo, b * 130 + 159 AS hi FROM range(8) t(b)) ON p_partkey BETWEEN lo AND hi")
def r16_range_join(spark, sf_dir):
    blocks = spark.range(8).select((F.col("id") * 130).alias("lo"), (F.col("id") * 130 + 159).alias("hi"))
    return relational.range_join(read_table(spark, sf_dir, "part"), blocks, "p_partkey", "lo", "hi", 100).select("p_partkey", "lo")


@register("r17_asof_join", "WITH e AS (SELECT user_id, ts, event_id FROM events WHERE event_type = 'error'), c AS (SELECT user_id, ts, event_id FROM events WHERE event_type = 'click') SELECT e.event_id, c.event_id AS last_event_id FROM e ASOF LEFT JOIN c ON e.user_id = c.user_id AND e.ts >= c.ts")
def r17_asof_join(spark, sf_dir):
    e = read_table(spark, sf_dir, "events").select("user_id", "ts", "event_id", "event_type")
    errors, clicks = (e.where(F.col("event_type") == k).drop("event_type") for k in ("error", "click"))
    return relational.asof_join(errors, clicks, ["user_id"], "ts", ["event_id"]).select("event_id", "last_event_id")


@register("r18_interval_join", "SELECT a.event_id AS first, b.event_id AS second FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id <> b.event_id AND epoch(date_trunc('second', b.ts)) - epoch(date_trunc('second', a.ts)) BETWEEN 0 AND 3600")
def r18_interval_join(spark, sf_dir):
    return relational.interval_pairs(read_table(spark, sf_dir, "events"), "user_id", "ts", "event_id", 3600)


@register("r19_self_join", "SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
def r19_self_join(spark, sf_dir):
    n = read_table(spark, sf_dir, "nation")
    a, b = n.select(F.col("n_nationkey").alias("a"), "n_regionkey"), n.select(F.col("n_nationkey").alias("b"), "n_regionkey")
    return a.join(b, "n_regionkey").where("a < b").select("a", "b")


@register("r23_approx_distinct")
def r23_approx_distinct(spark, sf_dir):
    return read_table(spark, sf_dir, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.02).alias("estimate"), F.count_distinct("l_partkey").alias("exact"))


@register("r24_rollup", "SELECT r_name, n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")
def r24_rollup(spark, sf_dir):
    t = Tables(spark, sf_dir)
    rows = t.table("customer").join(F.broadcast(t.table("nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(t.table("region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return rows.rollup("r_name", "n_name").agg(F.count("*").alias("n"))


@register("r25_grouping_sets", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority))")
def r25_grouping_sets(spark, sf_dir):
    return spark.sql("SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM {orders} GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority))", orders=read_table(spark, sf_dir, "orders"))


@register("r32_top_k_per_row", sql("SELECT i, j, v FROM op QUALIFY row_number() OVER (PARTITION BY i ORDER BY v DESC, j) <= 2", "op"))
def r32_top_k_per_row(spark, sf_dir):
    from gridsparse.operators.product import top_per_row

    return top_per_row(Tables(spark, sf_dir).order_part(), 2).df.select("i", "j", "v")


@register("r33_union", "SELECT c_nationkey AS nation FROM customer UNION ALL SELECT s_nationkey FROM supplier")
def r33_union(spark, sf_dir):
    t = Tables(spark, sf_dir)
    return t.table("customer").select(F.col("c_nationkey").alias("nation")).unionByName(t.table("supplier").select(F.col("s_nationkey").alias("nation")))


@register("r34_intersect", "SELECT l_partkey AS p FROM lineitem WHERE l_returnflag = 'R' INTERSECT SELECT l_partkey FROM lineitem WHERE l_returnflag = 'A'")
def r34_intersect(spark, sf_dir):
    d = read_table(spark, sf_dir, "lineitem")
    a, b = (d.where(F.col("l_returnflag") == k).select(F.col("l_partkey").alias("p")) for k in "RA")
    return a.intersect(b)


@register("r35_except", "SELECT l_partkey AS p FROM lineitem EXCEPT ALL SELECT l_partkey FROM lineitem WHERE l_returnflag = 'R'")
def r35_except(spark, sf_dir):
    d = read_table(spark, sf_dir, "lineitem")
    return d.select(F.col("l_partkey").alias("p")).exceptAll(d.where("l_returnflag = 'R'").select(F.col("l_partkey").alias("p")))


@register("r36_subqueries", "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) FROM orders) AND o_custkey IN (SELECT c_custkey FROM customer WHERE c_acctbal < 0) AND EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_returnflag = 'R')")
def r36_subqueries(spark, sf_dir):
    t = Tables(spark, sf_dir)
    return spark.sql(ORACLE_SQL["r36_subqueries"].replace("FROM orders", "FROM {orders}").replace("FROM customer", "FROM {customer}").replace("FROM lineitem", "FROM {lineitem}"), **{n: t.table(n) for n in ("orders", "customer", "lineitem")})


@register("r42_maps", sql("SELECT i, count(*) AS size, max(v) FILTER (j = m) AS first_value FROM (SELECT *, min(j) OVER (PARTITION BY i) AS m FROM op) GROUP BY i", "op"))
def r42_maps(spark, sf_dir):
    rows = relational.row_as_map(Tables(spark, sf_dir).order_part().df, "i", "j", "v")
    return rows.select("i", F.size("cells").cast("long").alias("size"), F.element_at("cells", F.array_min(F.map_keys("cells"))).alias("first_value"))


@register("r50_scalar_udf", f"SELECT l_orderkey, l_partkey, l_linenumber, ({CENTS_SQL} * 7919) % 1000 AS v FROM lineitem")
def r50_scalar_udf(spark, sf_dir):
    """A product of the user's own, in numpy over Arrow batches."""

    @F.pandas_udf("long")
    def own(x: pd.Series) -> pd.Series:
        return (x * 7919) % 1000

    return read_table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_linenumber", own(cents()).alias("v"))


@register("r51_grouped_udf", "SELECT l_suppkey, CAST(bit_xor(l_partkey) AS BIGINT) AS v FROM lineitem GROUP BY 1")
def r51_grouped_udf(spark, sf_dir):
    """A sum of the user's own, over the values of a group."""

    @F.pandas_udf("long")
    def xor(x: pd.Series) -> int:
        return int(np.bitwise_xor.reduce(x.to_numpy()))

    return read_table(spark, sf_dir, "lineitem").groupBy("l_suppkey").agg(xor("l_partkey").alias("v"))


@register("r52_table_function", sql("SELECT i, j, v AS n FROM h", "h"))
def r52_table_function(spark, sf_dir):
    """Edges that a table function makes of each order's returned parts, counted."""
    files.register_table_functions(spark)
    orders = read_table(spark, sf_dir, "lineitem").where("l_returnflag = 'R'").groupBy("l_orderkey").agg(F.collect_set("l_partkey").alias("parts"))
    return spark.sql("SELECT e.i, e.j, count(*) AS n FROM {orders} o, LATERAL set_edges(o.parts) e GROUP BY e.i, e.j", orders=orders.where(F.size("parts") > 1))


def _scratch(spark) -> str:
    return f"{shared_dir(spark)}/io-{uuid.uuid4().hex}"


@register("r04_data_source", "SELECT l_orderkey AS i, l_partkey AS j, count(*) AS count FROM lineitem GROUP BY ALL")
def r04_data_source(spark, sf_dir):
    """Orders and their parts, written to and read from a data source in Python, counted."""
    spark.dataSource.register(files.EdgeFiles)
    path = _scratch(spark)
    lines = read_table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("i"), F.col("l_partkey").alias("j"))
    lines.write.format("edge_files").mode("append").save(path)
    return spark.read.format("edge_files").load(path).groupBy("i", "j").count()


@register("r02_coordinate_text", sql("SELECT i, j, v FROM h", "h"))
def r02_coordinate_text(spark, sf_dir):
    path = _scratch(spark)
    files.write_coordinate(Tables(spark, sf_dir).co_purchase(), path)
    return files.read_coordinate(spark, path, "long").df


def _round_trip(form):
    def run(spark, sf_dir):
        path = _scratch(spark)
        files.write_edges(read_table(spark, sf_dir, "events").select("event_id", "user_id", "event_type"), path, form)
        return files.read_edges(spark, path, form, "event_id long, user_id long, event_type string")

    return run


for _form in ("csv", "json", "orc", "parquet"):
    register(f"r03_{_form}", "SELECT event_id, user_id, event_type FROM events")(_round_trip(_form))


@register("r05_blocks_pruned", sql("SELECT i, j, v FROM h WHERE i BETWEEN 20 AND 59", "h"))
def r05_blocks_pruned(spark, sf_dir):
    h, path = Tables(spark, sf_dir).co_purchase(), _scratch(spark)
    files.write_blocks(h, path, Grid(8, 2))
    return files.read_window(spark, path, h.shape, Grid(8, 2), 20, 60)


@register("r54_sql_facade", sql("SELECT a.i, b.j, CAST(sum(a.v * b.v) AS BIGINT) AS v FROM h a JOIN h b ON a.j = b.i GROUP BY ALL", "h"))
def r54_sql_facade(spark, sf_dir):
    """A product written by the user over a registered matrix."""
    Tables(spark, sf_dir).co_purchase().register("returned_pairs")
    return spark.sql("SELECT a.i, b.j, CAST(sum(a.v * b.v) AS BIGINT) AS v FROM returned_pairs a JOIN returned_pairs b ON a.j = b.i GROUP BY a.i, b.j")


@register("role_transitions", "SELECT role, next_role, count(*) AS n FROM (SELECT role, lead(role) OVER (PARTITION BY conv_id ORDER BY turn) AS next_role FROM conversations) WHERE next_role IS NOT NULL GROUP BY ALL")
def role_transitions(spark, sf_dir):
    return Tables(spark, sf_dir).role_counts()


@register("term_intersection", r"WITH w AS (SELECT item_id AS i, unnest(regexp_extract_all(lower(coalesce(text, '')), '[^\x20\x09-\x0D]+')) AS t FROM benchmark), d AS (SELECT doc_id AS j, unnest(regexp_extract_all(lower(coalesce(text, '')), '[^\x20\x09-\x0D]+')) AS t FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)) SELECT i, j, count(*) AS v FROM (SELECT DISTINCT i, t FROM w) JOIN (SELECT DISTINCT j, t FROM d) USING (t) GROUP BY ALL")
def term_intersection(spark, sf_dir):
    """Benchmark items against documents labelled good, by the words they share."""
    from gridsparse.semiring import Semiring

    t = Tables(spark, sf_dir)
    good = t.table("labels").where("quality = 1").select(F.col("doc_id").alias("i")).distinct()
    items = t.words("benchmark", "item_id").distinct()
    # a number per word that some item has: two words never share one, as hashes of many words do
    known = small(settle(items.select("w").distinct().withColumn("k", F.monotonically_increasing_id()), "words"))
    cells = lambda rows: rows.join(known, "w").select("i", F.col("k").alias("j"), F.lit(1).cast("long").alias("v"))
    b = SparseMatrix(cells(items), t.dim("benchmark", "item_id"), 1 << 62)
    d = SparseMatrix(cells(t.words("documents", "doc_id").join(good, "i", "left_semi").distinct()), t.dim("documents", "doc_id"), 1 << 62)
    return b.multiply(d.transpose(), semiring=Semiring.count_pairs()).df.select("i", "j", "v")


assert QUERIES  # the module is imported for its registrations
