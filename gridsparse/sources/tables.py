"""Matrices drawn from the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from gridsparse.matrix import SparseMatrix
from gridsparse.operators import build

HASH_DIM = 1 << 31
WORD = r"[^\x20\x09-\x0D]+"


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def count_keys(df: DataFrame, key: str) -> int:
    """One more than the largest key: the dimension of dense 0-based keys."""
    top = df.agg(F.max(key)).first()[0]
    return 0 if top is None else top + 1


class Tables:
    """The tables of one directory, and matrices over them; dimensions come from small aggregates."""

    def __init__(self, spark: SparkSession, sf_dir: str):
        self.spark, self.dir = spark, sf_dir

    def table(self, name: str) -> DataFrame:
        return read_table(self.spark, self.dir, name)

    def dim(self, name: str, key: str) -> int:
        return count_keys(self.table(name), key)

    @property
    def parts(self) -> int:
        return self.dim("part", "p_partkey")

    def order_part(self) -> SparseMatrix:
        cells = self.table("lineitem").groupBy(F.col("l_orderkey").alias("i"), F.col("l_partkey").alias("j")).agg(F.sum("l_quantity").cast("long").alias("v"))
        return SparseMatrix(cells, self.dim("orders", "o_orderkey"), self.parts)

    def cust_supp(self) -> SparseMatrix:
        lines = self.table("lineitem").join(self.table("orders"), F.col("l_orderkey") == F.col("o_orderkey"))
        cells = lines.groupBy(F.col("o_custkey").alias("i"), F.col("l_suppkey").alias("j")).agg(F.sum("l_quantity").cast("long").alias("v"))
        return SparseMatrix(cells, self.dim("customer", "c_custkey"), self.dim("supplier", "s_suppkey"))

    def co_purchase(self, returned_only: bool = True) -> SparseMatrix:
        """Pairs of distinct parts that share an order, counted by orders."""
        lines = self.table("lineitem")
        if returned_only:
            lines = lines.where("l_returnflag = 'R'")
        rows = lines.select("l_orderkey", "l_partkey").distinct()
        other = rows.select("l_orderkey", F.col("l_partkey").alias("j"))
        cells = rows.withColumnRenamed("l_partkey", "i").join(other, "l_orderkey").where("i <> j").groupBy("i", "j").agg(F.count("*").alias("v"))
        return SparseMatrix(cells, self.parts, self.parts)

    def part_diag(self) -> SparseMatrix:
        """The returned co-purchases with a full diagonal of degree + 1."""
        h = self.co_purchase()
        d = h.df.groupBy("i").agg(F.count("*").alias("n"))
        own = self.table("part").select(F.col("p_partkey").alias("i")).join(d, "i", "left").select("i", F.col("i").alias("j"), (F.coalesce("n", F.lit(0)) + 1).alias("v"))
        return h.with_df(h.df.unionByName(own))

    def user_hop(self) -> SparseMatrix:
        """Consecutive users in event order; the order is global, so the window is one task over two narrow columns."""
        events = self.table("events").select("ts", "event_id", "user_id")
        day = F.to_date("ts")
        inside = Window.partitionBy(day).orderBy("ts", "event_id")
        hops = events.withColumn("d", day).withColumn("to", F.lead("user_id").over(inside)).withColumn("first", F.row_number().over(inside) == 1)
        ends = events.withColumn("d", day).groupBy("d").agg(F.max_by("user_id", F.struct("ts", "event_id")).alias("last"), F.min_by("user_id", F.struct("ts", "event_id")).alias("first_user"))
        across = ends.withColumn("next_user", F.lead("first_user").over(Window.orderBy("d"))).where("next_user IS NOT NULL").select(F.col("last").alias("i"), F.col("next_user").alias("j"))
        pairs = hops.where("to IS NOT NULL").select(F.col("user_id").alias("i"), F.col("to").alias("j")).unionByName(across)
        n = self.dim("events", "user_id")
        return SparseMatrix(pairs.groupBy("i", "j").agg(F.count("*").alias("v")), n, n)

    EVENT_TYPES = ("click", "error", "purchase", "signup", "view")

    def user_type(self) -> SparseMatrix:
        code = F.array_position(F.array(*map(F.lit, self.EVENT_TYPES)), F.col("event_type")) - 1
        cells = self.table("events").groupBy(F.col("user_id").alias("i"), code.alias("j")).agg(F.count("*").alias("v"))
        return SparseMatrix(cells, self.dim("events", "user_id"), 5)

    def nat_cust(self) -> SparseMatrix:
        return build.restriction_from(self.table("customer"), "c_custkey", "c_nationkey", (25, self.dim("customer", "c_custkey")))

    def nat_supp(self) -> SparseMatrix:
        return build.restriction_from(self.table("supplier"), "s_suppkey", "s_nationkey", (25, self.dim("supplier", "s_suppkey")))

    def reg_nat(self) -> SparseMatrix:
        return build.restriction_from(self.table("nation"), "n_nationkey", "n_regionkey", (5, 25))

    def restriction(self, order: int) -> SparseMatrix:
        return build.restriction(self.spark, self.parts, order)

    def words(self, name: str, key: str) -> DataFrame:
        """(i, w): the words of each row's text, A-Z and other letters in lower case."""
        return self.table(name).select(F.col(key).alias("i"), F.explode(F.regexp_extract_all(F.lower(F.coalesce("text", F.lit(""))), F.lit(WORD), F.lit(0))).alias("w"))

    def _terms(self, name: str, key: str) -> DataFrame:
        return self.words(name, key).groupBy("i", F.conv(F.substring(F.md5("w"), 1, 7), 16, 10).cast("long").alias("j")).agg(F.count("*").alias("v"))

    def doc_term(self) -> SparseMatrix:
        """Documents by hashed words: far more columns than entries."""
        return SparseMatrix(self._terms("documents", "doc_id"), self.dim("documents", "doc_id"), HASH_DIM)

    def bench_term(self) -> SparseMatrix:
        return SparseMatrix(self._terms("benchmark", "item_id"), self.dim("benchmark", "item_id"), HASH_DIM)

    def page_link(self) -> SparseMatrix:
        links = self.table("pages").select(F.col("page_id").alias("i"), F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("w"))
        cells = links.groupBy("i", F.conv(F.substring(F.md5("w"), 1, 7), 16, 10).cast("long").alias("j")).agg(F.count("*").alias("v"))
        return SparseMatrix(cells, self.dim("pages", "page_id"), HASH_DIM)

    def embedding(self) -> SparseMatrix:
        cells = self.table("embeddings").select(F.col("vec_id").alias("i"), F.posexplode("embedding").alias("j", "x"))
        return SparseMatrix(cells.select("i", F.col("j").cast("long").alias("j"), F.round(F.col("x").cast("double") * 10000).cast("long").alias("v")), self.dim("embeddings", "vec_id"), 64)

    def role_counts(self) -> DataFrame:
        """(role, next_role, n) over consecutive turns."""
        turn = Window.partitionBy("conv_id").orderBy("turn")
        rows = self.table("conversations").withColumn("next_role", F.lead("role").over(turn)).where("next_role IS NOT NULL")
        return rows.groupBy("role", "next_role").agg(F.count("*").alias("n"))
