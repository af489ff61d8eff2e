"""The registry: each query is a function of (spark, sf_dir) with its SQL, if SQL can express it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE_SQL: dict[str, str] = {}

#: Table expressions that the SQL texts share, written from the matrices' definitions.
WITH = {
    "n": "SELECT count(*) AS n FROM part",
    "op": "SELECT l_orderkey AS i, l_partkey AS j, CAST(sum(l_quantity) AS BIGINT) AS v FROM lineitem GROUP BY ALL",
    "cs": "SELECT o_custkey AS i, l_suppkey AS j, CAST(sum(l_quantity) AS BIGINT) AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY ALL",
    "h": "SELECT a.l_partkey AS i, b.l_partkey AS j, count(DISTINCT a.l_orderkey) AS v FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey <> b.l_partkey WHERE a.l_returnflag = 'R' AND b.l_returnflag = 'R' GROUP BY ALL",
    "g": "SELECT a.l_partkey AS i, b.l_partkey AS j, count(DISTINCT a.l_orderkey) AS v FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey <> b.l_partkey GROUP BY ALL",
    "pd": "SELECT * FROM h UNION ALL SELECT p_partkey, p_partkey, (SELECT count(*) FROM h WHERE h.i = p_partkey) + 1 FROM part",
    "s2": "SELECT p_partkey // 2 AS i, p_partkey AS j, 1 AS v FROM part",
    "s4": "SELECT p_partkey // 4 AS i, p_partkey AS j, 1 AS v FROM part",
    "s8": "SELECT p_partkey // 8 AS i, p_partkey AS j, 1 AS v FROM part",
    "perm": "SELECT row_number() OVER (ORDER BY md5('7:' || p_partkey)) - 1 AS pos, p_partkey AS idx FROM part",
    "aff": "SELECT p_partkey AS pos, (1103 * p_partkey + 17) % (SELECT n FROM n) AS idx FROM part",
    "ut": "SELECT user_id AS i, list_position(['click', 'error', 'purchase', 'signup', 'view'], event_type) - 1 AS j, count(*) AS v FROM events GROUP BY ALL",
    "hop": "SELECT i, j, count(*) AS v FROM (SELECT user_id AS i, lead(user_id) OVER (ORDER BY ts, event_id) AS j FROM events) WHERE j IS NOT NULL GROUP BY ALL",
    "deg": "SELECT i, count(*) AS d FROM h GROUP BY i",
}
NEEDS = {"pd": ["h"], "aff": ["n"], "deg": ["h"]}


def sql(body: str, *names: str) -> str:
    """``body`` under a WITH of the named expressions and what they need."""
    order: list[str] = []

    def add(name):
        for other in NEEDS.get(name, []):
            add(other)
        if name not in order:
            order.append(name)

    for name in names:
        add(name)
    heads = ", ".join(f"{x} AS ({WITH[x]})" for x in order)
    joiner = ", " if body.startswith("+") else " "
    return f"WITH {heads}{joiner}{body.lstrip('+')}" if heads else body


def register(name: str, text: str | None = None):
    """Decorator: add a query and its SQL."""

    def keep(f):
        QUERIES[name] = f
        if text is not None:
            ORACLE_SQL[name] = text
        return f

    return keep
