"""Registering queries, and the views over the given tables as SQL."""

from __future__ import annotations

from collections.abc import Callable

QUERIES: dict[str, Callable] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    """Registers a function (spark, folder) under its name, with the SQL that must give the same rows."""

    def add(f):
        key = name or f.__name__
        QUERIES[key] = f
        if sql:
            ORACLES[key] = sql
        return f

    return add


VIEWS = {
    "co_order": "SELECT DISTINCT x.l_partkey AS u, y.l_partkey AS v FROM lineitem x JOIN lineitem y ON x.l_orderkey = y.l_orderkey AND x.l_partkey <> y.l_partkey",
    "handoff": "SELECT DISTINCT u, v FROM (SELECT user_id AS u, lead(user_id) OVER (ORDER BY ts, event_id) AS v FROM events) WHERE v IS NOT NULL AND u <> v",
    "handoff_purchase": "SELECT DISTINCT u, v FROM (SELECT user_id AS u, lead(user_id) OVER (ORDER BY ts, event_id) AS v FROM events WHERE event_type = 'purchase') WHERE v IS NOT NULL AND u <> v",
    "supply": "SELECT DISTINCT l_partkey AS u, l_suppkey AS v FROM lineitem",
    "qty": "SELECT l_partkey AS u, l_suppkey AS v, CAST(sum(CAST(round(l_quantity * 100) AS BIGINT)) AS BIGINT) AS w FROM lineitem GROUP BY 1, 2",
    "cust_supp": "SELECT DISTINCT o_custkey AS u, l_suppkey AS v FROM orders JOIN lineitem ON l_orderkey = o_orderkey",
    "doc_term": "SELECT doc_id AS u, term AS v, count(*) AS w FROM (SELECT doc_id, unnest(string_split_regex(lower(text), '[^\\p{L}]+')) AS term FROM documents) WHERE term <> '' GROUP BY 1, 2",
    "page_link": "SELECT DISTINCT page_id AS u, unnest(regexp_extract_all(html, 'href=\"/([^\"]+)\"', 1)) AS v FROM pages",
    "alike": """SELECT x.vec_id AS u, y.vec_id AS v FROM (SELECT vec_id, label, CAST(embedding AS DOUBLE[]) AS e FROM embeddings) x JOIN (SELECT vec_id, label, CAST(embedding AS DOUBLE[]) AS e FROM embeddings) y
      ON x.label = y.label AND x.vec_id <> y.vec_id AND list_cosine_similarity(x.e, y.e) >= 0.15""",
    "forest": """SELECT u, v FROM (SELECT 1000000000000 + c_custkey AS u, 3000000000000 + c_nationkey AS v FROM customer
      UNION ALL SELECT 2000000000000 + s_suppkey, 3000000000000 + s_nationkey FROM supplier
      UNION ALL SELECT 3000000000000 + n_nationkey, 4000000000000 + n_regionkey FROM nation)
      UNION SELECT v, u FROM (SELECT 1000000000000 + c_custkey AS u, 3000000000000 + c_nationkey AS v FROM customer
      UNION ALL SELECT 2000000000000 + s_suppkey, 3000000000000 + s_nationkey FROM supplier
      UNION ALL SELECT 3000000000000 + n_nationkey, 4000000000000 + n_regionkey FROM nation)""",
    "order_chain": """SELECT u, v FROM (SELECT o_orderkey AS u, lead(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS v FROM orders) WHERE v IS NOT NULL
      UNION SELECT v, u FROM (SELECT o_orderkey AS u, lead(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS v FROM orders) WHERE v IS NOT NULL""",
}


def over(views: str, body: str, recursive: bool = False) -> str:
    """``body`` with the named views in front of it."""
    named = ", ".join(f"{v} AS MATERIALIZED ({VIEWS[v]})" for v in views.split())
    start = "WITH RECURSIVE" if recursive else "WITH"
    body = body.strip()
    return f"{start} {named}, {body[5:]}" if body.startswith("WITH ") else f"{start} {named} {body}"


def dealt(key: str, weight: str, k: str, within: str = "") -> str:
    """The hand that round-robin dealing in the order of weights gives, as a SQL expression."""
    part = f"PARTITION BY {within}" if within else ""
    return f"CAST((row_number() OVER ({part} ORDER BY {weight}, {key}) - 1 + ({k} - count(*) OVER ({part}) % {k}) % {k}) % {k} AS INTEGER)"


PRODUCT = "SELECT x.u AS row, y.v AS col, count(*) AS val FROM {0} x JOIN {1} y ON x.v = y.u GROUP BY 1, 2"
CUBE_SIDE = "(SELECT min(q) FROM range(1, 3000) t(q) WHERE q * q * q >= {0})"
