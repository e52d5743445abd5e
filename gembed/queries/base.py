"""Registry, and SQL fragments that several checks share."""

from __future__ import annotations

from collections.abc import Callable

from ..functions.hashing import sql_h32

QUERIES: dict[str, Callable] = {}
SQL: dict[str, str] = {}

TOKENS = r"list_filter(regexp_split_to_array(lower(text), '[^\p{L}]+'), lambda w: w <> '')"


def query(name: str, sql: str | None = None):
    def add(f: Callable) -> Callable:
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def word_next_ctes(least: int = 10) -> str:
    return f"""
    toks AS (SELECT {TOKENS} AS w FROM documents),
    pairs AS (SELECT unnest(w[1:len(w)-1]) AS src, unnest(w[2:len(w)]) AS dst FROM toks WHERE len(w) > 1),
    raw AS (SELECT src, dst, count(*)::BIGINT AS weight FROM pairs GROUP BY ALL),
    often AS (SELECT word FROM (SELECT src AS word, weight FROM raw UNION ALL SELECT dst, weight FROM raw) GROUP BY word HAVING sum(weight) >= {least}),
    edges AS (SELECT 'follows' AS rel, src, dst, weight FROM raw WHERE src IN (SELECT word FROM often) AND dst IN (SELECT word FROM often))"""


DOC_WORD = f"edges AS (SELECT 'contains' AS rel, doc_id::VARCHAR AS src, w AS dst, count(*)::BIGINT AS weight FROM (SELECT doc_id, unnest({TOKENS}) AS w FROM documents) GROUP BY ALL)"
USER_EVENT = "edges AS (SELECT 'did' AS rel, user_id::VARCHAR AS src, event_type AS dst, count(*)::BIGINT AS weight FROM events GROUP BY ALL)"
PLACED = "edges AS (SELECT 'placed_by' AS rel, o_orderkey::VARCHAR AS src, o_custkey::VARCHAR AS dst, 1::BIGINT AS weight FROM orders)"
PURCHASES = "edges AS (SELECT 'buys' AS rel, o_custkey::VARCHAR AS src, l_partkey::VARCHAR AS dst, count(*)::BIGINT AS weight FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY ALL)"


def kb_ctes() -> str:
    one = lambda rel, table, st, s, dt, d: f"SELECT '{rel}' AS rel, '{st}:' || {s} AS src, '{dt}:' || {d} AS dst, 1::BIGINT AS weight FROM {table}"
    parts = [
        one("customer_in_nation", "customer", "customer", "c_custkey", "nation", "c_nationkey"),
        one("supplier_in_nation", "supplier", "supplier", "s_suppkey", "nation", "s_nationkey"),
        one("nation_in_region", "nation", "nation", "n_nationkey", "region", "n_regionkey"),
        one("part_brand", "part", "part", "p_partkey", "brand", "p_brand"),
        one("part_type", "part", "part", "p_partkey", "type", "p_type"),
        one("part_size", "part", "part", "p_partkey", "size", "p_size"),
        one("customer_segment", "customer", "customer", "c_custkey", "segment", "c_mktsegment"),
        one("order_by_customer", "orders", "order", "o_orderkey", "customer", "o_custkey"),
        one("order_priority", "orders", "order", "o_orderkey", "priority", "o_orderpriority"),
        "SELECT 'order_has_part', 'order:' || l_orderkey, 'part:' || l_partkey, count(*)::BIGINT FROM lineitem GROUP BY ALL",
        "SELECT 'part_from_supplier', 'part:' || l_partkey, 'supplier:' || l_suppkey, count(*)::BIGINT FROM lineitem GROUP BY ALL",
        "SELECT 'user_' || event_type, 'user:' || user_id, 'hour:' || hour(ts), count(*)::BIGINT FROM events WHERE event_type IN ('click','view','purchase','signup','error') GROUP BY ALL",
    ]
    return "edges AS (" + " UNION ALL ".join(parts) + ")"


def sql_vec(d: int, spread: float, seed: int, *key: str) -> str:
    """The hash-made starting vector as SQL."""
    h = sql_h32(f"'{seed}'", *key, "k")
    return f"list_transform(range({d}), lambda k: ({h} / 4294967296.0::DOUBLE - 0.5::DOUBLE) * {2 * spread!r}::DOUBLE)"


def sql_dot(a: str, b: str) -> str:
    return f"list_sum(list_transform(list_zip({a}, {b}), lambda z: z[1] * z[2]))"
