"""The registry of queries and of the SQL that gives the same rows."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}

#: Streams as common table expressions.
STREAM_SQL = {
    "s1": """s1 AS (SELECT row_number() OVER (ORDER BY ts, event_id) - 1 AS pos, 2 * user_id AS src, 2 * CAST(props->>'$.k' AS BIGINT) + 1 AS dst, ts, 'edge_add' AS kind, 'communication' AS kind_class, value AS weight FROM events)""",
    "s1m": """s1m AS (SELECT row_number() OVER (ORDER BY ts, event_id) - 1 AS pos, 2 * user_id AS src, CASE WHEN event_type <> 'signup' THEN 2 * CAST(props->>'$.k' AS BIGINT) + 1 END AS dst, ts,
      CASE event_type WHEN 'signup' THEN 'node_add' WHEN 'error' THEN 'edge_del' ELSE 'edge_add' END AS kind, CASE WHEN event_type IN ('click', 'view') THEN 'communication' ELSE 'association' END AS kind_class, value AS weight FROM events)""",
    "s2": """s2 AS (SELECT row_number() OVER (ORDER BY o_orderdate, l_orderkey, l_linenumber, l_partkey, l_suppkey, l_extendedprice) - 1 AS pos, 2 * o_custkey AS src, 2 * l_partkey + 1 AS dst, o_orderdate AS ts, 'edge_add' AS kind, 'association' AS kind_class, l_quantity AS weight FROM lineitem JOIN orders ON l_orderkey = o_orderkey)""",
    "s3": """s3 AS (SELECT row_number() OVER (ORDER BY o_orderdate, l_orderkey, l_linenumber, l_partkey, l_suppkey, l_extendedprice) - 1 AS pos, 2 * o_custkey AS src, 2 * l_suppkey + 1 AS dst, o_orderdate AS ts, 'edge_add' AS kind, 'association' AS kind_class, l_quantity AS weight FROM lineitem JOIN orders ON l_orderkey = o_orderkey)""",
    "s4": """s4 AS (SELECT row_number() OVER (ORDER BY conv_id, turn, role) - 1 AS pos, 2 * conv_id AS src, 2 * CASE role WHEN 'system' THEN 0 WHEN 'user' THEN 1 ELSE 2 END + 1 AS dst, TIMESTAMP '2000-01-01' + to_seconds(turn) AS ts, 'edge_add' AS kind, 'communication' AS kind_class, CAST(length(text) AS DOUBLE) AS weight FROM conversations)""",
    "links": """links AS (SELECT page_id, regexp_extract(url, '^[a-z]+://([^/?#:]+)', 1) AS host, o - 1 AS ord, hrefs[o] AS href FROM (SELECT page_id, url, hrefs, unnest(generate_series(1, len(hrefs))) AS o FROM (SELECT page_id, url, regexp_extract_all(html, 'href="([^"]*)"', 1) AS hrefs FROM pages)))""",
    "s5": """s5 AS (SELECT row_number() OVER (ORDER BY page_id, ord) - 1 AS pos, 2 * CAST('0x' || substr(md5(host), 1, 12) AS BIGINT) AS src, 2 * CAST('0x' || substr(md5(href), 1, 12) AS BIGINT) + 1 AS dst, TIMESTAMP '2000-01-01' AS ts, 'edge_add' AS kind, 'association' AS kind_class, 1.0 AS weight FROM links)""",
    "s6": """s6 AS (SELECT row_number() OVER (ORDER BY doc_id) - 1 AS pos, 2 * CAST(regexp_extract(source, '([0-9]+)$', 1) AS BIGINT) AS src, 2 * doc_id + 1 AS dst, TIMESTAMP '2000-01-01' + to_seconds(doc_id) AS ts, 'edge_add' AS kind, 'association' AS kind_class, CAST(n_chars AS DOUBLE) AS weight FROM documents)""",
}


def query(name: str, sql: str | None = None) -> Callable:
    """Register a query, with SQL where it can express it."""

    def add(f: Callable[[SparkSession, str], DataFrame]) -> Callable:
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


def cte(*names: str, more: str = "", recursive: bool = False) -> str:
    """The WITH clause of the named streams and further expressions."""
    parts = [STREAM_SQL[n] for n in names] + ([more] if more else [])
    return f"WITH {'RECURSIVE ' if recursive else ''}" + ",\n".join(parts) + "\n"
