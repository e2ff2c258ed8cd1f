"""Where query modules register a query and, if SQL can express it, its SQL."""

from __future__ import annotations

from collections.abc import Callable

QUERIES: dict[str, Callable] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


def with_items(sql: str) -> str:
    """SQL over the document items, with their keys, as ``items``."""
    return ITEMS + sql


def with_star(sql: str) -> str:
    return STAR + sql


#: The item carriers in SQL.
ITEMS = """
WITH items AS (
  SELECT source AS dataset_id, CAST(substr(source, 4) AS INT) AS no, CAST(doc_id AS VARCHAR) AS item_id,
         CAST(DATE '2024-01-01' + 30 * CAST(substr(source, 4) AS INT) AS DATE) AS released_at, doc_id AS seq,
         text AS prompt, lang AS answer, sha1(text) AS key,
         CASE WHEN CAST(substr(source, 4) AS INT) <= 1 THEN 'atomic_source' WHEN CAST(substr(source, 4) AS INT) <= 4 THEN 'aggregate_source' ELSE 'training' END AS role
  FROM documents
), ranked AS (
  SELECT *, row_number() OVER (PARTITION BY key ORDER BY released_at, no, seq) AS rn FROM items
), ks AS (
  SELECT key, dataset_id, no, role, min(released_at) AS released_at, min(seq) AS seq, count(*) AS n FROM items GROUP BY 1, 2, 3, 4
), origin AS (
  SELECT key, arg_min(dataset_id, no) FILTER (role = 'atomic_source') AS atom, arg_min(dataset_id, no) FILTER (role = 'aggregate_source') AS aggr FROM ks GROUP BY key
), attributed AS (
  SELECT i.*, coalesce(o.atom, o.aggr) AS atomic_source,
         CASE WHEN o.atom IS NOT NULL THEN 'exact' WHEN o.aggr IS NOT NULL THEN 'via_aggregate' ELSE 'unmatched' END AS stage
  FROM items i JOIN origin o USING (key) WHERE i.role = 'training'
)
"""

STAR = """
WITH items AS (
  SELECT 's' || l_suppkey AS dataset_id, l_suppkey AS no, l_orderkey * 10 + l_linenumber AS seq,
         p_name || ' ' || p_size AS prompt, l_returnflag AS answer, sha1(p_name || ' ' || p_size) AS key
  FROM lineitem JOIN part ON p_partkey = l_partkey
)
"""
