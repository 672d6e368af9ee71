"""Registry of queries: name -> callable, and the equivalent DuckDB SQL where there is one."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

Query = Callable[[SparkSession, str], DataFrame]

QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        if name in QUERIES:
            raise ValueError(f"two queries named {name}")
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return add


#: SQL of the word log, its vocabulary and its exact one-dimensional chain, as common table expressions.
USES_SQL = r"""uses AS (SELECT doc_id, (doc_id % 8 + 1)::INT AS day, CASE WHEN lang = 'fr' THEN 1 ELSE 0 END AS fr,
 unnest(regexp_extract_all(lower(text), '\p{L}+')) AS word FROM documents)"""
VOCAB_SQL = USES_SQL + """, vocab AS (SELECT dense_rank() OVER (ORDER BY word) - 1 AS id, word, accesses, fr_uses FROM
 (SELECT word, count(*) AS accesses, sum(fr)::BIGINT AS fr_uses FROM uses GROUP BY word))"""
CHAIN_SQL = VOCAB_SQL + """, chain AS MATERIALIZED (SELECT row_number() OVER (ORDER BY value, id) AS pos, * FROM
 (SELECT id, 1000000 * fr_uses // accesses AS value, 1::BIGINT AS size, accesses FROM vocab))"""
ORDERS_SQL = """samples AS (SELECT l_orderkey * 8 + l_linenumber AS sample_id,
 least(datediff('day', DATE '1995-01-02', l_shipdate::DATE) * 8 // datediff('day', DATE '1995-01-02', DATE '2001-11-05') + 1, 8)::INT AS day,
 CASE WHEN l_returnflag = 'R' THEN 1 ELSE 0 END AS label,
 CASE WHEN 32 * (sp + sc) + sp * sc + 32 * e > 0 THEN 1 ELSE 0 END AS planted,
 l_partkey AS part, l_suppkey AS supplier, o_custkey AS customer, p_brand AS brand, p_type AS type, o_orderpriority AS priority,
 c_mktsegment AS segment, c_nationkey AS nation
 FROM (SELECT *, (l_partkey * 37) % 97 - 48 AS sp, (o_custkey * 53) % 97 - 48 AS sc,
   (((l_orderkey * 8 + l_linenumber) % 2147483647 * 1103515245 + 12345) % 2147483647) % 201 - 100 AS e
  FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey JOIN customer ON o_custkey = c_custkey))"""
EVENTS_SQL = """ev AS (SELECT event_id AS sample_id, (datediff('day', DATE '2024-01-04', ts::DATE) + 1)::INT AS day, ts,
 CASE WHEN event_type = 'purchase' THEN 1 ELSE 0 END AS label, user_id, event_type, (props ->> '$.k')::BIGINT AS k
 FROM events WHERE event_type IN ('view', 'click', 'purchase'))"""
