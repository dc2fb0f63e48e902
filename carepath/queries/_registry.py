"""Where queries and their twins are put, and SQL that many twins begin with."""

from __future__ import annotations

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def put(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return put


ENC = """WITH stay AS (
  SELECT l_orderkey, 1 + CAST(sum(CAST(l_quantity AS BIGINT)) % 14 AS INTEGER) AS days FROM lineitem GROUP BY l_orderkey
), enc AS (
  SELECT o_custkey AS subject_id, o_orderkey AS visit_id, CAST(o_orderdate AS DATE) AS admit,
    CAST(o_orderdate AS DATE) + coalesce(days, 1) AS discharge, o_orderpriority AS urgency
  FROM orders LEFT JOIN stay ON l_orderkey = o_orderkey
), seq AS (
  SELECT *, lag(discharge) OVER w AS prior_discharge, lag(admit) OVER w AS prior_admit, lead(admit) OVER w AS next_admit,
    lead(urgency) OVER w AS next_urgency, lead(visit_id) OVER w AS next_visit, row_number() OVER w AS pos,
    count(*) OVER (PARTITION BY subject_id) AS m
  FROM enc WINDOW w AS (PARTITION BY subject_id ORDER BY admit, visit_id)
), lab AS (
  SELECT *, CASE WHEN next_admit - discharge < 30 THEN 1 ELSE 0 END AS y FROM seq
)"""

#: Diagnoses of a visit at a level, in order, first occurrences only.
DX = """, d0 AS (
  SELECT l_orderkey AS visit_id, {level} AS code, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey) AS i
  FROM lineitem JOIN part ON l_partkey = p_partkey
), d1 AS (SELECT visit_id, code, min(i) AS i FROM d0 GROUP BY visit_id, code),
dx AS (SELECT visit_id, list(code ORDER BY i) AS codes FROM d1 GROUP BY visit_id)"""

HASH = "('0x' || substr(md5({key} || '/' || '{seed}'), 1, 8))::BIGINT"
