"""Oracle fragments: the graph's tables as DuckDB common table expressions."""

from __future__ import annotations

LINES = """
li AS (SELECT l.*, o.o_custkey,
         CASE WHEN l_returnflag = 'A' THEN 'assay' WHEN l_returnflag = 'N' THEN 'drug'
              WHEN l_returnflag = 'R' AND l_quantity = 50 THEN 'surgery' WHEN l_returnflag = 'R' THEN 'diagnosis' END AS kind,
         concat_ws('-', 'L', l_orderkey, l_linenumber, l_partkey, l_suppkey, strftime(l_shipdate, '%Y%m%d')) AS event_id
       FROM lineitem l JOIN orders o ON o.o_orderkey = l.l_orderkey)"""

EVENTS = (
    LINES
    + """,
ev AS MATERIALIZED (
  SELECT 'O-' || o_orderkey AS event_id, o_custkey AS patient_id, 'stay' AS kind, NULL AS entity_id, o_orderdate AS begin_ts,
         greatest(o_orderdate, coalesce(last, o_orderdate)) AS end_ts,
         CASE WHEN greatest(o_orderdate, coalesce(last, o_orderdate)) = o_orderdate THEN 'point' ELSE 'period' END AS time_kind,
         NULL AS stay_id, o_orderstatus AS situation, NULL::DOUBLE AS result, NULL AS prompt
  FROM orders LEFT JOIN (SELECT l_orderkey, max(l_shipdate) AS last FROM lineitem GROUP BY 1) ON l_orderkey = o_orderkey
  UNION ALL
  SELECT event_id, o_custkey, kind, kind || '-' || l_partkey, l_shipdate,
         CASE WHEN kind = 'drug' THEN l_shipdate + to_days(CAST(l_quantity AS INTEGER)) ELSE l_shipdate END,
         CASE WHEN kind = 'drug' THEN 'period' ELSE 'point' END, 'O-' || l_orderkey,
         CASE WHEN kind = 'diagnosis' THEN l_linestatus END, CASE WHEN kind = 'assay' THEN l_extendedprice END, CASE WHEN kind = 'assay' THEN l_linestatus END
  FROM li WHERE kind IS NOT NULL)"""
)

ENTITIES = """
ent AS (SELECT DISTINCT kind || '-' || l_partkey AS entity_id, kind, p_name AS label, p_brand AS brand, p_type AS type
        FROM li JOIN part ON p_partkey = l_partkey WHERE kind IS NOT NULL)"""

#: Bounds of immediate successors and the edges, of a relation {src}.
BOUNDS = """
{n}_m AS (SELECT patient_id, begin_ts, min(min(end_ts)) OVER (PARTITION BY patient_id ORDER BY begin_ts DESC ROWS UNBOUNDED PRECEDING) AS m FROM {src} GROUP BY 1, 2),
{n} AS (SELECT a.patient_id, a.event_id AS src, b.event_id AS dst,
          CASE WHEN a.time_kind = 'point' AND b.time_kind = 'point' THEN 1 WHEN a.time_kind = 'period' AND b.time_kind = 'period' THEN 2 ELSE 3 END AS step
        FROM (SELECT e.*, s.m FROM {src} e ASOF JOIN {n}_m s ON e.patient_id = s.patient_id AND e.end_ts < s.begin_ts) a
        JOIN {src} b ON a.patient_id = b.patient_id AND b.begin_ts > a.end_ts AND b.begin_ts <= a.m)"""


def bounds(name: str, src: str) -> str:
    return BOUNDS.format(n=name, src=src)


CONCURRENT = """
con AS (SELECT a.patient_id, a.event_id AS src, b.event_id AS dst, CASE WHEN a.time_kind = 'point' THEN 1 ELSE 2 END AS step
        FROM ev a JOIN ev b USING (patient_id, begin_ts, end_ts) WHERE a.event_id < b.event_id)"""

STABBED = """
stab AS (SELECT b.patient_id, a.event_id AS src, b.event_id AS dst,
           CASE WHEN a.end_ts < b.end_ts OR (a.time_kind = 'point' AND a.begin_ts = b.end_ts) THEN 'During'
                WHEN a.time_kind = 'period' AND a.begin_ts > b.begin_ts AND a.end_ts > b.end_ts THEN 'Overlap' END AS relation,
           CASE WHEN a.time_kind = 'point' THEN 3 ELSE 4 END AS step, a.end_ts = b.end_ts AND a.time_kind = 'period' AND a.begin_ts > b.begin_ts AS finishes
         FROM ev b JOIN ev a ON a.patient_id = b.patient_id AND a.begin_ts BETWEEN b.begin_ts AND b.end_ts AND a.event_id <> b.event_id
         WHERE b.time_kind = 'period')"""

RELATIONS = f"""
{bounds("bef", "ev")}, {CONCURRENT}, {STABBED},
rel AS (SELECT patient_id, src, dst, 'Before' AS relation, step FROM bef
        UNION ALL SELECT patient_id, dst, src, 'After', step FROM bef
        UNION ALL SELECT patient_id, src, dst, 'Concurrent', step FROM con
        UNION ALL SELECT patient_id, src, dst, relation, step FROM stab WHERE relation IS NOT NULL)"""


def sql(*parts: str, body: str, recursive: bool = False) -> str:
    """WITH of the named parts, then the body."""
    return f"WITH {'RECURSIVE ' if recursive else ''}{', '.join(parts)} {body}"
