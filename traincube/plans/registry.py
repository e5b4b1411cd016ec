"""Queries by name, with the SQL that gives the same rows."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    """Register a query, and its SQL where SQL can express it."""

    def register(f: Query) -> Query:
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return register


#: Shared heads of the SQL texts.
VEHICLE = """
WITH cells AS MATERIALIZED (
  SELECT date_diff('microsecond', TIMESTAMP '2024-01-01', ts) // 1800000000 AS step, user_id AS entity,
         sum(value) AS c1, sum(CAST(json_extract_string(props, '$.k') AS DOUBLE)) AS c2, CAST(count(*) AS DOUBLE) AS c3
  FROM events GROUP BY ALL),
users AS (SELECT unnest(range(m + 1)) AS entity FROM (SELECT max(user_id) AS m FROM events)),
rates AS MATERIALIZED (
  SELECT s.step, u.entity, coalesce(c1, 0.0) AS c1, coalesce(c2, 0.0) AS c2, coalesce(c3, 0.0) AS c3
  FROM (SELECT unnest(range(1440)) AS step) s CROSS JOIN users u LEFT JOIN cells c ON c.step = s.step AND c.entity = u.entity),
levels AS MATERIALIZED (
  SELECT step, entity, round(sum(c1) OVER w, 4) AS c1, round(sum(c2) OVER w, 4) AS c2, round(sum(c3) OVER w, 4) AS c3
  FROM rates WINDOW w AS (PARTITION BY entity ORDER BY step ROWS UNBOUNDED PRECEDING)),
box AS (SELECT min(c1) a1, max(c1) b1, min(c2) a2, max(c2) b2, min(c3) a3, max(c3) b3 FROM levels),
cube AS (
  SELECT step, entity,
         least(CASE WHEN b1 > a1 THEN (c1 - a1) / (b1 - a1) ELSE 0.0 END, 1.0 - 1.0 / 1024) AS ux,
         least(CASE WHEN b2 > a2 THEN (c2 - a2) / (b2 - a2) ELSE 0.0 END, 1.0 - 1.0 / 1024) AS uy,
         least(CASE WHEN b3 > a3 THEN (c3 - a3) / (b3 - a3) ELSE 0.0 END, 1.0 - 1.0 / 1024) AS uz
  FROM levels, box),
"""


def interleave(names: list[str], bits: int) -> str:
    """SQL for the Morton key of whole numbers, the first most significant."""
    q = len(names)
    return " | ".join(f"((({x} >> {b}) & 1) << {q * b + q - 1 - a})" for b in range(bits) for a, x in enumerate(names))


VEHICLE_KEYS = VEHICLE + f"""
cells3 AS (SELECT step, entity, CAST(floor(ux * 1024) AS BIGINT) AS x, CAST(floor(uy * 1024) AS BIGINT) AS y, CAST(floor(uz * 1024) AS BIGINT) AS z FROM cube),
keys AS (SELECT step, entity, {interleave(['x', 'y', 'z'], 10)} AS morton FROM cells3),
"""
