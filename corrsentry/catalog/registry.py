"""Registration of queries, and the pieces of SQL that many twins share."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):  # noqa: ANN201
    """Register a function under its name; sql: the twin that must give the same rows."""

    def take(f: Callable[[SparkSession, str], DataFrame]) -> Callable[[SparkSession, str], DataFrame]:
        QUERIES[name or f.__name__] = f
        if sql:
            ORACLES[name or f.__name__] = sql
        return f

    return take


def u6(c: Column | str) -> Column:
    """Millionths as a whole number, by the same arithmetic in both engines."""
    return F.floor((F.col(c) if isinstance(c, str) else c) * 1000000 + 0.5).cast("long")


def s6(e: str) -> str:
    return f"CAST(floor(({e}) * 1000000 + 0.5) AS BIGINT)"


#: DuckDB expressions of the feature profiles.
FEATURE = {"type": "event_type", "k10": "CAST(k // 10 AS VARCHAR)", "type_k10": "event_type || '-' || CAST(k // 10 AS VARCHAR)", "k": "CAST(k AS VARCHAR)"}
EV = "ev AS (SELECT user_id AS entity, event_type, value, CAST(floor(epoch(ts)) AS BIGINT) AS at_s, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events)"


def cells(profile: str = "type_k10", width: int = 86400) -> str:
    """CTEs ev and cells of tumbling windows."""
    return f"{EV}, cells AS (SELECT at_s - at_s % {width} AS win_id, entity, {FEATURE[profile]} AS feature, count(*) AS x FROM ev WHERE entity IS NOT NULL AND {FEATURE[profile]} IS NOT NULL GROUP BY ALL)"


STATS = """st AS (SELECT c.win_id, entity, count(*) AS nnz, sum(x)::BIGINT AS s, sum(x * x)::BIGINT AS ss, max(m)::BIGINT AS m FROM cells c JOIN (SELECT win_id, count(DISTINCT feature) AS m FROM cells GROUP BY 1) f USING (win_id) GROUP BY 1, 2),
live AS (SELECT * FROM st WHERE m * ss <> s * s)"""
#: All pairs, signed; those without a common feature included.
PAIRS = f"""{STATS},
dots AS (SELECT a.win_id, a.entity AS i, b.entity AS j, sum(a.x * b.x)::BIGINT AS c FROM cells a JOIN cells b ON a.win_id = b.win_id AND a.feature = b.feature AND a.entity < b.entity GROUP BY 1, 2, 3),
pairs AS (SELECT a.win_id, a.entity AS i, b.entity AS j, (a.m * coalesce(c, 0) - a.s * b.s)::DOUBLE / (sqrt((a.m * a.ss - a.s * a.s)::DOUBLE) * sqrt((b.m * b.ss - b.s * b.s)::DOUBLE)) AS rho
 FROM live a JOIN live b ON a.win_id = b.win_id AND a.entity < b.entity LEFT JOIN dots d ON d.win_id = a.win_id AND d.i = a.entity AND d.j = b.entity)"""


def power(edges: str, steps: int = 60) -> str:
    """CTEs it (power iteration from ones on edges (win_id, i, j, rho)) and lam (win_id, n, lambda1), and vec (win_id, i, v)."""
    return f"""edges AS ({edges}),
it AS (SELECT 0 AS step, win_id, i, 1.0::DOUBLE AS v, 0.0::DOUBLE AS l FROM (SELECT DISTINCT win_id, i FROM edges) UNION ALL
 SELECT step + 1, win_id, i, y / max(y) OVER (PARTITION BY win_id), max(y) OVER (PARTITION BY win_id) FROM (SELECT it.step, e.win_id, e.i, sum(e.rho * it.v) AS y FROM it JOIN edges e ON e.win_id = it.win_id AND e.j = it.i WHERE it.step < {steps} GROUP BY 1, 2, 3)),
lam AS (SELECT win_id, count(*) AS n, max(l) AS lambda1 FROM it WHERE step = {steps} GROUP BY 1),
vec AS (SELECT win_id, i, v FROM it WHERE step = {steps})"""


ABS_EDGES = "SELECT win_id, i, j, abs(rho) AS rho FROM pairs UNION ALL SELECT win_id, j, i, abs(rho) FROM pairs UNION ALL SELECT win_id, entity, entity, 1.0::DOUBLE FROM live"
#: Members by plain rules on event counts, so that both engines have the same ones: three stand-in detectors.
RULES = """rule_members AS (SELECT win_id, 'sampled' AS detector, entity FROM cells GROUP BY 1, 3 HAVING sum(x) >= 5
 UNION ALL SELECT win_id, 'block', entity FROM cells GROUP BY 1, 3 HAVING count(*) >= 4
 UNION ALL SELECT win_id, 'direct', entity FROM cells GROUP BY 1, 3 HAVING max(x) >= 2)"""


def rule_members(cells_: DataFrame) -> DataFrame:
    own = cells_.groupBy("win_id", "entity").agg(F.sum("x").alias("s"), F.count(F.lit(1)).alias("k"), F.max("x").alias("top"))
    part = lambda name, cond: own.where(cond).select("win_id", F.lit(name).alias("detector"), "entity")
    return part("sampled", "s >= 5").unionByName(part("block", "k >= 4")).unionByName(part("direct", "top >= 2"))
