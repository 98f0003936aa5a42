"""Windows, cells, prices, norms."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import kernels as K
from ..operators import matrix, prices
from ..plans import evaluate as E
from ..sources.readers import table
from .registry import EV, FEATURE, STATS, cells, query, s6, u6

SLIDING = matrix.MatrixSpec(length="1 day", slide="6 hours")
_WIDE = f"""{EV}, wide AS (SELECT at_s - at_s % 21600 - o * 21600 AS win_id, entity, {FEATURE['type_k10']} AS feature, value FROM ev, (SELECT unnest([0, 1, 2, 3]) AS o) o)"""


@query(f"WITH {cells()} SELECT * FROM cells")
def cells_tumbling(spark, d):
    return E.log_cells(spark, d)


for _profile in matrix.PROFILES[:2] + matrix.PROFILES[3:]:

    @query(f"WITH {cells(_profile)} SELECT * FROM cells", name=f"cells_profile_{_profile}")
    def _cells_profile(spark, d, profile=_profile):
        return E.log_cells(spark, d, profile)


@query(f"WITH {_WIDE} SELECT win_id, entity, feature, count(*) AS x FROM wide GROUP BY ALL")
def cells_sliding(spark, d):
    return matrix.count_cells(table(spark, d, "events"), SLIDING)


@query(f"WITH {_WIDE} SELECT win_id, entity, feature, count(*) AS x FROM wide GROUP BY ALL")
def cells_from_panes(spark, d):
    return matrix.panes_to_windows(matrix.pane_cells(table(spark, d, "events"), SLIDING), SLIDING)


@query(f"WITH {EV} SELECT at_s - at_s % 86400 AS win_id, entity, {FEATURE['type_k10']} AS feature, {s6('sum(value) / 1000')} AS x_u6 FROM ev GROUP BY ALL")
def cells_value_sum(spark, d):
    return matrix.sum_cells(table(spark, d, "events")).select("win_id", "entity", "feature", u6(F.col("x") / 1000).alias("x_u6"))


@query(f"WITH {EV}, c AS (SELECT at_s - at_s % 3600 AS win_id, entity, {FEATURE['type_k10']} AS feature, count(*) AS x FROM ev GROUP BY ALL) SELECT * FROM c WHERE win_id IN (SELECT win_id FROM c GROUP BY 1 HAVING count(DISTINCT entity) >= 8)")
def min_entities(spark, d):
    return matrix.min_entities(E.log_cells(spark, d, length="1 hour"), 8)


_CLOSE = """rows AS (SELECT l_suppkey AS entity, CAST(date_trunc('week', l_shipdate) AS DATE) AS period, l_extendedprice / l_quantity AS price, l_shipdate, l_orderkey, l_linenumber FROM lineitem WHERE l_suppkey IS NOT NULL AND l_shipdate IS NOT NULL),
closing AS (SELECT entity, period, price FROM rows QUALIFY row_number() OVER (PARTITION BY entity, period ORDER BY l_shipdate DESC, l_orderkey DESC, l_linenumber DESC) = 1)"""
_FILL = f"""{_CLOSE}, cal AS (SELECT period, row_number() OVER (ORDER BY period) - 1 AS t FROM (SELECT DISTINCT period FROM closing)),
grid AS (SELECT entity, cal.period, cal.t FROM (SELECT entity, min(period) AS p0 FROM closing GROUP BY 1) f JOIN cal ON cal.period >= p0),
filled AS (SELECT g.entity, g.period, g.t, last_value(price IGNORE NULLS) OVER (PARTITION BY g.entity ORDER BY g.t ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS price FROM grid g LEFT JOIN closing c USING (entity, period))"""
_CHANGE = f"""{_FILL}, lagged AS (SELECT entity, t, price, lag(price) OVER (PARTITION BY entity ORDER BY t) AS old FROM filled),
changes AS (SELECT entity, t - 1 AS period, CAST(floor((price - old) / old * 10000 + 0.5) AS BIGINT) AS x FROM lagged WHERE old IS NOT NULL)"""


def _rows(step: int, full: bool = True) -> str:
    keep = " QUALIFY count(*) OVER (PARTITION BY f, entity) = 30" if full else ""
    return f"WITH {_CHANGE}, starts AS (SELECT unnest(generate_series(0, (SELECT max(period) - 29 FROM changes), {step})) AS f) SELECT f AS win_id, entity, CAST(period AS VARCHAR) AS feature, x FROM changes JOIN starts ON period BETWEEN f AND f + 29{keep}"


def _weekly(spark, d):
    rows = table(spark, d, "lineitem")
    return prices.closing(rows, "l_suppkey", "l_shipdate", F.col("l_extendedprice") / F.col("l_quantity"), ["l_orderkey", "l_linenumber"])


@query(f"WITH {_CLOSE} SELECT entity, period, {s6('price')} AS price_u6 FROM closing")
def closing_price_week(spark, d):
    return _weekly(spark, d).select("entity", "period", u6("price").alias("price_u6"))


@query(f"WITH {_FILL} SELECT entity, period, t, {s6('price')} AS price_u6 FROM filled")
def price_ffill(spark, d):
    return prices.fill_forward(_weekly(spark, d)).select("entity", "period", "t", u6("price").alias("price_u6"))


@query(f"WITH {_CHANGE} SELECT * FROM changes")
def price_pct_change_bp(spark, d):
    return E.price_changes(spark, d)


@query(_rows(3))
def row_windows_30_3(spark, d):
    return E.price_cells(spark, d)


@query(f"SELECT win_id, count(*) AS cells, count(DISTINCT entity) AS entities, sum(x)::BIGINT AS total FROM ({_rows(1)}) GROUP BY 1")
def row_windows_30_1(spark, d):
    c = E.price_cells(spark, d, 30, 1)
    return c.groupBy("win_id").agg(F.count(F.lit(1)).alias("cells"), F.count_distinct("entity").alias("entities"), F.sum("x").alias("total"))


@query(f"SELECT win_id, count(DISTINCT entity) AS entities, sum(full_) AS full_entities FROM (SELECT win_id, entity, CASE WHEN count(*) = 30 THEN 1 ELSE 0 END AS full_ FROM ({_rows(3, False)}) GROUP BY 1, 2) GROUP BY 1")
def full_coverage(spark, d):
    c = matrix.row_windows(E.price_changes(spark, d), 30, 3, full=False)
    own = c.groupBy("win_id", "entity").agg((F.count(F.lit(1)) == 30).cast("int").alias("f"))
    return own.groupBy("win_id").agg(F.count_distinct("entity").alias("entities"), F.sum("f").alias("full_entities"))


for _p, _name in ((1.0, "p1"), (1.4, "p14"), (2.0, "p2"), (float("inf"), "inf")):
    _e = "max(abs(x))::DOUBLE" if _name == "inf" else f"pow(sum(pow(abs(x)::DOUBLE, CAST({_p} AS DOUBLE))), CAST(1 AS DOUBLE) / CAST({_p} AS DOUBLE))"

    @query(f"WITH {cells()} SELECT win_id, entity, {s6(_e)} AS norm_u6 FROM cells GROUP BY 1, 2", name=f"pnorm_{_name}")
    def _pnorm(spark, d, p=_p):
        return matrix.norms(E.log_cells(spark, d), p).select("win_id", "entity", u6("norm_p").alias("norm_u6"))


@query(f"WITH {cells()}, {STATS} SELECT * FROM st")
def col_stats(spark, d):
    return matrix.col_stats(E.log_cells(spark, d))


@query(f"WITH {cells('type')}, {STATS} SELECT win_id, count(*) AS n_entities, count(*) FILTER (WHERE m * ss = s * s) AS n_constant FROM st GROUP BY 1")
def constant_columns(spark, d):
    return matrix.constant_columns(E.log_cells(spark, d, "type"))


@query(f"WITH {EV}, t AS (SELECT at_s - at_s % 86400 AS day, count(*) FILTER (WHERE event_type = 'click') AS a, count(*) FILTER (WHERE event_type = 'view') AS b FROM ev GROUP BY 1) SELECT {s6('corr(a, b)')} AS rho_u6, {s6('corr(a, 10 * b)')} AS rho_scaled_u6 FROM t")
def toy_correlation(spark, d):
    """Two count vectors, clicks and views by day: scaling one of them changes nothing."""
    import numpy as np
    import pandas as pd

    at = matrix.epoch(F.col("ts").cast("timestamp_ntz"))
    days = table(spark, d, "events").groupBy((at - F.pmod(at, F.lit(86400))).alias("day")).agg(F.count_if(F.col("event_type") == "click").alias("a"), F.count_if(F.col("event_type") == "view").alias("b"))

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        a, b = (pdf[c].to_numpy(float) for c in "ab")
        r = [float(K.pearson(np.stack([a, k * b]))[0, 1]) for k in (1, 10)]
        return pd.DataFrame([r], columns=["a", "b"])

    return days.groupBy().applyInPandas(run, "a double, b double").select(u6("a").alias("rho_u6"), u6("b").alias("rho_scaled_u6"))


@query(f"WITH w AS (SELECT date_trunc('week', l_shipdate) AS week, max(l_extendedprice / l_quantity) AS price FROM lineitem WHERE l_shipdate IS NOT NULL GROUP BY 1), p AS (SELECT row_number() OVER (ORDER BY week) - 1 AS t, price FROM w) SELECT period, pct_u6 FROM (SELECT t - 1 AS period, {s6('(price - lag(price) OVER (ORDER BY t)) / lag(price) OVER (ORDER BY t) * 100')} AS pct_u6 FROM p) WHERE pct_u6 IS NOT NULL")
def toy_price_change(spark, d):
    """Changes of one price series, the week's greatest price, in percent."""
    from pyspark.sql import Window

    weeks = table(spark, d, "lineitem").where("l_shipdate is not null").groupBy(F.date_trunc("week", "l_shipdate").alias("week")).agg(F.max(F.col("l_extendedprice") / F.col("l_quantity")).alias("price"))
    p = weeks.select(F.lit(1).cast("long").alias("entity"), (F.row_number().over(Window.orderBy("week")) - 1).alias("t"), "price")
    return prices.changes(p).select("period", u6("x").alias("pct_u6"))
