"""Windows of events as entity-by-feature cells, and per-column statistics of them.

A cell is (win_id, entity, feature, x); win_id is the window's start in seconds since 1970.  Cells stay in this long form
until a kernel needs one window as an array: wide pivots would grow with the number of features.
"""

from __future__ import annotations

from typing import NamedTuple

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

SECOND = {"minute": 60, "minutes": 60, "hour": 3600, "hours": 3600, "day": 86400, "days": 86400, "week": 604800, "weeks": 604800}
#: Feature profiles of the event stream: what a row of the matrix stands for.
PROFILES = ("type", "k10", "type_k10", "k")


class MatrixSpec(NamedTuple):
    """Which columns make the matrix, and how time is cut into windows."""

    entity: str = "user_id"
    time: str = "ts"
    profile: str = "type_k10"
    length: str = "1 day"
    slide: str | None = None


def seconds(span: str) -> int:
    n, unit = span.split()
    return int(n) * SECOND[unit]


def feature(profile: str) -> Column:
    k = F.get_json_object("props", "$.k").cast("long")
    ten = F.floor(k / 10).cast("string")
    kinds = {"type": F.col("event_type"), "k10": ten, "type_k10": F.concat_ws("-", "event_type", ten), "k": k.cast("string")}
    if profile not in kinds:
        raise ValueError(f"profile must be one of {PROFILES}")
    return kinds[profile]


def epoch(t: Column) -> Column:
    """Seconds since 1970 of a timestamp without zone."""
    return F.timestamp_diff("SECOND", F.lit("1970-01-01 00:00:00").cast("timestamp_ntz"), t)


def _assigned(events: DataFrame, spec: MatrixSpec) -> DataFrame:
    """win_id for each window an event falls in; only the needed columns are read."""
    at = epoch(F.col(spec.time).cast("timestamp_ntz"))
    length, slide = seconds(spec.length), seconds(spec.slide or spec.length)
    last = at - F.pmod(at, F.lit(slide))
    slim = events.select(F.col(spec.entity).alias("entity"), feature(spec.profile).alias("feature"), last.alias("_last"), *(["value"] if "value" in events.columns else []))
    slim = slim.where("entity is not null and feature is not null")
    if length == slide:
        return slim.withColumnRenamed("_last", "win_id")
    return slim.withColumn("win_id", F.explode(F.sequence(F.col("_last") - (length - slide), F.col("_last"), F.lit(slide)))).drop("_last")


def count_cells(events: DataFrame, spec: MatrixSpec = MatrixSpec()) -> DataFrame:  # noqa: B008
    """Counts by window, entity and feature; each event is expanded to its length / slide windows."""
    return _assigned(events, spec).groupBy("win_id", "entity", "feature").agg(F.count(F.lit(1)).alias("x"))


def sum_cells(events: DataFrame, spec: MatrixSpec = MatrixSpec()) -> DataFrame:  # noqa: B008
    """As count_cells, with the sum of `value` instead of the count."""
    return _assigned(events, spec).groupBy("win_id", "entity", "feature").agg(F.sum("value").alias("x"))


def pane_cells(events: DataFrame, spec: MatrixSpec = MatrixSpec()) -> DataFrame:  # noqa: B008
    """Counts by pane, the stretch of one slide: each event is counted once, whatever the windows' overlap."""
    return count_cells(events, spec._replace(length=spec.slide or spec.length, slide=None)).withColumnRenamed("win_id", "pane")


def panes_to_windows(panes: DataFrame, spec: MatrixSpec) -> DataFrame:
    """Sum of the panes of each window; the shuffle holds one row for each pane cell and window, not for each event."""
    length, slide = seconds(spec.length), seconds(spec.slide or spec.length)
    wide = panes.withColumn("win_id", F.explode(F.sequence(F.col("pane") - (length - slide), F.col("pane"), F.lit(slide))))
    return wide.groupBy("win_id", "entity", "feature").agg(F.sum("x").alias("x"))


def norms(cells: DataFrame, p: float) -> DataFrame:
    """win_id, entity, norm_p of raw magnitudes (not centred)."""
    a = F.abs(F.col("x").cast("double"))
    norm = F.max(a) if p == float("inf") else F.pow(F.sum(F.pow(a, F.lit(float(p)))), F.lit(1.0 / p))
    return cells.groupBy("win_id", "entity").agg(norm.alias("norm_p"))


def feature_counts(cells: DataFrame) -> DataFrame:
    """win_id, m: distinct features of each window, used by any entity."""
    return cells.groupBy("win_id").agg(F.count_distinct("feature").alias("m"))


def col_stats(cells: DataFrame) -> DataFrame:
    """win_id, entity, nnz, s (sum), ss (sum of squares), m (features of the window)."""
    own = cells.groupBy("win_id", "entity").agg(F.count(F.lit(1)).alias("nnz"), F.sum("x").alias("s"), F.sum(F.col("x") * F.col("x")).alias("ss"))
    return own.join(feature_counts(cells), "win_id")


def constant_columns(cells: DataFrame) -> DataFrame:
    """win_id, n_entities, n_constant: entities whose vector has no spread take no part in correlations."""
    flat = F.col("m") * F.col("ss") == F.col("s") * F.col("s")
    return col_stats(cells).groupBy("win_id").agg(F.count(F.lit(1)).alias("n_entities"), F.count_if(flat).alias("n_constant"))


def min_entities(cells: DataFrame, least: int = 21) -> DataFrame:
    """Cells of the windows with at least so many entities."""
    big = cells.groupBy("win_id").agg(F.count_distinct("entity").alias("n")).where(F.col("n") >= least).select("win_id")
    return cells.join(big, "win_id", "left_semi")


def row_windows(changes: DataFrame, length: int = 30, step: int = 3, full: bool = True, arrays: bool = False) -> DataFrame:
    """(entity, period, x), periods numbered from 0 -> cells of windows of `length` periods every `step`; win_id is the
    first period, the feature is the period's number.  full: only entities with every period of the window.  arrays: full
    rows as (win_id, entity, x array), periods in order, which hold each window's values without a row for each cell."""
    if arrays:
        return _full_rows(changes, length, step)
    last = changes.agg(F.max("period")).first()[0]
    top = -1 if last is None else last - length + 1
    first = F.greatest(F.lit(0), F.ceil((F.col("period") - (length - 1)) / step) * step).cast("long")
    end = F.least(F.floor(F.col("period") / step) * step, F.lit(top - top % step if top >= 0 else -1)).cast("long")
    wide = changes.where(first <= end).withColumn("win_id", F.explode(F.sequence(first, end, F.lit(step).cast("long"))))
    cells = wide.select("win_id", "entity", F.col("period").cast("string").alias("feature"), "x")
    if not full:
        return cells
    w = Window.partitionBy("win_id", "entity")
    return cells.withColumn("_n", F.count(F.lit(1)).over(w)).where(F.col("_n") == length).drop("_n")


def _full_rows(changes: DataFrame, length: int, step: int) -> DataFrame:
    """One row of an entity's series, cut into the windows that have every period."""
    own = changes.groupBy("entity").agg(F.sort_array(F.collect_list(F.struct("period", "x"))).alias("s")).select("entity", F.col("s.period").alias("p"), F.col("s.x").alias("x"))
    # a place in the series whose window ends length - 1 periods later is one without a gap
    at = F.filter(F.sequence(F.lit(0), F.size("p") - length), lambda i: (F.element_at("p", i + length) - F.element_at("p", i + 1) == length - 1) & (F.element_at("p", i + 1) % step == 0))
    wide = own.where(F.size("p") >= length).select("entity", "p", "x", F.explode(at).alias("i"))
    return wide.select(F.element_at("p", F.col("i") + 1).cast("long").alias("win_id"), "entity", F.slice("x", F.col("i") + 1, length).alias("x"))
