"""Accuracy and cost of detectors against injected truth."""

from __future__ import annotations

from pyspark.sql import DataFrame, Observation, Window
from pyspark.sql import functions as F


def alerts_raised(best: DataFrame, truth_wins: DataFrame) -> DataFrame:
    """detector, regime, windows, alerts.  truth_wins: win_id, regime."""
    return best.join(truth_wins, "win_id").groupBy("detector", "regime").agg(F.count(F.lit(1)).alias("windows"), F.count_if("alert").alias("alerts"))


def entity_table(found: DataFrame, truth: DataFrame, before: DataFrame | None = None) -> DataFrame:
    """detector, regime, hits, found, old.  found: win_id, detector, entity (of alerted windows, or of all); truth: win_id,
    regime, entity, injected.  old: found but not injected and already suspicious before injection (before: win_id,
    detector, entity)."""
    named = found.select("win_id", "detector", "entity").distinct()
    t = truth.select("win_id", "regime", "entity", "injected")
    hit = named.join(t, ["win_id", "entity"])
    if before is not None:
        hit = hit.join(before.select("win_id", "detector", "entity").distinct().withColumn("known", F.lit(True)), ["win_id", "detector", "entity"], "left")
    else:
        hit = hit.withColumn("known", F.lit(None).cast("boolean"))
    return hit.groupBy("detector", "regime").agg(F.count_if("injected").alias("hits"), F.count(F.lit(1)).alias("found"), F.count_if(~F.col("injected") & F.coalesce("known", F.lit(False))).alias("old"))


def table1(best: DataFrame, found: DataFrame, truth: DataFrame, before: DataFrame | None = None) -> DataFrame:
    """detector, regime (null: overall), windows, alerts, recall, accuracy, seconds_avg, seconds_max.

    recall: injected entities found in alerted windows over all injected.  accuracy: hits over found less those that were
    suspicious before.  The overall row pools the injected regimes; control windows have alerts only."""
    wins = truth.select("win_id", "regime").distinct()
    injected = truth.where("injected").groupBy("regime").agg(F.count(F.lit(1)).alias("injected"))
    a = best.join(wins, "win_id").groupBy("detector", "regime").agg(F.count(F.lit(1)).alias("windows"), F.count_if("alert").alias("alerts"), F.sum("seconds").alias("s"), F.max("seconds").alias("seconds_max"))
    e = entity_table(found, truth, before)
    x = a.join(e, ["detector", "regime"], "left").join(injected, "regime", "left").fillna(0, ["hits", "found", "old", "injected"])
    x = x.withColumn("case", F.when(F.col("regime") != "control", F.col("regime")))
    rows = x.where("case is not null").rollup("detector", "case").agg(*[F.sum(c).alias(c) for c in ("windows", "alerts", "hits", "found", "old", "injected", "s")], F.max("seconds_max").alias("seconds_max")).where("detector is not null")
    control = x.where("case is null").select("detector", F.lit("control").alias("case"), "windows", "alerts", "hits", "found", "old", "injected", "s", "seconds_max")
    y = rows.unionByName(control)
    return y.select("detector", F.coalesce("case", F.lit("overall")).alias("regime"), "windows", "alerts", (F.col("hits") / F.nullif("injected", F.lit(0))).alias("recall"), (F.col("hits") / F.nullif(F.col("found") - F.col("old"), F.lit(0))).alias("accuracy"), (F.col("s") / F.col("windows")).alias("seconds_avg"), "seconds_max")


def balance(recall: str = "recall", accuracy: str = "accuracy"):  # noqa: ANN201
    """Harmonic mean of recall and accuracy, the choice criterion of the parameter tables."""
    r, a = F.col(recall), F.col(accuracy)
    return F.when(r + a > 0, 2 * r * a / (r + a))


def speed_ratio(best: DataFrame, against: str = "direct") -> DataFrame:
    """detector, seconds_avg, ratio of the reference detector's time to its own."""
    t = best.groupBy("detector").agg(F.avg("seconds").alias("seconds_avg"))
    every = Window.partitionBy(F.lit(1))  # a row for each detector
    ref = F.max(F.when(F.col("detector") == against, F.col("seconds_avg"))).over(every)
    return t.withColumn("ratio", ref / F.col("seconds_avg"))


def observed(findings: DataFrame) -> tuple[DataFrame, Observation]:
    """findings, and the counters that the first action on them fills while the rows pass by: groups judged, alerts raised by
    groups, entities named, and the greatest seconds, steps, rounds and touched (a detector's groups repeat its cost, so
    these are not added up)."""
    counters = Observation()
    own = F.col("entity").isNull()
    most = [F.max(c).alias(c) for c in ("seconds", "steps", "rounds", "touched")]
    return findings.observe(counters, F.count_if(own).alias("groups"), F.count_if(own & F.col("alert")).alias("alerts"), F.count_if(~own).alias("named"), *most), counters
