"""Principal score of pair tables: distributed power iteration, bounds, members, alerts."""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def cut_lineage(df: DataFrame) -> DataFrame:
    """df with its lineage ended: a checkpoint in the shared folder of spark.checkpoint.dir, set here only if unset."""
    sc = df.sparkSession.sparkContext
    if sc.getCheckpointDir() is None:
        at = df.sparkSession.conf.get("spark.checkpoint.dir", None) or scratch_dir(df.sparkSession)
        sc.setCheckpointDir(at)
    return df.checkpoint()


def scratch_dir(spark: SparkSession) -> str:
    """A folder all executors share: in the warehouse, or a temporary one if Spark runs in this process alone."""
    if spark.sparkContext.master.startswith("local[") or spark.sparkContext.master == "local":
        import tempfile

        return tempfile.mkdtemp(prefix="corrsentry-")
    return f"{spark.conf.get('spark.sql.warehouse.dir')}/_scratch-{uuid.uuid4().hex}"


def both_ways(pairs: DataFrame) -> DataFrame:
    """Pairs i < j as directed edges and the unit diagonal of every entity that occurs."""
    a = pairs.select("win_id", "i", "j", "rho")
    b = pairs.select("win_id", F.col("j").alias("i"), F.col("i").alias("j"), "rho")
    nodes = a.select("win_id", "i").unionByName(b.select("win_id", "i")).distinct()
    return a.unionByName(b).unionByName(nodes.select("win_id", "i", F.col("i").alias("j"), F.lit(1.0).alias("rho")))


def row_sum_bounds(pairs: DataFrame) -> DataFrame:
    """win_id, n, lower and upper bound of the score from row sums, and the mean entry, a lower bound that is often closer."""
    rows = both_ways(pairs).groupBy("win_id", "i").agg(F.sum("rho").alias("s"))
    n = F.count(F.lit(1))
    return rows.groupBy("win_id").agg(n.alias("n"), (F.min("s") / n).alias("lower"), (F.max("s") / n).alias("upper"), (F.sum("s") / n / n).alias("mean_entry"))


def power_step(edges: DataFrame, v: DataFrame) -> DataFrame:
    """One product and its normalisation by the largest entry: (win_id, i, v), and lambda as that entry."""
    y = edges.join(v.select("win_id", F.col("i").alias("j"), "v"), ["win_id", "j"]).groupBy("win_id", "i").agg(F.sum(F.col("rho") * F.col("v")).alias("y"))
    top = F.max("y").over(Window.partitionBy("win_id"))
    return y.select("win_id", "i", (F.col("y") / top).alias("v"), top.alias("lambda1"))


def power(pairs: DataFrame, iterations: int = 40, every: int = 10) -> DataFrame:
    """win_id, n, lambda1, score of abs or positive pairs by distributed power iteration from the all-ones vector.

    Every `every` steps the vector is checkpointed, so plans stay short and lost executors do not restart the loop."""
    edges = cut_lineage(both_ways(pairs))
    v = edges.select("win_id", "i").distinct().withColumn("v", F.lit(1.0))
    for k in range(1, iterations + 1):
        v = power_step(edges, v)
        if k % every == 0 and k < iterations:
            v = cut_lineage(v)
    n = F.count(F.lit(1))
    return v.groupBy("win_id").agg(n.alias("n"), F.max("lambda1").alias("lambda1"), (F.max("lambda1") / n).alias("score"))


def alerts(scores: DataFrame, threshold: float = 0.7, min_strength: float | None = None) -> DataFrame:
    """Scores over the threshold; with a least strength, alerts of lighter groups are muted."""
    loud = scores.where(F.col("score") > threshold)
    return loud if min_strength is None else loud.where(F.col("strength") >= min_strength)


def strength(norms: DataFrame, members: DataFrame) -> DataFrame:
    """win_id, strength: the members' share of the window's total magnitude."""
    inside = members.select("win_id", "entity", F.lit(True).alias("inside")).distinct()
    both = norms.join(inside, ["win_id", "entity"], "left")
    return both.groupBy("win_id").agg((F.coalesce(F.sum(F.when(F.col("inside"), F.col("norm_p"))), F.lit(0.0)) / F.sum("norm_p")).alias("strength"))


def rounded(c: Column | str, digits: int = 6) -> Column:
    return F.round(F.col(c) if isinstance(c, str) else c, digits)
