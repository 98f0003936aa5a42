"""Batch peeling of large edge lists: each pass drops every node that is light against the density."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .score import cut_lineage


def densities(edges: DataFrame) -> DataFrame:
    """win_id, nodes, weight, density of edges (win_id, u, v, w); ends u and v are told apart by the caller."""
    ends = edges.select("win_id", F.col("u").alias("node")).unionByName(edges.select("win_id", F.col("v").alias("node"))).distinct()
    n = ends.groupBy("win_id").agg(F.count(F.lit(1)).alias("nodes"))
    return n.join(edges.groupBy("win_id").agg(F.sum("w").alias("weight")), "win_id").withColumn("density", F.col("weight") / F.col("nodes"))


def batch_pass(edges: DataFrame, eps: float = 0.1) -> DataFrame:
    """The edges left when all nodes with an incident weight of at most 2 (1 + eps) times the density are dropped."""
    d = densities(edges).select("win_id", "density")
    load = edges.select("win_id", F.col("u").alias("node"), "w").unionByName(edges.select("win_id", F.col("v").alias("node"), "w")).groupBy("win_id", "node").agg(F.sum("w").alias("load"))
    light = load.join(d, "win_id").where(F.col("load") <= 2 * (1 + eps) * F.col("density")).select("win_id", "node")
    return edges.join(light.withColumnRenamed("node", "u"), ["win_id", "u"], "left_anti").join(light.withColumnRenamed("node", "v"), ["win_id", "v"], "left_anti").select("win_id", "u", "v", "w")


def batch_peel(edges: DataFrame, eps: float = 0.1, max_passes: int = 60) -> tuple[DataFrame, DataFrame]:
    """(edges of each window's densest remainder, its density).  Passes are logarithmic in the nodes; the answer is within
    a factor 2 (1 + eps) of the densest subgraph."""
    edges = cut_lineage(edges.select("win_id", "u", "v", "w"))
    best = cut_lineage(densities(edges).select("win_id", "density"))
    keep = edges
    for _ in range(max_passes):
        edges = cut_lineage(batch_pass(edges, eps))
        if edges.isEmpty():
            break
        now = densities(edges).select("win_id", F.col("density").alias("new"))
        better = cut_lineage(now.join(best, "win_id").where("new > density").select("win_id", "new"))
        keep = cut_lineage(keep.join(better, "win_id", "left_anti").unionByName(edges.join(better, "win_id", "left_semi")))
        best = cut_lineage(best.join(better, "win_id", "left").select("win_id", F.coalesce("new", "density").alias("density")))
    return keep, best


def feature_edges(cells: DataFrame) -> DataFrame:
    """Cells as edges between entities (u) and features (v); prefixes keep the two kinds apart."""
    return cells.select("win_id", F.concat(F.lit("e:"), F.col("entity").cast("string")).alias("u"), F.concat(F.lit("f:"), F.col("feature")).alias("v"), F.abs("x").alias("w"))
