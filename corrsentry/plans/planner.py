"""Which path a window takes, from cheap counts: nothing quadratic is run blindly."""

from __future__ import annotations

from typing import NamedTuple

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import alerts, detect
from ..operators.corr import columns, pairs_dense, pairs_sparse, tile_pairs, tiles
from ..operators.detect import FINDINGS, DetectConfig
from ..operators.sampled import weights
from ..operators.score import cut_lineage
from .sampled_large import sampled_large
from .spread import HEADS, NAMED, classes, judge


class Limits(NamedTuple):
    exact: int = 512  # entities up to which the exact eigenvalue solver runs
    one_task: int = 8_192  # entities of a window that one task may hold
    tiled: int = 200_000  # entities up to which all pairs are made, in tiles
    cell_budget: int = 50_000_000  # cells of a window that one task may hold


def shape(cells: DataFrame) -> DataFrame:
    """win_id, n, m, nnz, join_rows (sum of squared feature degrees: what a sparse self join would make)."""
    deg = cells.groupBy("win_id", "feature").agg(F.count(F.lit(1)).alias("d"))
    f = deg.groupBy("win_id").agg(F.count(F.lit(1)).alias("m"), F.sum("d").alias("nnz"), F.sum(F.col("d") * F.col("d")).alias("join_rows"))
    return f.join(cells.groupBy("win_id").agg(F.count_distinct("entity").alias("n")), "win_id").select("win_id", "n", "m", "nnz", "join_rows")


def choose(shapes: DataFrame, limits: Limits = Limits()) -> DataFrame:  # noqa: B008
    """shapes with solver (exact, lanczos, tiles or sampled) and pairs_path (sparse or dense): sparse joins only where they
    make fewer rows than half of all pairs."""
    n = F.col("n")
    solver = F.when((n <= limits.exact) & (F.col("nnz") <= limits.cell_budget), "exact").when((n <= limits.one_task) & (F.col("nnz") <= limits.cell_budget), "lanczos").when(n <= limits.tiled, "tiles").otherwise("sampled")
    return shapes.withColumn("solver", solver).withColumn("pairs_path", F.when(F.col("join_rows") * 2 < n * n, "sparse").otherwise("dense"))


def route(cells: DataFrame, limits: Limits = Limits()) -> tuple[DataFrame, DataFrame]:  # noqa: B008
    """(cells of windows one task can hold, cells of larger windows)."""
    plan = choose(shape(cells), limits).select("win_id", "solver")
    small = plan.where(F.col("solver").isin("exact", "lanczos")).select("win_id")
    return cells.join(small, "win_id", "left_semi"), cells.join(small, "win_id", "left_anti")


def all_pairs(cells: DataFrame, limits: Limits = Limits()) -> DataFrame:  # noqa: B008
    """Signed pairs of every window by the path its shape asks for; windows over `tiled` entities are refused."""
    plan = choose(shape(cells), limits)
    if not plan.where("solver = 'sampled'").isEmpty():
        raise ValueError("a window has too many entities for all its pairs: sample it first")
    of = lambda cond: cells.join(plan.where(cond).select("win_id"), "win_id", "left_semi")
    sparse = pairs_sparse(of("pairs_path = 'sparse'"), complete=True)
    dense = pairs_dense(of("pairs_path = 'dense' and solver <> 'tiles'"))
    tiled = tile_pairs(tiles(columns(of("pairs_path = 'dense' and solver = 'tiles'"))))
    return sparse.unionByName(dense).unionByName(tiled)


def detect_any(cells: DataFrame, cfg: DetectConfig = DetectConfig(), limits: Limits = Limits(), tile: int = 2048) -> DataFrame:  # noqa: B008
    """Findings (detect.FINDINGS) of windows of any size: those one task can hold by detect.detect, larger ones by the same draws
    and the same steps over blocks of distinct rows, which are multiplied anew for each product.  What is found does not depend
    on the path; there, a finding tells no steps, rounds or seconds, and peel and mixture are refused."""
    plan = cut_lineage(choose(shape(cells), limits))
    of = lambda cond: cells.join(F.broadcast(plan.where(cond).select("win_id")), "win_id", "left_semi")
    one_task = F.col("solver").isin("exact", "lanczos")
    out = detect.detect(of(one_task), cfg)
    wide = plan.where(~one_task).select("win_id", "n")
    if wide.isEmpty():
        return out
    if set(cfg.detectors) - {"direct", "sampled", "block", "cascade"}:
        raise ValueError("a window is too large for peel or mixture")
    return out.unionByName(_large(of(~one_task), wide, cfg, tile))


def _large(cells: DataFrame, wide: DataFrame, cfg: DetectConfig, tile: int) -> DataFrame:
    cols = cut_lineage(classes(columns(cells), cfg.mode))
    used = cols.groupBy("win_id").agg(F.count(F.lit(1)).alias("n_used"))
    w = weights(cells, cfg.p).withColumnRenamed("w", "weight").join(cols.select("win_id", "entity"), ["win_id", "entity"], "left_semi")
    load = cut_lineage(sampled_large(cells, cfg.r, cfg.p, cfg.max_sample, cfg.mode, cols=cols))
    head = load.groupBy("win_id").agg(F.first("lambda1").alias("lambda1"), F.first("score").alias("score"))
    heads = {"sampled": head.select("win_id", F.lit(1).alias("group_id"), "lambda1", "score", (F.col("score") > cfg.threshold).alias("loud"))}
    named = {"sampled": load.where(F.col("loading") >= cfg.loading_cut).select("win_id", F.lit(1).alias("group_id"), "entity", "loading")}
    if {"direct", "block", "cascade"} & set(cfg.detectors):
        spark = cells.sparkSession
        found = judge(cols, named["sampled"], cfg, tile)
        every, members = spark.createDataFrame(found.heads, HEADS), spark.createDataFrame(found.named, NAMED)
        for d in {h[1] for h in found.heads}:
            heads[d], named[d] = (x.where(F.col("detector") == d).drop("detector") for x in (every, members))
    join_all = lambda parts: [d.withColumn("detector", F.lit(k)) for k, d in parts.items()]
    union = lambda ds: ds[0] if len(ds) == 1 else ds[0].unionByName(union(ds[1:]))
    own = union(join_all(named)).join(w, ["win_id", "entity"])
    total = w.groupBy("win_id").agg(F.sum("weight").alias("total"))
    sums = own.groupBy("win_id", "detector", "group_id").agg(F.sum("weight").alias("mine"), F.count(F.lit(1)).alias("n_members"))
    found = union(join_all(heads)).join(sums, ["win_id", "detector", "group_id"], "left").join(total, "win_id")
    found = found.withColumn("n_members", F.coalesce("n_members", F.lit(0))).withColumn("strength", F.coalesce(F.col("mine") / F.col("total"), F.lit(0.0)))
    found = found.withColumn("alert", F.col("loud") & (F.col("strength") >= cfg.min_strength)).drop("mine", "total", "loud")
    own = own.drop("weight")
    if "cascade" in cfg.detectors:
        loud = own.where(F.col("detector").isin("sampled", "block")).join(found.where("alert").select("win_id", "detector", "group_id"), ["win_id", "detector", "group_id"]).drop("group_id")
        grades = alerts.merge(loud).select("win_id", "entity", F.when(F.col("grade") == "core", 1).otherwise(2).alias("group_id"))
        both = grades.join(loud.groupBy("win_id", "entity").agg(F.max("loading").alias("loading")), ["win_id", "entity"]).withColumn("detector", F.lit("cascade"))
        parts = both.join(w, ["win_id", "entity"]).groupBy("win_id", "group_id").agg(F.sum("weight").alias("mine"), F.count(F.lit(1)).alias("n_members")).join(total, "win_id")
        top = found.where(F.col("detector").isin("sampled", "block")).groupBy("win_id").agg(F.max("score").alias("score"))
        merged = top.join(parts, "win_id", "left").select("win_id", F.lit("cascade").alias("detector"), F.lit(None).cast("double").alias("lambda1"), "score", F.coalesce("n_members", F.lit(0)).alias("n_members"), F.coalesce(F.col("mine") / F.col("total"), F.lit(0.0)).alias("strength"), F.coalesce("group_id", F.lit(1)).alias("group_id"), F.col("group_id").isNotNull().alias("alert"))
        found, own = found.unionByName(merged), own.unionByName(both.select(*own.columns))
    found = found.where(F.col("detector").isin(*cfg.detectors)).join(used, "win_id").join(wide, "win_id").withColumn("n_constant", F.col("n") - F.col("n_used"))
    rows = found.withColumn("entity", F.lit(None).cast("long")).withColumn("loading", F.lit(None).cast("double"))
    rows = rows.unionByName(own.join(found, ["win_id", "detector", "group_id"]).select(*rows.columns))
    for name, kind in (x.split() for x in FINDINGS.split(", ")):
        rows = rows.withColumn(name, (F.col(name) if name in rows.columns else F.lit(None)).cast(kind))
    return rows.select(*[x.split()[0] for x in FINDINGS.split(", ")])
