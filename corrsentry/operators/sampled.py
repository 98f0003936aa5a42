"""Norm-weighted sampling of a window's entities, in column expressions and windows over one window's entities."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .matrix import norms

SCHEMES = ("hash", "systematic", "poisson")


def weights(cells: DataFrame, p: float = 1.4, weighting: str = "norm") -> DataFrame:
    """win_id, entity, w: whole millionths of the p-norm, or 1 each for uniform sampling."""
    n = norms(cells, p)
    w = F.floor(F.col("norm_p") * 1000000 + 0.5).cast("long") if weighting == "norm" else F.lit(1).cast("long")
    return n.select("win_id", "entity", w.alias("w"))


def sample_size(n: Column, r: float, most: int | None = None) -> Column:
    m = F.greatest(F.lit(1), F.floor(n * F.lit(float(r)) + 0.5)).cast("long")
    return F.least(m, F.lit(most).cast("long")) if most else m


def _cumulated(w: DataFrame, r: float, most: int | None) -> DataFrame:
    part = Window.partitionBy("win_id")
    run = part.orderBy("entity").rowsBetween(Window.unboundedPreceding, 0)
    return w.select("win_id", "entity", "w", F.sum("w").over(run).alias("c"), F.sum("w").over(part).alias("total"), sample_size(F.count(F.lit(1)).over(part), r, most).alias("m"))


def hash_unit(*parts: Column | str) -> Column:
    """A whole number in [0, 2**32) from the md5 of the parts, the same in any engine."""
    text = F.concat_ws(":", *[p.cast("string") if isinstance(p, Column) else F.col(p).cast("string") for p in parts])
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long")


def draw_systematic(w: DataFrame, r: float = 0.2, u: float = 0.5, most: int | None = None) -> DataFrame:
    """win_id, entity, mult: multiplicities of m evenly spaced draws; they add up to m exactly."""
    c = _cumulated(w, r, most).where("total > 0")
    at = lambda x: F.floor(F.col("m") * x / F.col("total") + F.lit(float(u)))
    return c.select("win_id", "entity", (at(F.col("c")) - at(F.col("c") - F.col("w"))).cast("long").alias("mult")).where("mult > 0")


def draw_hash(w: DataFrame, r: float = 0.2, seed: int = 1, most: int | None = None) -> DataFrame:
    """win_id, entity, mult: m independent draws with replacement.  Each draw's place on the cumulated weights comes from
    an md5 and falls in one entity's interval.  The range join is an equi-join on buckets of a 256th of the window's
    total, so no draw meets entities far away, and it is not a nested loop."""
    c = _cumulated(w, r, most).where("total > 0 and w > 0")
    span = F.greatest(F.lit(1), F.ceil(F.col("total") / 256)).cast("long")
    intervals = c.withColumn("span", span).withColumn("b", F.explode(F.sequence(F.floor((F.col("c") - F.col("w")) / F.col("span")), F.floor((F.col("c") - 1) / F.col("span")))))
    draws = c.groupBy("win_id").agg(F.max("m").alias("m"), F.max("total").alias("total")).withColumn("t", F.explode(F.sequence(F.lit(1).cast("long"), F.col("m"))))
    place = F.floor(hash_unit(F.lit(seed), "win_id", "t") * (F.col("total") / F.lit(4294967296.0))).cast("long")
    draws = draws.select("win_id", place.alias("x"), F.floor(place / F.greatest(F.lit(1), F.ceil(F.col("total") / 256)).cast("long")).alias("b"))
    hit = draws.join(intervals, ["win_id", "b"]).where((F.col("x") >= F.col("c") - F.col("w")) & (F.col("x") < F.col("c")))
    return hit.groupBy("win_id", "entity").agg(F.count(F.lit(1)).alias("mult"))


def draw_poisson(w: DataFrame, r: float = 0.2, seed: int = 1, most: int | None = None, terms: int = 24) -> DataFrame:
    """win_id, entity, mult: independent Poisson counts with mean m w / W from a hash: only the window's total is shared,
    no order of the entities is needed."""
    part = Window.partitionBy("win_id")
    c = w.select("win_id", "entity", "w", F.sum("w").over(part).alias("total"), sample_size(F.count(F.lit(1)).over(part), r, most).alias("m")).where("total > 0")
    mean = F.col("m") * F.col("w") / F.col("total")
    c = c.withColumn("mean", mean).withColumn("u", (hash_unit(F.lit(seed), "win_id", "entity") + 0.5) / F.lit(4294967296.0))
    step = F.aggregate(
        F.sequence(F.lit(1), F.lit(terms)),
        F.struct(F.exp(-F.col("mean")).alias("term"), F.exp(-F.col("mean")).alias("cdf"), F.lit(0).alias("k")),
        lambda s, i: F.struct((s["term"] * F.col("mean") / i).alias("term"), (s["cdf"] + s["term"] * F.col("mean") / i).alias("cdf"), F.when(F.col("u") > s["cdf"], i).otherwise(s["k"]).alias("k")),
        lambda s: s["k"],
    )
    return c.select("win_id", "entity", step.cast("long").alias("mult")).where("mult > 0")


def draw(cells: DataFrame, r: float = 0.2, p: float = 1.4, scheme: str = "systematic", weighting: str = "norm", dedupe: bool = False, seed: int = 1, u: float = 0.5, most: int | None = None) -> DataFrame:
    w = weights(cells, p, weighting)
    if scheme not in SCHEMES:
        raise ValueError(f"scheme must be one of {SCHEMES}")
    d = draw_systematic(w, r, u, most) if scheme == "systematic" else draw_hash(w, r, seed, most) if scheme == "hash" else draw_poisson(w, r, seed, most)
    return d.withColumn("mult", F.lit(1).cast("long")) if dedupe else d
