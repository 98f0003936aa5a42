"""Joins that Spark has no operator for: as of a time, into intervals, between overlapping intervals."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def asof_join(left: DataFrame, right: DataFrame, key: str, left_time: str, right_time: str, value: str) -> DataFrame:
    """left with `value` of the right row of its key that is latest at or before its time.  One union and one window sort by
    key and time: no row meets more than its predecessor.  Both times are whole numbers; ties on the right: the greatest value."""
    none = F.lit(None)
    kind = right.schema[value].dataType
    extra = [c for c in left.columns if c not in (key, left_time)]
    a = left.select(F.col(key).alias("_k"), F.col(left_time).alias("_t"), F.lit(1).alias("_side"), none.cast(kind).alias("_v"), F.struct(*[F.col(c) for c in extra]).alias("_row") if extra else F.lit(0).alias("_row"))
    b = right.groupBy(F.col(key).alias("_k"), F.col(right_time).alias("_t")).agg(F.max(value).alias("_v")).select("_k", "_t", F.lit(0).alias("_side"), "_v", none.cast(a.schema["_row"].dataType).alias("_row"))
    w = Window.partitionBy("_k").orderBy("_t", "_side").rowsBetween(Window.unboundedPreceding, 0)
    both = a.unionByName(b).withColumn("_found", F.last("_v", ignorenulls=True).over(w)).where("_side = 1")
    rest = [F.col(f"_row.{c}").alias(c) for c in extra]
    return both.select(F.col("_k").alias(key), F.col("_t").alias(left_time), *rest, F.col("_found").alias(value))


def overlap_join(a: DataFrame, b: DataFrame, width: int) -> DataFrame:
    """Pairs of rows of a (a_id, a_lo, a_hi) and b (b_id, b_lo, b_hi) whose half-open intervals overlap.  Intervals are dealt
    to buckets of `width`; a pair is reported in the bucket of the later start only, so once."""
    cut = lambda x, p: x.withColumn("_b", F.explode(F.sequence(F.floor(F.col(f"{p}_lo") / width), F.floor((F.col(f"{p}_hi") - 1) / width)))).where(F.col(f"{p}_lo") < F.col(f"{p}_hi"))
    both = cut(a.where("a_lo < a_hi"), "a").join(cut(b.where("b_lo < b_hi"), "b"), "_b").where("a_lo < b_hi and b_lo < a_hi")
    return both.where(F.floor(F.greatest("a_lo", "b_lo") / width) == F.col("_b")).drop("_b")


def point_join(points: DataFrame, intervals: DataFrame, width: int) -> DataFrame:
    """points (x, ...) with the intervals (lo, hi, ...) that hold them, half-open, by an equi-join on buckets of `width`."""
    cut = intervals.where("lo < hi").withColumn("_b", F.explode(F.sequence(F.floor(F.col("lo") / width), F.floor((F.col("hi") - 1) / width))))
    return points.withColumn("_b", F.floor(F.col("x") / width)).join(cut, "_b").where("x >= lo and x < hi").drop("_b")
