"""Price histories: last price of each period, gaps filled, changes in percent or basis points."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def closing(rows: DataFrame, entity: str, time: str, price: Column, tie: list[str], period: str = "week") -> DataFrame:
    """entity, period (first day), price: the price of the latest row, ties by the given columns.  One aggregate, no sort."""
    return (
        rows.where(F.col(entity).isNotNull() & F.col(time).isNotNull())
        .groupBy(F.col(entity).alias("entity"), F.to_date(F.date_trunc(period, time)).alias("period"))
        .agg(F.max_by(price, F.struct(time, *tie)).alias("price"))
    )


def calendar(prices: DataFrame) -> DataFrame:
    """period, t: the periods that occur, numbered from 0.  One row for each period of the history, so it is small."""
    w = Window.orderBy("period")
    return prices.select("period").distinct().withColumn("t", (F.row_number().over(w) - 1).cast("long"))


def fill_forward(prices: DataFrame) -> DataFrame:
    """entity, period, t, price for every period from an entity's first price on; missing ones repeat the last price.

    The grid is made from each entity's first period by a range join with the numbered calendar, so entities that come
    late get no rows before."""
    days = F.broadcast(calendar(prices))
    first = prices.join(days, "period").groupBy("entity").agg(F.min("t").alias("t0"))
    last = calendar(prices).agg(F.max("t").alias("t1")).first()["t1"]
    grid = first.withColumn("t", F.explode(F.sequence("t0", F.greatest(F.col("t0"), F.lit(last if last is not None else 0)), F.lit(1).cast("long")))).drop("t0")
    known = prices.join(days, "period").select("entity", "t", "price")
    w = Window.partitionBy("entity").orderBy("t").rowsBetween(Window.unboundedPreceding, 0)
    filled = grid.join(known, ["entity", "t"], "left").withColumn("price", F.last("price", ignorenulls=True).over(w))
    return filled.join(days, "t").select("entity", "period", "t", "price")


def changes(filled: DataFrame, basis_points: bool = False) -> DataFrame:
    """entity, period (number of the later record less one), x: change against the record before, in percent or whole
    basis points."""
    w = Window.partitionBy("entity").orderBy("t")
    rate = (F.col("price") - F.lag("price").over(w)) / F.lag("price").over(w)
    x = F.floor(rate * 10000 + 0.5).cast("long") if basis_points else rate * 100
    return filled.select("entity", (F.col("t") - 1).alias("period"), x.alias("x")).where("x is not null")
