"""Tables in, results out: Parquet, CSV, JSON and ORC with explicit schemas, file streams, partitioned sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"
FORMATS = ("parquet", "csv", "json", "orc")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table of the test folder; Parquet carries its schema."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read(spark: SparkSession, path: str, schema: str, kind: str = "parquet", **options: str) -> DataFrame:
    """Any of FORMATS with a fixed schema: nothing is inferred from the data."""
    if kind not in FORMATS:
        raise ValueError(f"kind must be one of {FORMATS}")
    return spark.read.schema(schema).options(**options).format(kind).load(path)


def stream_events(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """Event files as they arrive; event time is cast to an instant, which watermarks need."""
    raw = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
    return raw.withColumn("ts", F.to_timestamp("ts"))


def write_by_day(df: DataFrame, path: str, time: str = "win_start", kind: str = "parquet", mode: str = "append") -> None:
    """One folder for each day of `time`, so that readers of a few days open just those."""
    df.withColumn("day", F.to_date(time)).write.mode(mode).partitionBy("day").format(kind).save(path)
