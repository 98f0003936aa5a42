"""Detection on a live stream: closed panes are kept, windows are rebuilt from panes, each window is judged once.

Which windows are due is told by the calendar of window ends since the last one judged, not by where events fell: a
window whose last pane is quiet is judged with the next batch.  Panes are kept by pane, so a batch reads only those that
its windows cover.

State holds open panes only.  A pane leaves it when the watermark passes its end; rows that come later are dropped and
counted by Spark.  foreachBatch writes panes and alerts under the batch's id, so a batch that is run again after a
failure replaces its own output instead of adding to it.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from ..operators import alerts
from ..operators.detect import DetectConfig, best_scores, detect, members
from ..operators.matrix import MatrixSpec, feature, panes_to_windows, seconds


def closed_panes(events: DataFrame, spec: MatrixSpec, lateness: str = "1 hour") -> DataFrame:
    """pane, entity, feature, x of panes that the watermark has passed (append mode)."""
    slim = events.select(F.col(spec.time).alias("ts"), F.col(spec.entity).alias("entity"), feature(spec.profile).alias("feature")).where("entity is not null and feature is not null")
    counted = slim.withWatermark("ts", lateness).groupBy(F.window("ts", spec.slide or spec.length), "entity", "feature").agg(F.count(F.lit(1)).alias("x"))
    return counted.select(F.unix_timestamp("window.start").alias("pane"), "entity", "feature", "x")


def windows_to_judge(panes: DataFrame, spec: MatrixSpec, after: int, upto: int) -> DataFrame:
    """Cells of the windows that end after `after` and not later than `upto`; only the panes they cover are read."""
    length, slide = seconds(spec.length), seconds(spec.slide or spec.length)
    need = panes.where((F.col("pane") > after - length) & (F.col("pane") <= upto - slide))
    end = F.col("win_id") + length
    return panes_to_windows(need, spec).where((end > after) & (end <= upto))


def start(events: DataFrame, out: str, spec: MatrixSpec = MatrixSpec(length="1 day", slide="6 hours"), cfg: DetectConfig = DetectConfig(early_out=True), lateness: str = "1 hour", available_now: bool = True) -> StreamingQuery:  # noqa: B008
    """Run detection over a stream of events.  By batch, under out: panes, scores, members, grades (core and suspicious
    entities of the merged alerts) and judged (the end of the last window that was due)."""
    slide = seconds(spec.slide or spec.length)

    def judge(batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        own = "partitionOverwriteMode"
        save = lambda df, name, *keys: df.withColumn("batch", F.lit(batch_id)).write.mode("overwrite").option(own, "dynamic").partitionBy(*keys, "batch").parquet(f"{out}/{name}")
        save(batch, "panes", "pane")
        kept = spark.read.schema(batch.schema.add("batch", "integer")).option("basePath", f"{out}/panes").parquet(f"{out}/panes").where(F.col("batch") <= batch_id).drop("batch")
        first, last = batch.agg(F.min("pane"), F.max("pane")).first()
        if last is None:
            return
        before = spark.read.parquet(f"{out}/judged").where(F.col("batch") < batch_id).agg(F.max("upto")).first()[0] if batch_id and _exists(spark, f"{out}/judged") else None
        upto = last + slide
        found = detect(windows_to_judge(kept, spec, first if before is None else before, upto), cfg).persist()
        save(best_scores(found), "scores")
        save(members(found), "members")
        save(alerts.merge(members(found)), "grades")
        save(spark.range(1).select(F.lit(upto).cast("long").alias("upto")), "judged")
        found.unpersist()

    writer = closed_panes(events, spec, lateness).writeStream.outputMode("append").foreachBatch(judge).option("checkpointLocation", f"{out}/_checkpoint")
    return (writer.trigger(availableNow=True) if available_now else writer.trigger(processingTime="1 minute")).start()


def _exists(spark: SparkSession, path: str) -> bool:
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(p)


def sessions(events: DataFrame, gap: str = "6 hours", lateness: str = "1 hour") -> DataFrame:
    """user_id, session start and end, n: activity sessions of a stream (or of a batch).  An event a whole gap after the one
    before it starts a session; session_window joins sessions that touch, so its gap is one microsecond shorter."""
    s = events.withWatermark("ts", lateness) if events.isStreaming else events
    out = s.groupBy(F.session_window("ts", f"{gap} -1 microseconds"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return out.select("user_id", F.unix_timestamp("session_window.start").alias("first_s"), F.unix_timestamp(F.col("session_window.end") + F.expr("interval 1 microsecond")).alias("end_s"), "n")


def distinct_events(events: DataFrame, lateness: str = "1 hour") -> DataFrame:
    """Events once each: repeats that come within the watermark are dropped."""
    return events.withWatermark("ts", lateness).dropDuplicatesWithinWatermark(["event_id"]) if events.isStreaming else events.dropDuplicates(["event_id"])


def replay(df: DataFrame, out: str) -> tuple[DataFrame, list]:
    """(rows, progress) of a stream run over what its source has now; rows go to files under out, not to the driver.  The
    batch without data that follows the last one closes what its watermark has passed."""
    q = df.writeStream.outputMode("append").format("parquet").option("checkpointLocation", f"{out}/_checkpoint").start(f"{out}/rows")
    q.processAllAvailable()
    q.stop()
    return df.sparkSession.read.schema(df.schema).parquet(f"{out}/rows"), q.recentProgress
