"""Streams, SQL functions and views."""

from __future__ import annotations

import json
import uuid

from pyspark.sql import functions as F

from .. import sql as surface
from ..operators import corr, matrix
from ..operators.score import scratch_dir
from ..plans import evaluate as E
from ..sources import readers
from ..streaming import live
from .registry import EV, FEATURE, cells, query, s6, u6

_DAY = matrix.MatrixSpec()


def _shared(spark) -> str:
    return f"{spark.conf.get('spark.checkpoint.dir', None) or scratch_dir(spark)}/stream-{uuid.uuid4().hex}"


def _replayed(spark, d, parts: int = 4) -> str:
    """The events as a folder of files in time order, for a file stream."""
    out = _shared(spark)
    spark.read.parquet(f"{d}/events.parquet").repartitionByRange(parts, "ts").sortWithinPartitions("ts").write.parquet(out)
    return out


@query(f"WITH {cells()}, w AS (SELECT max(at_s) - 3600 AS mark FROM ev) SELECT win_id AS pane, entity, feature, x FROM cells, w WHERE win_id + 86400 <= mark")
def stream_panes_closed(spark, d):
    """Panes a stream has closed at its end: those whose end the watermark has passed."""
    s = live.closed_panes(readers.stream_events(spark, _replayed(spark, d), 100), _DAY)
    return live.replay(s, _shared(spark))[0]


@query()
def stream_detection(spark, d):
    """Live detection over the replayed stream: scores of the closed windows."""
    out = _shared(spark)
    q = live.start(readers.stream_events(spark, _replayed(spark, d)), out, matrix.MatrixSpec(length="1 day", slide="6 hours"))
    q.awaitTermination()
    return spark.read.parquet(f"{out}/scores").select("win_id", "detector", "score", "alert", "n")


@query()
def stream_grades(spark, d):
    """Core and suspicious entities of the live alerts."""
    out = _shared(spark)
    live.start(readers.stream_events(spark, _replayed(spark, d)), out, matrix.MatrixSpec(length="1 day", slide="6 hours")).awaitTermination()
    return spark.read.parquet(f"{out}/grades").select("win_id", "entity", "grade", "found_by")


@query(f"""WITH {EV}, l AS (SELECT entity, at_s, lag(at_s) OVER (PARTITION BY entity ORDER BY at_s) AS old FROM ev), g AS (SELECT entity, at_s, sum(CASE WHEN old IS NULL OR at_s >= old + 21600 THEN 1 ELSE 0 END) OVER (PARTITION BY entity ORDER BY at_s RANGE UNBOUNDED PRECEDING) AS s FROM l)
SELECT entity AS user_id, min(at_s) AS first_s, max(at_s) + 21600 AS end_s, count(*) AS n FROM g GROUP BY entity, s""")
def sessions(spark, d):
    e = readers.table(spark, d, "events").withColumn("ts", F.timestamp_seconds(matrix.epoch(F.col("ts"))))
    return live.sessions(e)


@query("SELECT count(DISTINCT event_id) AS events FROM events")
def stream_dedupe(spark, d):
    """Every file twice, each event once."""
    out = _replayed(spark, d, 2)
    e = spark.read.parquet(out)
    twice = _shared(spark)
    e.unionByName(e).repartitionByRange(2, "ts").write.parquet(twice)
    s = live.distinct_events(readers.stream_events(spark, twice).select("event_id", "ts"), "40 days")
    return live.replay(s, _shared(spark))[0].agg(F.count(F.lit(1)).alias("events"))


@query()
def stream_late_dropped(spark, d):
    """Rows that come after the watermark has passed their pane: dropped, and counted by the stream.  The watermark of one
    batch judges lateness in the next but one, so there is a batch between."""
    out = _shared(spark)
    e = spark.read.parquet(f"{d}/events.parquet")
    e.orderBy(F.desc("ts")).limit(50).coalesce(1).write.parquet(out)
    e.orderBy(F.desc("ts")).limit(5).coalesce(1).write.mode("append").parquet(out)
    e.orderBy("ts").limit(200).coalesce(1).write.mode("append").parquet(out)
    s = live.closed_panes(readers.stream_events(spark, out), _DAY)
    _, progress = live.replay(s, _shared(spark))
    late = sum(json.loads(p.json)["stateOperators"][0]["numRowsDroppedByWatermark"] for p in progress if json.loads(p.json)["stateOperators"])
    return spark.createDataFrame([(int(late),)], "dropped long")


@query(f"WITH {EV} SELECT event_id, {s6('5.5::DOUBLE * ln(x) + 0.5::DOUBLE * ln(1 - x) - (lgamma(6.5::DOUBLE) + lgamma(1.5::DOUBLE) - lgamma(8::DOUBLE))')} AS density_u6 FROM (SELECT event_id, least(greatest((event_id % 97) / 97.0::DOUBLE, 0.001::DOUBLE), 0.999::DOUBLE) AS x FROM events)")
def udf_beta_logpdf(spark, d):
    surface.register(spark)
    readers.table(spark, d, "events").select("event_id", (F.col("event_id") % 97 / 97.0).alias("x")).createOrReplaceTempView("_u")
    return spark.sql("SELECT event_id, CAST(floor(beta_logpdf(x, 6.5D, 1.5D) * 1000000 + 0.5) AS BIGINT) AS density_u6 FROM _u")


@query()
def udaf_principal_score(spark, d):
    """Principal score as an aggregate over arrays, by label of the embeddings."""
    surface.register(spark)
    spark.read.parquet(f"{d}/embeddings.parquet").createOrReplaceTempView("_e")
    return spark.sql("SELECT label, principal_score(embedding) AS score FROM _e GROUP BY label")


@query(f"WITH {EV} SELECT at_s - at_s % 21600 - o * 21600 AS win_id, count(*) AS n FROM ev, (SELECT unnest([0, 1, 2, 3]) AS o) GROUP BY 1")
def udtf_window_assign(spark, d):
    surface.register(spark)
    readers.table(spark, d, "events").select(matrix.epoch(F.col("ts")).alias("at_s")).createOrReplaceTempView("_t")
    return spark.sql("SELECT w.win_id, count(*) AS n FROM _t, LATERAL window_assign(_t.at_s, 86400, 21600) w GROUP BY w.win_id")


@query()
def sql_detect(spark, d):
    """Views over one detection run, asked in SQL."""
    c = E.log_cells(spark, d)
    surface.register_views(c, corr.pairs_sparse(c))
    return spark.sql("SELECT s.detector, count(*) AS windows, count_if(s.alert) AS alerts, max(s.score) AS top FROM scores s GROUP BY s.detector")


@query(f"WITH {EV} SELECT {FEATURE['type']} AS feature, count(*) AS n, {s6('sum(value) / 1000')} AS v_u6 FROM ev GROUP BY 1")
def roundtrip_formats(spark, d):
    """Events through every file format with fixed schemas, and the aggregate of what comes back."""
    base = _shared(spark)
    e = readers.table(spark, d, "events").select("event_id", "event_type", "value")
    out = None
    for kind in readers.FORMATS:
        e.write.format(kind).save(f"{base}/{kind}")
        x = readers.read(spark, f"{base}/{kind}", "event_id long, event_type string, value double", kind)
        out = x if out is None else out.join(x.select("event_id"), "event_id", "left_semi")
    return out.groupBy(F.col("event_type").alias("feature")).agg(F.count(F.lit(1)).alias("n"), u6(F.sum("value") / 1000).alias("v_u6"))


@query(f"WITH {cells()} SELECT win_id, count(*) AS n FROM cells WHERE win_id >= (SELECT min(win_id) FROM cells) + 5 * 86400 AND win_id < (SELECT min(win_id) FROM cells) + 8 * 86400 GROUP BY 1")
def partitioned_sink(spark, d):
    """Cells written by day and read back for three days only."""
    c = E.log_cells(spark, d).withColumn("win_start", F.timestamp_seconds("win_id"))
    out = _shared(spark)
    readers.write_by_day(c, out)
    first = spark.read.parquet(out).agg(F.min("day")).first()[0]
    return spark.read.parquet(out).where((F.col("day") >= F.date_add(F.lit(first), 5)) & (F.col("day") < F.date_add(F.lit(first), 8))).groupBy("win_id").agg(F.count(F.lit(1)).alias("n"))
