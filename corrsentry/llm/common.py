"""Spark helpers of the operators: shared scratch tables, gapless ranks, bounded label samples."""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

_SCRATCH: list[tuple[SparkSession, str]] = []


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir, which driver and executors share; where it is unset, one in the
    warehouse, or a temporary one if Spark runs in this process alone."""
    at = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not at:
        local = spark.sparkContext.master.startswith("local") and "cluster" not in spark.sparkContext.master
        if not hasattr(shared_dir, "own"):
            shared_dir.own = tempfile.mkdtemp(prefix="corrsentry-") if local else spark.conf.get("spark.sql.warehouse.dir") + "/_scratch"
        at = shared_dir.own
    return at.rstrip("/")


def written(df: DataFrame, label: str) -> DataFrame:
    """df as a Parquet table in the shared folder, read again: lineage ends there, and lost executors lose nothing.
    Tables are removed when the driver's Python ends, or by clear_scratch()."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/corrsentry-{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    _SCRATCH.append((spark, path))
    out = spark.read.schema(df.schema).parquet(path)
    out._written_at = path
    release(spark)
    return out


def forget(*tables: DataFrame) -> None:
    """Remove tables of written() that nothing will read again."""
    for t in tables:
        _remove(t.sparkSession, t._written_at)
        _SCRATCH[:] = [(s, p) for s, p in _SCRATCH if p != t._written_at]


def release(spark: SparkSession) -> None:
    """Let Spark's cleaner remove the shuffle files of finished jobs now; else they stay until the driver's heap fills."""
    spark.sparkContext._jvm.System.gc()


def _remove(spark: SparkSession, path: str) -> None:
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def clear_scratch() -> None:
    """Remove all tables that written() made in this process."""
    while _SCRATCH:
        try:
            _remove(*_SCRATCH.pop())
        except Exception:  # noqa: BLE001  the session may have ended before
            return


atexit.register(clear_scratch)


def ranked(df: DataFrame, keys: list[str], order: list[str], out: str, rows: int | None = None, per_task: int = 2_048, place: Column | None = None) -> DataFrame:
    """df with a gapless rank from 0 (long) within `keys`, by the buckets of a hash of `order`, then by `order`.

    place: numbers from 0 to rows - 1 that grow with `order` over the whole of df; buckets are ranges of it, and the rank is by `order` alone.

    A key may hold any share of the rows: it is dealt to many buckets, each ranked alone and shifted by the sizes of
    the buckets before it, of which there is one small row each.  df is read twice, so it should be a written table."""
    rows = df.count() if rows is None else rows
    buckets = max(1, min(1 << 20, rows // per_task))
    bucket = (F.pmod(F.xxhash64(*order), F.lit(buckets)) if place is None else F.floor(place * F.lit(buckets) / F.lit(max(rows, 1)))).cast("int")
    df = df.withColumn("_b", bucket)
    own = Window.partitionBy(*keys, "_b").orderBy(*order)
    if buckets == 1:
        return df.withColumn(out, (F.row_number().over(own) - 1).cast("long")).drop("_b")
    before = Window.partitionBy(*keys).orderBy("_b").rowsBetween(Window.unboundedPreceding, -1)
    named = [F.col(k).alias(f"_k{i}") for i, k in enumerate(keys)]
    shift = df.groupBy(*keys, "_b").agg(F.count(F.lit(1)).alias("_n")).select(*named, F.col("_b").alias("_c"), F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_s")) if keys else None
    ranks = df.withColumn("_r", F.row_number().over(own) - 1)
    on = (F.col("_b") == F.col("_c"))
    for i, k in enumerate(keys):
        on = on & F.col(k).eqNullSafe(F.col(f"_k{i}"))
    return ranks.join(shift, on).withColumn(out, (F.col("_r") + F.col("_s")).cast("long")).drop("_b", "_r", "_s", "_c", *[f"_k{i}" for i in range(len(keys))])


def even_join(rows: DataFrame, few: DataFrame, keys: list[str], how: str = "inner", share: int = 256, salts: int = 64, sizes: DataFrame | None = None) -> DataFrame:
    """rows joined with few, hot keys spread evenly.  sizes (few, if it has one row a key): a written table with one row a
    key and c, how many of rows have it.

    Keys with more than 1/share of all the rows that sizes counts are dealt to `salts` tasks each; there are less than
    `share` of them, so their list stays small at any size."""
    sizes = few if sizes is None else sizes
    total = sizes.agg(F.sum("c")).first()[0] or 0
    hot = [r[0] for r in sizes.where(F.col("c") > max(total / share, 1000)).select(F.xxhash64(*keys)).collect()]
    if not hot:
        return rows.join(few, keys, how)
    is_hot = F.xxhash64(*keys).isin(hot)
    rows = rows.withColumn("_salt", F.when(is_hot, F.pmod(F.xxhash64(*rows.columns), F.lit(salts)).cast("int")).otherwise(0))
    few = few.withColumn("_salt", F.explode(F.when(is_hot, F.sequence(F.lit(0), F.lit(salts - 1))).otherwise(F.array(F.lit(0)))))
    return rows.join(few, [*keys, "_salt"], how).drop("_salt")


def held_out(doc_id: Column) -> Column:
    """True for the fifth of the rows that no model may learn from."""
    return F.coalesce(F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(5)) == 0, F.lit(False))


def labelled_sample(labels: DataFrame, column: str, limit: int) -> dict[int, int]:
    """doc_id -> label of at most `limit` labelled rows that may be learned from, chosen by hash (one label a document,
    the largest).  The bound keeps what reaches the driver and the broadcast small at any input size."""
    known = labels.where(F.col(column).isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id")))
    rows = known.groupBy("doc_id").agg(F.max(column).alias("y")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(limit).collect()
    return {r["doc_id"]: int(r["y"] > 0) for r in rows}


def only_ids(docs: DataFrame, ids: dict[int, int]) -> DataFrame:
    """doc_id, text, y of the documents in a bounded sample; no shuffle of texts."""
    if not ids:
        return docs.select("doc_id", "text", F.lit(0).alias("y")).limit(0)
    few = docs.sparkSession.createDataFrame([(k, v) for k, v in ids.items()], "doc_id long, y int")
    return docs.select("doc_id", "text").join(F.broadcast(few), "doc_id")
