"""From raw documents to mixed, sharded training data: five stages, each over all rows that the stage before it kept.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame, which is written as Parquet and read again as the next
stage's docs.  All but the last return the columns of documents; the last adds shard and slot.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corrsentry.llm import common, decontam, mixing, neardup, quality, shards

N_SHARDS = 40


def good_documents(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier accepts."""
    return quality.keep_good(docs, common.table(spark, sf_dir, "labels"))


def one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates (five-word shingles, similarity 0.8 or more)."""
    return neardup.drop_near_duplicates(docs)


def without_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark item."""
    return decontam.decontaminated(docs, common.table(spark, sf_dir, "benchmark"))


def in_mixed_order(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, in the order of the mix of their sources; the next stage gets the same order from the same columns."""
    return mixing.mix_documents(docs)


def in_shards(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents with their shard and slot.  Shards are cells of the metadata; the slots of a shard follow the mix of all sources."""
    rows = common.written(mixing.placed(common.written(shards.sized(docs), "sized")).drop("block", "phase", "release", "deadline", "slot"), "mixed")
    docs = docs.drop("shard", "slot")
    placed = shards.kd_shards(rows, ["chars", "lang", "source", "doc_id"], n_shards=N_SHARDS, by="pos").select(F.col("doc_id").alias("_doc"), F.col("gkey").alias("_gkey"), "shard", "slot")
    # ids may be missing or repeated with other texts; repeated rows get one place, the first
    placed = placed.groupBy("_doc", "_gkey").agg(F.min("shard").alias("shard"), F.min("slot").alias("slot"))
    out = docs.join(placed, docs["doc_id"].eqNullSafe(F.col("_doc")) & (shards.text_key() == F.col("_gkey"))).drop("_doc", "_gkey")
    return out.repartitionByRange("shard", "slot").sortWithinPartitions("shard", "slot")


STAGES = [("quality", good_documents), ("near_duplicates", one_of_each), ("decontamination", without_benchmark), ("mixing", in_mixed_order), ("sharding", in_shards)]
#: The trees, minhashes and medians have no SQL form; tests/llm holds the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = common.written(stage(spark, docs, sf_dir), name)
    out = STAGES[-1][1](spark, docs, sf_dir)
    return out.withColumn("text_crc32", F.crc32(F.coalesce("text", F.lit("")).cast("binary"))).drop("text")
