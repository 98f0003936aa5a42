import os

import duckdb
import pytest

from corrsentry.llm import queries as Q

SF = os.environ.get("TEST_SF_DIR", "/root/testdata/sf0.001")
COLUMNS = {
    "op1_": ["doc_id", "size", "text_crc32", "law", "shard", "slot", "grown_shard"],
    "op2_": ["doc_id", "held_out", "score", "predicted"],
    "op3_": ["doc_id", "n_words", "n_removed", "kept_sha256"],
    "op4_": ["doc_id", "held_out", "score", "predicted"],
    "op6_": ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"],
    "op7_": ["doc_id", "n_shingles", "component_id", "kept"],
    "op9_": ["page_id", "host", "path", "rule", "verdict"],
}


@pytest.mark.parametrize("name", sorted(Q.queries()))
def test_query_runs_over_its_whole_table(spark, name):
    out = Q.queries()[name](spark, SF)
    for start, columns in COLUMNS.items():
        if name.startswith(start):
            assert out.columns[: len(columns)] == columns
            whole = spark.read.parquet(f"{SF}/{'pages' if start == 'op9_' else 'documents'}.parquet").count()
            assert out.count() == whole
    sql = Q.oracle_sql().get(name)
    if sql:
        con = duckdb.connect()
        for t in ("pages", "labels", "documents", "benchmark"):
            con.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
        want = con.execute(sql).df()
        got = out.toPandas()[list(want.columns)]
        key = want.columns[0]
        assert got.sort_values(key).astype(str).to_numpy().tolist() == want.sort_values(key).astype(str).to_numpy().tolist()


def test_pipeline_stages_keep_clean_documents(spark):
    import corpus_pipeline as P

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns, before = docs.columns, docs.count()
    for name, stage in P.STAGES:
        docs = stage(spark, docs, SF).cache()
        n = docs.count()
        assert n > 0.6 * before and (docs.columns == columns or name == "sharding")
        if name in ("mixing", "sharding"):
            assert n == before
        before = n
    assert P.run(spark, SF).count() == before
