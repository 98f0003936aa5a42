import os

from pyspark.sql import functions as F

from corrsentry import catalog
from corrsentry.catalog import blocks, experiments
from corrsentry.functions import kernels as K

SF = os.environ.get("TEST_SF_DIR", "/root/testdata/sf0.001")


def test_scaling_and_pair_model_get_all_windows_and_rounds(spark, monkeypatch):
    want = {r.win_id for r in experiments.E.log_cells(spark, SF).select("win_id").distinct().collect()}
    monkeypatch.setattr(experiments.E, "scaling", lambda c: c)
    got = catalog.queries()["scaling_eval"](spark, SF)
    assert {r.win_id for r in got.select("win_id").distinct().collect()} == want
    rounds = []
    monkeypatch.setattr(blocks.block, "fit_pairs", lambda pairs, z, cfg=K.BlockConfig(): (rounds.append(cfg.max_iter) or pairs, {}))  # noqa: B008
    got = catalog.queries()["block_fit_pairs"](spark, SF)
    assert {r.win_id for r in got.select("win_id").distinct().collect()} == want and rounds == [K.BlockConfig().max_iter]


def test_conversations_keep_words_of_any_length(spark, monkeypatch):
    monkeypatch.setattr(experiments, "detect", lambda c, cfg: c)
    monkeypatch.setattr(experiments, "best_scores", lambda c: c)
    lengths = catalog.queries()["workload_conversations"](spark, SF).select(F.length("feature").alias("n")).agg(F.min("n"), F.max("n")).first()
    assert 1 <= lengths[0] and lengths[1] > 3
