"""Pair queries as kernels of whole windows: no table of pairs is joined or shuffled."""

import io
from contextlib import redirect_stdout

import pytest
from pyspark.sql import functions as F

from corrsentry import catalog
from corrsentry.operators import alerts, block, corr
from corrsentry.plans import evaluate as E

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def cells(spark):
    return E.log_cells(spark, SF).where(F.col("win_id") < 1704067200 + 5 * 86400).localCheckpoint()


def pairs(df):
    return {(r.win_id, r.i, r.j): round(r.rho, 9) for r in df.collect()}


@pytest.mark.parametrize("name", ["pairs_common_feature", "background_mu_sigma", "beta_relabel_round", "block_fit_pairs"])
def test_no_pairs_are_joined(spark, name):
    out = io.StringIO()
    with redirect_stdout(out):
        catalog.queries()[name](spark, SF).explain()
    assert "Join" not in out.getvalue().replace("BroadcastNestedLoopJoin", "") and "Generate explode(p" not in out.getvalue()


def test_pairs_by_windows_are_those_of_the_joins(spark, cells):
    whole, few = pairs(corr.pairs_sparse(cells, complete=True)), cells.select("win_id", "entity").where("entity % 3 = 0")
    assert pairs(corr.pairs_dense(cells)) == whole and pairs(corr.pairs_sharing(cells)) == pairs(corr.pairs_sparse(cells))
    named = {(r.win_id, r.entity) for r in few.collect()}
    assert pairs(corr.pairs_among(cells, few)) == {k: v for k, v in whole.items() if {(k[0], k[1]), (k[0], k[2])} <= named}
    doubled = cells.withColumn("x", F.col("x") * 1.0)
    assert pairs(corr.pairs_dense(doubled)) == whole and alerts.edge_summary(corr.pairs_among(doubled, few), few).count() > 0


def test_labels_and_background_without_a_member(spark, cells):
    none = cells.select("win_id", "entity", F.lit(1).alias("z")).where("entity < -1")
    assert {r.n_inner for r in corr.background_cells(cells, none).collect()} == {0}
    assert block.fit_pairs(cells, none)[0].count() == 0
    assert {r.z for r in block.relabel_cells(cells, none, [(0, 1.2, 9.0), (1, 7.5, 2.5)]).collect()} == {0}


def test_fit_by_windows_is_that_of_the_pair_table(spark):
    cells = spark.createDataFrame([(1, e, f"f{f}", (5 + e % 3 if f < 3 else 1) if e < 8 else 1 + (e * 7 + f * 11) % 9) for e in range(30) for f in range(8)], "win_id long, entity long, feature string, x long")
    z = spark.createDataFrame([(1, e, 1) for e in range(4)], "win_id long, entity long, z int")
    a, _ = block.fit_pairs(cells, z)
    b, _ = block.fit_pairs(corr.apply_mode(corr.pairs_sparse(cells, complete=True), "abs"), z)
    assert {(r.entity, r.z) for r in a.collect()} == {(r.entity, r.z) for r in b.collect()} and a.count() >= 8
