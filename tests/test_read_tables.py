import pytest

from corrsentry import catalog

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", ["balance_measure", "degeneration_curve", "predict_score", "share_needed", "table1_measures", "toy_correlation", "toy_price_change", "upper_bound"])
def test_rows_come_from_a_given_table(spark, name):
    df = catalog.queries()[name](spark, SF)
    assert any(f"{SF}/" in f for f in df.inputFiles()) and df.count() > 0


def test_the_score_sinks_as_ordinary_entities_are_added(spark):
    rows = catalog.queries()["degeneration_curve"](spark, "/root/testdata/sf0.01").where("growth = 'power'").collect()
    by = {}
    for r in rows:
        by.setdefault(r.win_id, []).append((r.n, r.score))
    assert all(min(v)[1] > max(v)[1] for v in by.values())
