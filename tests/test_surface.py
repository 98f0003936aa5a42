"""The table function, the counters, and cross sums along windows."""

from pyspark.sql import functions as F

from corrsentry import sql
from corrsentry.operators import corr, detect, measures
from corrsentry.plans import evaluate as E

SF = "/root/testdata/sf0.001"
KEYS = ("win_id", "detector", "group_id", "entity", "n", "score", "alert", "n_members")


def told(df):
    return sorted(tuple(str(v) for v in r) for r in df.select(*(F.round(k, 9) if k == "score" else k for k in KEYS)).collect())


def test_table_function_finds_what_detect_finds(spark):
    cells = E.log_cells(spark, SF)
    sql.register(spark)
    cells.createOrReplaceTempView("own_cells")
    cfg = detect.DetectConfig(detectors=("direct", "cascade"))
    got = spark.sql("SELECT * FROM detect_window(TABLE(SELECT win_id, entity, feature, x FROM own_cells) PARTITION BY (win_id), 'direct,cascade')")
    assert told(got) == told(detect.detect(cells, cfg))
    none = spark.sql("SELECT * FROM detect_window(TABLE(SELECT win_id, entity, feature, x FROM own_cells WHERE false) PARTITION BY (win_id))")
    assert none.collect() == [] and none.columns == got.columns


def test_counters_are_filled_by_the_action_itself(spark):
    found, counters = measures.observed(detect.detect(E.log_cells(spark, SF)))
    rows = found.collect()
    own = [r for r in rows if r.entity is None]
    assert counters.get["groups"] == len(own) and counters.get["named"] == len(rows) - len(own)
    assert counters.get["alerts"] == sum(r.alert for r in own) and counters.get["seconds"] == max(r.seconds for r in own)


def test_cross_sums_along_windows(spark):
    """Window 10 starts, 20 drops and adds cells, 30 repeats 20, 40 has entity 3 alone, 50 has what 10 had."""
    of = {10: [(1, "a", 2), (1, "b", 1), (2, "a", 3)], 20: [(1, "b", 4), (2, "b", 5), (3, "a", 1)], 40: [(3, "a", 1)]}
    of |= {30: of[20], 50: of[10]}
    cells = spark.createDataFrame([(w, *c) for w, cs in of.items() for c in cs], "win_id long, entity long, feature string, x long")
    key = ("win_id", "i", "j", "c")
    got = sorted(map(tuple, corr.online_count_windows(cells).select(*key).collect()))
    assert got == sorted(map(tuple, corr.cross_sums(cells).select(*key).collect()))
    # one slide alone gives the same next window
    pick = lambda w: cells.where(F.col("win_id") == w).drop("win_id")
    delta = pick(10).select("entity", "feature", (-F.col("x")).alias("d")).unionByName(pick(20).withColumnRenamed("x", "d"))
    slid = corr.online_counts(corr.cross_sums(cells.where("win_id = 10")).drop("win_id"), pick(10), delta)
    assert sorted(map(tuple, slid.select(*key[1:]).collect())) == [r[1:] for r in got if r[0] == 20]
    assert corr.online_count_windows(cells.where("false")).collect() == []
