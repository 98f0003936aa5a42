"""The experiments on the given tables."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.kernels import BlockConfig
from ..operators import inject, measures
from ..operators.detect import DetectConfig, best_scores, detect, members
from ..plans import evaluate as E
from ..plans.planner import Limits, detect_any
from .registry import query, s6, u6
from .scoring import document_cells

ALL = ("direct", "sampled", "block", "peel")


@query()
def workload_access_log(spark, d):
    """Day windows every six hours, all detectors, no injection."""
    return best_scores(detect(E.log_cells(spark, d, slide="6 hours"), DetectConfig(detectors=ALL), named=False))


@query()
def workload_prices(spark, d):
    """Thirty weeks of supplier prices, step three, five groups."""
    return best_scores(detect(E.price_cells(spark, d), DetectConfig(detectors=ALL, peel_graph="pairs", block=BlockConfig(k=5))))


@query()
def table1_log(spark, d):
    return E.table1(E.log_cells(spark, d))


@query()
def table1_log_calibrated(spark, d):
    """Big groups as large as the theory asks of the direct score: with the stream's low background, most of the window."""
    return E.table1(E.log_cells(spark, d), DetectConfig(detectors=("direct", "sampled", "block", "cascade")), inject.InjectConfig(calibrate=0.7))


@query()
def table1_log_seed_neighbourhoods(spark, d):
    """The block model started from dense neighbourhoods where the sample names nobody."""
    return E.table1(E.log_cells(spark, d), DetectConfig(detectors=("sampled", "block"), fallback=True))


@query()
def table1_log_random_draws(spark, d):
    """Draws with replacement, five seeds: mean and spread of the alerts in each regime."""
    out = None
    for seed in range(5):
        x = E.table1(E.log_cells(spark, d), DetectConfig(detectors=("sampled",), scheme="random", seed=seed)).select("regime", "alerts", "recall", "accuracy")
        out = x if out is None else out.unionByName(x)
    return out.groupBy("regime").agg(F.avg("alerts").alias("alerts"), F.stddev_pop("alerts").alias("alerts_sd"), F.avg("recall").alias("recall"), F.avg("accuracy").alias("accuracy"))


@query()
def workload_access_log_hourly(spark, d):
    """Hour windows every ten minutes."""
    return best_scores(detect(E.log_cells(spark, d, length="1 hour", slide="10 minutes"), DetectConfig()))


@query()
def detect_cascade(spark, d):
    """The merged detector by itself: core and suspicious entities of each window."""
    return detect(E.log_cells(spark, d), DetectConfig(detectors=("cascade",))).where("entity is not null").select("win_id", "group_id", "entity", "score")


@query()
def detect_large_windows(spark, d):
    """The whole span as one window, taken as one that no task holds: blocks of rows and a whole sample."""
    return best_scores(detect_any(E.log_cells(spark, d, length="32 days"), DetectConfig(detectors=("direct", "sampled", "block", "cascade")), Limits(exact=1, one_task=1))).drop("seconds")


@query()
def table1_log_direct06(spark, d):
    """The classical score at the lower threshold: more alerts, more false ones."""
    return E.table1(E.log_cells(spark, d, "type"), DetectConfig(detectors=("direct", "sampled", "block"), threshold=0.6))


@query()
def table1_log_noisy(spark, d):
    """The bed whose background correlation is high (five features)."""
    return E.table1(E.log_cells(spark, d, "type"), DetectConfig(detectors=ALL))


@query()
def table1_prices(spark, d):
    return E.table1(E.price_cells(spark, d), DetectConfig(detectors=ALL, peel_graph="pairs", block=BlockConfig(k=5)), inject.InjectConfig(kind="price"))


for _g in E.GRIDS:

    @query(name=f"table2_{_g}")
    def _table2(spark, d, g=_g):
        return E.sweep(E.log_cells(spark, d), g, icfg=inject.InjectConfig(inner=0.87), scope="all")


@query()
def scaling_eval(spark, d):
    return E.scaling(E.log_cells(spark, d))


@query()
def speed_ratio(spark, d):
    return measures.speed_ratio(best_scores(detect(E.log_cells(spark, d), DetectConfig())))


@query()
def workload_documents(spark, d):
    """Copies among documents are natural groups; the background is noisy."""
    return best_scores(detect(document_cells(spark, d), DetectConfig(detectors=("direct", "sampled", "block"))))


@query()
def workload_baskets(spark, d):
    """Months of orders: customers by the brands they buy."""
    o, li, p = (spark.read.parquet(f"{d}/{t}.parquet") for t in ("orders", "lineitem", "part"))
    x = li.select("l_orderkey", "l_partkey").join(p.select("p_partkey", "p_brand"), F.col("l_partkey") == F.col("p_partkey")).join(o.select("o_orderkey", "o_custkey", "o_orderdate"), F.col("l_orderkey") == F.col("o_orderkey"))
    c = x.groupBy((F.year("o_orderdate") * 12 + F.month("o_orderdate")).cast("long").alias("win_id"), F.col("o_custkey").alias("entity"), F.col("p_brand").alias("feature")).agg(F.count(F.lit(1)).alias("x"))
    return best_scores(detect(c, DetectConfig(detectors=("direct", "sampled", "block"))))


@query()
def workload_conversations(spark, d):
    """Words of conversation turns by role: conversations as entities, a role's word as a feature."""
    return best_scores(detect(conversation_cells(spark, d), DetectConfig(detectors=("direct", "sampled", "block")), named=False))


def conversation_cells(spark, d):
    """Cells (conversation's number modulo 4, conversation, role and word); turns without a role are under an empty one."""
    t = spark.read.parquet(f"{d}/conversations.parquet").where("conv_id is not null")
    role = F.coalesce("role", F.lit(""))
    w = t.select("conv_id", role.alias("role"), F.explode(F.split(F.lower(F.coalesce("text", F.lit(""))), r"[^\p{L}]+")).alias("w")).where("w <> ''")
    return w.groupBy(F.pmod("conv_id", F.lit(4)).alias("win_id"), F.col("conv_id").alias("entity"), F.concat_ws(":", "role", "w").alias("feature")).agg(F.count(F.lit(1)).alias("x"))


#: Result rows of an experiment as a function of the customers' keys, to hold the measures to exact values.
_K = "c_custkey"
_ROWS = {"win_id": _K, "detector": f"CASE WHEN {_K} % 8 < 4 THEN 'a' ELSE 'b' END", "regime": f"CASE {_K} % 4 WHEN 0 THEN 'control' WHEN 1 THEN 'big' WHEN 2 THEN 'strong' ELSE 'hidden' END", "injected": f"CASE WHEN {_K} % 4 = 0 THEN 0 ELSE 4 + {_K} % 7 END", "hits": f"CASE WHEN {_K} % 4 = 0 THEN 0 ELSE {_K} % 5 END", "others": f"{_K} % 11", "old": f"{_K} % 11 % 3", "alert": f"{_K} % 3 <> 0", "seconds": f"CAST({_K} % 16 AS DOUBLE) / 4"}
_RESULTS = f"SELECT win_id AS win, detector, regime, injected, hits + others AS found, hits, old, alert, seconds FROM (SELECT {', '.join(f'{e} AS {c}' for c, e in _ROWS.items())} FROM customer)"


@query(f"""WITH r AS ({_RESULTS}), q AS (SELECT detector, CASE WHEN regime <> 'control' THEN regime END AS c, * EXCLUDE (detector) FROM r),
g AS (SELECT detector, CASE WHEN grouping(c) = 1 THEN 'overall' ELSE c END AS regime, count(*) AS windows, count(*) FILTER (WHERE alert) AS alerts, sum(CASE WHEN alert THEN hits ELSE 0 END) AS hits, sum(CASE WHEN alert THEN found - old ELSE 0 END) AS net, sum(injected) AS injected, sum(seconds) AS s, max(seconds) AS seconds_max FROM q WHERE c IS NOT NULL GROUP BY ROLLUP (detector, c) HAVING detector IS NOT NULL),
k AS (SELECT * FROM g UNION ALL SELECT detector, 'control', count(*), count(*) FILTER (WHERE alert), 0, sum(CASE WHEN alert THEN found - old ELSE 0 END), 0, sum(seconds), max(seconds) FROM r WHERE regime = 'control' GROUP BY 1)
SELECT detector, regime, windows, alerts, {s6('hits / nullif(injected, 0)::DOUBLE')} AS recall_u6, {s6('hits / nullif(net, 0)::DOUBLE')} AS accuracy_u6, {s6('s / windows')} AS seconds_avg_u6, {s6('seconds_max')} AS seconds_max_u6 FROM k""")
def table1_measures(spark, d):
    """Recall, estimated accuracy, extra alerts and times on results made from the customers' keys."""
    rows = spark.read.parquet(f"{d}/customer.parquet").selectExpr(*[f"{e} AS {c}" for c, e in _ROWS.items()])
    rows = rows.withColumn("found", F.col("hits") + F.col("others")).withColumn("injected", F.col("injected").cast("long"))
    best = rows.select("win_id", "detector", "alert", "seconds")
    ids = lambda a, n: F.explode(F.when(n > 0, F.sequence(a, a + n - 1)).otherwise(F.array().cast("array<long>")))
    truth = rows.select("win_id", "regime", ids(F.lit(1).cast("long"), F.col("injected")).alias("entity"), F.lit(True).alias("injected"))
    others = F.col("found") - F.col("hits")
    truth = truth.unionByName(rows.select("win_id", "regime", ids(F.lit(1000).cast("long"), F.greatest(others, F.lit(1))).alias("entity"), F.lit(False).alias("injected")))
    loud = rows.where("alert")
    found = loud.select("win_id", "detector", ids(F.lit(1).cast("long"), F.col("hits")).alias("entity")).unionByName(loud.select("win_id", "detector", ids(F.lit(1000).cast("long"), others).alias("entity")))
    before = loud.select("win_id", "detector", ids(F.lit(1000).cast("long"), F.col("old")).alias("entity"))
    # windows of several detectors differ here, so the injected counts of a regime are taken by detector
    out = None
    for name in ("a", "b"):
        mine = rows.where(F.col("detector") == name).select("win_id")
        x = measures.table1(best.join(mine, "win_id"), found.join(mine, "win_id"), truth.join(mine, "win_id"), before.join(mine, "win_id"))
        out = x if out is None else out.unionByName(x)
    return out.select("detector", "regime", "windows", "alerts", u6("recall").alias("recall_u6"), u6("accuracy").alias("accuracy_u6"), u6("seconds_avg").alias("seconds_avg_u6"), u6("seconds_max").alias("seconds_max_u6"))


@query(f"WITH r AS (SELECT user_id, count(*) FILTER (WHERE event_type = 'click') / count(*)::DOUBLE AS recall, count(*) FILTER (WHERE event_type = 'view') / count(*)::DOUBLE AS accuracy FROM events GROUP BY 1) SELECT user_id, {s6('recall')} AS recall_u6, {s6('accuracy')} AS accuracy_u6, {s6('CASE WHEN recall + accuracy > 0 THEN 2 * recall * accuracy / (recall + accuracy) END')} AS balance_u6 FROM r")
def balance_measure(spark, d):
    """The balance of two shares, clicks and views among each user's events."""
    share = lambda kind: F.count_if(F.col("event_type") == kind) / F.count(F.lit(1))
    x = spark.read.parquet(f"{d}/events.parquet").groupBy("user_id").agg(share("click").alias("recall"), share("view").alias("accuracy"))
    return x.select("user_id", u6("recall").alias("recall_u6"), u6("accuracy").alias("accuracy_u6"), u6(measures.balance()).alias("balance_u6"))


@query()
def injected_truth(spark, d):
    """Injected groups by regime: number, size, measured share of the magnitude."""
    c = inject.inject(E.log_cells(spark, d))
    n = c.groupBy("win_id", "regime", "entity").agg(F.max("injected").alias("injected"), F.pow(F.sum(F.pow(F.abs("x"), F.lit(1.4))), F.lit(1 / 1.4)).alias("norm"))
    return n.groupBy("win_id", "regime").agg(F.count(F.lit(1)).alias("n"), F.count_if("injected").alias("injected"), (F.coalesce(F.sum(F.when(F.col("injected"), F.col("norm"))), F.lit(0.0)) / F.sum("norm")).alias("share"))


@query()
def recall_by_label(spark, d):
    """Recall of labels whether or not the window raised an alert."""
    return E.table1(E.log_cells(spark, d), DetectConfig(detectors=("direct", "sampled", "block")), scope="all").select("detector", "regime", "alerts", "recall", "accuracy")


@query()
def members_per_alert(spark, d):
    f = detect(inject.inject(E.log_cells(spark, d)), DetectConfig(detectors=ALL))
    m = members(f).groupBy("detector", "win_id").agg(F.count_distinct("entity").alias("k"))
    return m.groupBy("detector").agg(F.count(F.lit(1)).alias("alerts"), F.avg("k").alias("members_avg"))
