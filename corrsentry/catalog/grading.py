"""What is done with members and alerts.  Twins run on members by plain rules, which both engines can make; the real
detectors' results are the rows-only queries beside them."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import alerts, block, corr, inject
from ..operators.detect import DetectConfig, best_scores, detect, members
from ..plans import evaluate as E
from .registry import PAIRS, RULES, cells, query, rule_members, s6, u6

_M = f"WITH {cells()}, {RULES} "


def _members(spark, d):
    return rule_members(E.log_cells(spark, d))


@query(f"{_M} SELECT win_id, entity FROM rule_members WHERE detector = 'sampled' INTERSECT SELECT win_id, entity FROM rule_members WHERE detector = 'block'")
def core_members(spark, d):
    return alerts.core(_members(spark, d))


@query(f"{_M} SELECT win_id, entity, min(detector) AS found_by FROM rule_members WHERE detector IN ('sampled', 'block') GROUP BY 1, 2 HAVING count(DISTINCT detector) = 1")
def suspicious_members(spark, d):
    return alerts.suspicious(_members(spark, d))


@query(f"{_M} SELECT win_id, entity, CASE WHEN count(DISTINCT detector) = 2 THEN 'core' ELSE 'suspicious' END AS grade, string_agg(DISTINCT detector, '+' ORDER BY detector) AS found_by FROM rule_members WHERE detector IN ('sampled', 'block') GROUP BY 1, 2")
def merged_members(spark, d):
    return alerts.merge(_members(spark, d))


@query(f"{_M}, k AS (SELECT win_id, entity, count(*) AS k FROM rule_members GROUP BY 1, 2) SELECT win_id, detector, count(*) AS n_members, count(*) FILTER (WHERE k = 1) AS n_unique, count(*) FILTER (WHERE k = 1) > 0 AS is_unique FROM rule_members JOIN k USING (win_id, entity) GROUP BY 1, 2")
def unique_alerts(spark, d):
    return alerts.unique(_members(spark, d))


@query(f"{_M}, m AS (SELECT DISTINCT win_id, entity FROM rule_members) SELECT win_id, entity, count(*) OVER (PARTITION BY entity ORDER BY win_id RANGE BETWEEN 604800 PRECEDING AND 1 PRECEDING) AS seen FROM m")
def alert_history(spark, d):
    return alerts.history(_members(spark, d), 604_800)


@query(f"WITH {cells()}, {PAIRS}, {RULES}, m AS (SELECT DISTINCT win_id, entity FROM rule_members WHERE detector = 'sampled') SELECT i, j, count(*) AS windows, {s6('avg(abs(rho))')} AS mean_u6, count(*) FILTER (WHERE abs(rho) > 0.3) AS strong FROM pairs p JOIN m a ON a.win_id = p.win_id AND a.entity = i JOIN m b ON b.win_id = p.win_id AND b.entity = j GROUP BY 1, 2")
def edge_summary(spark, d):
    c = E.log_cells(spark, d)
    x = alerts.edge_summary(corr.pairs_sparse(c, complete=True), rule_members(c).where("detector = 'sampled'"), 0.3)
    return x.select("i", "j", "windows", u6("mean_rho").alias("mean_u6"), "strong")


def _price_pairs() -> str:
    from .windows import _rows

    return f"""cells AS ({_rows(12)}), {PAIRS}"""


@query(f"WITH {_price_pairs()}, cat AS (SELECT s_suppkey AS entity, n_name AS category FROM supplier JOIN nation ON s_nationkey = n_nationkey) SELECT a.category, count(*) AS pairs, count(*) FILTER (WHERE abs(rho) > 0.5) AS strong FROM pairs JOIN cat a ON a.entity = i JOIN cat b ON b.entity = j AND a.category = b.category GROUP BY 1")
def pair_frequency_sector(spark, d):
    """How often two suppliers of one nation have correlated price changes."""
    cat = spark.read.parquet(f"{d}/supplier.parquet").join(F.broadcast(spark.read.parquet(f"{d}/nation.parquet")), F.col("s_nationkey") == F.col("n_nationkey")).select(F.col("s_suppkey").alias("entity"), F.col("n_name").alias("category"))
    return alerts.pair_frequency(corr.pairs_sparse(E.price_cells(spark, d, 30, 12), complete=True), cat, 0.5)


@query(f"{_M} SELECT win_id, detector, n_members, {s6('avg(n_members) OVER (PARTITION BY detector)')} AS mean_u6 FROM (SELECT win_id, detector, count(DISTINCT entity) AS n_members FROM rule_members GROUP BY 1, 2)")
def alert_sizes(spark, d):
    x = alerts.sizes(_members(spark, d))
    return x.select("win_id", "detector", "n_members", u6("mean_members").alias("mean_u6"))


_LOUD = "SELECT win_id, detector FROM rule_members GROUP BY 1, 2 HAVING (detector = 'sampled' AND count(*) >= 35) OR (detector = 'block' AND count(*) >= 75) OR (detector = 'direct' AND count(*) >= 20)"


@query(f"{_M}, a AS ({_LOUD}), n AS (SELECT detector, win_id, CASE WHEN win_id - lag(win_id) OVER w > 172800 THEN 1 ELSE 0 END AS jump, lag(win_id) OVER w IS NULL AS first_ FROM a WINDOW w AS (PARTITION BY detector ORDER BY win_id)), b AS (SELECT detector, win_id, sum(CASE WHEN first_ THEN 1 ELSE jump END) OVER (PARTITION BY detector ORDER BY win_id) AS burst FROM n) SELECT detector, CAST(burst AS BIGINT) AS burst, min(win_id) AS first_win, max(win_id) AS last_win, count(*) AS n_alerts FROM b GROUP BY 1, 2")
def alert_bursts(spark, d):
    m = _members(spark, d).groupBy("win_id", "detector").agg(F.count(F.lit(1)).alias("k"))
    loud = m.where("(detector = 'sampled' and k >= 35) or (detector = 'block' and k >= 75) or (detector = 'direct' and k >= 20)")
    return alerts.bursts(loud, 172_800)


@query(f"WITH {cells()}, {PAIRS}, {RULES}, g AS (SELECT win_id, entity, count(*) AS k FROM rule_members GROUP BY 1, 2), p AS (SELECT win_id, entity, row_number() OVER (PARTITION BY win_id ORDER BY k, entity) - 1 AS at_ FROM g) SELECT q.win_id, least(a.at_, b.at_) AS row, greatest(a.at_, b.at_) AS col, {s6('rho')} AS rho_u6 FROM pairs q JOIN p a ON a.win_id = q.win_id AND a.entity = i JOIN p b ON b.win_id = q.win_id AND b.entity = j")
def permuted_pairs(spark, d):
    """Correlations with entities ordered by group: blocks lie on the diagonal."""
    c = E.log_cells(spark, d)
    m = rule_members(c).groupBy("win_id", "entity").agg(F.count(F.lit(1)).alias("group_id")).withColumn("loading", F.lit(1.0))
    x = block.ranked_groups(m, corr.pairs_sparse(c, complete=True))
    return x.select("win_id", F.col("row").cast("long").alias("row"), F.col("col").cast("long").alias("col"), u6("rho").alias("rho_u6"))


def _cases(spark, d):
    return inject.inject(E.log_cells(spark, d), inject.REGIMES)


@query()
def cascade_alerts(spark, d):
    """The merged detector over injected windows: grade, and who found what."""
    m = members(detect(_cases(spark, d), DetectConfig(detectors=("sampled", "block"))))
    return alerts.merge(m).groupBy("win_id", "grade", "found_by").agg(F.count(F.lit(1)).alias("n_members"))


@query()
def cascade_unique(spark, d):
    return alerts.unique(members(detect(_cases(spark, d), DetectConfig(detectors=("direct", "sampled", "block", "peel")))))


@query()
def timeline(spark, d):
    b = best_scores(detect(_cases(spark, d), DetectConfig(detectors=("direct", "sampled", "block"))))
    return alerts.timeline(b, ["direct", "sampled", "block"])


@query()
def alert_network(spark, d):
    """Pairs named together in alerts of injected days: mean correlation and days over the cut."""
    c = _cases(spark, d).where("regime = 'strong'")
    m = members(detect(c, DetectConfig(detectors=("sampled",))))
    return alerts.edge_summary(corr.pairs_among(c, m, rows=True), m)
