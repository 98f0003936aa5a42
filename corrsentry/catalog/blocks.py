"""The beta block model, step by step and whole."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import kernels as K
from ..functions.special import log_beta
from ..operators import block, corr
from ..operators.detect import DetectConfig, best_scores, detect, members
from ..plans import evaluate as E
from .registry import PAIRS, RULES, cells, query, rule_members, s6, u6

_LOGS = "logs AS (SELECT win_id, i, j, abs(rho) AS rho, ln(least(greatest(abs(rho), 0.001::DOUBLE), 1 - 0.001::DOUBLE)) AS l1, ln(1 - least(greatest(abs(rho), 0.001::DOUBLE), 1 - 0.001::DOUBLE)) AS l2 FROM pairs)"
#: Fixed labels of both engines: group 1 the rule's 'sampled' members, group 2 those of 'block' that are not in it.
_Z = "z AS (SELECT win_id, entity, min(CASE detector WHEN 'sampled' THEN 1 ELSE 2 END) AS z FROM rule_members WHERE detector IN ('sampled', 'block') GROUP BY 1, 2)"
_HEAD = f"WITH {cells()}, {PAIRS}, {RULES}, {_Z}, {_LOGS}"
_STAT = """own AS (SELECT l.win_id, a.z AS g, count(*) AS pairs, sum(l1) AS s1, sum(l2) AS s2 FROM logs l JOIN z a ON a.win_id = l.win_id AND a.entity = l.i JOIN z b ON b.win_id = l.win_id AND b.entity = l.j WHERE a.z = b.z GROUP BY 1, 2),
stats AS (SELECT * FROM own UNION ALL SELECT t.win_id, 0, t.pairs - coalesce(o.pairs, 0), t.s1 - coalesce(o.s1, 0), t.s2 - coalesce(o.s2, 0) FROM (SELECT win_id, count(*) AS pairs, sum(l1) AS s1, sum(l2) AS s2 FROM logs GROUP BY 1) t LEFT JOIN (SELECT win_id, sum(pairs) AS pairs, sum(s1) AS s1, sum(s2) AS s2 FROM own GROUP BY 1) o USING (win_id))"""
#: Fixed shapes of background and groups for the single-step queries.
SHAPES = ((0, 1.2, 9.0), (1, 7.5, 2.5), (2, 6.0, 1.5))
_PAR = ", ".join(f"({g}, CAST({a} AS DOUBLE), CAST({b} AS DOUBLE), CAST({float(log_beta(a, b))!r} AS DOUBLE))" for g, a, b in SHAPES)


def _z(c):
    m = rule_members(c).where("detector <> 'direct'")
    return m.groupBy("win_id", "entity").agg(F.min(F.when(F.col("detector") == "sampled", 1).otherwise(2)).alias("z"))


def _both(spark, d):
    c = E.log_cells(spark, d)
    return corr.apply_mode(corr.pairs_sparse(c, complete=True), "abs"), _z(c)


def _params(spark, p):
    wins = p.select("win_id").distinct()
    shapes = spark.createDataFrame([(g, a, b, float(log_beta(a, b))) for g, a, b in SHAPES], "g int, a double, b double, lnb double")
    return wins.crossJoin(F.broadcast(shapes))


_MICRO = "CAST(floor({} * 10000 + 0.5) AS BIGINT)"


@query(f"{_HEAD}, {_STAT} SELECT win_id, g, pairs, {_MICRO.format('s1')} AS s1_e4, {_MICRO.format('s2')} AS s2_e4 FROM stats")
def beta_suff_stats(spark, d):
    p, z = _both(spark, d)
    e4 = lambda c: F.floor(F.col(c) * 10000 + 0.5).alias(f"{c}_e4")
    return block.suff_stats(block.log_pairs(p), z).select("win_id", "g", "pairs", e4("s1"), e4("s2"))


@query(f"{_HEAD}, {_STAT}, par(g, a, b, lnb) AS (VALUES {_PAR}) SELECT win_id, {_MICRO.format('sum((a - 1) * s1 + (b - 1) * s2 - pairs * lnb)')} AS loglik_e4 FROM stats JOIN par USING (g) GROUP BY 1")
def beta_loglik(spark, d):
    p, z = _both(spark, d)
    x = block.loglik(block.suff_stats(block.log_pairs(p), z), _params(spark, p))
    return x.select("win_id", F.floor(F.col("loglik") * 10000 + 0.5).alias("loglik_e4"))


@query(f"""{_HEAD}, par(g, a, b, lnb) AS (VALUES {_PAR}), both_ AS (SELECT win_id, i, j, l1, l2 FROM logs UNION ALL SELECT win_id, j, i, l1, l2 FROM logs),
own AS (SELECT e.win_id, e.i, z.z AS g, sum(l1) AS t1, sum(l2) AS t2, count(*) AS c FROM both_ e JOIN z ON z.win_id = e.win_id AND z.entity = e.j GROUP BY 1, 2, 3),
gain AS (SELECT win_id, i, own.g, (p.a - q.a) * t1 + (p.b - q.b) * t2 + c * (q.lnb - p.lnb) AS gain FROM own JOIN par p ON p.g = own.g, (SELECT * FROM par WHERE g = 0) q),
best AS (SELECT win_id, i, g, gain FROM gain QUALIFY row_number() OVER (PARTITION BY win_id, i ORDER BY gain DESC, g) = 1)
SELECT n.win_id, n.i AS entity, CASE WHEN gain > 0 THEN g ELSE 0 END AS z FROM (SELECT DISTINCT win_id, i FROM both_) n LEFT JOIN best USING (win_id, i)""")
def beta_relabel_round(spark, d):
    c = E.log_cells(spark, d)
    return block.relabel_cells(c, _z(c), SHAPES)


@query(f"""{_HEAD}, near AS (SELECT win_id, i, j FROM logs WHERE rho >= 0.4 UNION ALL SELECT win_id, j, i FROM logs WHERE rho >= 0.4),
top AS (SELECT win_id, i FROM (SELECT win_id, i, count(*) AS d FROM near GROUP BY 1, 2) QUALIFY row_number() OVER (PARTITION BY win_id ORDER BY d DESC, i) = 1)
SELECT win_id, j AS entity, 1 AS z FROM near JOIN top USING (win_id, i) UNION ALL SELECT win_id, i, 1 FROM top""")
def neighbourhood_seed(spark, d):
    p, _ = _both(spark, d)
    return block.seed_neighbourhood(p, 0.4)


@query(f"""{_HEAD}, g AS (SELECT l.win_id, CASE WHEN a.z = b.z THEN a.z ELSE 0 END AS g, rho FROM logs l LEFT JOIN z a ON a.win_id = l.win_id AND a.entity = l.i LEFT JOIN z b ON b.win_id = l.win_id AND b.entity = l.j),
m AS (SELECT win_id, g, CASE WHEN g = 0 THEN least(avg(rho), 0.5) ELSE greatest(avg(rho), 0.75) END AS mean FROM g GROUP BY 1, 2) SELECT win_id, g, {s6('mean * 10')} AS a_u6, {s6('(1 - mean) * 10')} AS b_u6 FROM m""")
def init_params(spark, d):
    p, z = _both(spark, d)
    return block.init_params(p, z).select("win_id", "g", u6("a").alias("a_u6"), u6("b").alias("b_u6"))


def _found(spark, d, **kind):
    from ..operators import inject

    cases = inject.inject(E.log_cells(spark, d), ("control", "hidden"))
    return detect(cases, DetectConfig(detectors=("block",), block=K.BlockConfig(**kind)))


@query()
def block_members(spark, d):
    return members(_found(spark, d), alerted=False).select("win_id", "group_id", "entity", "loading")


@query()
def block_scores(spark, d):
    return _found(spark, d).where("entity is null").select("win_id", "group_id", "n_members", "score", "rounds", "touched")


@query()
def block_alerts(spark, d):
    return best_scores(_found(spark, d)).where("alert").select("win_id", "score", "strength", "n_members")


@query()
def block_sequential(spark, d):
    """Labels updated one by one."""
    return best_scores(_found(spark, d, schedule="sequential", max_iter=5)).select("win_id", "score", "alert", "n_members")


@query()
def block_unimodal(spark, d):
    return best_scores(_found(spark, d, unimodal=True)).select("win_id", "score", "alert", "n_members")


@query()
def block_groups_k(spark, d):
    """Groups and members found for k from 1 to 6."""
    out = None
    for k in E.GRIDS["k"]:
        x = _found(spark, d, k=k).where("entity is null").groupBy("win_id").agg(F.count(F.lit(1)).alias("groups"), F.sum("n_members").alias("n_members"), F.max("score").alias("score")).select(F.lit(k).alias("k"), "*")
        out = x if out is None else out.unionByName(x)
    return out


@query()
def block_mean_floors(spark, d):
    out = None
    for a in E.GRIDS["a"]:
        x = best_scores(_found(spark, d, mean_floor=a)).select(F.lit(a).alias("mean_floor"), "win_id", "n_members", "score", "alert")
        out = x if out is None else out.unionByName(x)
    return out


@query()
def block_fit_pairs(spark, d):
    """The whole model over all pairs: all windows, as many rounds as the model takes."""
    c = E.log_cells(spark, d)
    z, _ = block.fit_pairs(c, _z(c))
    return z
