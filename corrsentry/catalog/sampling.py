"""Norm-weighted sampling and the sampled score."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import matrix, sampled, score
from ..operators.detect import DetectConfig, best_scores, detect, members
from ..plans import evaluate as E
from ..plans.sampled_large import sampled_large
from .registry import PAIRS, RULES, cells, power, query, rule_members, s6, u6

_NORM = "pow(sum(pow(abs(x)::DOUBLE, CAST(1.4 AS DOUBLE))), CAST(1 AS DOUBLE) / CAST(1.4 AS DOUBLE))"
_W = f"wt AS (SELECT win_id, entity, {s6(_NORM)} AS w FROM cells GROUP BY 1, 2)"


def _cum(r: str = "0.2", cap: str = "") -> str:
    m = f"greatest(1, CAST(floor(count(*) OVER p * CAST({r} AS DOUBLE) + 0.5) AS BIGINT))"
    return f"cum AS (SELECT win_id, entity, w, sum(w) OVER (PARTITION BY win_id ORDER BY entity ROWS UNBOUNDED PRECEDING)::BIGINT AS c, sum(w) OVER p::BIGINT AS total, {f'least({m}, {cap})' if cap else m} AS m FROM wt WINDOW p AS (PARTITION BY win_id))"


_SYS = "drawn AS (SELECT win_id, entity, mult FROM (SELECT win_id, entity, CAST(floor(m * c / total::DOUBLE + 0.5) - floor(m * (c - w) / total::DOUBLE + 0.5) AS BIGINT) AS mult FROM cum) WHERE mult > 0)"


@query(f"WITH {cells()}, {_W} SELECT * FROM wt")
def sampling_weights(spark, d):
    return sampled.weights(E.log_cells(spark, d))


@query(f"WITH {cells()}, {_W}, {RULES}, m AS (SELECT DISTINCT win_id, entity FROM rule_members WHERE detector = 'sampled') SELECT win_id, {s6('coalesce(sum(w) FILTER (WHERE m.entity IS NOT NULL), 0) / sum(w)::DOUBLE')} AS strength_u6 FROM wt LEFT JOIN m USING (win_id, entity) GROUP BY 1")
def strength(spark, d):
    c = E.log_cells(spark, d)
    n = sampled.weights(c).withColumnRenamed("w", "norm_p")
    return score.strength(n, rule_members(c).where("detector = 'sampled'")).select("win_id", u6("strength").alias("strength_u6"))


@query(f"WITH {cells()}, {_W}, {_cum()}, {_SYS} SELECT * FROM drawn")
def draws_systematic(spark, d):
    return sampled.draw(E.log_cells(spark, d))


@query(f"WITH {cells()}, {_W}, {_cum(cap='10')}, {_SYS} SELECT * FROM drawn")
def draws_capped(spark, d):
    return sampled.draw(E.log_cells(spark, d), most=10)


@query(f"WITH {cells()}, {_W}, {_cum()}, {_SYS} SELECT win_id, entity, 1::BIGINT AS mult FROM drawn")
def draws_dedupe(spark, d):
    return sampled.draw(E.log_cells(spark, d), dedupe=True)


@query(f"WITH {cells()}, wt AS (SELECT DISTINCT win_id, entity, 1::BIGINT AS w FROM cells), {_cum()}, {_SYS} SELECT * FROM drawn")
def draws_uniform(spark, d):
    return sampled.draw(E.log_cells(spark, d), weighting="uniform")


@query(f"""WITH {cells()}, {_W}, {_cum()},
t AS (SELECT win_id, max(m) AS m, max(total) AS total FROM cum GROUP BY 1), d AS (SELECT win_id, total, unnest(generate_series(1, m)) AS t FROM t),
x AS (SELECT win_id, CAST(floor(('0x' || substr(md5('1:' || win_id || ':' || t), 1, 8))::BIGINT * (total / 4294967296.0::DOUBLE)) AS BIGINT) AS x FROM d)
SELECT x.win_id, entity, count(*) AS mult FROM x JOIN cum ON cum.win_id = x.win_id AND x.x >= c - w AND x.x < c GROUP BY 1, 2""")
def draws_hash(spark, d):
    return sampled.draw(E.log_cells(spark, d), scheme="hash")


@query()
def draws_poisson(spark, d):
    return sampled.draw(E.log_cells(spark, d), scheme="poisson")


_RATES = (0.05, 0.1, 0.2, 0.3, 0.4, 0.5)


@query(" UNION ALL ".join(f"SELECT {int(r * 100)} AS percent, * FROM (WITH {cells()}, {_W}, {_cum(str(r))}, {_SYS} SELECT win_id, sum(mult)::BIGINT AS draws, count(*) AS entities FROM drawn GROUP BY 1)" for r in _RATES))
def draws_rates(spark, d):
    out = None
    for r in _RATES:
        x = sampled.draw(E.log_cells(spark, d), r).groupBy("win_id").agg(F.sum("mult").alias("draws"), F.count(F.lit(1)).alias("entities")).select(F.lit(int(r * 100)).alias("percent"), "win_id", "draws", "entities")
        out = x if out is None else out.unionByName(x)
    return out


_EDGES = "SELECT p.win_id, i, j, abs(rho) * sqrt(a.mult * b.mult) AS rho FROM pairs p JOIN drawn a ON a.win_id = p.win_id AND a.entity = p.i JOIN drawn b ON b.win_id = p.win_id AND b.entity = p.j UNION ALL SELECT p.win_id, j, i, abs(rho) * sqrt(a.mult * b.mult) FROM pairs p JOIN drawn a ON a.win_id = p.win_id AND a.entity = p.i JOIN drawn b ON b.win_id = p.win_id AND b.entity = p.j UNION ALL SELECT win_id, entity, entity, mult::DOUBLE FROM drawn"


@query(f"WITH RECURSIVE {cells()}, {_W}, {_cum()}, {_SYS}, {PAIRS}, {power(_EDGES, 200)}, k AS (SELECT win_id, sum(mult) AS m FROM drawn GROUP BY 1) SELECT win_id, n AS sample, CAST(floor(lambda1 / m * 10000 + 0.5) AS BIGINT) AS score_e4 FROM lam JOIN k USING (win_id)")
def sampled_score(spark, d):
    f = detect(E.log_cells(spark, d), DetectConfig(detectors=("sampled",), min_strength=0.0)).where("entity is null")
    return f.select("win_id", F.col("sample").cast("long").alias("sample"), F.floor(F.col("score") * 10000 + 0.5).alias("score_e4"))


def _hour(spark, d, **kind):
    c = matrix.min_entities(E.log_cells(spark, d, "type", "1 hour"), 8)
    return detect(c, DetectConfig(detectors=("sampled",), **kind))


@query()
def sampled_members_window(spark, d):
    return members(_hour(spark, d), alerted=False).select("win_id", "entity", "loading")


@query()
def sampled_members_sample(spark, d):
    return members(_hour(spark, d, whole_labels=False), alerted=False).select("win_id", "entity", "loading")


@query()
def sampled_alerts(spark, d):
    return best_scores(_hour(spark, d)).where("alert").select("win_id", "score", "strength")


@query()
def sampled_repeats(spark, d):
    """Majority of five draws against one draw."""
    one = best_scores(_hour(spark, d)).select("win_id", F.col("alert").alias("one"))
    return best_scores(_hour(spark, d, repeats=5)).select("win_id", "score", F.col("alert").alias("majority")).join(one, "win_id")


@query()
def sampled_norm_exponents(spark, d):
    """The score for each norm exponent of the tuning grid."""
    out = None
    for p in E.GRIDS["p"]:
        x = best_scores(detect(E.log_cells(spark, d), DetectConfig(detectors=("sampled",), p=p))).select(F.lit(p).alias("p"), "win_id", "score")
        out = x if out is None else out.unionByName(x)
    return out


@query()
def sampled_uniform_score(spark, d):
    """The ablation: columns drawn alike."""
    return best_scores(detect(E.log_cells(spark, d), DetectConfig(detectors=("sampled",), weighting="uniform"))).select("win_id", "score")


@query()
def sampled_large_windows(spark, d):
    """The path for windows no task can hold: broadcast sample, streamed columns."""
    x = sampled_large(E.log_cells(spark, d), cap=4096)
    return x.groupBy("win_id").agg(F.count(F.lit(1)).alias("n"), F.max("score").alias("score"), F.max("loading").alias("top_loading"))


@query(f"WITH {cells()} SELECT win_id, count(*) AS n FROM (SELECT DISTINCT win_id, entity FROM cells) WHERE ('0x' || substr(md5('5:' || win_id || ':' || entity), 1, 8))::BIGINT < 429496730 GROUP BY 1")
def sample_by_hash(spark, d):
    """A tenth of each window's entities, the same in every run."""
    c = E.log_cells(spark, d).select("win_id", "entity").distinct()
    return c.where(sampled.hash_unit(F.lit(5), "win_id", "entity") < 429496730).groupBy("win_id").agg(F.count(F.lit(1)).alias("n"))
