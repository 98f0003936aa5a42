"""Dense-subgraph peeling, attribute mixture and other things the method is compared with."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import inject, peel
from ..operators.detect import DetectConfig, best_scores, detect, members
from ..plans import evaluate as E
from .registry import cells, query, s6, u6

_E = f"WITH {cells()}, e AS (SELECT win_id, 'e:' || entity AS u, 'f:' || feature AS v, x AS w FROM cells)"


def _density(t: str, name: str) -> str:
    return f"{name} AS (SELECT win_id, count(DISTINCT node) AS nodes, sum(w)::BIGINT AS weight FROM (SELECT win_id, u AS node, w FROM {t} UNION ALL SELECT win_id, v, 0 FROM {t}) GROUP BY 1)"


def _pass(t: str, d: str, out: str) -> str:
    light = f"SELECT win_id, node FROM (SELECT win_id, u AS node, w FROM {t} UNION ALL SELECT win_id, v, w FROM {t}) JOIN {d} USING (win_id) GROUP BY win_id, node, weight, nodes HAVING sum(w) <= 2 * (1 + 0.1::DOUBLE) * (weight / nodes::DOUBLE)"
    return f"light_{out} AS ({light}), {out} AS (SELECT * FROM {t} x WHERE NOT EXISTS (SELECT 1 FROM light_{out} l WHERE l.win_id = x.win_id AND l.node = x.u) AND NOT EXISTS (SELECT 1 FROM light_{out} l WHERE l.win_id = x.win_id AND l.node = x.v))"


def _edges(spark, d):
    return peel.feature_edges(E.log_cells(spark, d))


@query(f"{_E}, {_density('e', 'd')} SELECT win_id, nodes, weight, {s6('weight / nodes::DOUBLE')} AS density_u6 FROM d")
def graph_density(spark, d):
    return peel.densities(_edges(spark, d)).select("win_id", "nodes", "weight", u6("density").alias("density_u6"))


@query(f"{_E}, {_density('e', 'd0')}, {_pass('e', 'd0', 'e1')}, {_density('e1', 'd1')}, {_pass('e1', 'd1', 'e2')} SELECT win_id, count(*) AS edges, sum(w)::BIGINT AS weight FROM e2 GROUP BY 1")
def peel_batch_pass(spark, d):
    """Two passes of batch peeling."""
    x = peel.batch_pass(peel.batch_pass(_edges(spark, d)))
    return x.groupBy("win_id").agg(F.count(F.lit(1)).alias("edges"), F.sum("w").alias("weight"))


@query()
def peel_batch(spark, d):
    keep, best = peel.batch_peel(_edges(spark, d))
    return peel.densities(keep).select("win_id", "nodes", "weight").join(best, "win_id")


def _run(spark, d, regimes=("control", "strong"), **kind):
    return detect(inject.inject(E.log_cells(spark, d), regimes), DetectConfig(**kind))


@query()
def peel_bipartite(spark, d):
    return members(_run(spark, d, detectors=("peel",)), alerted=False).select("win_id", "entity", "loading")


@query()
def peel_weighted_columns(spark, d):
    """Popular features weighed down, the setting the comparison switches off."""
    return best_scores(_run(spark, d, detectors=("peel",), col_weight="log")).select("win_id", "score", "n_members")


@query()
def peel_dense(spark, d):
    return best_scores(_run(spark, d, detectors=("peel",), peel_graph="pairs")).select("win_id", "score", "n", "n_members")


@query()
def peel_first_drop(spark, d):
    """Ended where a removal does not raise the density: on a dense graph nearly everything is kept."""
    return best_scores(_run(spark, d, detectors=("peel",), peel_graph="pairs", peel_stop="first_drop")).select("win_id", "n", "n_members")


@query()
def peel_score(spark, d):
    return best_scores(_run(spark, d, detectors=("peel",))).select("win_id", "score", "alert")


@query()
def mixture_groups(spark, d):
    return best_scores(_run(spark, d, detectors=("mixture",))).select("win_id", "score", "alert", "n_members")


@query()
def ml_gaussian_mixture(spark, d):
    """The library's mixture on per-user attributes of the whole stream: size of each component."""
    from pyspark.ml.clustering import GaussianMixture
    from pyspark.ml.feature import StandardScaler, VectorAssembler

    c = E.log_cells(spark, d).groupBy("entity").agg(F.log1p(F.sum("x")).alias("a"), F.count_distinct("feature").cast("double").alias("b"), F.avg("x").alias("c"))
    v = VectorAssembler(inputCols=["a", "b", "c"], outputCol="raw").transform(c)
    v = StandardScaler(inputCol="raw", outputCol="features", withMean=True).fit(v).transform(v)
    m = GaussianMixture(k=3, seed=1, maxIter=20).fit(v)
    return m.transform(v).groupBy("prediction").agg(F.count(F.lit(1)).alias("entities"))
