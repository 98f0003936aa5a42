"""Principal scores, bounds, members and theory."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import theory
from ..operators import corr, score
from ..operators.detect import DetectConfig, best_scores, detect, members
from ..plans import evaluate as E
from ..plans.sampled_large import tiled_power
from .registry import ABS_EDGES, PAIRS, cells, power, query, s6, u6

_DIRECT = f"WITH RECURSIVE {cells()}, {PAIRS}, {power(ABS_EDGES)}"
_SCORES = f"{_DIRECT} SELECT win_id, n, {s6('lambda1')} AS lambda_u6, {s6('lambda1 / n')} AS score_u6 FROM lam"


def _pairs(spark, d, profile="type_k10", mode="abs"):
    return corr.apply_mode(corr.pairs_sparse(E.log_cells(spark, d, profile), complete=True), mode)


def _kernel(spark, d, **kind):
    f = detect(E.log_cells(spark, d), DetectConfig(detectors=("direct",), min_strength=0.0, **kind))
    e4 = F.floor(F.col("score") * 10000 + 0.5).alias("score_e4")
    return f.where("entity is null").select("win_id", F.col("n_used").alias("n"), u6("lambda1").alias("lambda_u6"), u6("score").alias("score_u6"), e4)


@query(_SCORES)
def direct_score_sql(spark, d):
    """Distributed power iteration on the pair table."""
    return score.power(_pairs(spark, d), 32, 16).select("win_id", "n", u6("lambda1").alias("lambda_u6"), u6("score").alias("score_u6"))


@query(_SCORES)
def direct_score_lanczos(spark, d):
    return _kernel(spark, d).drop("score_e4")


@query(_SCORES)
def direct_score_exact(spark, d):
    return _kernel(spark, d, exact=100_000).drop("score_e4")


@query(_SCORES)
def direct_score_tiles(spark, d):
    t = score.cut_lineage(corr.tiles(corr.columns(E.log_cells(spark, d)), 100))
    return tiled_power(t, iterations=32).select("win_id", "n", u6("lambda1").alias("lambda_u6"), u6("score").alias("score_u6"))


_POS = "SELECT win_id, i, j, greatest(rho, 0) AS rho FROM pairs UNION ALL SELECT win_id, j, i, greatest(rho, 0) FROM pairs UNION ALL SELECT win_id, entity, entity, 1.0::DOUBLE FROM live"


_MODE = "SELECT win_id, n, CAST(floor(lambda1 / n * 10000 + 0.5) AS BIGINT) AS score_e4 FROM lam"


@query(f"WITH RECURSIVE {cells()}, {PAIRS}, {power(_POS, 150)} {_MODE}")
def direct_score_positive(spark, d):
    return _kernel(spark, d, mode="positive").select("win_id", "n", "score_e4")


@query(f"WITH RECURSIVE {cells()}, {PAIRS}, {power(_POS.replace('greatest(rho', 'greatest(-rho'), 150)} {_MODE}")
def direct_score_negative(spark, d):
    return _kernel(spark, d, mode="negative").select("win_id", "n", "score_e4")


@query(f"{_DIRECT}, q AS (SELECT vec.win_id, i, v, lambda1, sqrt(sum(v * v) OVER (PARTITION BY vec.win_id)) AS size FROM vec JOIN lam ON vec.win_id = lam.win_id) SELECT win_id, i AS entity, CAST(floor(least(sqrt(lambda1) * v / size, 1) * 10000 + 0.5) AS BIGINT) AS loading_e4 FROM q WHERE sqrt(lambda1) * v / size >= 0.3")
def direct_members(spark, d):
    """Members at a cut of 0.3, which ordinary days of this stream pass."""
    f = members(detect(E.log_cells(spark, d), DetectConfig(detectors=("direct",), loading_cut=0.3)), alerted=False)
    return f.select("win_id", "entity", F.floor(F.col("loading") * 10000 + 0.5).alias("loading_e4"))


_HOUR = f"WITH RECURSIVE {cells('type', 3600)}, {PAIRS}, big AS (SELECT win_id FROM live GROUP BY 1 HAVING count(*) >= 3), {power(f'SELECT * FROM ({ABS_EDGES}) e WHERE win_id IN (SELECT win_id FROM big)', 300)}"
for _t in (0.7, 0.6):

    @query(f"{_HOUR} SELECT win_id, n, CAST(floor(lambda1 / n * 1000 + 0.5) AS BIGINT) AS score_e3 FROM lam WHERE lambda1 / n > {_t} + 1e-9", name=f"direct_alerts_0{int(_t * 10)}")
    def _direct_alerts(spark, d, t=_t):
        """Hours of five features, where few users correlate by chance: many alerts."""
        f = detect(E.log_cells(spark, d, "type", "1 hour"), DetectConfig(detectors=("direct",), threshold=t, min_strength=0.0))
        s = f.where("entity is null and n_used >= 3")
        return score.alerts(s, t + 1e-9).select("win_id", F.col("n_used").alias("n"), F.floor(F.col("score") * 1000 + 0.5).alias("score_e3"))


@query(f"WITH {cells()}, {PAIRS}, e AS ({ABS_EDGES}), r AS (SELECT win_id, i, sum(rho) AS s FROM e GROUP BY 1, 2) SELECT win_id, count(*) AS n, {s6('min(s) / count(*)')} AS lower_u6, {s6('max(s) / count(*)')} AS upper_u6, {s6('sum(s) / count(*) / count(*)')} AS mean_u6 FROM r GROUP BY 1")
def row_sum_bounds(spark, d):
    return score.row_sum_bounds(_pairs(spark, d)).select("win_id", "n", u6("lower").alias("lower_u6"), u6("upper").alias("upper_u6"), u6("mean_entry").alias("mean_u6"))


@query()
def direct_early_out(spark, d):
    """Windows whose bound is under the threshold are settled without a solver (steps is null)."""
    f = detect(E.log_cells(spark, d), DetectConfig(detectors=("direct",), early_out=True))
    return f.where("entity is null").select("win_id", "score", "alert", "steps")


#: Parameters of the theory, spread over their ranges by the orders' keys.
_GRID = "SELECT 100 * (1 + o_orderkey % 100) AS n, 5 + o_custkey % 46 AS k, 0.08::DOUBLE + (o_custkey % 8) * 0.06::DOUBLE AS mu, 0.75::DOUBLE + (o_orderkey % 4) * 0.05::DOUBLE AS inner_, 0.05::DOUBLE + (o_custkey % 19) * 0.05::DOUBLE AS phi FROM orders"


def _grid(spark, d):
    o, c = F.col("o_orderkey"), F.col("o_custkey")
    return spark.read.parquet(f"{d}/orders.parquet").select((100 * (1 + o % 100)).alias("n"), (5 + c % 46).alias("k"), (F.lit(0.08) + (c % 8) * 0.06).alias("mu"), (F.lit(0.75) + (o % 4) * 0.05).alias("inner_"), (F.lit(0.05) + (c % 19) * 0.05).alias("phi"))


@query(f"SELECT DISTINCT n, k, {s6('mu')} AS mu_u6, {s6('mu + 0.1::DOUBLE * sqrt(2 * ln(n) / n) + (k + 1) / n::DOUBLE')} AS bound_u6 FROM ({_GRID})")
def upper_bound(spark, d):
    g = _grid(spark, d).select("n", "k", "mu").distinct()
    return g.select("n", "k", u6("mu").alias("mu_u6"), u6(theory.upper_bound(F.col("n"), F.col("k"), F.col("mu"), F.lit(0.1))).alias("bound_u6"))


_TR, _DET = "(inner_ * phi + mu * (1 - phi))", "((inner_ - mu) * mu * phi * (1 - phi))"


@query(f"SELECT DISTINCT {s6('mu')} AS mu_u6, {s6('inner_')} AS inner_u6, {s6('phi')} AS phi_u6, {s6('mu + (inner_ - mu) * phi * phi')} AS iid_u6, {s6('mu + (inner_ - mu) * phi')} AS linear_u6, {s6(f'({_TR} + sqrt(greatest({_TR} * {_TR} - 4 * {_DET}, 0))) / 2')} AS block2_u6 FROM ({_GRID})")
def predict_score(spark, d):
    g = _grid(spark, d).select("mu", "inner_", "phi").distinct()
    kinds = [u6(theory.predict(F.col("mu"), F.col("inner_"), F.col("phi"), k)).alias(f"{k}_u6") for k in ("iid", "linear", "block2")]
    return g.select(u6("mu").alias("mu_u6"), u6("inner_").alias("inner_u6"), u6("phi").alias("phi_u6"), *kinds)


@query(f"""WITH g AS (SELECT DISTINCT mu, inner_ FROM ({_GRID})), s AS (SELECT mu, inner_, x / 10000.0::DOUBLE AS phi FROM g, (SELECT unnest(generate_series(0, 10000)) AS x)),
v AS (SELECT mu, inner_, phi, ({_TR} + sqrt(greatest({_TR} * {_TR} - 4 * {_DET}, 0))) / 2 AS score FROM s)
SELECT {s6('mu')} AS mu_u6, {s6('inner_')} AS inner_u6, CAST(min(round(phi * 10000)) AS BIGINT) AS phi_e4 FROM v WHERE score >= 0.7 GROUP BY mu, inner_""")
def share_needed(spark, d):
    """The closed form against a search over ten thousand shares."""
    g = _grid(spark, d).select("mu", "inner_").distinct()
    s = theory.share_needed(F.col("mu"), F.col("inner_"), F.lit(0.7))
    return g.select(u6("mu").alias("mu_u6"), u6("inner_").alias("inner_u6"), F.ceil(s * 10000 - 1e-6).cast("long").alias("phi_e4")).where("phi_e4 is not null")


@query()
def degeneration_curve(spark, d):
    """The score of each day sinks towards the background as its ordinary entities are added, from a sixteenth of them to all,
    whatever the group's growth order below n."""
    return theory.degeneration_of(E.log_cells(spark, d))


@query(f"WITH RECURSIVE {cells('type')}, {PAIRS}, {power('SELECT win_id, i, j, rho FROM pairs UNION ALL SELECT win_id, j, i, rho FROM pairs UNION ALL SELECT win_id, entity, entity, 1.0::DOUBLE FROM live', 1)} SELECT win_id, count(*) AS n FROM edges WHERE i = j GROUP BY 1")
def signed_pca_windows(spark, d):
    """Windows that the classical route takes: principal components of the signed correlation, by the feature matrix."""
    return _pca(spark, d).select("win_id", "n")


def _pca(spark, d):
    """Largest eigenvalue of the signed correlation over n from the M x M side: unit columns have the same spectrum."""
    import numpy as np
    import pandas as pd

    cols = corr.columns(E.log_cells(spark, d, "type"))

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        x = np.stack(pdf["x"].to_list())
        return pd.DataFrame({"win_id": [pdf["win_id"].iloc[0]], "n": [len(x)], "score": [float(np.linalg.eigvalsh(x.T @ x)[-1]) / len(x)]})

    return cols.groupBy("win_id").applyInPandas(run, "win_id long, n long, score double")


@query()
def signed_pca_score(spark, d):
    """The small side's eigenvalue next to the kernel's signed score."""
    k = detect(E.log_cells(spark, d, "type"), DetectConfig(detectors=("direct",), mode="signed", exact=100_000, min_strength=0.0)).where("entity is null")
    return _pca(spark, d).join(k.select("win_id", F.col("score").alias("kernel")), "win_id").select("win_id", "n", u6("score").alias("pca_u6"), u6("kernel").alias("kernel_u6"))


@query()
def ml_pca_embeddings(spark, d):
    """Explained variance of the first components of the embeddings by the library's PCA."""
    from pyspark.ml.feature import PCA
    from pyspark.ml.functions import array_to_vector

    e = spark.read.parquet(f"{d}/embeddings.parquet").select(array_to_vector(F.col("embedding").cast("array<double>")).alias("x"))
    m = PCA(k=3, inputCol="x", outputCol="y").fit(e)
    return spark.createDataFrame([(i, float(v)) for i, v in enumerate(m.explainedVariance)], "component int, share double")


@query()
def direct_scores_documents(spark, d):
    """The noisy bed: documents of one language as entities, its 500 most frequent words as features."""
    return best_scores(detect(document_cells(spark, d), DetectConfig(detectors=("direct", "sampled")))).select("win_id", "detector", "n", "score", "alert")


def document_cells(spark, d, words: int = 500, most: int = 300):
    """Cells (language bucket, document, word); buckets of about `most` documents."""
    docs = spark.read.parquet(f"{d}/documents.parquet").where("lang is not null")
    w = docs.select("doc_id", "lang", F.explode(F.split(F.lower(F.coalesce("text", F.lit(""))), r"[^\p{L}]+")).alias("feature")).where("feature <> ''")
    from pyspark.sql import Window

    top = w.groupBy("lang", "feature").agg(F.count(F.lit(1)).alias("c")).withColumn("r", F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("c"), "feature"))).where(F.col("r") <= words).select("lang", "feature")
    n = docs.groupBy("lang").agg(F.ceil(F.count(F.lit(1)) / most).alias("buckets"))
    own = w.join(top, ["lang", "feature"]).join(n, "lang").groupBy("lang", "buckets", F.col("doc_id").alias("entity"), "feature").agg(F.count(F.lit(1)).alias("x"))
    win = F.crc32(F.col("lang").cast("binary")) % 1000 * 1000 + F.pmod("entity", F.col("buckets"))
    return own.select(win.alias("win_id"), "entity", "feature", "x")
