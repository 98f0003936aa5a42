"""How the principal score behaves with the anomaly's share: bounds, predictions and a simulation, as column expressions."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def upper_bound(n: Column, k: Column, mu: Column, sigma: Column) -> Column:
    """What a group of k in n entities can raise the score to, as n grows with k of smaller order."""
    return mu + sigma * F.sqrt(2 * F.ln(n) / n) + (k + 1) / n


def predict(mu: Column, inner: Column, share: Column, kind: str = "block2") -> Column:
    """Expected score of a group with inner correlation `inner` and share `share` before background `mu`.

    iid: the mean entry, a lower bound.  linear: the sampled score's first-order form.  block2: the largest eigenvalue
    of the two-block mean matrix, which measurements agree with."""
    if kind == "iid":
        return mu + (inner - mu) * share * share
    if kind == "linear":
        return mu + (inner - mu) * share
    if kind == "block2":
        trace = inner * share + mu * (1 - share)
        det = (inner - mu) * mu * share * (1 - share)
        return (trace + F.sqrt(F.greatest(trace * trace - 4 * det, F.lit(0.0)))) / 2
    raise ValueError("kind must be iid, linear or block2")


def share_needed(mu: Column, inner: Column, threshold: Column) -> Column:
    """Smallest share whose block2 prediction reaches the threshold: from det(M - t) = 0, linear in the share after
    expansion to a quadratic; null where even share 1 stays below."""
    # t^2 - t (inner s + mu (1 - s)) + (inner - mu) mu s (1 - s) = 0, solved for s: A s^2 + B s + C = 0
    a = -(inner - mu) * mu
    b = (inner - mu) * mu - threshold * (inner - mu)
    c = threshold * threshold - threshold * mu
    root = (-b - F.sqrt(F.greatest(b * b - 4 * a * c, F.lit(0.0)))) / (2 * a)
    other = (-b + F.sqrt(F.greatest(b * b - 4 * a * c, F.lit(0.0)))) / (2 * a)
    best = F.when((root >= 0) & (root <= 1), root).when((other >= 0) & (other <= 1), other)
    return F.when(threshold <= mu, F.lit(0.0)).when(inner < threshold, F.lit(None).cast("double")).otherwise(best)


def degeneration(spark: SparkSession, sizes: list[int], growth: str = "power", inner: float = 0.85, mu: float = 0.2, noise: float = 0.1, seed: int = 7) -> DataFrame:
    """n, k, score: principal score of random block matrices, one task a size.  growth 'power': k = n**0.8 from half the
    entities at the first size on; 'linear': a fifth of them."""
    first = min(sizes)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        import numpy as np

        from .kernels import lanczos

        for b in batches:
            for n in b["n"]:
                k = int(round(0.5 * first * (n / first) ** 0.8)) if growth == "power" else int(round(0.2 * n))
                rng = np.random.default_rng([seed, int(n)])
                m = np.full((n, n), mu)
                m[:k, :k] = inner
                e = rng.uniform(-noise, noise, (n, n))
                p = np.clip(m + np.triu(e, 1) + np.triu(e, 1).T, 0, 1)
                np.fill_diagonal(p, 1.0)
                yield pd.DataFrame({"n": [int(n)], "k": [k], "score": [lanczos(p)[0] / n]})

    sizes_ = spark.createDataFrame([(int(n),) for n in sizes], "n long").repartition(len(sizes), "n")
    return sizes_.mapInPandas(run, "n long, k long, score double")


def degeneration_of(cells: DataFrame, parts: tuple[int, ...] = (16, 8, 4, 2, 1), inner: float = 0.85, seed: int = 7) -> DataFrame:
    """win_id, growth, n, k, score: principal score of the first 1 / part of a window's entities with a group of k, n in all.
    growth as in degeneration; the group has the correlation `inner` and its members' rows are random."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        import numpy as np

        from ..operators.corr import as_array, varying
        from ..operators.inject import members_of
        from .folded import Folded

        win, (_, x) = int(pdf["win_id"].iloc[0]), as_array(pdf)
        x = x[varying(x)]
        sizes = sorted({max(2, len(x) // p) for p in parts if len(x) > 1})
        rng, out = np.random.default_rng([seed, win % (1 << 32)]), []
        group = members_of(rng.gamma(0.35, 1.0, x.shape[1]) + 0.01, len(x), inner, rng, False) if sizes else x
        for growth in ("power", "linear"):
            for n in sizes:
                k = max(1, int(round(0.5 * sizes[0] * (n / sizes[0]) ** 0.8)) if growth == "power" else int(round(0.2 * n)))
                out.append((win, growth, n, k, Folded(np.concatenate([group[:k], x[: n - k]])).all.principal()[0] / n))
        return pd.DataFrame(out, columns=["win_id", "growth", "n", "k", "score"])

    return cells.select("win_id", "entity", "feature", "x").groupBy("win_id").applyInPandas(run, "win_id long, growth string, n long, k long, score double")
