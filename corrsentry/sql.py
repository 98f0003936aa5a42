"""SQL surface: scalar and aggregate functions, table functions, views."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Row, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .functions import kernels as K
from .functions import special
from .operators.corr import as_rows
from .operators.detect import FINDINGS, DetectConfig, best_scores, detect, find, members


@F.pandas_udf(T.DoubleType())
def beta_logpdf(x: pd.Series, a: pd.Series, b: pd.Series) -> pd.Series:
    return pd.Series(special.beta_logpdf(x.to_numpy(float), a.to_numpy(float), b.to_numpy(float)))


@F.pandas_udf(T.DoubleType())
def digamma(x: pd.Series) -> pd.Series:
    return pd.Series(special.digamma(x.to_numpy(float)))


@F.pandas_udf(T.DoubleType())
def principal_score(x: pd.Series) -> float:
    """Score of a group of equally long arrays; constant ones are left out."""
    a = np.stack([np.asarray(v, float) for v in x]) if len(x) else np.zeros((0, 1))
    a = a[a.std(1) > 1e-12]
    return K.principal(K.correlations(a), 512)[0] / len(a) if len(a) else 0.0


@F.udtf(returnType=T.StructType([T.StructField("win_id", T.LongType())]))
class WindowAssign:
    """Starts of the windows that cover an instant, all in seconds."""

    def eval(self, at: int, length: int, slide: int) -> Iterator[tuple[int]]:
        last = at - at % slide
        for start in range(last - (length - slide), last + 1, slide):
            yield (start,)


@F.udtf(returnType=FINDINGS)
class DetectWindow:
    """Findings of one window of cells (win_id, entity, feature, x): the table argument is partitioned by win_id, so a call
    holds one window as detect does: TABLE(cells) PARTITION BY (win_id).  detectors: names with commas between; none: those of DetectConfig."""

    def __init__(self) -> None:
        self.cells: list[tuple] = []
        self.cfg = DetectConfig()

    def eval(self, row: Row, detectors: str | None = None) -> None:
        if detectors:
            self.cfg = self.cfg._replace(detectors=tuple(detectors.split(",")))
        self.cells.append((row["win_id"], row["entity"], row["feature"], row["x"]))

    def terminate(self) -> Iterator[tuple]:
        if self.cells:
            own = pd.DataFrame(self.cells, columns=["win_id", "entity", "feature", "x"])
            found = find(int(own["win_id"].iloc[0]), *as_rows(own), self.cfg)
            for row in found.astype(object).itertuples(index=False, name=None):
                yield tuple(None if pd.isna(v) else v for v in row)


def register(spark: SparkSession) -> None:
    """beta_logpdf, digamma, principal_score, window_assign and detect_window in SQL."""
    spark.udf.register("beta_logpdf", beta_logpdf)
    spark.udf.register("digamma", digamma)
    spark.udf.register("principal_score", principal_score)
    spark.udtf.register("window_assign", WindowAssign)
    spark.udtf.register("detect_window", DetectWindow)


def register_views(cells: DataFrame, pairs: DataFrame, cfg: DetectConfig = DetectConfig()) -> DataFrame:  # noqa: B008
    """Views cells, pairs, scores, members and alerts; returns the findings behind them."""
    found = detect(cells, cfg)
    cells.createOrReplaceTempView("cells")
    pairs.createOrReplaceTempView("pairs")
    best_scores(found).createOrReplaceTempView("scores")
    members(found, alerted=False).createOrReplaceTempView("members")
    best_scores(found).where("alert").createOrReplaceTempView("alerts")
    return found
