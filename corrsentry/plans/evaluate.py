"""The experiments: injected cases against all detectors, parameter sweeps, growth in size."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import alerts, detect, inject, matrix, measures, prices
from ..operators.detect import DetectConfig
from ..operators.score import cut_lineage
from ..sources.readers import table

#: Parameter grids of the tuning tables.
GRIDS = {"r": (0.05, 0.1, 0.2, 0.3, 0.4, 0.5), "p": (1.0, 1.2, 1.4, 1.6, 1.8, 2.0), "a": (0.6, 0.65, 0.7, 0.75, 0.8, 0.85), "k": (1, 2, 3, 4, 5, 6)}


def log_cells(spark: SparkSession, sf_dir: str, profile: str = "type_k10", length: str = "1 day", slide: str | None = None) -> DataFrame:
    return matrix.count_cells(table(spark, sf_dir, "events"), matrix.MatrixSpec(profile=profile, length=length, slide=slide))


def price_changes(spark: SparkSession, sf_dir: str, basis_points: bool = True) -> DataFrame:
    rows = table(spark, sf_dir, "lineitem").select("l_suppkey", "l_shipdate", "l_orderkey", "l_linenumber", "l_extendedprice", "l_quantity")
    weekly = prices.closing(rows, "l_suppkey", "l_shipdate", F.col("l_extendedprice") / F.col("l_quantity"), ["l_orderkey", "l_linenumber"])
    return prices.changes(prices.fill_forward(weekly), basis_points)


def price_cells(spark: SparkSession, sf_dir: str, length: int = 30, step: int = 3) -> DataFrame:
    return matrix.row_windows(price_changes(spark, sf_dir), length, step)


def without_core(cells: DataFrame, cfg: DetectConfig) -> tuple[DataFrame, DataFrame]:
    """(cells without the entities that an alert of the block model names, members found before injection): what is there
    already is taken out, what is merely suspicious is remembered."""
    found = cut_lineage(detect.detect(cells, cfg))
    core = detect.members(found).where("detector = 'block'").select("win_id", "entity").distinct()
    before = detect.members(found, alerted=False).select("win_id", "detector", "entity").distinct()
    return cells.join(core, ["win_id", "entity"], "left_anti"), before


def made_cases(cells: DataFrame, cfg: DetectConfig, icfg: inject.InjectConfig, regimes: tuple[str, ...] = inject.REGIMES) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(cells of every window in every regime, truth, members before injection), each checkpointed once for all uses."""
    clean, before = without_core(cells, cfg._replace(detectors=tuple(dict.fromkeys([*cfg.detectors, "block"]))))
    cases = cut_lineage(inject.inject(clean, regimes, icfg))
    t = cut_lineage(inject.truth(cases))
    old = t.select("win_id", "base_win").distinct().join(before.withColumnRenamed("win_id", "base_win"), "base_win").select("win_id", "detector", "entity")
    return cases, t, cut_lineage(old)


def run_cases(cells: DataFrame, cfg: DetectConfig, icfg: inject.InjectConfig, regimes: tuple[str, ...] = inject.REGIMES) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(findings, truth, members before injection) of every window in every regime, each checkpointed."""
    cases, t, old = made_cases(cells, cfg, icfg, regimes)
    return cut_lineage(detect.detect(cases, cfg)), t, old


def merged(best: DataFrame, found: DataFrame) -> tuple[DataFrame, DataFrame]:
    """best and found with a further detector that joins the sampled and the block results."""
    both = F.col("detector").isin("sampled", "block")
    b = best.where(both).groupBy("win_id").agg(F.max("score").alias("score"), F.max("alert").alias("alert"), F.max("strength").alias("strength"), F.max("n").alias("n"), F.sum("n_members").alias("n_members"), F.sum("seconds").alias("seconds"))
    m = alerts.merge(found).select("win_id", F.lit("cascade").alias("detector"), "entity")
    return best.unionByName(b.withColumn("detector", F.lit("cascade")).select(*best.columns)), found.select("win_id", "detector", "entity").unionByName(m)


def table1(cells: DataFrame, cfg: DetectConfig | None = None, icfg: inject.InjectConfig = inject.InjectConfig(), scope: str = "alerted") -> DataFrame:  # noqa: B008
    """Alerts, recall, accuracy and time of each detector and the merged one in each regime.  scope: entities found in
    alerted windows, or 'all'."""
    cfg = cfg or DetectConfig(detectors=("direct", "sampled", "block", "peel"))
    findings, t, old = run_cases(cells, cfg, icfg)
    best, found = merged(detect.best_scores(findings), detect.members(findings, scope == "alerted"))
    old = old.unionByName(old.where(F.col("detector").isin("sampled", "block")).select("win_id", F.lit("cascade").alias("detector"), "entity").distinct())
    return measures.table1(best, found, t, old)


def sweep(cells: DataFrame, parameter: str, values: tuple | None = None, icfg: inject.InjectConfig = inject.InjectConfig(), regime: str = "strong", scope: str = "alerted") -> DataFrame:  # noqa: B008
    """parameter, value, recall, accuracy, extra (control alerts), balance for one grid of GRIDS.  The cases are made once,
    by the detector's usual settings."""
    out = None
    base = DetectConfig(detectors=("sampled",) if parameter in "rp" else ("block",))
    cases, t, old = made_cases(cells, base, icfg, ("control", regime))
    for v in values or GRIDS[parameter]:
        cfg = base._replace(**{parameter: v}) if parameter in "rp" else base._replace(block=base.block._replace(**({"mean_floor": v} if parameter == "a" else {"k": int(v)})))
        findings = cut_lineage(detect.detect(cases, cfg))
        x = measures.table1(detect.best_scores(findings), detect.members(findings, scope == "alerted"), t, old)
        part = x.where(F.col("regime") == regime).select("recall", "accuracy", "alerts", "windows").crossJoin(F.broadcast(x.where("regime = 'control'").select(F.col("alerts").alias("extra"))))
        part = part.select(F.lit(parameter).alias("parameter"), F.lit(float(v)).alias("value"), "alerts", "windows", F.coalesce("recall", F.lit(0.0)).alias("recall"), "accuracy", "extra")
        out = part if out is None else out.unionByName(part)
    return out.withColumn("balance", measures.balance())


def grown(cells: DataFrame, factor: int) -> DataFrame:
    """Windows with the entities of factor - 1 later windows added as ordinary ones, under new ids."""
    wins = cells.select("win_id").distinct()
    step = 86_400
    out = cells
    for i in range(1, factor):
        later = cells.select((F.col("win_id") - i * step).alias("win_id"), (F.col("entity") + i * 10_000_000).alias("entity"), "feature", "x")
        out = out.unionByName(later.join(wins, "win_id", "left_semi"))
    return out


def scaling(cells: DataFrame, factors: tuple[int, ...] = (1, 2, 3), cfg: DetectConfig | None = None, icfg: inject.InjectConfig = inject.InjectConfig()) -> DataFrame:  # noqa: B008
    """factor, detector, mean n, recall (by label) and seconds of windows with 1 to 3 times as many ordinary entities and
    the same injected groups."""
    cfg = cfg or DetectConfig()
    base = inject.inject(cells, ("strong",), icfg)
    t = inject.truth(base)
    extra = base.where("injected").select("base_win", "win_id", "entity", "feature", "x")
    out = None
    for f in factors:
        wide = grown(cells, f).withColumn("x", F.col("x").cast("double")).withColumn("win_id", F.col("win_id") * inject.CODES + inject.REGIMES.index("strong"))
        full = wide.select("win_id", "entity", "feature", "x").unionByName(extra.select("win_id", "entity", "feature", "x"))
        findings = cut_lineage(detect.detect(full, cfg))
        best, found = detect.best_scores(findings), detect.members(findings, alerted=False)
        hits = found.select("win_id", "detector", "entity").distinct().join(t.where("injected"), ["win_id", "entity"]).groupBy("detector").agg(F.count(F.lit(1)).alias("hits"))
        total = t.where("injected").count()
        part = best.groupBy("detector").agg(F.avg("n").alias("n"), F.avg("seconds").alias("seconds"), F.avg(F.col("alert").cast("int")).alias("alerted")).join(hits, "detector", "left")
        part = part.select(F.lit(f).alias("factor"), "detector", "n", "seconds", "alerted", (F.coalesce("hits", F.lit(0)) / F.lit(total)).alias("recall"))
        out = part if out is None else out.unionByName(part)
    return out
