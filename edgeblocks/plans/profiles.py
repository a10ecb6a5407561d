"""Comparing methods over instances: runs (alg, graph, k, rf, seconds, bytes, …), a row per run; null means that it failed."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def geomean(c: Column) -> Column:
    return F.exp(F.avg(F.ln(c)))


def by_k(runs: DataFrame, measure: str) -> DataFrame:
    """(alg, k, mean): geometric mean over graphs for each k."""
    return runs.where(F.col(measure) > 0).groupBy("alg", "k").agg(geomean(F.col(measure)).alias("mean"))


def rolled(runs: DataFrame, measure: str) -> DataFrame:
    """The same with totals over k and over all (null k, null alg)."""
    return runs.where(F.col(measure) > 0).rollup("alg", "k").agg(F.count(F.lit(1)).alias("runs"), F.round(geomean(F.col(measure)), 6).alias("mean"))


def paired(runs: DataFrame, a: str, b: str, measure: str) -> DataFrame:
    """(graph, k, qa, qb) where both ran."""
    one = runs.where(F.col("alg") == a).select("graph", "k", F.col(measure).alias("qa"))
    two = runs.where(F.col("alg") == b).select("graph", "k", F.col(measure).alias("qb"))
    return one.join(two, ["graph", "k"]).where("qa > 0 AND qb > 0")


def improvement_pct(qa: Column, qb: Column, lower_is_better: bool = True) -> Column:
    """How much better a is than b in percent."""
    return (qb / qa - 1) * 100 if lower_is_better else (qa / qb - 1) * 100


def improvement_pct_literal(qa: Column, qb: Column) -> Column:
    """The printed form, (a / b - 1) x 100, whichever of the two is better."""
    return (qa / qb - 1) * 100


def mean_improvement(runs: DataFrame, a: str, b: str, measure: str) -> DataFrame:
    """One row: instances, improvement of a over b by geometric means, and the share of instances that a wins."""
    p = paired(runs, a, b, measure)
    return p.agg(F.count(F.lit(1)).alias("instances"), F.round(improvement_pct(geomean(F.col("qa")), geomean(F.col("qb"))), 6).alias("improvement"), F.round(F.avg((F.col("qa") < F.col("qb")).cast("double")), 6).alias("win_rate"))


def relative(runs: DataFrame, measure: str, base: str) -> DataFrame:
    """(alg, graph, k, ratio) to the run of base on the same instance."""
    ref = runs.where(F.col("alg") == base).select("graph", "k", F.col(measure).alias("_base"))
    return runs.join(ref, ["graph", "k"]).select("alg", "graph", "k", (F.col(measure) / F.col("_base")).alias("ratio"))


def performance_profile(runs: DataFrame, measure: str, taus: list[float], least_k: int | None = None) -> DataFrame:
    """(alg, tau, share): instances in which alg is within tau times the best. Failed or missing runs are within no tau."""
    kept = runs if least_k is None else runs.where(F.col("k") >= least_k)
    instances = kept.select("graph", "k").distinct()
    grid = kept.select("alg").distinct().join(instances, how="cross")  # methods times instances, both a few hundred at most
    full = grid.join(kept.select("alg", "graph", "k", measure), ["alg", "graph", "k"], "left")
    best = F.min(measure).over(Window.partitionBy("graph", "k"))
    ratios = full.withColumn("ratio", F.col(measure) / best)
    within = [F.struct(F.lit(float(t)).alias("tau"), F.coalesce((F.col("ratio") <= F.lit(float(t))).cast("int"), F.lit(0)).alias("inside")) for t in taus]
    long = ratios.select("alg", F.explode(F.array(*within)).alias("x"))
    return long.groupBy("alg", F.col("x.tau").alias("tau")).agg(F.round(F.avg("x.inside"), 6).alias("share"))


def pivoted(runs: DataFrame, measure: str, algs: list[str]) -> DataFrame:
    """Results table: a row per graph and k, a column per method."""
    return runs.groupBy("graph", "k").pivot("alg", algs).agg(F.first(measure))


def slope(runs: DataFrame, measure: str) -> DataFrame:
    """(alg, graph, slope): growth of a measure with k as a power, by least squares on logarithms."""
    return runs.where(F.col(measure) > 0).groupBy("alg", "graph").agg(F.round(F.regr_slope(F.ln(measure), F.ln("k")), 4).alias("slope"))
