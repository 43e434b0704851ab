"""Accuracy measures over test windows. dist is (start, node_id, p); windows carry cur and target."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .walk import EPSILON, suffix_steps


def _mass_on_target(dist: DataFrame, windows: DataFrame) -> DataFrame:
    mass = dist.select(F.col("start").alias("cur"), F.col("node_id").alias("target"), "p")
    return windows.select("window_id", "cur", "target").join(mass, ["cur", "target"], "left").select("window_id", "cur", "target", F.coalesce("p", F.lit(0.0)).alias("p"))


def target_probability(dist: DataFrame, windows: DataFrame, *, mode: str = "all") -> DataFrame:
    """Mean mass on the true node; mode nonzero: over windows where it is positive."""
    rows = _mass_on_target(dist, windows)
    if mode == "nonzero":
        rows = rows.where("p > 0")
    return rows.agg(F.lit("target_probability").alias("metric"), F.avg("p").alias("value"), F.count("*").alias("support")).select("metric", "value", "support")


def ranked(dist: DataFrame) -> DataFrame:
    order = Window.partitionBy("start").orderBy(F.desc(F.round("p", 9)), "node_id")
    return dist.withColumn("rank", F.row_number().over(order))


def precision_at(dist: DataFrame, windows: DataFrame, *, ks: tuple[int, ...] = (1, 5)) -> DataFrame:
    """Share of windows whose true node is among the first k; ties go to the smaller id. For at="next", give windows and dist of h=1."""
    place = ranked(dist).select(F.col("start").alias("cur"), F.col("node_id").alias("target"), "rank")
    rows = windows.select("window_id", "cur", "target").join(place, ["cur", "target"], "left")
    found = rows.agg(F.count("*").alias("support"), *(F.avg((F.coalesce("rank", F.lit(1 << 30)) <= k).cast("double")).alias(f"precision_top{k}") for k in ks))
    return found.unpivot("support", [f"precision_top{k}" for k in ks], "metric", "value").select("metric", "value", "support")


def hit_share(rows: DataFrame, *keys: str) -> DataFrame:
    """rows(keys..., hit, weight) of decisions -> keys, metric, value, support; no decision gives null."""
    found = rows.groupBy(*keys).agg((F.sum(F.col("hit") * F.col("weight")) / F.nullif(F.sum("weight"), F.lit(0))).alias("value"), F.coalesce(F.sum("weight"), F.lit(0)).cast("long").alias("support"))
    return found.select(*keys, F.lit("choice_accuracy").alias("metric"), "value", "support")


def choice_accuracy(windows: DataFrame, latent: DataFrame, degrees: DataFrame, *, min_degree: int = 3, degree: str = "total", average: str = "micro", anchor: str = "node") -> DataFrame:
    """Share of decisions at nodes of min_degree or more where the heaviest exit that may be taken is the true one.

    degree: total or out. average: micro over decisions, macro over paths first. No decision gives null.
    """
    size = F.col("out_degree") if degree == "out" else F.col("in_degree") + F.col("out_degree")
    junctions = degrees.where(size >= min_degree).select(F.col("node_id").alias("src"))
    moves = suffix_steps(windows).join(junctions, "src", "left_semi")
    if anchor == "node":
        moves = moves.withColumn("before", F.when(F.col("i") > 0, F.col("before")))
    # The heaviest exit, or the second if the first leads back: at most two rows per node reach the join.
    order = Window.partitionBy("src").orderBy(F.desc(F.round("w", 12)), "dst")
    best = latent.withColumn("_r", F.row_number().over(order)).where("_r <= 2")
    best = best.groupBy("src").agg(F.max(F.when(F.col("_r") == 1, F.col("dst"))).alias("first"), F.max(F.when(F.col("_r") == 2, F.col("dst"))).alias("second"))
    choice = F.when(F.coalesce(F.col("first") == F.col("before"), F.lit(False)), F.col("second")).otherwise(F.col("first"))
    hit = F.coalesce((choice == F.col("dst")).cast("double"), F.lit(0.0))
    rows = moves.join(best, "src", "left").select("path_id", hit.alias("hit"))
    if average == "macro":
        rows = rows.groupBy("path_id").agg(F.avg("hit").alias("hit"))
    return hit_share(rows.select("hit", F.lit(1).alias("weight")))


def extra_metrics(dist: DataFrame, windows: DataFrame) -> DataFrame:
    """Mean negative log likelihood (unreachable targets count with the least mass), mean reciprocal rank, coverage, mean lost mass."""
    place = ranked(dist).select(F.col("start").alias("cur"), F.col("node_id").alias("target"), "rank", "p")
    rows = windows.select("window_id", "cur", "target").join(place, ["cur", "target"], "left")
    lost = dist.groupBy(F.col("start").alias("cur")).agg(F.sum("p").alias("_kept"))
    rows = rows.join(lost, "cur", "left")
    found = rows.agg(
        F.count("*").alias("support"), F.avg(-F.log(F.greatest(F.coalesce("p", F.lit(0.0)), F.lit(EPSILON)))).alias("nll"), F.avg(F.coalesce(1.0 / F.col("rank"), F.lit(0.0))).alias("mrr"),
        F.avg(F.col("rank").isNotNull().cast("double")).alias("coverage"), F.avg(1.0 - F.coalesce("_kept", F.lit(0.0))).alias("lost_mass"),
    )
    return found.unpivot("support", ["nll", "mrr", "coverage", "lost_mass"], "metric", "value").select("metric", "value", "support")


def all_metrics(dist: DataFrame, windows: DataFrame, latent: DataFrame, degrees: DataFrame, **options: object) -> DataFrame:
    """The four measures of the experiments, one row each."""
    parts = [target_probability(dist, windows), choice_accuracy(windows, latent, degrees, **options), precision_at(dist, windows)]
    return reduce(DataFrame.unionByName, parts)


def summarize_runs(runs: DataFrame, *, keys: tuple[str, ...] = ("features", "metric")) -> DataFrame:
    """Mean and deviation over repeats, in percent."""
    return runs.groupBy(*keys).agg((100 * F.avg("value")).alias("mean"), (100 * F.coalesce(F.stddev_samp("value"), F.lit(0.0))).alias("deviation"), F.count("*").alias("runs"))


def lift(results: DataFrame, *, base: str = "original", key: str = "features") -> DataFrame:
    """results(key, metric, value) with points and ratio over the base row of the same metric."""
    own = results.where(F.col(key) == base).select("metric", F.col("value").alias("_base"))
    rows = results.where(F.col(key) != base).join(own, "metric")
    return rows.select(key, "metric", "value", (100 * (F.col("value") - F.col("_base"))).alias("points"), F.when(F.col("_base") != 0, F.col("value") / F.col("_base")).alias("ratio"))


def density_trend(results: DataFrame) -> DataFrame:
    """results(graph, density, metric, value) -> (metric, correlation) over graphs."""
    return results.groupBy("metric").agg(F.corr("density", "value").alias("correlation"))
