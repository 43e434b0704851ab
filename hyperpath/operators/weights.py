"""Edge weights that need no training: baselines and fixed scores. All are latent(src, dst, w), with w summing to 1 per source."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def weights_uniform(edges: DataFrame) -> DataFrame:
    """Each exit alike."""
    out = edges.groupBy("src").agg(F.count("*").alias("_d"))
    return edges.select("src", "dst").join(out, "src").select("src", "dst", (F.lit(1.0) / F.col("_d")).alias("w"))


def weights_empirical(nof: DataFrame, *, alpha: float = 1.0) -> DataFrame:
    """By clicks in training, with alpha more for each exit; uniform where nothing counts."""
    total = nof.groupBy("src").agg(F.sum(F.col("nof") + alpha).alias("_all"), F.count("*").alias("_d"))
    w = F.when(F.col("_all") > 0, (F.col("nof") + alpha) / F.col("_all")).otherwise(F.lit(1.0) / F.col("_d"))
    return nof.join(total, "src").select("src", "dst", w.alias("w"))


def softmax_out(scores: DataFrame, *, keys: tuple[str, ...] = ("src",), score: str = "z") -> DataFrame:
    """scores with w: softmax over the exits of a source, shifted by its largest score.

    Two partial aggregations instead of a window, so that the exits of a hub needn't be in one task.
    """
    keys = list(keys)
    top = scores.groupBy(*keys).agg(F.max(score).alias("_top"))
    raised = scores.join(top, keys).withColumn("_e", F.exp(F.col(score) - F.col("_top")))
    total = raised.groupBy(*keys).agg(F.sum("_e").alias("_sum"))
    return raised.join(total, keys).withColumn("w", F.col("_e") / F.col("_sum")).drop("_top", "_e", "_sum")


def weights_text(text: DataFrame, *, sharpness: float = 1.0) -> DataFrame:
    """Softmax of the text similarity."""
    return softmax_out(text.select("src", "dst", (F.col("text_sim") * sharpness).alias("z"))).select("src", "dst", "w")


def linear_scores(features: DataFrame, coefficients: dict[str, float]) -> DataFrame:
    """(src, dst, z): a fixed linear score of feature columns, in SQL expressions alone."""
    z: Column = reduce(lambda a, b: a + b, (F.col(c).cast("double") * k for c, k in coefficients.items()))
    return features.select("src", "dst", z.alias("z"))


def with_back(latent: DataFrame) -> DataFrame:
    """latent with w_back: the weight of the edge the other way, null if there is none."""
    back = latent.select(F.col("dst").alias("src"), F.col("src").alias("dst"), F.col("w").alias("w_back"))
    return latent.select("src", "dst", "w").join(back, ["src", "dst"], "left")


def rank_exits(latent: DataFrame) -> DataFrame:
    order = Window.partitionBy("src").orderBy(F.desc(F.round("w", 12)), "dst")
    return latent.withColumn("rank", F.row_number().over(order))
