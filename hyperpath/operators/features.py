"""Edge and node features, and the four feature sets."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .graph import node_degrees, transitions

#: Columns of each feature set beside text_sim and nof; the base set has none.
DUAL_COLUMNS = {"original": (), "similarity": ("hyper_sim",), "degree": ("dual_in", "dual_out"), "combined": ("hyper_sim", "dual_in", "dual_out")}
NODE_WIDTH = 2


def feature_width(features: str) -> int:
    return 2 + len(DUAL_COLUMNS[features])


def click_counts(train_steps: DataFrame, edges: DataFrame, *, scale: str = "raw") -> DataFrame:
    """(src, dst, nof): how often training paths take each edge; scale raw, log1p or share (of the clicks that leave src)."""
    counted = transitions(train_steps).groupBy("src", "dst").agg(F.count("*").alias("nof"))
    rows = edges.select("src", "dst").join(counted, ["src", "dst"], "left").select("src", "dst", F.coalesce("nof", F.lit(0)).alias("nof"))
    if scale == "log1p":
        return rows.withColumn("nof", F.log1p("nof"))
    if scale == "share":
        total = rows.groupBy("src").agg(F.sum("nof").alias("_all"))
        return rows.join(total, "src").select("src", "dst", F.when(F.col("_all") > 0, F.col("nof") / F.col("_all")).otherwise(F.lit(0.0)).alias("nof"))
    return rows


def assemble_edge_features(edges: DataFrame, text: DataFrame, nof: DataFrame, dual: DataFrame | None, *, features: str = "original", standardize: bool = False) -> DataFrame:
    """(src, dst, f): the feature array of each edge; missing values are 0. standardize: zero mean, unit deviation over the edges."""
    columns = ["text_sim", "nof", *DUAL_COLUMNS[features]]
    rows = edges.select("src", "dst").join(text, ["src", "dst"], "left").join(nof, ["src", "dst"], "left")
    if DUAL_COLUMNS[features]:
        rows = rows.join(dual, ["src", "dst"], "left")
    rows = rows.select("src", "dst", *(F.coalesce(F.col(c).cast("double"), F.lit(0.0)).alias(c) for c in columns))
    if standardize:
        stats = rows.agg(*(F.avg(c).alias(f"{c}_m") for c in columns), *(F.stddev_pop(c).alias(f"{c}_s") for c in columns))
        rows = rows.crossJoin(F.broadcast(stats))  # one row
        value = lambda c: F.when(F.col(f"{c}_s") > 0, (F.col(c) - F.col(f"{c}_m")) / F.col(f"{c}_s")).otherwise(F.lit(0.0))
    else:
        value = F.col
    return rows.select("src", "dst", F.array(*(value(c) for c in columns)).alias("f"))


def node_features(edges: DataFrame) -> DataFrame:
    """(node_id, f): in-degree and out-degree."""
    return node_degrees(edges).select("node_id", F.array(F.col("in_degree").cast("double"), F.col("out_degree").cast("double")).alias("f"))
