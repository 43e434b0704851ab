"""The graph of a set of trajectories and its measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def transitions(steps: DataFrame) -> DataFrame:
    """(path_id, src, dst, step) of consecutive steps."""
    ahead = F.lead("node_id").over(Window.partitionBy("path_id").orderBy("step"))
    return steps.select("path_id", "step", F.col("node_id").alias("src"), ahead.alias("dst")).where("dst is not null and src <> dst")


def build_edges(steps: DataFrame) -> DataFrame:
    """edges(src, dst) walked by some path; distinct after a partial aggregation."""
    return transitions(steps).select("src", "dst").distinct()


def build_nodes(steps: DataFrame) -> DataFrame:
    return steps.select("node_id").distinct()


def build_graph(steps: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(nodes(node_id), edges(edge_id, src, dst))."""
    edges = build_edges(steps)
    return build_nodes(steps), edges.select(F.xxhash64("src", "dst").alias("edge_id"), "src", "dst")


def edge_nodes(edges: DataFrame) -> DataFrame:
    return edges.select(F.explode(F.array("src", "dst")).alias("node_id")).distinct()


def density(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """(n, m, density): edges of all possible ones without loops; 0 below two nodes."""
    counts = nodes.agg(F.count("*").alias("n")).crossJoin(edges.agg(F.count("*").alias("m")))  # two rows of one
    room = F.col("n").cast("double") * (F.col("n") - 1)
    return counts.select("n", "m", F.when(F.col("n") > 1, F.col("m") / room).otherwise(F.lit(0.0)).alias("density"))


def node_degrees(edges: DataFrame) -> DataFrame:
    """(node_id, in_degree, out_degree); one partial aggregation over both ends instead of two and a join."""
    ends = edges.select(F.explode(F.array(F.struct(F.col("src").alias("node_id"), F.lit(1).alias("o"), F.lit(0).alias("i")), F.struct(F.col("dst").alias("node_id"), F.lit(0).alias("o"), F.lit(1).alias("i")))).alias("e"))
    return ends.groupBy("e.node_id").agg(F.sum("e.i").alias("in_degree"), F.sum("e.o").alias("out_degree"))


def hubs(edges: DataFrame, *, top: int = 10) -> DataFrame:
    degree = node_degrees(edges).select("node_id", (F.col("in_degree") + F.col("out_degree")).alias("degree"))
    return degree.orderBy(F.desc("degree"), "node_id").limit(top)


def category_profile(steps: DataFrame, categories: DataFrame) -> DataFrame:
    """(category, length, paths): how many paths of each length touch each category, with subtotals (nulls)."""
    length = steps.groupBy("path_id").agg(F.count("*").alias("length"))
    touched = steps.join(categories, "node_id").select("path_id", "category").distinct().join(length, "path_id")
    return touched.rollup("category", "length").agg(F.count_distinct("path_id").alias("paths"))


def categorize(nodes: DataFrame, types: DataFrame, *, fallback: str = "subject.General") -> DataFrame:
    """(node_id, category): the looked-up type, or the fallback where it is missing or blank."""
    found = nodes.join(types.select("node_id", F.nullif(F.trim("type"), F.lit("")).alias("type")), "node_id", "left")
    return found.select("node_id", F.coalesce("type", F.lit(fallback)).alias("category"))
