"""Paths, their steps, splits, windows and observations."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.columns import hash8


def explode_paths(paths: DataFrame) -> DataFrame:
    return paths.select("path_id", F.posexplode("nodes").alias("step", "node_id"))


def gather_paths(steps: DataFrame) -> DataFrame:
    """paths(path_id, nodes, length); a path is short, so its array is."""
    rows = steps.groupBy("path_id").agg(F.sort_array(F.collect_list(F.struct("step", "node_id"))).alias("s"))
    return rows.select("path_id", F.col("s.node_id").alias("nodes"), F.size("s").alias("length"))


def path_lengths(steps: DataFrame) -> DataFrame:
    return steps.groupBy("path_id").agg(F.count("*").alias("length"))


def assign_ids(titles: DataFrame, *, dense: bool = False) -> DataFrame:
    """(title, node_id): a stable 64-bit id, or with dense consecutive ids in the order of titles.

    Dense ids come from range partitions and the counts of the partitions before, not from one global window.
    """
    distinct = titles.select("title").where("title is not null").distinct()
    if not dense:
        return distinct.select("title", F.xxhash64("title").alias("node_id"))
    dealt = distinct.repartitionByRange("title").select("title", F.spark_partition_id().alias("part"))
    from .store import stored

    dealt = stored(dealt, "ids")
    sizes = dealt.groupBy("part").agg(F.count("*").alias("n"))
    before = sizes.select("part", F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("offset"))
    rank = F.row_number().over(Window.partitionBy("part").orderBy("title")) - 1
    return dealt.join(F.broadcast(before), "part").select("title", (rank + F.col("offset")).cast("long").alias("node_id"))


def split_paths(paths: DataFrame, *, ratios: tuple[int, int, int] = (8, 1, 1)) -> DataFrame:
    """paths with split: train, validation or test, by the md5 of the id."""
    train, validation, _ = ratios
    bucket = hash8(F.col("path_id")) % sum(ratios)
    return paths.withColumn("split", F.when(bucket < train, "train").when(bucket < train + validation, "validation").otherwise("test"))


def windows(paths: DataFrame, *, horizons: tuple[int, ...] = (1, 2, 3), min_prefix: int = 1) -> DataFrame:
    """(window_id, path_id, t, h, prefix, suffix, cur, target): every place of a path with min_prefix nodes before and h after. Map-only."""
    rows = paths.select("path_id", "nodes", *(c for c in ("split", "outcome") if c in paths.columns), F.explode(F.array(*(F.lit(h) for h in horizons))).alias("h"))
    rows = rows.where(F.size("nodes") >= min_prefix + F.col("h"))
    rows = rows.select("*", F.explode(F.sequence(F.lit(min_prefix), F.size("nodes") - F.col("h"))).alias("t"))
    rows = rows.select(
        F.concat_ws("-", F.col("path_id").cast("string"), F.col("t").cast("string"), F.col("h").cast("string")).alias("window_id"), "path_id", "t", "h",
        F.slice("nodes", F.lit(1), F.col("t")).alias("prefix"), F.slice("nodes", F.col("t") + 1, F.col("h")).alias("suffix"),
        *(c for c in ("split", "outcome") if c in paths.columns),
    )
    return rows.withColumn("cur", F.element_at("prefix", -1)).withColumn("target", F.element_at("suffix", -1))


def nearest_nodes(nodes: DataFrame, neighbours: DataFrame, *, k_nearest: int = 5) -> DataFrame:
    """(node_id, seen, weight): what is seen of an agent at a node: the node and its nearest ones, with unit sum.

    neighbours(src, dst, pos, sim) ranks the nodes near src; weights fall with the distance 1 - sim, from 1 at the node itself to 0 at
    distance 1 and beyond.
    """
    near = neighbours.where(F.col("pos") < k_nearest - 1).select(F.col("src").alias("node_id"), F.col("dst").alias("seen"), F.greatest(F.lit(0.0), F.least(F.lit(1.0), F.col("sim"))).alias("raw"))
    own = nodes.select("node_id").distinct()
    raw = own.select("node_id", F.col("node_id").alias("seen"), F.lit(1.0).alias("raw")).unionByName(near.join(own, "node_id", "left_semi"))
    total = raw.groupBy("node_id").agg(F.sum("raw").alias("_all"))
    return raw.join(total, "node_id").select("node_id", "seen", (F.col("raw") / F.col("_all")).alias("weight"))


def observe(steps: DataFrame, *, kind: str = "onehot", k_nearest: int = 5, neighbours: DataFrame | None = None) -> DataFrame:
    """(path_id, step, node_id, weight) with unit sum per step: the node itself, or the k nearest nodes by distance (see nearest_nodes)."""
    if kind == "onehot":
        return steps.select("path_id", "step", "node_id", F.lit(1.0).alias("weight"))
    near = nearest_nodes(steps.select("node_id"), neighbours, k_nearest=k_nearest)
    return steps.select("path_id", "step", "node_id").join(near, "node_id").select("path_id", "step", F.col("seen").alias("node_id"), "weight")
