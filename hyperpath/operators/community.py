"""Communities of the undirected graph: modularity of a partition, and iterated local moves that raise it."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .graph import node_degrees
from .store import stored


def undirected(edges: DataFrame) -> DataFrame:
    """(a, b, weight) with a <= b: reciprocal links are one edge of weight 1; weighted edges add up."""
    weight = F.sum("weight") if "weight" in edges.columns else F.lit(1.0)
    grouped = edges.groupBy(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b"))
    return grouped.agg(weight.cast("double").alias("weight")) if "weight" in edges.columns else edges.select(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b")).distinct().withColumn("weight", weight)


def modularity(edges: DataFrame, membership: DataFrame, *, resolution: float = 1.0) -> DataFrame:
    """(modularity, communities) of membership(node_id, community)."""
    return _modularity(undirected(edges), membership, resolution)


def _modularity(links: DataFrame, membership: DataFrame, resolution: float) -> DataFrame:
    ca, cb = (membership.select(F.col("node_id").alias(x), F.col("community").alias(f"c{x}")) for x in "ab")
    rows = links.join(ca, "a").join(cb, "b")
    ends = rows.select("ca", "cb", "weight", F.explode(F.array("ca", "cb")).alias("community"))
    shares = ends.groupBy("community").agg(F.sum("weight").alias("degree"), F.sum(F.when(F.col("ca") == F.col("cb"), F.col("weight")).otherwise(0.0)).alias("inner2"))
    total = links.agg(F.sum("weight").alias("_m"))
    scored = shares.crossJoin(F.broadcast(total))  # one row
    part = F.col("inner2") / (2 * F.col("_m")) - resolution * (F.col("degree") / (2 * F.col("_m"))) ** 2
    return scored.agg(F.coalesce(F.sum(part), F.lit(0.0)).alias("modularity"), F.count("*").alias("communities"))


def communities(edges: DataFrame, *, resolution: float = 1.0, max_levels: int = 3, max_sweeps: int = 6) -> DataFrame:
    """(node_id, community): local moves in sweeps, then the communities become nodes and sweeps go on.

    In a sweep the nodes of one hash parity move at a time, each to the neighbouring community of the largest gain, so
    two nodes don't swap for ever; a sweep that doesn't raise modularity is undone and ends its level. All tables
    between sweeps are written to the shared folder.
    """
    links = stored(undirected(edges), "links")
    label = stored(links.select(F.explode(F.array("a", "b")).alias("node_id")).distinct().withColumn("community", F.col("node_id")), "label")
    for level in range(max_levels):
        moved = _sweeps(links, resolution, max_sweeps)
        to = moved.select(F.col("node_id").alias("community"), F.col("community").alias("_to"))
        label = stored(label.join(to, "community", "left").select("node_id", F.coalesce("_to", "community").alias("community")), "label")
        ca, cb = (moved.select(F.col("node_id").alias(x), F.col("community").alias(f"c{x}")) for x in "ab")
        joined = links.join(ca, "a").join(cb, "b").groupBy(F.least("ca", "cb").alias("a"), F.greatest("ca", "cb").alias("b")).agg(F.sum("weight").alias("weight"))
        joined = stored(joined, "links")
        if joined.count() == links.count():
            break
        links = joined
    return label


def _sweeps(links: DataFrame, resolution: float, max_sweeps: int) -> DataFrame:
    both = stored(links.where("a <> b").select(F.col("a").alias("node_id"), F.col("b").alias("to"), "weight").unionAll(links.where("a <> b").select("b", "a", "weight")), "both")
    ends = links.select(F.explode(F.array("a", "b")).alias("node_id"), "weight")
    degree = stored(ends.groupBy("node_id").agg(F.sum("weight").alias("k")), "degree")
    m = links.agg(F.sum("weight")).first()[0] or 0.0
    label = degree.select("node_id", F.col("node_id").alias("community"))
    best = _modularity(links, label, resolution).first()[0]
    for sweep in range(max_sweeps):
        fresh = label
        for parity in (0, 1):
            sums = fresh.join(degree, "node_id").groupBy("community").agg(F.sum("k").alias("total"))
            near = both.join(fresh.select(F.col("node_id").alias("to"), F.col("community").alias("c")), "to").groupBy("node_id", "c").agg(F.sum("weight").alias("w"))
            rows = near.join(degree, "node_id").join(fresh.withColumnRenamed("community", "own"), "node_id").join(sums.withColumnRenamed("community", "c"), "c")
            others = F.col("total") - F.when(F.col("c") == F.col("own"), F.col("k")).otherwise(0.0)
            gain = F.col("w") - resolution * F.col("k") * others / (2 * m)
            picked = rows.withColumn("gain", gain).groupBy("node_id").agg(
                F.max(F.struct("gain", -F.col("c"), F.col("c"))).alias("best"), F.max(F.when(F.col("c") == F.col("own"), F.col("gain"))).alias("stay"), F.first("k").alias("k"), F.first("own").alias("own")
            )
            alone = fresh.join(degree, "node_id").groupBy("community").agg(F.sum("k").alias("total")).withColumnRenamed("community", "own")
            picked = picked.join(alone, "own").withColumn("stay", F.coalesce("stay", -resolution * F.col("k") * (F.col("total") - F.col("k")) / (2 * m)))
            turn = F.pmod(F.xxhash64("node_id"), F.lit(2)) == parity
            move = picked.where(turn & (F.col("best.gain") > F.col("stay") + 1e-12)).select("node_id", F.col("best.c").alias("_to"))
            fresh = stored(fresh.join(move, "node_id", "left").select("node_id", F.coalesce("_to", "community").alias("community")), "sweep")
        now = _modularity(links, fresh, resolution).first()[0]
        if now <= best + 1e-9:
            break
        label, best = fresh, now
    return label


def node_view(edges: DataFrame, membership: DataFrame, *, labels_per_cluster: int = 3) -> DataFrame:
    """(node_id, community, degree, size, labelled): colour by community, size by degree, labels on each cluster's largest nodes."""
    degree = node_degrees(edges).select("node_id", (F.col("in_degree") + F.col("out_degree")).alias("degree"))
    rows = membership.join(degree, "node_id")
    top = F.max("degree").over(Window.partitionBy("community"))
    rank = F.row_number().over(Window.partitionBy("community").orderBy(F.desc("degree"), "node_id"))
    return rows.select("node_id", "community", "degree", (F.col("degree") / top).alias("size"), (rank <= labels_per_cluster).alias("labelled"))


def cluster_profile(edges: DataFrame, membership: DataFrame, categories: DataFrame, *, seed_node: int = 0) -> DataFrame:
    """(community, size, inner_share, holds_seed, category): of each cluster, with its commonest category."""
    ca, cb = (membership.select(F.col("node_id").alias(x), F.col("community").alias(f"c{x}")) for x in ("src", "dst"))
    rows = edges.select("src", "dst").join(ca, "src").join(cb, "dst").withColumnRenamed("csrc", "community")
    share = rows.groupBy("community").agg(F.avg((F.col("community") == F.col("cdst")).cast("double")).alias("inner_share"))
    sizes = membership.groupBy("community").agg(F.count("*").alias("size"), F.max((F.col("node_id") == seed_node).cast("int")).cast("boolean").alias("holds_seed"))
    counted = membership.join(categories, "node_id").groupBy("community", "category").agg(F.count("*").alias("n"))
    common = counted.groupBy("community").agg(F.min_by("category", F.struct(-F.col("n"), "category")).alias("category"))
    return sizes.join(share, "community", "left").join(common, "community", "left").select("community", "size", F.coalesce("inner_share", F.lit(0.0)).alias("inner_share"), "holds_seed", "category")
