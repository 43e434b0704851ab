"""Building a data set by simulated navigation: links of pages, their targets, and random walks over them."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.columns import hash8, is_valid_title

ANCHOR = r'<a\s[^>]*href="/([^"]*)"'
TITLE = r"(?s)<title>(.*?)</title>"


def page_titles(pages: DataFrame) -> DataFrame:
    return pages.select(F.col("page_id").alias("node_id"), F.regexp_extract("html", TITLE, 1).alias("title"))


def extract_links(pages: DataFrame, *, pattern: str = ANCHOR) -> DataFrame:
    """links(src, slug, pos): the anchors of each page in document order; of equal targets the first counts. One partial aggregation."""
    slugs = F.regexp_extract_all("html", F.lit(pattern), F.lit(1))
    rows = pages.select(F.col("page_id").alias("src"), F.posexplode(slugs).alias("pos", "slug"))
    return rows.groupBy("src", "slug").agg(F.min("pos").alias("pos"))


def external_links(links: DataFrame) -> DataFrame:
    """Links that leave their article."""
    return links.where("src <> dst")


def resolve_links(links: DataFrame, pages: DataFrame, *, how: str = "bucket") -> DataFrame:
    """links(src, dst, pos) without self-links, each target once at its first place.

    bucket: the md5 of the href picks a page by rank of page id; every link resolves. title: the page of lowest id whose
    title has the slug as a word; others fall away.
    """
    if how == "bucket":
        n = pages.agg(F.count("*").alias("n"))
        ids = pages.select(F.col("page_id").alias("dst"), (F.col("page_id") - F.lit(0)).alias("at"))
        rows = links.crossJoin(F.broadcast(n)).select("src", "pos", (hash8(F.concat(F.lit("/"), "slug")) % F.col("n")).alias("at"))  # one row
        rows = rows.join(ids, "at")
    else:
        words = page_titles(pages).select("node_id", F.explode(F.regexp_extract_all(F.lower("title"), F.lit(r"[\p{L}]+"), F.lit(0))).alias("word"))
        first = words.groupBy("word").agg(F.min("node_id").alias("dst"))
        rows = links.select("src", "pos", F.lower("slug").alias("word")).join(first, "word")
    return external_links(rows).groupBy("src", "dst").agg(F.min("pos").cast("int").alias("pos"))


#: Vectors in a block of knn_links: a task holds two blocks and a matrix of their products.
BLOCK_VECTORS = 2048


def knn_links(embeddings: DataFrame, *, k: int = 50, blocks: int | None = None) -> DataFrame:
    """links(src, dst, pos, sim): the k nearest vectors by cosine, nearest first, ties by id; exact.

    Vectors are dealt into blocks of bounded size, at least four; each pair of blocks is one matrix product, and of its rows only k per
    source go on. The number of products grows with the square of the vectors, their size doesn't.
    """
    blocks = blocks or max(4, -(-embeddings.count() // BLOCK_VECTORS))
    rows = embeddings.select(F.col("vec_id").cast("long").alias("id"), "embedding", F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int").alias("block"))
    packed = rows.groupBy("block").agg(F.sort_array(F.collect_list(F.struct("id", "embedding"))).alias("rows"))
    left = packed.select(F.col("block").alias("b"), F.col("rows").alias("own"), F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("block"))
    pairs = left.join(packed, "block").select("own", "rows").repartition(blocks * blocks)

    def nearest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def of(cell) -> tuple[np.ndarray, np.ndarray]:
            cell = cell.as_py()
            x = np.array([r["embedding"] for r in cell], dtype=np.float64)
            norm = np.sqrt((x * x).sum(axis=1, keepdims=True))
            return np.array([r["id"] for r in cell], dtype=np.int64), x / np.where(norm > 0, norm, 1)

        for batch in batches:
            for own, other in zip(batch.column(0), batch.column(1), strict=True):
                (a, x), (b, y) = of(own), of(other)
                sims = x @ y.T
                sims[a[:, None] == b[None, :]] = -np.inf
                if sims.shape[1] > k:  # all that reach the k-th value, ties too, before the order by id is known
                    bound = np.partition(sims, -k, axis=1)[:, -k, None]
                    width = int((sims >= bound - 1e-11).sum(axis=1).max())
                    top = np.argpartition(-sims, width - 1, axis=1)[:, :width]
                else:
                    top = np.tile(np.arange(sims.shape[1]), (len(a), 1))
                src, dst, sim = np.repeat(a, top.shape[1]), b[top].ravel(), np.take_along_axis(sims, top, 1).ravel()
                ok = np.isfinite(sim)
                yield pa.RecordBatch.from_arrays([pa.array(src[ok]), pa.array(dst[ok]), pa.array(sim[ok])], names=["src", "dst", "sim"])

    found = pairs.mapInArrow(nearest, "src long, dst long, sim double")
    rank = F.row_number().over(Window.partitionBy("src").orderBy(F.desc(F.round("sim", 12)), "dst"))
    return found.withColumn("pos", (rank - 1).cast("int")).where(F.col("pos") < k).select("src", "dst", "pos", F.round("sim", 12).alias("sim"))


def adjacency(links: DataFrame, *, k: int | None = None, titles: DataFrame | None = None, count: str = "after_valid") -> DataFrame:
    """adj(src, dsts): targets in order of id; with k, of the first k only, counted after or before invalid titles go."""
    place = Window.partitionBy("src").orderBy("pos", "dst")
    if k is not None and count == "before_valid":
        links = links.withColumn("_r", F.row_number().over(place)).where(F.col("_r") <= k)
    if titles is not None:
        valid = titles.where(is_valid_title(F.col("title"))).select(F.col("node_id").alias("dst"))
        links = links.join(valid, "dst", "left_semi")
    if k is not None and count == "after_valid":
        links = links.withColumn("_r", F.row_number().over(place)).where(F.col("_r") <= k)
    return links.groupBy("src").agg(F.array_sort(F.collect_list("dst")).alias("dsts"))


def simulate_walks(
    spark: SparkSession, links: DataFrame, *, start: int = 0, n_paths: int = 3000, min_len: int = 4, max_len: int = 7, policy: str = "all", k: int = 5, seed: int = 42,
    keep_short: bool = True, distinct: bool = False, titles: DataFrame | None = None, count: str = "after_valid",
) -> DataFrame:
    """paths(path_id, nodes, goal, length, stop_reason): walks that never revisit a node.

    Every choice is the candidate of least md5 of (seed, path, step, candidate), so walks need no state and are the
    same in any engine. A step joins one row per walk with the adjacency of its last node.
    """
    adj = adjacency(links, k=k if policy == "first_k" else None, titles=titles, count=count)
    walk = spark.range(n_paths).select(
        F.col("id").alias("path_id"), F.array(F.lit(start).cast("long")).alias("nodes"),
        (min_len + hash8(str(seed), F.col("id"), "len") % (max_len - min_len + 1)).cast("int").alias("goal"),
    )
    for _ in range(max_len - 1):
        now = walk.withColumn("src", F.when(F.size("nodes") < F.col("goal"), F.element_at("nodes", -1)))
        joined = now.join(adj, "src", "left")
        step = F.size("nodes")
        free = F.array_except(F.coalesce("dsts", F.array().cast("array<bigint>")), "nodes")
        pick = F.array_min(F.transform(free, lambda d: F.struct(F.md5(F.concat_ws("|", F.lit(str(seed)), F.col("path_id").cast("string"), step.cast("string"), d.cast("string"))).alias("h"), d.alias("d"))))
        walk = joined.withColumn("_pick", pick).select("path_id", F.when(F.col("_pick").isNotNull(), F.concat("nodes", F.array("_pick.d"))).otherwise(F.col("nodes")).alias("nodes"), "goal")
    out = walk.withColumn("length", F.size("nodes")).withColumn("stop_reason", F.when(F.col("length") == F.col("goal"), "goal").otherwise("no_link"))
    if not keep_short:
        out = out.where(F.col("length") >= min_len)
    return out.dropDuplicates(["nodes"]) if distinct else out


def crawl_cost(steps: DataFrame, *, delay_s: float = 1.0, cache: bool = True) -> DataFrame:
    """(requests, seconds) of fetching the visited articles with a pause between requests; with a cache, each article once."""
    n = F.count_distinct("node_id") if cache else F.count("*")
    return steps.agg(n.cast("long").alias("requests")).select("requests", (F.greatest(F.col("requests") - 1, F.lit(0)) * F.lit(float(delay_s))).alias("seconds"))
