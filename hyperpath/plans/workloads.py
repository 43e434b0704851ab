"""The experiment graphs on the given tables, each stored once per session and folder."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import crawl, dual, features, graph, trajectories, weights
from ..operators.store import stored
from ..sources import tables

_held: dict[tuple, DataFrame] = {}
#: Coefficients of the fixed linear score.
LINEAR = {"hyper_sim": 1.0, "dual_out": 0.5, "dual_in": -0.25, "log_nof": 0.3}
WALKS, START, H = 3000, 0, 2


def once(spark: SparkSession, sf_dir: str, name: str, build: Callable[[], DataFrame]) -> DataFrame:
    """The stored table of this name, built at the first call of a session."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _held:
        _held[key] = stored(build(), name)
    return _held[key]


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return tables.load(spark, sf_dir, name)


def knn(spark: SparkSession, sf_dir: str) -> DataFrame:
    return once(spark, sf_dir, "knn", lambda: crawl.knn_links(load(spark, sf_dir, "embeddings"), k=50))


def walk_paths(spark: SparkSession, sf_dir: str, which: str = "dense") -> DataFrame:
    """W1 (dense: first five links) and W2 (sparse: all links) over ranked links."""
    policy = "first_k" if which == "dense" else "all"
    return once(spark, sf_dir, f"walks_{which}", lambda: crawl.simulate_walks(spark, knn(spark, sf_dir), start=START, n_paths=WALKS, policy=policy, k=5))


def page_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = load(spark, sf_dir, "pages")
    return crawl.resolve_links(crawl.extract_links(pages), pages, how="bucket")


def page_walks(spark: SparkSession, sf_dir: str, k: int | None = 2) -> DataFrame:
    """W1p, W2p: the same from the pages' own anchors, with titles checked."""
    titles = crawl.page_titles(load(spark, sf_dir, "pages"))
    return crawl.simulate_walks(spark, page_links(spark, sf_dir), start=START, n_paths=WALKS, policy="first_k" if k else "all", k=k or 0, titles=titles)


def order_steps(spark: SparkSession, sf_dir: str, node: str = "part") -> DataFrame:
    return tables.from_orders(load(spark, sf_dir, "lineitem"), node=node)


def session_steps(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tables.from_events(load(spark, sf_dir, "events"))


def game_paths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W3c: sessions of four to seven steps, with their outcome."""
    steps = session_steps(spark, sf_dir)
    outcome = steps.groupBy("path_id").agg(F.first("outcome").alias("outcome"))
    return trajectories.gather_paths(steps).where("length between 4 and 7").join(outcome, "path_id")


class Crawl:
    """A walk graph with its split, counts, features and fixed weights."""

    def __init__(self, spark: SparkSession, sf_dir: str, which: str = "dense") -> None:
        self.spark, self.sf_dir, self.which = spark, sf_dir, which
        if which in ("dense", "sparse"):
            paths = walk_paths(spark, sf_dir, which).select("path_id", "nodes", "length")
        else:
            paths = once(spark, sf_dir, "game", lambda: game_paths(spark, sf_dir))
        self.paths = trajectories.split_paths(paths)
        self.steps = trajectories.explode_paths(self.paths)

    def _once(self, name: str, build: Callable[[], DataFrame]) -> DataFrame:
        return once(self.spark, self.sf_dir, f"{self.which}_{name}", build)

    @property
    def edges(self) -> DataFrame:
        return self._once("edges", lambda: graph.build_edges(self.steps))

    @property
    def nof(self) -> DataFrame:
        train = trajectories.explode_paths(self.paths.where("split = 'train'"))
        return self._once("nof", lambda: features.click_counts(train, self.edges))

    @property
    def dual(self) -> DataFrame:
        return self._once("dual", lambda: dual.dual_features(self.edges))

    @property
    def text(self) -> DataFrame:
        """Text similarity of linked articles; document ids stand for node ids."""
        from ..operators import text

        def build() -> DataFrame:
            articles = load(self.spark, self.sf_dir, "documents").select(F.col("doc_id").alias("node_id"), "text")
            articles = articles.join(graph.edge_nodes(self.edges), "node_id", "left_semi")
            return text.edge_text_similarity(self.edges, text.tfidf(articles))

        return self._once("text", build)

    def latent(self, kind: str) -> DataFrame:
        def build() -> DataFrame:
            if kind == "uniform":
                return weights.weights_uniform(self.edges)
            if kind == "empirical":
                return weights.weights_empirical(self.nof, alpha=1.0)
            if kind == "text":
                return weights.weights_text(self.text)
            rows = self.dual.join(self.nof, ["src", "dst"]).withColumn("log_nof", F.log1p("nof"))
            return weights.softmax_out(weights.linear_scores(rows, LINEAR)).select("src", "dst", "w")

        return self._once(f"w_{kind}", build)

    def windows(self, *, split: str = "test", horizons: tuple[int, ...] = (H,)) -> DataFrame:
        return trajectories.windows(self.paths.where(F.col("split") == split), horizons=horizons)

    @property
    def starts(self) -> DataFrame:
        return self.edges.select(F.col("src").alias("node_id")).distinct()

    @property
    def degrees(self) -> DataFrame:
        return graph.node_degrees(self.edges)
