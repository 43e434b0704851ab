"""The experiments: feature sets by graph by measure, repeats, suffix examples, communities. python -m hyperpath.plans.experiments SF_DIR prints them."""

from __future__ import annotations

import sys
from dataclasses import replace
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.columns import hash8
from ..operators import community, features, graph, metrics, train, trajectories, walk
from ..operators.store import stored
from .workloads import Crawl, knn, once

SETS = ("original", "similarity", "degree", "combined")
#: Columns of the combined features that each set has.
SET_COLUMNS = {"original": [0, 1], "similarity": [0, 1, 2], "degree": [0, 1, 3, 4], "combined": [0, 1, 2, 3, 4]}
GRAPHS = ("sparse", "dense", "game")
SEEDS = (1, 2, 3)
#: Production settings of the experiments: the walk and its pseudoinverse, one layer of coordinates (more cost a product of the
#: ball's nodes each).
SETTINGS = {"h": 2, "layers": 1, "epochs": 12, "lr": 0.08, "readout": "pinv"}

_models: dict[tuple, list[tuple[str, int, train.Model]]] = {}


def balls(crawl: Crawl, split: str, *, h: int, layers: int, readout: str, whole: bool = False, windows: DataFrame | None = None, name: str = "") -> DataFrame:
    """Packed balls with all five edge features; agents are seen at the nearest vectors where the graph has vectors."""

    def build() -> DataFrame:
        nof = crawl.nof.select("src", "dst", F.log1p("nof").alias("nof"))
        edges = stored(features.assemble_edge_features(crawl.edges, crawl.text, nof, crawl.dual, features="combined", standardize=True), "features")
        nodes = stored(features.node_features(crawl.edges), "nodes")
        seen = None
        if crawl.which != "game":
            seen = stored(trajectories.nearest_nodes(nodes, knn(crawl.spark, crawl.sf_dir)), "seen")
        rows = crawl.windows(split=split, horizons=(h,)) if windows is None else windows
        return train.ego_graphs(rows, edges, nodes, h=h, layers=layers, readout=readout, whole=whole, observations=seen).repartition(2 * crawl.spark.sparkContext.defaultParallelism)

    return once(crawl.spark, crawl.sf_dir, f"{crawl.which}_{split}_{h}_{layers}_{readout}_{whole}{name}_balls", build)


def configs(sets: tuple[str, ...], seeds: tuple[int, ...], **options: object) -> list[train.ModelConfig]:
    return [train.ModelConfig(**({"edge_width": len(SET_COLUMNS[s]), "columns": SET_COLUMNS[s], "seed": seed} | options)) for s in sets for seed in seeds]


def trained(crawl: Crawl, *, sets: tuple[str, ...] = SETS, seeds: tuple[int, ...] = SEEDS, **options: object) -> list[tuple[str, int, train.Model]]:
    """(feature set, seed, model), all trained together on the training windows; kept for the session."""
    settings = SETTINGS | options
    key = (crawl.spark.sparkContext.applicationId, crawl.sf_dir, crawl.which, sets, seeds, tuple(sorted(settings.items())))
    if key not in _models:
        layers = settings["layers"] if settings.get("coords") != "none" else 0
        rows = balls(crawl, "train", h=settings["h"], layers=layers, readout=settings["readout"])
        models = train.fit_many(rows, configs(sets, seeds, **settings))
        _models[key] = [(s, seed, m) for (s, seed), m in zip(((s, seed) for s in sets for seed in seeds), models, strict=True)]
    return _models[key]


def predictions(crawl: Crawl, models: list[tuple[str, int, train.Model]], *, suffixes: int = 0, windows: DataFrame | None = None, name: str = "") -> DataFrame:
    """predict_many() on the test split, or on given windows, with the feature set and seed of each model."""
    config = models[0][2].config
    layers = config.layers if config.coords == "gnn" else 0
    h = config.h if windows is None else windows.select("h").first()["h"]
    rows = balls(crawl, "test", h=h, layers=layers, readout=config.readout, whole=True, windows=windows, name=name)
    shown = [train.Model(replace(m.config, h=h), m.params) for _, _, m in models]
    names = F.create_map(*(F.lit(x) for i, (s, seed, _) in enumerate(models) for x in (i, f"{s}|{seed}")))
    out = train.predict_many(rows, shown, suffixes=suffixes).withColumn("_name", F.split(F.element_at(names, F.col("model")), r"\|"))
    return out.withColumn("features", F.get("_name", 0)).withColumn("seed", F.get("_name", 1).cast("int")).drop("_name")


def all_node_balls(crawl: Crawl) -> DataFrame:
    """Balls of one step around every node that has exits, as a window each: for weights that don't depend on the prefix."""
    first = crawl.edges.groupBy("src").agg(F.min("dst").alias("target"))
    windows = first.select(F.col("src").alias("cur"), "target", F.array("src").alias("prefix"), F.array("target").alias("suffix"), F.lit(1).alias("h"))
    return balls(crawl, "none", h=1, layers=0, readout="head", whole=True, windows=windows, name="_nodes")


def run_experiment(crawl: Crawl, *, sets: tuple[str, ...] = SETS, seeds: tuple[int, ...] = SEEDS, **options: object) -> DataFrame:
    """(graph, features, seed, metric, value, support) of the whole test split; see metrics.summarize_runs for mean and deviation."""

    def build() -> DataFrame:
        models = trained(crawl, sets=sets, seeds=seeds, **options)
        # Stored, as the measures read them three times.
        found = stored(predictions(crawl, models).select("model", "features", "seed", "count", "p_target", "rank", "choices"), "predictions")
        names = found.select("model", "features", "seed").distinct()
        return train.measure(found).join(F.broadcast(names), "model").select(F.lit(crawl.which).alias("graph"), "features", "seed", "metric", "value", "support")

    tag = "_".join(map(str, (*sets, *seeds, *(f"{k}{v}" for k, v in sorted(options.items())))))
    return once(crawl.spark, crawl.sf_dir, f"{crawl.which}_runs_{abs(hash(tag))}", build)


def all_runs(spark: SparkSession, sf_dir: str, **options: object) -> DataFrame:
    return reduce(DataFrame.unionByName, [run_experiment(Crawl(spark, sf_dir, g), **options) for g in GRAPHS])


def report(runs: DataFrame) -> DataFrame:
    """Rows by graph and metric, columns by feature set, in percent."""
    mean = runs.groupBy("graph", "metric").pivot("features", list(SETS)).agg(F.round(100 * F.avg("value"), 4))
    return mean.orderBy("graph", "metric")


def compare_graphs(runs: DataFrame, densities: DataFrame) -> DataFrame:
    """Each run beside the density of its graph."""
    return runs.join(F.broadcast(densities), "graph")  # one row per graph


def graph_stats(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = GRAPHS) -> DataFrame:
    parts = []
    for name in names:
        c = Crawl(spark, sf_dir, name)
        parts.append(graph.density(graph.build_nodes(c.steps), c.edges).select(F.lit(name).alias("graph"), "n", "m", "density"))
    return reduce(DataFrame.unionByName, parts)


def example_windows(crawl: Crawl, horizons: tuple[int, ...] = (3, 2, 2)) -> dict[int, DataFrame]:
    """The test windows of least md5, as many of each horizon as it is named."""
    return {h: stored(crawl.windows(horizons=(h,)).withColumn("_o", hash8(F.col("window_id"))).orderBy("_o", "window_id").limit(horizons.count(h)).drop("_o"), "examples") for h in dict.fromkeys(horizons)}


def example_report(crawl: Crawl, *, horizons: tuple[int, ...] = (3, 2, 2), **options: object) -> DataFrame:
    """(features, h, cur, true_suffix, true_p, rival, rival_p): the example windows under the trained models of each feature set, first seed."""
    models = [m for m in trained(crawl, **options) if m[1] == SEEDS[0]]
    parts = []
    for h, chosen in example_windows(crawl, horizons).items():
        rows = predictions(crawl, models, suffixes=2, windows=chosen, name=f"_examples{h}")
        rival = F.get(F.filter("rivals", lambda r: r["suffix"] != F.col("suffix")), 0)
        parts.append(rows.select("features", F.lit(h).alias("h"), "cur", F.array_join("suffix", ">").alias("true_suffix"), F.col("p_path").alias("true_p"), F.array_join(rival["suffix"], ">").alias("rival"), rival["p"].alias("rival_p")))
    return reduce(DataFrame.unionByName, parts)


def fixed_example_report(crawl: Crawl, *, kinds: tuple[str, ...] = ("uniform", "empirical", "text", "linear"), horizons: tuple[int, ...] = (3, 2, 2)) -> DataFrame:
    """The same windows under fixed weights, with the whole graph's suffixes as rivals."""
    parts = []
    for h, chosen in example_windows(crawl, horizons).items():
        true = F.array_join("suffix", ">")
        for kind in kinds:
            latent = crawl.latent(kind)
            own = walk.suffix_probability(chosen, latent)
            top = walk.top_suffixes(chosen.select(F.col("cur").alias("node_id")).distinct(), latent, h=h, k=2).select(F.col("start").alias("cur"), F.col("suffix").alias("rival"), F.col("p").alias("rival_p"), "rank")
            rows = chosen.join(own, "window_id").join(top, "cur", "left").where("rival is null or rival <> array_join(suffix, '>')")
            best = rows.groupBy("window_id", "h", true.alias("true_suffix"), F.col("p").alias("true_p")).agg(F.min_by("rival", "rank").alias("rival"), F.min_by("rival_p", "rank").alias("rival_p"))
            parts.append(best.select(F.lit(kind).alias("weights"), "*"))
    return reduce(DataFrame.unionByName, parts)


def cluster_report(crawl: Crawl, categories: DataFrame) -> DataFrame:
    members = stored(community.communities(crawl.edges), "members")
    return community.cluster_profile(crawl.edges, members, categories, seed_node=0)


def main(sf_dir: str) -> None:
    spark = SparkSession.builder.master("local[*]").config("spark.sql.shuffle.partitions", "8").getOrCreate()
    densities = stored(graph_stats(spark, sf_dir), "densities")
    densities.show()
    runs = stored(all_runs(spark, sf_dir), "runs")
    report(runs).show(100, False)
    metrics.summarize_runs(runs, keys=("graph", "features", "metric")).orderBy("graph", "metric", "features").show(100, False)
    metrics.lift(runs.where("graph = 'sparse'").groupBy("features", "metric").agg(F.avg("value").alias("value"))).show(100, False)
    metrics.density_trend(compare_graphs(runs, densities)).show()
    example_report(Crawl(spark, sf_dir, "sparse")).show(50, False)
    labels = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select(F.col("vec_id").alias("node_id"), F.col("label").cast("string").alias("category"))
    for name in GRAPHS:
        cluster_report(Crawl(spark, sf_dir, name), labels).orderBy(F.desc("size")).show()


if __name__ == "__main__":
    main(sys.argv[1])
