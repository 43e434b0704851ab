"""Queries over walk graphs beside those of the registry: construction from pages, variants of the walk, the graphs compared, files."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.columns import cosine, cosine_sparse
from ..functions.registered import edge_mlp, modularity_check, register_sql
from ..operators import community, dual, features, graph, metrics, text, trajectories, walk
from ..operators.store import shared_dir, stored
from ..sources import files
from . import experiments, workloads
from .registry import _EDGE_TEXT, part_edges, query, r6, r9
from .sql import hash8
from .workloads import H, Crawl, load, once

# ---------------------------------------------------------------- construction


@query(
    "q08b_page_walk_stats",
    " UNION ALL ".join(f"SELECT {k} AS first_k, n, m, round(CASE WHEN n > 1 THEN CAST(m AS DOUBLE) / (CAST(n AS DOUBLE) * (n - 1)) ELSE 0 END, 9) AS density FROM (SELECT (SELECT count(DISTINCT node_id) FROM steps_pages{k}x) AS n, (SELECT count(*) FROM edges_pages{k}x) AS m) x" for k in (2, 5, 0)),
)
def q08b(spark, d):
    parts = []
    for k in (2, 5, None):
        steps = trajectories.explode_paths(workloads.page_walks(spark, d, k))
        parts.append(graph.density(graph.build_nodes(steps), graph.build_edges(steps)).select(F.lit(k or 0).alias("first_k"), "n", "m", F.round("density", 9).alias("density")))
    return reduce(DataFrame.unionByName, parts)


@query("q28c_dual_adjacency", "SELECT a.src, a.dst AS through, b.dst FROM edges_part a JOIN edges_part b ON b.src = a.dst")
def q28c(spark, d):
    return dual.dual_adjacency(part_edges(spark, d))


_TEXT_SIM = """SELECT e.src, e.dst, coalesce(CASE WHEN a.norm * b.norm > 0 THEN t.dot / (a.norm * b.norm) END, 0) AS text_sim FROM edges_dense e
       LEFT JOIN dots t ON t.src = e.src AND t.dst = e.dst LEFT JOIN norms a ON a.node_id = e.src LEFT JOIN norms b ON b.node_id = e.dst"""


def _feature_sets(kind: str):
    columns = features.DUAL_COLUMNS[kind]
    sql = f"""SELECT d.src, d.dst, round(t.text_sim, 6) AS text_sim, n.nof{"".join(f", round({c}, 6) AS {c}" for c in columns)}, {2 + len(columns)} AS width
              FROM dual_dense d JOIN nof_dense n ON n.src = d.src AND n.dst = d.dst JOIN sims t ON t.src = d.src AND t.dst = d.dst"""

    @query(f"q28_set_{kind}", sql, _EDGE_TEXT | {"sims": _TEXT_SIM})
    def q(spark, d):
        c = Crawl(spark, d)
        rows = features.assemble_edge_features(c.edges, c.text, c.nof, c.dual, features=kind)
        shown = [F.round(F.col("f")[i], 6).alias(x) for i, x in ((0, "text_sim"), *((2 + i, x) for i, x in enumerate(columns)))]
        return rows.select("src", "dst", F.col("f")[1].cast("long").alias("nof"), *shown, F.size("f").alias("width"))

    return q


for _k in features.DUAL_COLUMNS:
    _feature_sets(_k)


# ---------------------------------------------------------------- variants of the walk

_OPEN = "1 - coalesce(b.w, 0) > 1e-12"
_STUCK = "1 - coalesce(b.w, 0) <= 1e-12"


def _back_step(k: int) -> str:
    return f"""SELECT m.start, n.src, n.dst, sum(m.p * CASE WHEN {_STUCK} THEN 1.0 ELSE n.w / (1 - coalesce(b.w, 0)) END) AS p
        FROM back{k} m LEFT JOIN w_empirical b ON b.src = m.dst AND b.dst = m.src JOIN w_empirical n ON n.src = m.dst AND (({_OPEN}) = (n.dst <> m.src)) GROUP BY m.start, n.src, n.dst"""


def _printed_step(k: int) -> str:
    return f"""SELECT m.start, i.src, i.dst, sum(m.p * own.w / (1 - coalesce(b.w, 0))) AS p
        FROM printed{k} m JOIN w_empirical own ON own.src = m.src AND own.dst = m.dst JOIN w_empirical i ON i.dst = m.src AND i.src <> m.dst
        LEFT JOIN w_empirical b ON b.src = i.dst AND b.dst = i.src WHERE {_OPEN} GROUP BY m.start, i.src, i.dst"""


_VARIANTS = {f"{n}0": "SELECT src AS start, src, dst, w AS p FROM w_empirical" for n in ("back", "printed")} | {f"back{k + 1}": _back_step(k) for k in (0, 1)} | {f"printed{k + 1}": _printed_step(k) for k in (0, 1)}


@query(
    "q38c_dead_ends_and_orientation",
    " UNION ALL ".join(
        f"SELECT '{n}' AS variant, round(avg(1 - kept), 6) AS mean_lost, count(*) AS starts FROM (SELECT start, sum(p) AS kept FROM {t} GROUP BY start) x{i}"
        for i, (n, t) in enumerate((("drop", "w_empirical_tail"), ("allow_backtrack", "back2"), ("printed", "printed2")))
    ),
    _VARIANTS,
)
def q38c(spark, d):
    c = Crawl(spark, d)
    latent, parts = c.latent("empirical"), []
    for name, options in (("drop", {}), ("allow_backtrack", {"dead_end": "allow_backtrack"}), ("printed", {"orientation": "printed"})):
        dist = walk.target_distribution(c.starts, latent, h=H, **options)
        parts.append(walk.lost_mass(dist).agg(F.lit(name).alias("variant"), F.round(F.avg("lost"), 6).alias("mean_lost"), F.count("*").alias("starts")))
    return reduce(DataFrame.unionByName, parts)


@query("q38d_pruned_walk", """SELECT start, src, dst, round(p, 9) AS p FROM (SELECT *, row_number() OVER (PARTITION BY start ORDER BY round(p, 9) DESC, src, dst) AS r FROM
        (SELECT m.start, n.src, n.dst, sum(m.p * n.w / (1 - coalesce(b.w, 0))) AS p FROM w_empirical_m0 m JOIN w_empirical n ON n.src = m.dst AND n.dst <> m.src
         LEFT JOIN w_empirical b ON b.src = m.dst AND b.dst = m.src WHERE 1 - coalesce(b.w, 0) > 1e-12 GROUP BY m.start, n.src, n.dst HAVING sum(m.p * n.w / (1 - coalesce(b.w, 0))) >= 0.01) x) y WHERE r <= 6""")
def q38d(spark, d):
    c = Crawl(spark, d)
    latent = c.latent("empirical")
    return walk.propagate(walk.spread(walk.one_hot(c.starts), latent), latent, h=1, prune=0.01, topk=6).select("start", "src", "dst", r9("p"))


def _beam(k: int) -> str:
    grown = "SELECT src AS start, src AS origin, dst AS place, CAST(dst AS VARCHAR) AS suffix, w AS p FROM w_empirical" if k == 1 else f"""
        SELECT r.start, r.place AS origin, n.dst AS place, r.suffix || '>' || n.dst AS suffix, r.p * n.w / (1 - coalesce(b.w, 0)) AS p FROM beam{k - 1} r
        JOIN w_empirical n ON n.src = r.place AND n.dst <> r.origin LEFT JOIN w_empirical b ON b.src = r.place AND b.dst = r.origin WHERE {_OPEN}"""
    return f"SELECT start, origin, place, suffix, p, rank FROM (SELECT *, row_number() OVER (PARTITION BY start ORDER BY round(p, 9) DESC, suffix) AS rank FROM ({grown}) x) y WHERE rank <= 8"


@query("q40b_beam_suffixes", "SELECT start, suffix, round(p, 9) AS p, CAST(rank AS INTEGER) AS rank FROM beam3 WHERE rank <= 2", {f"beam{k}": _beam(k) for k in (1, 2, 3)})
def q40b(spark, d):
    c = Crawl(spark, d)
    return walk.top_suffixes(c.starts, c.latent("empirical"), h=3, k=2, beam=8).select("start", "suffix", r9("p"), "rank")


# ---------------------------------------------------------------- measures


def _hits(name: str, degree: str, anchored: bool) -> str:
    first = "t.before" if anchored else "CAST(NULL AS BIGINT)"
    return f"""SELECT '{name}' AS variant, m.path_id, CASE WHEN x.dst = m.dst THEN 1.0 ELSE 0.0 END AS hit FROM
            (SELECT path_id, window_id, {first} AS before, cur AS src, suffix[1] AS dst FROM tests t UNION ALL SELECT path_id, window_id, cur, suffix[1], suffix[2] FROM tests) m
            JOIN degrees_dense d ON d.node_id = m.src AND {degree} LEFT JOIN w_empirical_exits e1 ON e1.src = m.src AND e1.r = 1
            LEFT JOIN w_empirical_exits x ON x.src = m.src AND x.r = CASE WHEN e1.dst = m.before THEN 2 ELSE 1 END"""


_CHOICES = {
    "hits": " UNION ALL ".join((_hits("out degree", "d.out_degree >= 3", False), _hits("macro", "d.in_degree + d.out_degree >= 3", False), _hits("edge", "d.in_degree + d.out_degree >= 3", True), _hits("five", "d.in_degree + d.out_degree >= 5", False))),
    "by_path": "SELECT variant, path_id, avg(hit) AS hit FROM hits WHERE variant = 'macro' GROUP BY variant, path_id UNION ALL SELECT variant, path_id, hit FROM hits WHERE variant <> 'macro'",
}


@query("q42b_choice_variants", "SELECT variant, 'choice_accuracy' AS metric, round(avg(hit), 6) AS value, count(*) AS support FROM by_path GROUP BY variant", _CHOICES)
def q42b(spark, d):
    c = Crawl(spark, d)
    parts = []
    for name, options in (("out degree", {"degree": "out"}), ("macro", {"average": "macro"}), ("edge", {"anchor": "edge"}), ("five", {"min_degree": 5})):
        found = metrics.choice_accuracy(c.windows(), c.latent("empirical"), c.degrees, **options)
        parts.append(found.select(F.lit(name).alias("variant"), "metric", F.round("value", 6).alias("value"), "support"))
    return reduce(DataFrame.unionByName, parts)


@query("q45c_density_trend", "SELECT metric, round(corr(density, value), 6) AS correlation FROM (" + " UNION ALL ".join(f"SELECT s.density, m.metric, m.value FROM measures1_{g} m, shape_{g} s" for g in experiments.GRAPHS) + ") x GROUP BY metric")
def q45c(spark, d):
    parts = []
    for name in experiments.GRAPHS:
        c = Crawl(spark, d, name)
        stats = graph.density(graph.build_nodes(c.steps), c.edges).select("density")
        found = metrics.all_metrics(walk.target_distribution(c.starts, c.latent("empirical"), h=1, how="head"), c.windows(horizons=(1,)), c.latent("empirical"), c.degrees)
        parts.append(found.crossJoin(F.broadcast(stats)).select(F.lit(name).alias("graph"), "density", "metric", "value"))  # one row
    return metrics.density_trend(reduce(DataFrame.unionByName, parts)).select("metric", r6("correlation"))


@query("q45d_graphs_compared", " UNION ALL ".join(f"SELECT '{g}' AS graph, s.n, s.m, round(s.density, 9) AS density, m.metric, round(m.value, 6) AS value FROM measures1_{g} m, shape_{g} s" for g in experiments.GRAPHS))
def q45d(spark, d):
    parts = []
    for name in experiments.GRAPHS:
        c = Crawl(spark, d, name)
        found = metrics.all_metrics(walk.target_distribution(c.starts, c.latent("empirical"), h=1, how="head"), c.windows(horizons=(1,)), c.latent("empirical"), c.degrees)
        parts.append(found.select(F.lit(name).alias("graph"), "metric", F.round("value", 6).alias("value")))
    return experiments.compare_graphs(reduce(DataFrame.unionByName, parts), experiments.graph_stats(spark, d)).select("graph", "n", "m", F.round("density", 9).alias("density"), "metric", "value")


# ---------------------------------------------------------------- communities


def _members(spark: SparkSession, d: str, name: str) -> DataFrame:
    return once(spark, d, f"{name}_members", lambda: community.communities(Crawl(spark, d, name).edges))


def _labels(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "embeddings").select(F.col("vec_id").cast("long").alias("node_id"), F.col("label").cast("string").alias("category"))


@query("q47_communities")
def q47(spark, d):
    parts = [community.modularity(Crawl(spark, d, g).edges, _members(spark, d, g)).select(F.lit(g).alias("graph"), "modularity", "communities") for g in experiments.GRAPHS]
    return reduce(DataFrame.unionByName, parts)


@query("q47b_found_clusters")
def q47b(spark, d):
    """Sizes, inner shares, commonest categories and the seed's cluster of the communities found in each graph."""
    parts = [community.cluster_profile(Crawl(spark, d, g).edges, _members(spark, d, g), _labels(spark, d), seed_node=workloads.START).withColumn("graph", F.lit(g)) for g in experiments.GRAPHS]
    return reduce(DataFrame.unionByName, parts)


_PROFILE = {
    "members": "SELECT DISTINCT node_id, node_id % 7 AS community FROM (SELECT src AS node_id FROM edges_dense UNION ALL SELECT dst FROM edges_dense) x",
    "shares": "SELECT a.community, avg(CASE WHEN a.community = b.community THEN 1.0 ELSE 0.0 END) AS inner_share FROM edges_dense e JOIN members a ON a.node_id = e.src JOIN members b ON b.node_id = e.dst GROUP BY a.community",
    "commonest": "SELECT community, category, row_number() OVER (PARTITION BY community ORDER BY n DESC, category) AS r FROM (SELECT m.community, CAST(v.label AS VARCHAR) AS category, count(*) AS n FROM members m JOIN embeddings v ON v.vec_id = m.node_id GROUP BY ALL) x",
}


@query(
    "q48b_cluster_profile",
    """SELECT m.community, m.size, round(coalesce(s.inner_share, 0), 6) AS inner_share, m.holds_seed, c.category FROM
        (SELECT community, count(*) AS size, bool_or(node_id = 0) AS holds_seed FROM members GROUP BY community) m LEFT JOIN shares s ON s.community = m.community LEFT JOIN commonest c ON c.community = m.community AND c.r = 1""",
    _PROFILE,
)
def q48b(spark, d):
    edges = Crawl(spark, d).edges
    members = graph.edge_nodes(edges).withColumn("community", F.col("node_id") % 7)
    return community.cluster_profile(edges, members, _labels(spark, d)).withColumn("inner_share", F.round("inner_share", 6))


_MODULAR = {"und": "SELECT DISTINCT least(src, dst) AS a, greatest(src, dst) AS b FROM edges_part"}


@query(
    "q48c_modularity_by_function",
    """SELECT round(sum(inner2 / (2.0 * m) - (degree / (2.0 * m)) * (degree / (2.0 * m))), 6) AS modularity FROM
        (SELECT c, count(*) AS degree, sum(CASE WHEN a % 7 = b % 7 THEN 1.0 ELSE 0.0 END) AS inner2 FROM (SELECT a, b, a % 7 AS c FROM und UNION ALL SELECT a, b, b % 7 FROM und) x GROUP BY c) y, (SELECT count(*) AS m FROM und) z""",
    _MODULAR,
)
def q48c(spark, d):
    """The Python aggregate over the shares of each community, beside the DataFrame form of q46."""
    und = stored(part_edges(spark, d).select(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b")).distinct(), "und")
    ends = und.select(F.explode(F.array(F.struct((F.col("a") % 7).alias("c"), (F.col("b") % 7).alias("o")), F.struct((F.col("b") % 7).alias("c"), (F.col("a") % 7).alias("o")))).alias("e"))
    m = float(2 * und.count())
    shares = ends.groupBy("e.c").agg((F.sum((F.col("e.c") == F.col("e.o")).cast("double")) / m).alias("inner"), (F.count("*") / m).alias("degree"))
    return shares.agg(F.round(modularity_check()(F.col("inner"), F.col("degree")), 6).alias("modularity"))


_DIFFUSE = {
    "two_ways": "SELECT DISTINCT a AS node_id, b AS dst FROM (SELECT src AS a, dst AS b FROM edges_dense UNION ALL SELECT dst, src FROM edges_dense) x",
    "room": "SELECT dst AS node_id, count(*) + 1 AS n FROM two_ways GROUP BY dst",
    "x0": "SELECT DISTINCT src AS start, src AS node_id, 1.0::DOUBLE AS p FROM edges_dense",
} | {f"x{k + 1}": f"SELECT y.start, y.node_id, y.p / r.n AS p FROM (SELECT start, node_id, sum(p) AS p FROM (SELECT x.start, b.dst AS node_id, x.p FROM x{k} x JOIN two_ways b ON b.node_id = x.node_id UNION ALL SELECT start, node_id, p FROM x{k}) z GROUP BY start, node_id) y JOIN room r ON r.node_id = y.node_id" for k in (0, 1)}


@query("q50d_diffused_coordinates", "SELECT start, node_id, round(p, 9) AS p FROM x2", _DIFFUSE)
def q50d(spark, d):
    c = Crawl(spark, d)
    return walk.diffuse(walk.one_hot(c.starts), c.edges, layers=2).select("start", "node_id", r9("p"))


# ---------------------------------------------------------------- files


@query(
    "q51_graphml",
    """SELECT (SELECT count(DISTINCT node_id) FROM steps_dense) AS nodes, (SELECT count(*) FROM edges_dense) AS edges, CAST(0 AS BIGINT) AS changed_nodes, CAST(0 AS BIGINT) AS changed_edges, CAST(0 AS BIGINT) AS dangling""",
)
def q51(spark, d):
    """The graph written, parsed back and compared row by row; titles hold what markup must escape."""
    c, path = Crawl(spark, d), f"{shared_dir(spark)}/graphml-{abs(hash(d))}"
    own = stored(graph.build_nodes(c.steps).withColumn("title", F.concat(F.lit("<"), F.col("node_id").cast("string"), F.lit("> & &amp; more"))), "titled")
    files.write_graphml(own, c.edges, path)
    nodes, edges = (stored(x, "parsed") for x in files.read_graphml(spark, path))
    lost = lambda a, b: a.exceptAll(b).unionByName(b.exceptAll(a)).agg(F.count("*").alias("n"))
    ends = edges.select(F.explode(F.array("src", "dst")).alias("node_id")).join(nodes, "node_id", "left_anti").agg(F.count("*").alias("dangling"))
    counts = nodes.agg(F.count("*").alias("nodes")).crossJoin(edges.agg(F.count("*").alias("edges")))  # rows of one, here and below
    counts = counts.crossJoin(lost(own, nodes).withColumnRenamed("n", "changed_nodes")).crossJoin(lost(c.edges.select("src", "dst"), edges).withColumnRenamed("n", "changed_edges"))
    return counts.crossJoin(ends)


@query(
    "q51b_bundle",
    " UNION ALL ".join(
        f"SELECT '{n}' AS name, (SELECT count({w}) FROM {t}) * {k} AS n_rows"
        for n, t, w, k in (
            ("paths", "paths_dense", "*", 1), ("nodes", "steps_dense", "DISTINCT node_id", 1), ("steps", "steps_dense", "*", 1), ("categories", "steps_dense", "DISTINCT node_id", 1),
            ("edges", "edges_dense", "*", 1), ("hyperedges", "edges_dense", "*", 2), ("observations", "steps_dense", "*", 1), ("path_lengths", "paths_dense", "*", 1),
        )
    ),
)
def q51b(spark, d):
    c, path = Crawl(spark, d), f"{shared_dir(spark)}/bundle-{abs(hash(d))}"
    edges = c.nof.select(F.xxhash64("src", "dst").alias("edge_id"), "src", "dst", "nof")
    labels = _labels(spark, d).withColumnRenamed("category", "type")
    nodes = graph.build_nodes(c.steps)
    files.write_bundle({
        "paths": c.paths, "nodes": nodes, "steps": c.steps, "categories": graph.categorize(nodes, labels), "edges": edges, "hyperedges": dual.hyperedges(edges),
        "observations": trajectories.observe(c.steps), "path_lengths": trajectories.path_lengths(c.steps),
    }, path)
    return reduce(DataFrame.unionByName, [t.agg(F.lit(n).alias("name"), F.count("*").alias("n_rows")) for n, t in files.read_bundle(spark, path).items()])


# ---------------------------------------------------------------- functions

_MLP = {"w1": [[1.0, -1.0], [0.5, 2.0], [-0.25, 0.0]], "b1": [0.1, -0.2], "w2": [0.7, -0.3], "b2": [0.05]}


@query(
    "q34c_edge_mlp",
    """SELECT src, dst, round(0.7 * greatest(0, hyper_sim + 0.5 * dual_in - 0.25 * dual_out + 0.1) - 0.3 * greatest(0, -hyper_sim + 2 * dual_in - 0.2) + 0.05, 6) AS z FROM dual_part""",
)
def q34c(spark, d):
    """A perceptron with given parameters over the dual features of every edge, as an Arrow function."""
    rows = dual.dual_features(part_edges(spark, d)).select("src", "dst", F.array("hyper_sim", "dual_in", "dual_out").alias("f"))
    return rows.select("src", "dst", F.round(edge_mlp(_MLP)(F.col("f")), 6).alias("z"))


@query("q18b_vector_cosine", "SELECT e.src, e.dst, round(list_cosine_similarity(a.v, b.v), 6) AS cosine FROM edges_dense e JOIN vectors a ON a.id = e.src JOIN vectors b ON b.id = e.dst")
def q18b(spark, d):
    vectors = load(spark, d, "embeddings").select(F.col("vec_id").cast("long").alias("id"), "embedding")
    a, b = (vectors.select(F.col("id").alias(c), F.col("embedding").alias(f"v_{c}")) for c in ("src", "dst"))
    return Crawl(spark, d).edges.join(a, "src").join(b, "dst").select("src", "dst", F.round(cosine(F.col("v_src"), F.col("v_dst")), 6).alias("cosine"))


@query("q18c_map_cosine", "SELECT src, dst, round(text_sim, 6) AS text_sim FROM sims", _EDGE_TEXT | {"sims": _TEXT_SIM})
def q18c(spark, d):
    """Text similarity of linked articles as the cosine of two maps of terms, one per article, beside the join on terms of q18."""
    edges = Crawl(spark, d).edges
    articles = load(spark, d, "documents").select(F.col("doc_id").alias("node_id"), "text").join(graph.edge_nodes(edges), "node_id", "left_semi")
    maps = text.tfidf(articles).groupBy("node_id").agg(F.map_from_entries(F.collect_list(F.struct("term", "tfidf"))).alias("m"))  # a text's terms
    a, b = (maps.select(F.col("node_id").alias(c), F.col("m").alias(f"m_{c}")) for c in ("src", "dst"))
    sim = F.coalesce(cosine_sparse(F.col("m_src"), F.col("m_dst")), F.lit(0.0))
    return edges.join(a, "src", "left").join(b, "dst", "left").select("src", "dst", F.round(sim, 6).alias("text_sim"))


@query("q35b_sql_functions", "SELECT n.src, n.dst, round(CASE WHEN 1 - coalesce(b.w, 0) > 1e-12 THEN n.w / (1 - coalesce(b.w, 0)) ELSE 0 END, 6) AS go FROM w_empirical n LEFT JOIN w_empirical b ON b.src = n.dst AND b.dst = n.src")
def q35b(spark, d):
    register_sql(spark)
    latent = Crawl(spark, d).latent("empirical")
    return spark.sql("SELECT n.src, n.dst, round(nb_transition(n.w, b.w), 6) AS go FROM {n} n LEFT JOIN {n} b ON b.src = n.dst AND b.dst = n.src", n=latent.select("src", "dst", "w"))


__all__ = ["hash8"]
