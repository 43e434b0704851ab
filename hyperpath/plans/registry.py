"""QUERIES: name -> (spark, folder) -> DataFrame; ORACLE_SQL: the same in SQL where SQL can express it."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.columns import is_valid_title, url_host, url_path
from ..operators import community, crawl, dual, features, graph, metrics, relational, text, train, trajectories, walk, weights
from ..operators.store import shared_dir, stored
from ..sources import files, tables
from ..streaming import events as stream
from . import experiments, workloads
from .sql import edges_of, hash8, with_parts
from .workloads import H, Crawl, load, once

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE_SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None, parts: dict[str, str] | None = None):
    def add(f: Callable[[SparkSession, str], DataFrame]):
        QUERIES[name] = f
        if sql is not None:
            ORACLE_SQL[name] = with_parts(sql, parts)
        return f

    return add


def r6(c: str) -> F.Column:
    return F.round(c, 6).alias(c)


def r9(c: str) -> F.Column:
    return F.round(c, 9).alias(c)


def joined(c: str) -> F.Column:
    return F.concat_ws(">", F.col(c).cast("array<string>"))


def starred(df: DataFrame, *columns: str) -> DataFrame:
    """Subtotal rows show * for what they sum over."""
    for c in columns:
        df = df.withColumn(c, F.coalesce(F.col(c).cast("string"), F.lit("*")))
    return df


# ---------------------------------------------------------------- data-set construction

_TITLES = r"SELECT page_id AS node_id, regexp_extract(html, '(?s)<title>(.*?)</title>', 1) AS title FROM pages"
_LINKS = {"slugs": "SELECT page_id AS src, regexp_extract_all(html, '<a\\s[^>]*href=\"/([^\"]*)\"', 1) AS s FROM pages", "links": "SELECT src, slug, CAST(min(pos) AS INTEGER) AS pos FROM (SELECT src, unnest(s) AS slug, unnest(range(len(s))) AS pos FROM slugs) x GROUP BY src, slug"}


@query(
    "q01_valid_titles",
    r"""SELECT node_id, title, coalesce(NOT regexp_matches(title, 'Talk|User|File|ISO|[%#:]') AND NOT regexp_matches(title, '^[0-9]*$'), FALSE) AS valid,
               coalesce(NOT regexp_matches(title, '\b(?:Talk|User|File|ISO)\b|[%#:]') AND NOT regexp_matches(title, '^[0-9]*$'), FALSE) AS valid_word FROM titles""",
    {"titles": _TITLES},
)
def q01(spark, d):
    titles = crawl.page_titles(load(spark, d, "pages"))
    return titles.select("node_id", "title", is_valid_title(F.col("title")).alias("valid"), is_valid_title(F.col("title"), mode="word").alias("valid_word"))


@query("q02_page_links", "SELECT src, slug, pos FROM links", _LINKS)
def q02(spark, d):
    return crawl.extract_links(load(spark, d, "pages"))


@query(
    "q03_resolved_links_bucket",
    f"SELECT src, dst, CAST(min(pos) AS INTEGER) AS pos FROM (SELECT src, {hash8('chr(47) || slug')} % (SELECT count(*) FROM pages) AS dst, pos FROM links) x WHERE src <> dst GROUP BY src, dst",
    _LINKS,
)
def q03(spark, d):
    return workloads.page_links(spark, d)


@query(
    "q04_resolved_links_title",
    r"SELECT l.src, f.dst, CAST(min(l.pos) AS INTEGER) AS pos FROM links l JOIN firsts f ON lower(l.slug) = f.word WHERE l.src <> f.dst GROUP BY l.src, f.dst",
    _LINKS | {"titles": _TITLES, "firsts": r"SELECT word, min(node_id) AS dst FROM (SELECT node_id, unnest(regexp_extract_all(lower(title), '[\p{L}]+')) AS word FROM titles) x GROUP BY word"},
)
def q04(spark, d):
    pages = load(spark, d, "pages")
    return crawl.resolve_links(crawl.extract_links(pages), pages, how="title")


@query("q05_knn_links", "SELECT src, dst, pos FROM knn")
def q05(spark, d):
    return crawl.knn_links(load(spark, d, "embeddings"), k=50).drop("sim")


def _walks(which: str, policy: str):
    sql = f"SELECT path_id, array_to_string(nodes, '>') AS nodes, goal, length, CASE WHEN length = goal THEN 'goal' ELSE 'no_link' END AS stop_reason FROM paths_{which}"

    @query(f"q0{6 if which == 'dense' else 7}_walks_{policy}", sql)
    def q(spark, d):
        return workloads.walk_paths(spark, d, which).withColumn("nodes", joined("nodes"))

    return q


_walks("dense", "first5")
_walks("sparse", "all")


@query(
    "q08_walk_graph_stats",
    " UNION ALL ".join(
        f"SELECT '{g}' AS graph, n, m, round(CAST(m AS DOUBLE) / (CAST(n AS DOUBLE) * (n - 1)), 9) AS density FROM (SELECT (SELECT count(DISTINCT node_id) FROM steps_{g}) AS n, (SELECT count(*) FROM edges_{g}) AS m) x" for g in ("dense", "sparse")
    ),
)
def q08(spark, d):
    return experiments.graph_stats(spark, d, ("dense", "sparse")).withColumn("density", F.round("density", 9))


@query("q09_order_paths_part", "SELECT path_id, step, node_id FROM steps_part")
def q09(spark, d):
    return workloads.order_steps(spark, d)


@query("q10_order_paths_supplier", "SELECT path_id, step, node_id FROM steps_supp")
def q10(spark, d):
    return workloads.order_steps(spark, d, "supplier")


@query("q11_event_sessions", "SELECT path_id, agent, step, node_id, outcome FROM session_steps")
def q11(spark, d):
    return workloads.session_steps(spark, d)


@query("q12_graph_edges", "SELECT src, dst FROM edges_part")
def q12(spark, d):
    return graph.build_edges(workloads.order_steps(spark, d))


@query(
    "q13_density",
    " UNION ALL ".join(
        f"SELECT '{n}' AS graph, n, m, round(CAST(m AS DOUBLE) / (CAST(n AS DOUBLE) * (n - 1)), 9) AS density FROM (SELECT (SELECT count(DISTINCT node_id) FROM {s}) AS n, (SELECT count(*) FROM {e}) AS m) x"
        for n, s, e in (("part", "steps_part", "edges_part"), ("supplier", "steps_supp", "edges_supp"), ("session", "session_steps", "edges_sess"))
    ),
)
def q13(spark, d):
    parts = []
    for name, steps in (("part", workloads.order_steps(spark, d)), ("supplier", workloads.order_steps(spark, d, "supplier")), ("session", workloads.session_steps(spark, d))):
        parts.append(graph.density(graph.build_nodes(steps), graph.build_edges(steps)).select(F.lit(name).alias("graph"), "n", "m", F.round("density", 9).alias("density")))
    return reduce(DataFrame.unionByName, parts)


@query("q14_node_degrees", "SELECT node_id, in_degree, out_degree FROM degrees_part")
def q14(spark, d):
    return graph.node_degrees(graph.build_edges(workloads.order_steps(spark, d)))


@query(
    "q15_categories",
    """SELECT d.doc_id AS node_id, coalesce(CASE WHEN l.toxic = 1 THEN 'toxic' WHEN l.quality IS NOT NULL THEN 'quality' || l.quality END, 'subject.General') AS category
       FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id""",
)
def q15(spark, d):
    kind = F.when(F.col("toxic") == 1, "toxic").when(F.col("quality").isNotNull(), F.concat(F.lit("quality"), F.col("quality").cast("string")))
    types = load(spark, d, "labels").select(F.col("doc_id").alias("node_id"), kind.alias("type"))
    return graph.categorize(load(spark, d, "documents").select(F.col("doc_id").alias("node_id")), types)


@query(
    "q16_category_rollup",
    """SELECT coalesce(category, '*') AS category, coalesce(CAST(length AS VARCHAR), '*') AS length, count(DISTINCT path_id) AS paths FROM
        (SELECT DISTINCT s.path_id, p.p_type AS category, n.length FROM steps_part s JOIN part p ON p.p_partkey = s.node_id
         JOIN (SELECT path_id, count(*) AS length FROM steps_part GROUP BY path_id) n ON n.path_id = s.path_id) x GROUP BY ROLLUP (category, length)""",
)
def q16(spark, d):
    types = load(spark, d, "part").select(F.col("p_partkey").alias("node_id"), F.col("p_type").alias("category"))
    return starred(graph.category_profile(workloads.order_steps(spark, d), types), "category", "length")


# ---------------------------------------------------------------- text and click features

_TFIDF = {
    "terms": r"SELECT node_id, term, count(*) AS tf FROM (SELECT doc_id AS node_id, unnest(regexp_extract_all(lower(text), '[^\x20\x09-\x0D]+')) AS term FROM documents) x GROUP BY node_id, term",
    "tfidf_all": "SELECT t.node_id, t.term, t.tf, f.df, t.tf * ln((SELECT count(*) FROM documents) / CAST(f.df AS DOUBLE)) AS tfidf FROM terms t JOIN (SELECT term, count(*) AS df FROM terms GROUP BY term) f ON t.term = f.term",
}


@query("q17_tfidf", "SELECT node_id, term, tf, df, round(tfidf, 6) AS tfidf FROM tfidf_all", _TFIDF)
def q17(spark, d):
    articles = load(spark, d, "documents").select(F.col("doc_id").alias("node_id"), "text")
    return text.tfidf(articles).withColumn("tfidf", F.round("tfidf", 6))


_EDGE_TEXT = {
    "linked": "SELECT DISTINCT node_id FROM (SELECT src AS node_id FROM edges_dense UNION ALL SELECT dst FROM edges_dense) x",
    "articles": "SELECT doc_id AS node_id, text FROM documents WHERE doc_id IN (SELECT node_id FROM linked)",
    "eterms": r"SELECT node_id, term, count(*) AS tf FROM (SELECT node_id, unnest(regexp_extract_all(lower(text), '[^\x20\x09-\x0D]+')) AS term FROM articles) x GROUP BY node_id, term",
    "eweights": "SELECT t.node_id, t.term, t.tf * ln((SELECT count(*) FROM articles) / CAST(f.df AS DOUBLE)) AS x FROM eterms t JOIN (SELECT term, count(*) AS df FROM eterms GROUP BY term) f ON t.term = f.term",
    "norms": "SELECT node_id, sqrt(sum(x * x)) AS norm FROM eweights GROUP BY node_id",
    "dots": "SELECT e.src, e.dst, sum(a.x * b.x) AS dot FROM edges_dense e JOIN eweights a ON a.node_id = e.src JOIN eweights b ON b.node_id = e.dst AND b.term = a.term GROUP BY e.src, e.dst",
}


@query(
    "q18_edge_text_similarity",
    """SELECT e.src, e.dst, round(coalesce(CASE WHEN a.norm * b.norm > 0 THEN t.dot / (a.norm * b.norm) END, 0), 6) AS text_sim FROM edges_dense e
       LEFT JOIN dots t ON t.src = e.src AND t.dst = e.dst LEFT JOIN norms a ON a.node_id = e.src LEFT JOIN norms b ON b.node_id = e.dst""",
    _EDGE_TEXT,
)
def q18(spark, d):
    return Crawl(spark, d).text.select("src", "dst", r6("text_sim"))


@query(
    "q19_click_counts",
    f"""SELECT e.src, e.dst, CAST(coalesce(c.n, 0) AS BIGINT) AS nof FROM edges_part e LEFT JOIN
        (SELECT src, dst, count(*) AS n FROM (SELECT path_id, node_id AS src, lead(node_id) OVER (PARTITION BY path_id ORDER BY step) AS dst FROM steps_part WHERE {hash8('CAST(path_id AS VARCHAR)')} % 10 < 8) x WHERE dst IS NOT NULL GROUP BY src, dst) c
        ON c.src = e.src AND c.dst = e.dst""",
)
def q19(spark, d):
    steps = trajectories.split_paths(workloads.order_steps(spark, d))
    return features.click_counts(steps.where("split = 'train'"), graph.build_edges(steps))


# ---------------------------------------------------------------- dual hypergraph


def part_edges(spark: SparkSession, d: str) -> DataFrame:
    return graph.build_edges(workloads.order_steps(spark, d))


def session_edges(spark: SparkSession, d: str) -> DataFrame:
    return graph.build_edges(workloads.session_steps(spark, d))


@query("q20_incidence_undirected", "SELECT src AS node_id, src, dst, 1 AS sign FROM edges_part UNION ALL SELECT dst, src, dst, 1 FROM edges_part")
def q20(spark, d):
    return dual.incidence(part_edges(spark, d))


@query("q21_incidence_directed", "SELECT src AS node_id, src, dst, -1 AS sign FROM edges_part UNION ALL SELECT dst, src, dst, 1 FROM edges_part")
def q21(spark, d):
    return dual.incidence(part_edges(spark, d), directed=True)


@query("q22_dual_roundtrip", "SELECT * FROM (VALUES ('node_features', 0), ('incidence', 0), ('edge_features', 0)) t(part, differences)")
def q22(spark, d):
    from ..schemas import FeatureGraph

    edges = part_edges(spark, d).select(F.xxhash64("src", "dst").alias("edge_id"), "src", "dst")
    fg = FeatureGraph(graph.node_degrees(edges), dual.incidence(edges, directed=True).select("node_id", "edge_id", "sign"), edges.select("edge_id", F.lit(1).alias("weight")))
    return dual.roundtrip_differences(fg)


@query("q23_hyperedge_sizes", "SELECT node_id, in_degree + out_degree AS size FROM degrees_part")
def q23(spark, d):
    return dual.hyperedge_sizes(part_edges(spark, d))


@query("q24_hyperedge_similarity", "SELECT src, dst, round(hyper_sim, 6) AS hyper_sim FROM hyper_part")
def q24(spark, d):
    return dual.hyperedge_similarity(part_edges(spark, d)).select("src", "dst", r6("hyper_sim"))


@query(
    "q25_hyperedge_similarity_collapse",
    "SELECT e.src, e.dst, round(1 / sqrt(CAST(u.n AS DOUBLE) * v.n), 6) AS hyper_sim FROM edges_part e JOIN und_degree u ON u.node_id = e.src JOIN und_degree v ON v.node_id = e.dst",
    {"und": "SELECT DISTINCT least(src, dst) AS a, greatest(src, dst) AS b FROM edges_part", "und_degree": "SELECT node_id, count(*) AS n FROM (SELECT a AS node_id FROM und UNION ALL SELECT b FROM und) x GROUP BY node_id"},
)
def q25(spark, d):
    return dual.hyperedge_similarity(part_edges(spark, d), reciprocal="collapse").select("src", "dst", r6("hyper_sim"))


@query("q26_dual_degree", "SELECT src, dst, round(dual_in, 6) AS dual_in, round(dual_out, 6) AS dual_out FROM dual_part")
def q26(spark, d):
    return dual.dual_node_degree(part_edges(spark, d)).select("src", "dst", r6("dual_in"), r6("dual_out"))


@query(
    "q27_dual_degree_bruteforce",
    """SELECT e.src, e.dst, coalesce(o.n, 0) AS dual_out, coalesce(i.n, 0) AS dual_in FROM edges_sess e
       LEFT JOIN (SELECT a.src, a.dst, count(*) AS n FROM edges_sess a JOIN edges_sess b ON b.src = a.dst GROUP BY a.src, a.dst) o ON o.src = e.src AND o.dst = e.dst
       LEFT JOIN (SELECT b.src, b.dst, count(*) AS n FROM edges_sess a JOIN edges_sess b ON b.src = a.dst GROUP BY b.src, b.dst) i ON i.src = e.src AND i.dst = e.dst""",
)
def q27(spark, d):
    return dual.dual_node_degree(session_edges(spark, d), normalize=False)


@query("q28_combined_features", "SELECT src, dst, round(hyper_sim, 6) AS hyper_sim, round(dual_in, 6) AS dual_in, round(dual_out, 6) AS dual_out FROM dual_part")
def q28(spark, d):
    return dual.dual_features(part_edges(spark, d)).select("src", "dst", r6("hyper_sim"), r6("dual_in"), r6("dual_out"))


@query(
    "q28b_dual_degree_variants",
    """SELECT c.src, c.dst, round(c.dual_in / CAST(t.i AS DOUBLE), 6) AS in_separate, round(c.dual_out / CAST(t.o AS DOUBLE), 6) AS out_separate,
              c.dual_in - CASE WHEN b.src IS NULL THEN 0 ELSE 1 END AS in_forward, c.dual_out - CASE WHEN b.src IS NULL THEN 0 ELSE 1 END AS out_forward
       FROM cont_sess c CROSS JOIN (SELECT max(dual_in) AS i, max(dual_out) AS o FROM cont_sess) t LEFT JOIN edges_sess b ON b.src = c.dst AND b.dst = c.src""",
)
def q28b(spark, d):
    edges = session_edges(spark, d)
    a = dual.dual_node_degree(edges, dmax="separate").select("src", "dst", F.round("dual_in", 6).alias("in_separate"), F.round("dual_out", 6).alias("out_separate"))
    b = dual.dual_node_degree(edges, normalize=False, exclude_backtrack=True).select("src", "dst", F.col("dual_in").alias("in_forward"), F.col("dual_out").alias("out_forward"))
    return a.join(b, ["src", "dst"])


# ---------------------------------------------------------------- splits, windows, observations


@query("q29_split", f"SELECT path_id, CASE WHEN b < 8 THEN 'train' WHEN b < 9 THEN 'validation' ELSE 'test' END AS split FROM (SELECT DISTINCT path_id, {hash8('CAST(path_id AS VARCHAR)')} % 10 AS b FROM steps_part) x")
def q29(spark, d):
    return trajectories.split_paths(workloads.order_steps(spark, d).select("path_id").distinct())


_ALL_WINDOWS = " UNION ALL ".join(f"SELECT window_id, path_id, t, h, array_to_string(prefix, '>') AS prefix, array_to_string(suffix, '>') AS suffix, cur, target FROM windows{h}" for h in (1, 2, 3))


@query("q30_windows", _ALL_WINDOWS)
def q30(spark, d):
    rows = trajectories.windows(workloads.walk_paths(spark, d).select("path_id", "nodes"))
    return rows.select("window_id", "path_id", "t", "h", joined("prefix").alias("prefix"), joined("suffix").alias("suffix"), "cur", "target")


@query("q31_observations", "SELECT path_id, step, node_id, 1.0::DOUBLE AS weight FROM steps_part")
def q31(spark, d):
    return trajectories.observe(workloads.order_steps(spark, d))


@query(
    "q31b_nearest_observations",
    """SELECT path_id, step, node_id, round(raw / sum(raw) OVER (PARTITION BY path_id, step), 6) AS weight FROM
        (SELECT path_id, step, node_id, 1.0::DOUBLE AS raw FROM steps_dense UNION ALL SELECT s.path_id, s.step, k.dst, greatest(0, least(1, k.sim)) FROM steps_dense s JOIN knn k ON k.src = s.node_id AND k.pos < 4) x""",
)
def q31b(spark, d):
    c = Crawl(spark, d)
    return trajectories.observe(c.steps, kind="nearest", k_nearest=5, neighbours=workloads.knn(spark, d)).withColumn("weight", F.round("weight", 6))


# ---------------------------------------------------------------- weights and walks


def _weights(name: str, kind: str):
    @query(name, f"SELECT src, dst, round(w, 6) AS w FROM w_{kind}")
    def q(spark, d):
        return Crawl(spark, d).latent(kind).select("src", "dst", r6("w"))

    return q


_weights("q32_uniform_weights", "uniform")
_weights("q33_empirical_weights", "empirical")
_weights("q34_linear_scores_softmax", "linear")


@query("q34b_text_weights", "SELECT src, dst, round(e / sum(e) OVER (PARTITION BY src), 6) AS w FROM (SELECT src, dst, exp(text_sim) AS e FROM sims) x", _EDGE_TEXT | {"sims": """SELECT e.src, e.dst, coalesce(CASE WHEN a.norm * b.norm > 0 THEN t.dot / (a.norm * b.norm) END, 0) AS text_sim FROM edges_dense e
       LEFT JOIN dots t ON t.src = e.src AND t.dst = e.dst LEFT JOIN norms a ON a.node_id = e.src LEFT JOIN norms b ON b.node_id = e.dst"""})
def q34b(spark, d):
    return Crawl(spark, d).latent("text").select("src", "dst", r6("w"))


@query("q35_nb_step", "SELECT start, src, dst, round(p, 9) AS p FROM w_empirical_m1")
def q35(spark, d):
    c = Crawl(spark, d)
    latent = c.latent("empirical")
    return walk.nb_step(walk.spread(walk.one_hot(c.starts), latent), latent).select("start", "src", "dst", r9("p"))


def _distribution(name: str, how: str, sql: str):
    @query(name, sql)
    def q(spark, d):
        c = Crawl(spark, d)
        return walk.target_distribution(c.starts, c.latent("empirical"), h=H, how=how).select("start", "node_id", r9("p"))

    return q


_distribution("q36_target_dist_tail", "tail", "SELECT start, node_id, round(p, 9) AS p FROM w_empirical_tail")
_distribution("q37_target_dist_pinv", "pinv", "SELECT m.start, m.src AS node_id, round(sum(m.p * w.w) / max(q.ww), 9) AS p FROM w_empirical_m2 m JOIN w_empirical w ON w.src = m.src AND w.dst = m.dst JOIN (SELECT src, sum(w * w) AS ww FROM w_empirical GROUP BY src) q ON q.src = m.src GROUP BY m.start, m.src")
_distribution("q38_target_dist_head", "head", "SELECT start, node_id, round(p, 9) AS p FROM w_empirical_head")


@query(
    "q38b_plain_walk",
    "SELECT start, src AS node_id, round(sum(p), 9) AS p FROM b2 GROUP BY start, src",
    {"b1": "SELECT m.start, n.src, n.dst, sum(m.p * n.w) AS p FROM w_empirical_m0 m JOIN w_empirical n ON n.src = m.dst GROUP BY m.start, n.src, n.dst", "b2": "SELECT m.start, n.src, n.dst, sum(m.p * n.w) AS p FROM b1 m JOIN w_empirical n ON n.src = m.dst GROUP BY m.start, n.src, n.dst"},
)
def q38b(spark, d):
    c = Crawl(spark, d)
    return walk.target_distribution(c.starts, c.latent("empirical"), h=H, nb=False).select("start", "node_id", r9("p"))


@query(
    "q39_suffix_probability",
    """SELECT t.window_id, round(coalesce(a.w, 0) * coalesce(b.w / (1 - coalesce(k.w, 0)), 0), 6) AS p_node,
              round(coalesce(CASE WHEN suffix[1] = t.before THEN 0 ELSE a.w / (1 - coalesce(z.w, 0)) END, 0) * coalesce(b.w / (1 - coalesce(k.w, 0)), 0), 6) AS p_edge
       FROM tests t LEFT JOIN w_empirical a ON a.src = t.cur AND a.dst = t.suffix[1] LEFT JOIN w_empirical b ON b.src = t.suffix[1] AND b.dst = t.suffix[2]
       LEFT JOIN w_empirical k ON k.src = t.suffix[1] AND k.dst = t.cur LEFT JOIN w_empirical z ON z.src = t.cur AND z.dst = t.before""",
)
def q39(spark, d):
    c = Crawl(spark, d)
    latent, rows = c.latent("empirical"), c.windows()
    a, b = (walk.suffix_probability(rows, latent, anchor=x).select("window_id", F.round("p", 6).alias(f"p_{x}")) for x in ("node", "edge"))
    return a.join(b, "window_id")


@query(
    "q40_top_suffixes",
    """SELECT start, suffix, round(p, 9) AS p, CAST(rank AS INTEGER) AS rank FROM (SELECT *, row_number() OVER (PARTITION BY start ORDER BY round(p, 9) DESC, suffix) AS rank FROM
        (SELECT a.src AS start, a.dst || '>' || b.dst AS suffix, a.w * b.w / (1 - coalesce(k.w, 0)) AS p FROM w_empirical a JOIN w_empirical b ON b.src = a.dst AND b.dst <> a.src
         LEFT JOIN w_empirical k ON k.src = a.dst AND k.dst = a.src WHERE 1 - coalesce(k.w, 0) > 1e-12) x) y WHERE rank <= 2""",
)
def q40(spark, d):
    c = Crawl(spark, d)
    return walk.top_suffixes(c.starts, c.latent("empirical"), h=H, k=2).select("start", "suffix", r9("p"), "rank")


@query("q40c_sampled_suffixes")
def q40c(spark, d):
    c = Crawl(spark, d)
    return walk.sample_suffix(c.starts, c.latent("empirical"), h=3, n=4).select("start", "draw", joined("suffix").alias("suffix"))


# ---------------------------------------------------------------- measures


def _dist(c: Crawl, kind: str = "empirical") -> DataFrame:
    return once(c.spark, c.sf_dir, f"{c.which}_{kind}_dist", lambda: walk.target_distribution(c.starts, c.latent(kind), h=H))


def _measured(name: str, metrics_of: str, build):
    @query(name, f"SELECT metric, round(value, 6) AS value, support FROM w_empirical_measures WHERE metric IN ({metrics_of})")
    def q(spark, d):
        return build(Crawl(spark, d)).withColumn("value", F.round("value", 6))

    return q


_measured("q41_target_probability", "'target_probability'", lambda c: metrics.target_probability(_dist(c), c.windows()))
_measured("q42_choice_accuracy", "'choice_accuracy'", lambda c: metrics.choice_accuracy(c.windows(), c.latent("empirical"), c.degrees))
_measured("q43_precision_1_5", "'precision_top1', 'precision_top5'", lambda c: metrics.precision_at(_dist(c), c.windows()))


@query(
    "q41b_target_probability_nonzero",
    "SELECT 'target_probability' AS metric, round(avg(p), 6) AS value, count(*) AS support FROM w_empirical_judged WHERE p > 0",
)
def q41b(spark, d):
    c = Crawl(spark, d)
    return metrics.target_probability(_dist(c), c.windows(), mode="nonzero").withColumn("value", F.round("value", 6))


@query(
    "q43b_precision_next",
    """SELECT 'precision_top' || k AS metric, round(avg(CASE WHEN rank <= k THEN 1.0 ELSE 0.0 END), 6) AS value, count(*) AS support FROM
        (SELECT w.window_id, r.r AS rank FROM windows1 w LEFT JOIN w_empirical_exits r ON r.src = w.cur AND r.dst = w.target WHERE w.bucket = 9) x, (VALUES (1), (5)) t(k) GROUP BY k""",
)
def q43b(spark, d):
    c = Crawl(spark, d)
    dist = walk.target_distribution(c.starts, c.latent("empirical"), h=1, how="head")
    return metrics.precision_at(dist, c.windows(horizons=(1,))).withColumn("value", F.round("value", 6))


@query(
    "q44_extra_metrics",
    """SELECT 'nll' AS metric, round(avg(-ln(greatest(p, 1e-12))), 6) AS value, count(*) AS support FROM w_empirical_judged
       UNION ALL SELECT 'mrr', round(avg(coalesce(1.0 / rank, 0)), 6), count(*) FROM w_empirical_judged
       UNION ALL SELECT 'coverage', round(avg(CASE WHEN rank IS NULL THEN 0.0 ELSE 1.0 END), 6), count(*) FROM w_empirical_judged
       UNION ALL SELECT 'lost_mass', round(avg(1 - coalesce(k.kept, 0)), 6), count(*) FROM tests t LEFT JOIN (SELECT start, sum(p) AS kept FROM w_empirical_tail GROUP BY start) k ON k.start = t.cur""",
)
def q44(spark, d):
    c = Crawl(spark, d)
    return metrics.extra_metrics(_dist(c), c.windows()).withColumn("value", F.round("value", 6))


def _fixed_runs(spark: SparkSession, d: str) -> DataFrame:
    c = Crawl(spark, d)
    parts = [metrics.all_metrics(_dist(c, k), c.windows(), c.latent(k), c.degrees).select(F.lit(k).alias("weights"), "metric", "value", "support") for k in ("uniform", "empirical", "linear")]
    return reduce(DataFrame.unionByName, parts)


_RUNS = {"runs": " UNION ALL ".join(f"SELECT '{k}' AS weights, metric, value FROM w_{k}_measures" for k in ("uniform", "empirical", "linear"))}


@query("q45_metric_pivot", "SELECT metric, " + ", ".join(f"round(max(CASE WHEN weights = '{k}' THEN value END), 6) AS \"{k}\"" for k in ("uniform", "empirical", "linear")) + " FROM runs GROUP BY metric", _RUNS)
def q45(spark, d):
    return _fixed_runs(spark, d).groupBy("metric").pivot("weights", ["uniform", "empirical", "linear"]).agg(F.round(F.max("value"), 6))


@query("q45b_lift", "SELECT r.weights, r.metric, round(r.value, 6) AS value, round(100 * (r.value - b.value), 4) AS points FROM runs r JOIN runs b ON b.metric = r.metric AND b.weights = 'uniform' WHERE r.weights <> 'uniform'", _RUNS)
def q45b(spark, d):
    return metrics.lift(_fixed_runs(spark, d), base="uniform", key="weights").select("weights", "metric", r6("value"), F.round("points", 4).alias("points"))


# ---------------------------------------------------------------- communities and views


@query(
    "q46_modularity",
    """SELECT round(sum(inner2 / (2.0 * m) - (degree / (2.0 * m)) * (degree / (2.0 * m))), 6) AS modularity, count(*) AS communities FROM
        (SELECT c AS community, count(*) AS degree, sum(CASE WHEN a % 7 = b % 7 THEN 1.0 ELSE 0.0 END) AS inner2 FROM (SELECT a, b, a % 7 AS c FROM und UNION ALL SELECT a, b, b % 7 FROM und) x GROUP BY c) y, (SELECT count(*) AS m FROM und) z""",
    {"und": "SELECT DISTINCT least(src, dst) AS a, greatest(src, dst) AS b FROM edges_part"},
)
def q46(spark, d):
    edges = part_edges(spark, d)
    members = graph.edge_nodes(edges).withColumn("community", F.col("node_id") % 7)
    return community.modularity(edges, members).select(r6("modularity"), "communities")


@query(
    "q48_node_view",
    """SELECT node_id, community, degree, round(degree / CAST(max(degree) OVER (PARTITION BY community) AS DOUBLE), 6) AS size, row_number() OVER (PARTITION BY community ORDER BY degree DESC, node_id) <= 3 AS labelled
       FROM (SELECT node_id, node_id % 7 AS community, in_degree + out_degree AS degree FROM degrees_part) x""",
)
def q48(spark, d):
    edges = part_edges(spark, d)
    return community.node_view(edges, graph.edge_nodes(edges).withColumn("community", F.col("node_id") % 7)).withColumn("size", F.round("size", 6))


# ---------------------------------------------------------------- trained models (few epochs: the experiments run more)


@query("q49_fit_predict")
def q49(spark, d):
    c = Crawl(spark, d)
    return train.top_nodes(experiments.predictions(c, [m for m in experiments.trained(c) if m[:2] == ("combined", 1)])).drop("model")


_STATIC = {"coords": "none", "layers": 0, "optimizer": "lbfgs", "objective": "path", "epochs": 15}


@query("q49b_fit_path_lbfgs")
def q49b(spark, d):
    return experiments.run_experiment(Crawl(spark, d), sets=("original",), seeds=(1,), **_STATIC)


@query("q49c_trained_weights")
def q49c(spark, d):
    c = Crawl(spark, d)
    ((_, _, model),) = experiments.trained(c, sets=("original",), seeds=(1,), **_STATIC)
    return train.weights_table(experiments.all_node_balls(c), model)


@query("q49d_readouts")
def q49d(spark, d):
    c = Crawl(spark, d)
    runs = [experiments.run_experiment(c, sets=("original", "combined"), seeds=(1,), readout=r).withColumn("readout", F.lit(r)) for r in ("pinv", "tail", "head")]
    return reduce(DataFrame.unionByName, runs)


def _summary(name: str):
    @query(f"q50_{name}")
    def q(spark, d):
        return metrics.summarize_runs(experiments.run_experiment(Crawl(spark, d, name)), keys=("graph", "features", "metric"))

    return q


for _graph in experiments.GRAPHS:
    _summary(_graph)


@query("q50_table")
def q50(spark, d):
    return experiments.report(experiments.all_runs(spark, d))


@query("q50b_example_report")
def q50b(spark, d):
    return experiments.example_report(Crawl(spark, d, "sparse"))


@query("q50b_example_fixed")
def q50b_fixed(spark, d):
    return experiments.fixed_example_report(Crawl(spark, d, "sparse"))


@query("q50e_trained_lift")
def q50e(spark, d):
    mean = stored(experiments.all_runs(spark, d).groupBy("graph", "features", "metric").agg(F.avg("value").alias("value")), "means")
    return reduce(DataFrame.unionByName, [metrics.lift(mean.where(F.col("graph") == g)).withColumn("graph", F.lit(g)) for g in experiments.GRAPHS])


@query("q50f_trained_density_trend")
def q50f(spark, d):
    return metrics.density_trend(experiments.compare_graphs(experiments.all_runs(spark, d), experiments.graph_stats(spark, d)).where("features = 'combined'"))


@query("q50c_outcomes", """SELECT outcome, CAST(count(*) AS BIGINT) AS paths, round(avg(length), 6) AS mean_length FROM (SELECT path_id, min(outcome) AS outcome, count(*) AS length FROM session_steps GROUP BY path_id) x WHERE length BETWEEN 4 AND 7 GROUP BY outcome""")
def q50c(spark, d):
    return workloads.game_paths(spark, d).groupBy("outcome").agg(F.count("*").alias("paths"), F.round(F.avg("length"), 6).alias("mean_length"))


# ---------------------------------------------------------------- files


@query("q52_crawl_cost", "SELECT CAST(count(DISTINCT node_id) AS BIGINT) AS requests, (count(DISTINCT node_id) - 1)::DOUBLE AS seconds FROM steps_dense")
def q52(spark, d):
    return crawl.crawl_cost(Crawl(spark, d).steps)


# ---------------------------------------------------------------- relational operators

_BUCKET = hash8("CAST(path_id AS VARCHAR)") + " % 10"
_COLD = {"tr": edges_of(f"(SELECT * FROM steps_part WHERE {_BUCKET} < 8)"), "te": edges_of(f"(SELECT * FROM steps_part WHERE {_BUCKET} = 9)")}


def _split_edges(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    steps = trajectories.split_paths(workloads.order_steps(spark, d))
    return tuple(graph.build_edges(steps.where(F.col("split") == s)) for s in ("train", "test"))


@query("q53_cold_edges", "SELECT src, dst FROM te EXCEPT SELECT src, dst FROM tr", _COLD)
def q53(spark, d):
    return relational.cold_edges(*_split_edges(spark, d))


@query("q54_warm_edges", "SELECT src, dst FROM te INTERSECT SELECT src, dst FROM tr", _COLD)
def q54(spark, d):
    return relational.warm_edges(*_split_edges(spark, d))


@query("q55_edge_set_ops", " UNION ALL ".join(f"SELECT '{n}' AS op, count(*) AS n FROM (SELECT src, dst FROM tr {o} SELECT src, dst FROM te) x{i}" for i, (n, o) in enumerate((("union", "UNION"), ("union_all", "UNION ALL"), ("intersect", "INTERSECT"), ("intersect_all", "INTERSECT ALL"), ("except", "EXCEPT"), ("except_all", "EXCEPT ALL")))), _COLD)
def q55(spark, d):
    a, b = _split_edges(spark, d)
    return reduce(DataFrame.unionByName, [relational.edge_set_ops(a, b, op=o).agg(F.lit(o).alias("op"), F.count("*").alias("n")) for o in ("union", "union_all", "intersect", "intersect_all", "except", "except_all")])


@query("q56_degree_full_outer", "SELECT node_id, in_degree, out_degree FROM degrees_part")
def q56(spark, d):
    return relational.degree_full_outer(part_edges(spark, d))


@query("q57_asof_last_node", "SELECT p.event_id AS probe_id, p.agent, coalesce(c.node_id, -1) AS last_node FROM (SELECT * FROM clicks WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT * FROM clicks WHERE event_type = 'click') c ON p.agent = c.agent AND p.us > c.us")
def q57(spark, d):
    rows = tables.clicks(load(spark, d, "events"))
    return relational.asof_last(rows.where("event_type = 'click'"), rows.where("event_type = 'purchase'").select("agent", "us", F.col("event_id").alias("probe_id"))).withColumn("last_node", F.coalesce("last_node", F.lit(-1)))


@query("q58_interval_pairs", "SELECT a.event_id AS first_id, b.event_id AS second_id FROM clicks a JOIN clicks b ON a.agent = b.agent AND a.event_type = 'view' AND b.event_type = 'purchase' AND b.us > a.us AND b.us <= a.us + 86400000000")
def q58(spark, d):
    rows = tables.clicks(load(spark, d, "events"))
    return relational.interval_pairs(rows.where("event_type = 'view'"), rows.where("event_type = 'purchase'"), hours=24)


@query("q59_range_bands", "SELECT event_id, band FROM clicks, (VALUES ('low', 0.0, 15.0), ('mid', 10.0, 60.0), ('high', 50.0, 1000.0)) b(band, lo, hi) WHERE value >= lo AND value < hi")
def q59(spark, d):
    bands = spark.createDataFrame([("low", 0.0, 15.0), ("mid", 10.0, 60.0), ("high", 50.0, 1000.0)], "band string, lo double, hi double")
    return relational.range_bands(tables.clicks(load(spark, d, "events")), bands, width=25.0)


@query("q60_theta_pairs", "SELECT a.path_id, a.node_id AS earlier, b.node_id AS later FROM steps_part a JOIN steps_part b ON a.path_id = b.path_id AND a.step < b.step")
def q60(spark, d):
    return relational.theta_pairs(workloads.order_steps(spark, d))


@query("q61_broadcast_attrs", "SELECT s.node_id, s.path_id, s.step, p.p_brand, p.p_type FROM steps_part s JOIN part p ON p.p_partkey = s.node_id")
def q61(spark, d):
    return relational.with_attributes(workloads.order_steps(spark, d), load(spark, d, "part"))


@query("q62_merge_join_orders", "SELECT s.path_id, s.length, o.o_custkey AS agent FROM (SELECT path_id, count(*) AS length FROM steps_part GROUP BY path_id) s JOIN orders o ON o.o_orderkey = s.path_id")
def q62(spark, d):
    return relational.path_owners(workloads.order_steps(spark, d), load(spark, d, "orders"))


_PATHS = {"order_paths": "SELECT s.path_id, o.o_orderstatus AS status, o.o_orderpriority AS priority, s.length FROM (SELECT path_id, count(*) AS length FROM steps_part GROUP BY path_id) s JOIN orders o ON o.o_orderkey = s.path_id"}


def _order_paths(spark: SparkSession, d: str) -> DataFrame:
    length = trajectories.path_lengths(workloads.order_steps(spark, d))
    return length.join(load(spark, d, "orders").select(F.col("o_orderkey").alias("path_id"), F.col("o_orderstatus").alias("status"), F.col("o_orderpriority").alias("priority")), "path_id")


@query("q63_path_cube", "SELECT coalesce(status, '*') AS status, coalesce(priority, '*') AS priority, coalesce(CAST(length AS VARCHAR), '*') AS length, count(*) AS paths, CAST(grouping(status) * 4 + grouping(priority) * 2 + grouping(length) AS BIGINT) AS gid FROM order_paths GROUP BY CUBE (status, priority, length)", _PATHS)
def q63(spark, d):
    return starred(relational.path_cube(_order_paths(spark, d)), "status", "priority", "length")


@query(
    "q64_region_rollup",
    """SELECT coalesce(region, '*') AS region, coalesce(nation, '*') AS nation, coalesce(CAST(supplier AS VARCHAR), '*') AS supplier, count(DISTINCT path_id) AS paths, CAST(grouping(region) * 4 + grouping(nation) * 2 + grouping(supplier) AS BIGINT) AS gid FROM
        (SELECT v.path_id, r.r_name AS region, n.n_name AS nation, s.s_suppkey AS supplier FROM steps_supp v JOIN supplier s ON s.s_suppkey = v.node_id JOIN nation n ON n.n_nationkey = s.s_nationkey JOIN region r ON r.r_regionkey = n.n_regionkey) x
        GROUP BY ROLLUP (region, nation, supplier)""",
)
def q64(spark, d):
    places = load(spark, d, "supplier").join(load(spark, d, "nation"), F.col("s_nationkey") == F.col("n_nationkey")).join(load(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    places = places.select(F.col("s_suppkey").alias("node_id"), F.col("r_name").alias("region"), F.col("n_name").alias("nation"), F.col("s_suppkey").alias("supplier"))
    return starred(relational.region_rollup(workloads.order_steps(spark, d, "supplier").join(places, "node_id")), "region", "nation", "supplier")


_SETS = "SELECT coalesce(p_brand, '*') AS brand, coalesce(p_type, '*') AS kind, count(*) AS visits FROM {} GROUP BY GROUPING SETS ((p_brand), (p_type), (p_brand, p_type), ())"


@query("q65_grouping_sets", _SETS.format("(SELECT p.p_brand, p.p_type FROM steps_part s JOIN part p ON p.p_partkey = s.node_id) x"))
def q65(spark, d):
    return spark.sql(_SETS.format("{visits}"), visits=relational.with_attributes(workloads.order_steps(spark, d), load(spark, d, "part")))


@query(
    "q67_running_clicks",
    """SELECT event_id, count(*) OVER (w ROWS UNBOUNDED PRECEDING) AS so_far, count(*) OVER (PARTITION BY agent ORDER BY us RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW) AS recent,
              round(sum(value) OVER (w ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS last_three, first_value(event_id) OVER (w ROWS UNBOUNDED PRECEDING) AS first_event,
              nth_value(event_id, 2) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second_event
       FROM clicks WINDOW w AS (PARTITION BY agent ORDER BY us, event_id)""",
)
def q67(spark, d):
    return relational.running_clicks(tables.clicks(load(spark, d, "events")))


@query("q68_topk_per_group", "SELECT src, dst, nof, CAST(rank AS INTEGER) AS rank FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY nof DESC, dst) AS rank FROM nof_dense) x WHERE rank <= 3")
def q68(spark, d):
    return relational.topk_per_group(Crawl(spark, d).nof, k=3)


@query("q69_two_hop", "SELECT a.src, b.dst, count(*) AS ways FROM edges_dense a JOIN edges_dense b ON b.src = a.dst GROUP BY a.src, b.dst")
def q69(spark, d):
    return relational.two_hop(Crawl(spark, d).edges)


@query("q69b_reach", "SELECT node_id, CAST(min(hops) AS INTEGER) AS hops FROM (WITH RECURSIVE r(node_id, hops) AS (SELECT CAST(0 AS BIGINT), 0 UNION SELECT e.dst, r.hops + 1 FROM r JOIN edges_dense e ON e.src = r.node_id WHERE r.hops < 4) SELECT * FROM r) x GROUP BY node_id")
def q69b(spark, d):
    return relational.reach(Crawl(spark, d).edges, 0, h=4)


@query("q69c_hubs", "SELECT node_id, in_degree + out_degree AS degree FROM degrees_part ORDER BY degree DESC, node_id LIMIT 10")
def q69c(spark, d):
    return graph.hubs(part_edges(spark, d), top=10)


@query("q69d_hash_sample", f"SELECT DISTINCT path_id FROM steps_part WHERE {hash8(chr(39) + 'sample|' + chr(39) + ' || path_id')} % 100 < 10")
def q69d(spark, d):
    return relational.hash_sample(workloads.order_steps(spark, d).select("path_id").distinct(), percent=10)


@query(
    "q70_json_string_functions",
    """SELECT event_id, node_id AS k, upper(substr(event_type, 1, 3)) AS short, CAST(length(props) AS INTEGER) AS size, '{"t":"' || c.event_type || '","k":' || node_id || '}' AS packed FROM clicks c JOIN (SELECT event_id AS eid, props FROM events) e ON e.eid = c.event_id""",
)
def q70(spark, d):
    return relational.json_and_urls(load(spark, d, "events"))


@query("q70b_url_parts", r"SELECT page_id, lower(regexp_extract(url, '^[A-Za-z]+://([^/?#]*)', 1)) AS host, regexp_extract(url, '^[A-Za-z]+://[^/?#]*([^?#]*)', 1) AS path FROM pages")
def q70b(spark, d):
    return load(spark, d, "pages").select("page_id", url_host(F.col("url")).alias("host"), url_path(F.col("url")).alias("path"))


@query("q70c_stable_ids", "SELECT title, CAST(dense_rank() OVER (ORDER BY encode(title)) - 1 AS BIGINT) AS node_id FROM (SELECT DISTINCT title FROM titles) x", {"titles": _TITLES})
def q70c(spark, d):
    return trajectories.assign_ids(crawl.page_titles(load(spark, d, "pages")), dense=True)


# ---------------------------------------------------------------- streams, replayed


@query("q71_stream_nof", "SELECT src, dst, count(*) AS nof FROM (SELECT lag(node_id) OVER (PARTITION BY agent ORDER BY event_id) AS src, node_id AS dst FROM clicks) x WHERE src IS NOT NULL AND src <> dst GROUP BY src, dst")
def q71(spark, d):
    return stream.replay(stream.moves_by_list(spark, stream.stream_events(spark, d))).groupBy("src", "dst").agg(F.count("*").alias("nof"))


_CLOSED = {"spans": "SELECT agent, path_id, min(ts) AS t0, max(ts) + INTERVAL 12 HOURS AS t1, count(*) AS n FROM session_ids GROUP BY agent, path_id", "mark": "SELECT max(ts) - INTERVAL 1 HOUR AS cutoff FROM clicks"}


def _text(c: str) -> F.Column:
    return F.date_format(c, "yyyy-MM-dd HH:mm:ss.SSSSSS").alias(c)


@query("q72_stream_sessions", "SELECT agent, strftime(t0, '%Y-%m-%d %H:%M:%S.%f') AS start, strftime(t1, '%Y-%m-%d %H:%M:%S.%f') AS stop, n FROM spans, mark WHERE t1 <= cutoff", _CLOSED)
def q72(spark, d):
    return stream.replay(stream.sessions(stream.stream_events(spark, d))).select("agent", _text("start"), _text("stop"), "n")


@query("q73_stream_windows", "SELECT node_id, strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S.%f') AS start, count(*) AS n FROM clicks, mark WHERE date_trunc('day', ts) + INTERVAL 1 DAY <= cutoff GROUP BY node_id, date_trunc('day', ts)", _CLOSED)
def q73(spark, d):
    return stream.replay(stream.visit_windows(stream.stream_events(spark, d))).select("node_id", _text("start"), "n")


@query("q75_stream_predict", "SELECT c.event_id, x.dst, CAST(x.r AS INTEGER) AS rank FROM clicks c JOIN (SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY round(w, 12) DESC, dst) AS r FROM (SELECT src, dst, 1.0 / count(*) OVER (PARTITION BY src) AS w FROM edges_sess) y) x ON x.src = c.node_id AND x.r <= 3")
def q75(spark, d):
    ranked = stored(weights.rank_exits(weights.weights_uniform(session_edges(spark, d))), "ranked")
    return stream.replay(stream.predict_next(stream.stream_events(spark, d), ranked))


@query("q76_stream_interval", "SELECT a.event_id AS first_id, b.event_id AS second_id FROM clicks a JOIN clicks b ON a.agent = b.agent AND a.event_type = 'view' AND b.event_type = 'purchase' AND b.us > a.us AND b.us <= a.us + 86400000000")
def q76(spark, d):
    return stream.replay(stream.interval_join(stream.stream_events(spark, d), stream.stream_events(spark, d)))


@query("q77_stream_dedup", "SELECT DISTINCT agent, node_id FROM clicks")
def q77(spark, d):
    return stream.replay(stream.first_visits(stream.stream_events(spark, d, watermark="60 days"))).select("agent", "node_id")


from . import registry_graphs, registry_relational  # noqa: E402, F401  (they add their queries)

__all__ = ["ORACLE_SQL", "QUERIES", "query"]
