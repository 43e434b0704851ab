"""The SQL that queries are compared with: named parts, put together with the parts they need."""

from __future__ import annotations

import re

PARTS: dict[str, str] = {}


def part(name: str, sql: str) -> None:
    PARTS[name] = sql


def with_parts(sql: str, extra: dict[str, str] | None = None) -> str:
    """sql with a WITH list of all parts that it mentions, and that those mention, in order."""
    known = PARTS | (extra or {})
    order: list[str] = []

    def need(text: str) -> None:
        for name in known:
            if name not in order and re.search(rf"\b{name}\b", text):
                need(known[name])
                if name not in order:
                    order.append(name)

    need(sql)
    return ("WITH " + ",\n".join(f"{n} AS MATERIALIZED ({known[n]})" for n in order) + "\n" if order else "") + sql


def hash8(text: str) -> str:
    return f"CAST('0x' || substr(md5({text}), 1, 8) AS BIGINT)"


def order_steps(key: str) -> str:
    order = "l_linenumber, l_partkey, l_suppkey, l_extendedprice"
    return f"""
        SELECT path_id, CAST(row_number() OVER (PARTITION BY path_id ORDER BY {order}) - 1 AS INTEGER) AS step, node_id
        FROM (SELECT *, lag(node_id) OVER (PARTITION BY path_id ORDER BY {order}) AS prev
              FROM (SELECT l_orderkey AS path_id, {order}, {key} AS node_id, count(*) OVER (PARTITION BY l_orderkey) AS n FROM lineitem) r
              WHERE n BETWEEN 4 AND 7) q
        WHERE prev IS NULL OR prev <> node_id"""


def edges_of(steps: str) -> str:
    return f"SELECT DISTINCT src, dst FROM (SELECT node_id AS src, lead(node_id) OVER (PARTITION BY path_id ORDER BY step) AS dst FROM {steps}) x WHERE dst IS NOT NULL AND src <> dst"


part("steps_part", order_steps("l_partkey"))
part("steps_supp", order_steps("l_suppkey"))
part("edges_part", edges_of("steps_part"))
part("edges_supp", edges_of("steps_supp"))
part("clicks", "SELECT event_id, date_diff('microseconds', TIMESTAMP '1970-01-01', ts) AS us, user_id AS agent, event_type, value, CAST(json_extract(props, '$.k') AS BIGINT) AS node_id, ts FROM events")
part("session_starts", "SELECT *, CASE WHEN coalesce(us - lag(us) OVER (PARTITION BY agent ORDER BY us, event_id) > 43200000000, TRUE) THEN event_id END AS first_id FROM clicks")
part("session_ids", "SELECT *, last_value(first_id IGNORE NULLS) OVER (PARTITION BY agent ORDER BY us, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS path_id FROM session_starts")
part("session_ends", "SELECT *, last_value(event_type) OVER (PARTITION BY path_id ORDER BY us, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS last_type FROM session_ids")
part(
    "session_steps",
    """SELECT path_id, agent, CAST(row_number() OVER (PARTITION BY path_id ORDER BY us, event_id) - 1 AS INTEGER) AS step, node_id,
              CASE last_type WHEN 'purchase' THEN 'completed' WHEN 'error' THEN 'abandoned' ELSE 'open' END AS outcome
       FROM (SELECT *, lag(node_id) OVER (PARTITION BY path_id ORDER BY us, event_id) AS prev FROM session_ends) x WHERE prev IS NULL OR prev <> node_id""",
)
part("edges_sess", edges_of("session_steps"))
part("vectors", "SELECT CAST(vec_id AS BIGINT) AS id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings")
part("similar_vectors", "SELECT a.id AS src, b.id AS dst, round(list_cosine_similarity(a.v, b.v), 12) AS sim FROM vectors a JOIN vectors b ON a.id <> b.id")
part("knn", "SELECT src, dst, CAST(pos - 1 AS INTEGER) AS pos, sim FROM (SELECT src, dst, sim, row_number() OVER (PARTITION BY src ORDER BY sim DESC, dst) AS pos FROM similar_vectors) x WHERE pos <= 50")


def _walks(name: str, links: str) -> None:
    part(f"{name}0", f"SELECT CAST(i AS BIGINT) AS path_id, [CAST(0 AS BIGINT)] AS nodes, 4 + {hash8("'42|' || i || '|len'")} % 4 AS goal FROM range(3000) t(i)")
    for k in range(1, 7):
        part(
            f"{name}{k}c",
            f"""SELECT w.path_id, w.nodes, w.goal, l.dst, row_number() OVER (PARTITION BY w.path_id ORDER BY md5('42|' || w.path_id || '|' || len(w.nodes) || '|' || l.dst), l.dst) AS r
                FROM {name}{k - 1} w JOIN {links} l ON l.src = w.nodes[-1] AND len(w.nodes) < w.goal WHERE NOT list_contains(w.nodes, l.dst)""",
        )
        part(
            f"{name}{k}",
            f"""SELECT path_id, list_append(nodes, dst) AS nodes, goal FROM {name}{k}c WHERE r = 1
                UNION ALL SELECT path_id, nodes, goal FROM {name}{k - 1} WHERE path_id NOT IN (SELECT path_id FROM {name}{k}c)""",
        )
    part(f"paths_{name}", f"SELECT path_id, nodes, CAST(goal AS INTEGER) AS goal, CAST(len(nodes) AS INTEGER) AS length, {hash8('CAST(path_id AS VARCHAR)')} % 10 AS bucket FROM {name}6")
    part(f"steps_{name}", f"SELECT path_id, bucket, CAST(unnest(range(len(nodes))) AS INTEGER) AS step, unnest(nodes) AS node_id FROM paths_{name}")
    part(f"edges_{name}", edges_of(f"steps_{name}"))


part("knn5", "SELECT src, dst, pos FROM knn WHERE pos < 5")
_walks("dense", "knn5")
_walks("sparse", "knn")
part("train_clicks", "SELECT src, dst, count(*) AS n FROM (SELECT node_id AS src, lead(node_id) OVER (PARTITION BY path_id ORDER BY step) AS dst FROM steps_dense WHERE bucket < 8) x WHERE dst IS NOT NULL AND src <> dst GROUP BY src, dst")
part("nof_dense", "SELECT e.src, e.dst, CAST(coalesce(c.n, 0) AS BIGINT) AS nof FROM edges_dense e LEFT JOIN train_clicks c ON e.src = c.src AND e.dst = c.dst")
part("w_uniform", "SELECT src, dst, 1.0::DOUBLE / count(*) OVER (PARTITION BY src) AS w FROM edges_dense")
part("w_empirical", "SELECT src, dst, (nof + 1.0::DOUBLE) / sum(nof + 1.0::DOUBLE) OVER (PARTITION BY src) AS w FROM nof_dense")


def degrees_of(edges: str) -> str:
    return f"SELECT node_id, CAST(sum(i) AS BIGINT) AS in_degree, CAST(sum(o) AS BIGINT) AS out_degree FROM (SELECT src AS node_id, 0 AS i, 1 AS o FROM {edges} UNION ALL SELECT dst, 1, 0 FROM {edges}) x GROUP BY node_id"


for _g in ("part", "supp", "sess", "dense"):
    part(f"degrees_{_g}", degrees_of(f"edges_{_g}"))


def similarity_of(g: str) -> str:
    return f"""SELECT e.src, e.dst, (CASE WHEN b.src IS NULL THEN 1 ELSE 2 END) / sqrt(CAST(u.in_degree + u.out_degree AS DOUBLE) * (v.in_degree + v.out_degree)) AS hyper_sim
        FROM edges_{g} e JOIN degrees_{g} u ON u.node_id = e.src JOIN degrees_{g} v ON v.node_id = e.dst LEFT JOIN edges_{g} b ON b.src = e.dst AND b.dst = e.src"""


def dual_degree_of(g: str) -> str:
    return f"SELECT e.src, e.dst, u.in_degree AS dual_in, v.out_degree AS dual_out FROM edges_{g} e JOIN degrees_{g} u ON u.node_id = e.src JOIN degrees_{g} v ON v.node_id = e.dst"


for _g in ("part", "supp", "sess", "dense"):
    part(f"hyper_{_g}", similarity_of(_g))
    part(f"cont_{_g}", dual_degree_of(_g))
    part(f"contmax_{_g}", f"SELECT CAST(greatest(max(dual_in), max(dual_out)) AS DOUBLE) AS top FROM cont_{_g}")
    part(f"dual_{_g}", f"SELECT s.src, s.dst, s.hyper_sim, CASE WHEN m.top > 0 THEN c.dual_in / m.top ELSE 0.0 END AS dual_in, CASE WHEN m.top > 0 THEN c.dual_out / m.top ELSE 0.0 END AS dual_out FROM hyper_{_g} s JOIN cont_{_g} c ON s.src = c.src AND s.dst = c.dst CROSS JOIN contmax_{_g} m")
part("scores", "SELECT d.src, d.dst, 1.0 * hyper_sim + 0.5 * dual_out - 0.25 * dual_in + 0.3 * ln(1 + nof) AS z FROM dual_dense d JOIN nof_dense n ON d.src = n.src AND d.dst = n.dst")
part("w_linear", "SELECT src, dst, e / sum(e) OVER (PARTITION BY src) AS w FROM (SELECT src, dst, exp(z - max(z) OVER (PARTITION BY src)) AS e FROM scores) x")
for _h in (1, 2, 3):
    part(f"windows{_h}", f"SELECT path_id || '-' || t || '-{_h}' AS window_id, path_id, CAST(t AS INTEGER) AS t, {_h} AS h, nodes[1:t] AS prefix, nodes[t + 1:t + {_h}] AS suffix, nodes[t] AS cur, nodes[t + {_h}] AS target, CASE WHEN t > 1 THEN nodes[t - 1] END AS before, bucket FROM (SELECT *, unnest(range(1, len(nodes) - {_h} + 1)) AS t FROM paths_dense) x")
part("tests", "SELECT * FROM windows2 WHERE bucket = 9")


def mass_of(w: str, h: int) -> dict[str, str]:
    """Parts {w}_m0..h: edge mass of a walk from every node, after 0..h transitions."""
    parts = {f"{w}_m0": f"SELECT src AS start, src, dst, w AS p FROM {w}"}
    for k in range(1, h + 1):
        parts[f"{w}_m{k}"] = f"""SELECT m.start, n.src, n.dst, sum(m.p * n.w / (1 - coalesce(b.w, 0))) AS p
            FROM {w}_m{k - 1} m JOIN {w} n ON n.src = m.dst AND n.dst <> m.src LEFT JOIN {w} b ON b.src = m.dst AND b.dst = m.src
            WHERE 1 - coalesce(b.w, 0) > 1e-12 GROUP BY m.start, n.src, n.dst"""
    return parts


for _w in ("w_uniform", "w_empirical", "w_linear"):
    for _n, _s in mass_of(_w, 2).items():
        part(_n, _s)
    part(f"{_w}_tail", f"SELECT start, src AS node_id, sum(p) AS p FROM {_w}_m2 GROUP BY start, src")
    part(f"{_w}_head", f"SELECT start, dst AS node_id, sum(p) AS p FROM {_w}_m1 GROUP BY start, dst")
    part(f"{_w}_ranked", f"SELECT *, row_number() OVER (PARTITION BY start ORDER BY round(p, 9) DESC, node_id) AS rank FROM {_w}_tail")
    part(f"{_w}_judged", f"SELECT t.window_id, coalesce(r.p, 0) AS p, r.rank FROM tests t LEFT JOIN {_w}_ranked r ON r.start = t.cur AND r.node_id = t.target")
    part(f"{_w}_exits", f"SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY round(w, 12) DESC, dst) AS r FROM {_w}")
    part(
        f"{_w}_choices",
        f"""SELECT m.path_id, CASE WHEN x.dst = m.dst THEN 1.0 ELSE 0.0 END AS hit FROM
            (SELECT path_id, window_id, 0 AS i, CAST(NULL AS BIGINT) AS before, cur AS src, suffix[1] AS dst FROM tests
             UNION ALL SELECT path_id, window_id, 1, cur, suffix[1], suffix[2] FROM tests) m
            JOIN degrees_dense d ON d.node_id = m.src AND d.in_degree + d.out_degree >= 3
            LEFT JOIN {_w}_exits e1 ON e1.src = m.src AND e1.r = 1
            LEFT JOIN {_w}_exits x ON x.src = m.src AND x.r = CASE WHEN e1.dst = m.before THEN 2 ELSE 1 END""",
    )
    part(
        f"{_w}_measures",
        f"""SELECT 'target_probability' AS metric, avg(p) AS value, count(*) AS support FROM {_w}_judged
            UNION ALL SELECT 'choice_accuracy', avg(hit), count(*) FROM {_w}_choices
            UNION ALL SELECT 'precision_top1', avg(CASE WHEN rank <= 1 THEN 1.0 ELSE 0.0 END), count(*) FROM {_w}_judged
            UNION ALL SELECT 'precision_top5', avg(CASE WHEN rank <= 5 THEN 1.0 ELSE 0.0 END), count(*) FROM {_w}_judged""",
    )


def _experiment_graph(g: str) -> None:
    """Parts of an experiment graph other than the dense one: its clicks, fixed weights and the windows of one step."""
    part(f"train_clicks_{g}", f"SELECT src, dst, count(*) AS n FROM (SELECT node_id AS src, lead(node_id) OVER (PARTITION BY path_id ORDER BY step) AS dst FROM steps_{g} WHERE bucket < 8) x WHERE dst IS NOT NULL AND src <> dst GROUP BY src, dst")
    part(f"nof_{g}", f"SELECT e.src, e.dst, CAST(coalesce(c.n, 0) AS BIGINT) AS nof FROM edges_{g} e LEFT JOIN train_clicks_{g} c ON e.src = c.src AND e.dst = c.dst")
    part(f"we_{g}", f"SELECT src, dst, (nof + 1.0::DOUBLE) / sum(nof + 1.0::DOUBLE) OVER (PARTITION BY src) AS w FROM nof_{g}")


part("paths_game", f"SELECT path_id, nodes, {hash8('CAST(path_id AS VARCHAR)')} % 10 AS bucket FROM (SELECT path_id, list(node_id ORDER BY step) AS nodes FROM session_steps GROUP BY path_id) x WHERE len(nodes) BETWEEN 4 AND 7")
part("steps_game", "SELECT path_id, bucket, CAST(unnest(range(len(nodes))) AS INTEGER) AS step, unnest(nodes) AS node_id FROM paths_game")
part("edges_game", edges_of("steps_game"))
for _g in ("sparse", "game"):
    _experiment_graph(_g)
    part(f"degrees_{_g}", degrees_of(f"edges_{_g}"))
part("we_dense", "SELECT src, dst, w FROM w_empirical")
for _g in ("dense", "sparse", "game"):
    part(f"tests1_{_g}", f"SELECT path_id || '-' || t || '-1' AS window_id, path_id, nodes[t] AS cur, nodes[t + 1] AS target FROM (SELECT *, unnest(range(1, len(nodes))) AS t FROM paths_{_g}) x WHERE bucket = 9")
    part(f"exits_{_g}", f"SELECT src, dst, w, row_number() OVER (PARTITION BY src ORDER BY round(w, 12) DESC, dst) AS best, row_number() OVER (PARTITION BY src ORDER BY round(w, 9) DESC, dst) AS rank FROM we_{_g}")
    part(
        f"measures1_{_g}",
        f"""SELECT 'target_probability' AS metric, avg(coalesce(x.w, 0)) AS value FROM tests1_{_g} t LEFT JOIN exits_{_g} x ON x.src = t.cur AND x.dst = t.target
            UNION ALL SELECT 'choice_accuracy', avg(CASE WHEN x.best = 1 THEN 1.0 ELSE 0.0 END) FROM tests1_{_g} t JOIN degrees_{_g} d ON d.node_id = t.cur AND d.in_degree + d.out_degree >= 3 LEFT JOIN exits_{_g} x ON x.src = t.cur AND x.dst = t.target
            UNION ALL SELECT 'precision_top' || k, avg(CASE WHEN x.rank <= k THEN 1.0 ELSE 0.0 END) FROM (VALUES (1), (5)) v(k), tests1_{_g} t LEFT JOIN exits_{_g} x ON x.src = t.cur AND x.dst = t.target GROUP BY k""",
    )
    part(f"shape_{_g}", f"SELECT n, m, CAST(m AS DOUBLE) / (CAST(n AS DOUBLE) * (n - 1)) AS density FROM (SELECT (SELECT count(DISTINCT node_id) FROM steps_{_g}) AS n, (SELECT count(*) FROM edges_{_g}) AS m) x")

#: Anchors of the pages, and the walks over them with the first two, the first five and all valid links.
part("page_titles", r"SELECT page_id AS node_id, regexp_extract(html, '(?s)<title>(.*?)</title>', 1) AS title FROM pages")
part("valid_pages", r"SELECT node_id FROM page_titles WHERE coalesce(NOT regexp_matches(title, 'Talk|User|File|ISO|[%#:]') AND NOT regexp_matches(title, '^[0-9]*$'), FALSE)")
part("page_slugs", "SELECT page_id AS src, regexp_extract_all(html, '<a\\s[^>]*href=\"/([^\"]*)\"', 1) AS s FROM pages")
part("page_anchors", "SELECT src, slug, min(pos) AS pos FROM (SELECT src, unnest(s) AS slug, unnest(range(len(s))) AS pos FROM page_slugs) x GROUP BY src, slug")
part("page_edges", f"SELECT src, dst, min(pos) AS pos FROM (SELECT src, {hash8('chr(47) || slug')} % (SELECT count(*) FROM pages) AS dst, pos FROM page_anchors) x WHERE src <> dst GROUP BY src, dst")
part("page_ranked", "SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY pos, dst) AS r FROM page_edges WHERE dst IN (SELECT node_id FROM valid_pages)")
for _k in (2, 5, 0):
    part(f"page_links{_k}", f"SELECT src, dst FROM page_ranked WHERE r <= {_k or 1 << 30}")
    _walks(f"pages{_k}x", f"page_links{_k}")
