"""Files round trip, SQL functions, the paced source, and plans."""

import time

import numpy as np
import pytest

from hyperpath.functions import registered
from hyperpath.operators import dual, graph, relational, text
from hyperpath.sources import files, tables


def test_graphml_and_edge_lists_round_trip(spark, tmp_path):
    nodes = spark.createDataFrame([(1, "a < b & c"), (2, "line\nbreak"), (3, None)], "node_id long, title string")
    edges = spark.createDataFrame([(1, 2), (2, 3)], "src long, dst long")
    files.write_graphml(nodes, edges, str(tmp_path / "g"))
    n, e = files.read_graphml(spark, str(tmp_path / "g"))
    assert sorted(map(tuple, n.collect())) == [(1, "a < b & c"), (2, "line break"), (3, "")]
    assert sorted(map(tuple, e.collect())) == [(1, 2), (2, 3)]
    for fmt in ("csv", "json"):
        files.write_edges(edges, str(tmp_path / fmt), fmt=fmt)
        assert sorted(map(tuple, files.read_edges(spark, str(tmp_path / fmt), fmt=fmt).collect())) == [(1, 2), (2, 3)]


def test_bundle_needs_all_tables(tmp_path):
    with pytest.raises(ValueError, match="bundle"):
        files.write_bundle({}, str(tmp_path))


def test_paced_source_waits(spark):
    files.paced_source(spark)
    began = time.time()
    rows = spark.read.format("paced_pages").option("pages", "a=1,2,3").option("delay_s", 0.2).load().collect()
    assert [r["page_id"] for r in rows] == [1, 2, 3] and time.time() - began > 0.4


def test_sql_functions(spark):
    registered.register_sql(spark)
    row = spark.sql("SELECT is_valid_title('Talk x') a, is_valid_title('ok') b, nb_transition(0.3D, 0.4D) c, nb_transition(0.3D, null) d, hyper_cosine(1D, 4D, 1D) e").first()
    assert (row["a"], row["b"], round(row["c"], 6), row["d"], row["e"]) == (False, True, 0.5, 0.3, 0.5)
    score = registered.edge_mlp({"w1": np.eye(2), "b1": np.zeros(2), "w2": np.ones(2), "b2": np.array([0.5])})
    assert spark.createDataFrame([([1.0, -2.0],)], "f array<double>").select(score("f")).first()[0] == 1.5
    spark.udtf.register("walks_from", registered.walks_from({0: [1, 2], 1: [2]}))
    assert sorted(r["walk"] for r in spark.sql("SELECT * FROM walks_from(0, 2)").collect()) == ["0>1>2"]


def test_order_paths_drop_consecutive_repeats(spark):
    rows = [(1, i, p, 0, 1.0) for i, p in enumerate((5, 5, 6, 5))] + [(2, 0, 1, 0, 1.0)]
    lines = spark.createDataFrame(rows, "l_orderkey long, l_linenumber int, l_partkey long, l_suppkey long, l_extendedprice double")
    assert [(r["path_id"], r["step"], r["node_id"]) for r in tables.from_orders(lines).orderBy("step").collect()] == [(1, 0, 5), (1, 1, 6), (1, 2, 5)]


def test_text_similarity_against_numpy(spark):
    docs = spark.createDataFrame([(1, "a b b c"), (2, "b c d"), (3, "x"), (4, None)], "node_id long, text string")
    weights = text.tfidf(docs)
    edges = spark.createDataFrame([(1, 2), (1, 3), (1, 4)], "src long, dst long")
    got = {r["dst"]: r["text_sim"] for r in text.edge_text_similarity(edges, weights).collect()}
    idf = {"a": np.log(4), "b": np.log(2), "c": np.log(2), "d": np.log(4)}
    x, y = np.array([idf["a"], 2 * idf["b"], idf["c"], 0]), np.array([0, idf["b"], idf["c"], idf["d"]])
    assert np.isclose(got[2], x @ y / np.sqrt((x @ x) * (y @ y))) and got[3] == 0 and got[4] == 0


def test_plans_prune_columns_and_avoid_products(spark, small):
    plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
    steps = tables.from_orders(tables.load(spark, small, "lineitem"))
    text_ = plan(dual.dual_features(graph.build_edges(steps)))
    assert "l_discount" not in text_ and "CartesianProduct" not in text_ and "BatchEvalPython" not in text_
    pushed = plan(relational.interval_pairs(*(tables.clicks(tables.load(spark, small, "events")).where(f"event_type = '{t}'") for t in ("view", "purchase")), hours=24))
    assert "PushedFilters" in pushed and "EqualTo(event_type,view)" in pushed
