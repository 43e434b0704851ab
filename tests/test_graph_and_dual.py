"""Hand-checked graphs, closed forms against matrices, degenerate inputs."""

import math
import pickle
import random
import tracemalloc

import numpy as np
import pytest
from pyspark.sql import functions as F

from hyperpath.functions.columns import is_valid_title
from hyperpath.operators import community, crawl, dual, features, graph, metrics, train, trajectories, walk, weights
from hyperpath.schemas import FeatureGraph

FIVE = [(1, 2, 3), (2, 1, 1), (1, 3, 1), (2, 3, 3), (3, 4, 2), (3, 5, 2), (4, 1, 4)]


def edges_of(spark, pairs):
    return spark.createDataFrame([(a, b) for a, b, *_ in pairs], "src long, dst long")


@pytest.fixture(scope="module")
def five(spark):
    return edges_of(spark, FIVE)


def pairs(df, *columns):
    return {(r["src"], r["dst"]): tuple(r[c] for c in columns) for r in df.collect()}


def test_similarity_of_the_five_node_graph(five):
    keep = pairs(dual.hyperedge_similarity(five), "hyper_sim")
    want = {(1, 2): 0.577350, (2, 1): 0.577350, (1, 3): 0.25, (2, 3): 0.288675, (3, 4): 0.353553, (3, 5): 0.5, (4, 1): 0.353553}
    assert {k: round(v[0], 6) for k, v in keep.items()} == want
    collapse = pairs(dual.hyperedge_similarity(five, reciprocal="collapse"), "hyper_sim")
    want = {(1, 2): 0.408248, (2, 1): 0.408248, (1, 3): 0.288675, (2, 3): 0.353553, (3, 4): 0.353553, (3, 5): 0.5, (4, 1): 0.408248}
    assert {k: round(v[0], 6) for k, v in collapse.items()} == want


def test_dual_degrees_of_the_five_node_graph(five):
    got = pairs(dual.dual_node_degree(five, normalize=False), "dual_out", "dual_in")
    assert got == {(1, 2): (2, 2), (2, 1): (2, 1), (1, 3): (2, 2), (2, 3): (2, 1), (3, 4): (1, 2), (3, 5): (0, 2), (4, 1): (2, 1)}
    scaled = pairs(dual.dual_node_degree(five), "dual_out", "dual_in")
    assert scaled[(3, 4)] == (0.5, 1.0) and max(max(v) for v in scaled.values()) == 1.0
    both = pairs(dual.dual_features(five), "hyper_sim", "dual_in", "dual_out")
    assert both[(1, 3)] == (0.25, 1.0, 1.0)


def test_closed_forms_equal_matrices(spark):
    rng = random.Random(5)
    pairs_ = sorted({(a, b) for a, b in ((rng.randrange(12), rng.randrange(12)) for _ in range(60)) if a != b})
    e = edges_of(spark, pairs_)
    m = np.zeros((12, len(pairs_)))
    for j, (a, b) in enumerate(pairs_):
        m[a, j] = m[b, j] = 1
    got = pairs(dual.hyperedge_similarity(e), "hyper_sim")
    for a, b in pairs_:
        assert math.isclose(got[(a, b)][0], m[a] @ m[b] / math.sqrt((m[a] @ m[a]) * (m[b] @ m[b])), rel_tol=1e-12)
    degree = pairs(dual.dual_node_degree(e, normalize=False), "dual_in", "dual_out")
    forward = pairs(dual.dual_node_degree(e, normalize=False, exclude_backtrack=True), "dual_in", "dual_out")
    for a, b in pairs_:
        into, out = [p for p in pairs_ if p[1] == a], [p for p in pairs_ if p[0] == b]
        assert degree[(a, b)] == (len(into), len(out))
        assert forward[(a, b)] == (sum(p != (b, a) for p in into), sum(p != (b, a) for p in out))
    assert dual.dual_adjacency(e).count() == sum(v[1] for v in degree.values()) == sum(v[0] for v in degree.values())


def test_dual_of_dual_is_the_graph(five):
    e = five.selectExpr("xxhash64(src, dst) edge_id", "src", "dst")
    fg = FeatureGraph(graph.node_degrees(e), dual.incidence(e, directed=True).select("node_id", "edge_id", "sign"), e)
    assert {r["differences"] for r in dual.roundtrip_differences(fg).collect()} == {0}
    assert dual.dual(fg).node_key == "edge_id" and dual.dual(dual.dual(fg)) == fg


def test_densities(spark):
    for n, m, want in ((7307, 10612, 1.98783e-4), (912, 1311, 1.57794e-3), (4604, 119882, 5.65689e-3)):
        row = graph.density(spark.range(n), spark.range(m)).first()
        assert float(f"{row['density']:.6g}") == pytest.approx(want, rel=1e-5)
    assert graph.density(spark.range(1), spark.range(0)).first()["density"] == 0


@pytest.mark.parametrize(
    "title,valid",
    [("Old harbour", True), ("Route 12", True), ("talking drum", True), ("Talk page", False), ("User list", False), ("File store", False), ("ISO codes", False), ("100% wool", False), ("a#b", False), ("a:b", False), ("1984", False), ("", False), (None, False)],
)
def test_titles(spark, title, valid):
    df = spark.createDataFrame([(title,)], "title string")
    assert df.select(is_valid_title(df.title)).first()[0] is valid


def test_title_words(spark):
    df = spark.createDataFrame([("Talker",), ("a Talk",)], "title string")
    assert [r[0] for r in df.select(is_valid_title(df.title, mode="word")).collect()] == [True, False]


def latent_of(spark, rows):
    return spark.createDataFrame(rows, "src long, dst long, w double")


def node_mass(df, start):
    return {r["node_id"]: round(r["p"], 4) for r in df.where(f"start = {start}").collect()}


def test_readouts_of_the_reciprocal_triangle(spark):
    latent = latent_of(spark, [(0, 1, 0.7), (0, 2, 0.3), (1, 0, 0.2), (1, 2, 0.8), (2, 1, 0.6), (2, 0, 0.4)])
    starts = spark.createDataFrame([(0,)], "node_id long")
    for how in ("head", "tail"):
        assert node_mass(walk.target_distribution(starts, latent, h=1, how=how), 0) == {1: 0.7, 2: 0.3}
    assert node_mass(walk.target_distribution(starts, latent, h=1, how="pinv"), 0) == {1: 0.8235, 2: 0.3462}


def test_walks_on_the_five_node_graph(spark):
    nof = spark.createDataFrame(FIVE, "src long, dst long, nof long")
    latent = weights.weights_empirical(nof, alpha=0.0)
    assert pairs(latent, "w")[(1, 2)] == (0.75,)
    one = spark.createDataFrame([(1,)], "node_id long")
    dist = lambda h, how: node_mass(walk.target_distribution(one, latent, h=h, how=how), 1)
    assert dist(1, "head") == {2: 0.75, 3: 0.25} and dist(1, "pinv") == {2: 0.9, 3: 0.25}
    assert dist(2, "head") == {3: 0.75, 4: 0.125, 5: 0.125} and dist(2, "tail") == {3: 0.75, 4: 0.125} and dist(2, "pinv") == {3: 0.75, 4: 0.125}
    assert dist(3, "head") == {1: 0.125, 4: 0.375, 5: 0.375} and dist(3, "tail") == {1: 0.125, 4: 0.375}
    top = [(r["suffix"], round(r["p"], 3)) for r in walk.top_suffixes(one, latent, h=2, k=9).orderBy("rank").collect()]
    assert top == [("2>3", 0.75), ("3>4", 0.125), ("3>5", 0.125)]
    kept = walk.target_distribution(one, latent, h=1, how="pinv", normalize=True).collect()
    assert math.isclose(sum(r["p"] for r in kept), 1)


def enumerate_walks(weights_, start, h):
    walks = [([start], 1.0)]
    for _ in range(h):
        new = []
        for nodes, p in walks:
            back = weights_.get((nodes[-1], nodes[-2]), 0) if len(nodes) > 1 else 0
            for (a, b), w in weights_.items():
                if a == nodes[-1] and (len(nodes) < 2 or b != nodes[-2]) and 1 - back > 1e-12:
                    new.append(([*nodes, b], p * w / (1 - back)))
        walks = new
    return walks


def test_distribution_and_suffixes_equal_enumeration(spark):
    rng = random.Random(7)
    e = sorted({(a, b) for a, b in ((rng.randrange(9), rng.randrange(9)) for _ in range(34)) if a != b})
    latent = weights.weights_empirical(spark.createDataFrame([(a, b, rng.randrange(5)) for a, b in e], "src long, dst long, nof long"))
    table = {(r["src"], r["dst"]): r["w"] for r in latent.collect()}
    starts = spark.createDataFrame([(i,) for i in range(9)], "node_id long")
    for h in (1, 2, 3):
        want = {}
        for s in range(9):
            for nodes, p in enumerate_walks(table, s, h):
                want[(s, nodes[-1])] = want.get((s, nodes[-1]), 0) + p
        got = {(r["start"], r["node_id"]): r["p"] for r in walk.target_distribution(starts, latent, h=h, how="head").collect()}
        assert got.keys() == want.keys() and all(math.isclose(got[k], want[k], rel_tol=1e-9) for k in want)
    best = walk.top_suffixes(starts, latent, h=2, k=100).collect()
    want = {(s, ">".join(map(str, n[1:]))): p for s in range(9) for n, p in enumerate_walks(table, s, 2)}
    assert len(best) == len(want) and all(math.isclose(r["p"], want[(r["start"], r["suffix"])], rel_tol=1e-9) for r in best)
    for draw in walk.sample_suffix(starts, latent, h=3, n=2).collect():
        path = [draw["start"], *draw["suffix"]]
        assert all(step in table for step in zip(path, path[1:], strict=False)) and all(path[i] != path[i + 2] for i in range(len(path) - 2))


def test_pinv_is_the_pseudoinverse(spark):
    table = {(0, 1): 0.7, (0, 2): 0.3, (1, 0): 0.2, (1, 2): 0.8, (2, 1): 0.6, (2, 0): 0.4}
    keys = list(table)
    b = np.zeros((6, 3))
    for i, (a, _) in enumerate(keys):
        b[i, a] = table[keys[i]]
    mass = np.arange(1.0, 7.0)
    want = np.linalg.pinv(b) @ mass
    rows = spark.createDataFrame([(0, a, c, float(m)) for (a, c), m in zip(keys, mass, strict=True)], "start long, src long, dst long, p double")
    got = walk.readout(rows, latent_of(spark, [(*k, v) for k, v in table.items()]), how="pinv").collect()
    assert all(math.isclose(r["p"], want[r["node_id"]], rel_tol=1e-12) for r in got)


def test_dead_ends(spark):
    latent = latent_of(spark, [(0, 1, 1.0), (1, 0, 1.0)])
    one = spark.createDataFrame([(0,)], "node_id long")
    assert walk.target_distribution(one, latent, h=2, how="head").count() == 0
    assert node_mass(walk.target_distribution(one, latent, h=2, how="head", dead_end="allow_backtrack"), 0) == {0: 1.0}
    assert node_mass(walk.target_distribution(one, latent, h=2, how="head", nb=False), 0) == {0: 1.0}


def test_degenerate_graphs(spark):
    empty = spark.createDataFrame([], "src long, dst long")
    assert dual.dual_features(empty).count() == 0 and graph.node_degrees(empty).count() == 0
    one = edges_of(spark, [(1, 2)])
    assert pairs(dual.dual_features(one), "hyper_sim", "dual_in", "dual_out") == {(1, 2): (1.0, 0.0, 0.0)}
    star = edges_of(spark, [(0, i) for i in range(1, 51)])
    got = pairs(dual.hyperedge_similarity(star), "hyper_sim")
    assert all(math.isclose(v[0], 1 / math.sqrt(50)) for v in got.values())


def test_walks_never_revisit_and_obey_the_policies(spark):
    rng = random.Random(3)
    links = [(a, b, p) for a in range(30) for p, b in enumerate(rng.sample(range(30), 8)) if a != b]
    df = spark.createDataFrame(links, "src long, dst long, pos int")
    for policy in ("all", "first_k"):
        got = crawl.simulate_walks(spark, df, n_paths=200, policy=policy, k=3).collect()
        allowed = {}
        for a, b, p in sorted(links, key=lambda x: (x[0], x[2], x[1])):
            allowed.setdefault(a, []).append(b)
        if policy == "first_k":
            allowed = {a: b[:3] for a, b in allowed.items()}
        for r in got:
            n = r["nodes"]
            assert n[0] == 0 and len(set(n)) == len(n) <= r["goal"] <= 7 and r["goal"] >= 4
            assert all(y in allowed[x] for x, y in zip(n, n[1:], strict=False))
            assert (r["stop_reason"] == "goal") == (len(n) == r["goal"])
    titles = spark.createDataFrame([(i, "Talk" if i % 2 else "ok") for i in range(30)], "node_id long, title string")
    assert all(x % 2 == 0 for r in crawl.simulate_walks(spark, df, n_paths=20, titles=titles).collect() for x in r["nodes"])


def test_windows_and_observations(spark):
    paths = spark.createDataFrame([(1, [5, 6, 7, 8])], "path_id long, nodes array<long>")
    rows = trajectories.windows(paths, horizons=(2,)).orderBy("t").collect()
    assert [(r["prefix"], r["suffix"], r["cur"], r["target"]) for r in rows] == [([5], [6, 7], 5, 7), ([5, 6], [7, 8], 6, 8)]
    near = spark.createDataFrame([(5, 9, 0, 0.9), (5, 4, 1, 0.5), (6, 2, 0, 0.1)], "src long, dst long, pos int, sim double")
    seen = trajectories.observe(trajectories.explode_paths(paths), kind="nearest", k_nearest=3, neighbours=near)
    assert all(math.isclose(r[0], 1) for r in seen.groupBy("path_id", "step").sum("weight").select("sum(weight)").collect())
    ids = trajectories.assign_ids(spark.createDataFrame([("b",), ("a",), ("b",), (None,)], "title string"), dense=True)
    assert sorted(map(tuple, ids.collect())) == [("a", 0), ("b", 1)]


def test_click_counts_use_training_steps_only(spark):
    steps = spark.createDataFrame([(1, 0, 1), (1, 1, 2), (2, 0, 1), (2, 1, 2), (2, 2, 3)], "path_id long, step int, node_id long")
    edges = graph.build_edges(steps)
    assert pairs(features.click_counts(steps.where("path_id = 1"), edges), "nof") == {(1, 2): (1,), (2, 3): (0,)}
    shares = pairs(features.click_counts(steps, edges, scale="share"), "nof")
    assert shares == {(1, 2): (1.0,), (2, 3): (1.0,)}
    assert [features.feature_width(s) for s in ("original", "similarity", "degree", "combined")] == [2, 3, 4, 5]


def test_two_cliques_are_two_communities(spark):
    clique = [(a, b) for g in (0, 10) for a in range(g, g + 4) for b in range(g, g + 4) if a < b] + [(0, 10)]
    e = edges_of(spark, clique)
    members = {r["node_id"]: r["community"] for r in community.communities(e, max_sweeps=4).collect()}
    assert len({members[i] for i in range(4)}) == 1 and len({members[i] for i in range(10, 14)}) == 1 and members[0] != members[10]
    one = spark.createDataFrame([(n, 0) for n in members], "node_id long, community long")
    assert abs(community.modularity(e, one).first()["modularity"]) < 1e-9
    best = community.modularity(e, spark.createDataFrame(list(members.items()), "node_id long, community long")).first()["modularity"]
    assert math.isclose(best, 2 * (6 / 13 - (13 / 26) ** 2))


def ball(objective="target", coords="gnn", h=2, readout="pinv"):
    """A hand-made ball over the whole of a graph of seven nodes, with four windows."""
    rng = np.random.default_rng(1)
    e = sorted({(int(a), int(b)) for a, b in rng.integers(0, 7, (26, 2)) if a != b})
    config = train.ModelConfig(edge_width=3, layers=2, width=3, hidden=4, h=h, objective=objective, coords=coords, readout=readout)
    start = e[0][0]
    suffixes = []
    for a, b in e:
        if a == start:
            suffixes += [[b, d][:h] for c, d in e if c == b and d != start]
    suffixes = suffixes[:4]
    marks = [[(start, 0, 0.75), ((start + i) % 7, 0, 0.25), ((start + i + 2) % 7, 1, 1.0)] for i in range(len(suffixes))]
    pairs = np.array(e, dtype=np.int64)
    one = train.Ball(np.arange(7), rng.integers(0, 5, size=(7, 2)).astype(float), pairs, pairs, rng.normal(size=(len(e), 3)), start, h + 1, marks, suffixes, [1, 2, 1, 3][: len(suffixes)])
    return one.prepare(), config


def test_windows_of_equal_marks_share_a_group():
    one, config = ball()
    assert (np.diff(one.group) >= 0).all()
    same = train.Ball(one.nodes, one.features, one.near, np.stack((one.src, one.dst), axis=1), one.edge_features, one.start, 3, [[(0, 0, 1.0)], [(1, 0, 1.0)], [(0, 0, 1.0)]], [[1, 2], [2, 3], [2, 1]], [1, 1, 2]).prepare()
    assert same.group.tolist() == [0, 0, 1] and same.order.tolist() == [0, 2, 1] and same.counts.tolist() == [1, 2, 1]
    x = train.initial(config)
    loss, grad = train.loss_and_gradient(same, x, config)
    numeric = [(train.loss_and_gradient(same, x + 1e-6 * np.eye(len(x))[i], config)[0] - train.loss_and_gradient(same, x - 1e-6 * np.eye(len(x))[i], config)[0]) / 2e-6 for i in range(0, len(x), 7)]
    assert np.allclose(numeric, grad[::7], atol=1e-4)


CASES = [("target", "gnn", 2, "pinv"), ("target", "gnn", 2, "tail"), ("target", "gnn", 2, "head"), ("target", "none", 3, "pinv"), ("target", "gnn", 1, "pinv"), ("path", "gnn", 2, "pinv"), ("path", "none", 2, "pinv")]


@pytest.mark.parametrize("layers", [1, 2, 3])
@pytest.mark.parametrize("objective,coords,h,readout", CASES)
def test_gradient_equals_finite_differences(objective, coords, h, readout, layers):
    one, config = ball(objective, coords, h, readout)
    config.layers = layers
    x = train.initial(config) * 0.7
    loss, grad = train.loss_and_gradient(one, x, config)
    assert np.isfinite(loss)
    for i in range(0, len(x), 3):
        step = np.zeros_like(x)
        step[i] = 1e-6
        numeric = (train.loss_and_gradient(one, x + step, config)[0] - train.loss_and_gradient(one, x - step, config)[0]) / 2e-6
        assert abs(numeric - grad[i]) < 1e-4 * max(1, abs(numeric)), i


@pytest.mark.parametrize("dense", [True, False])
@pytest.mark.parametrize("readout", ["pinv", "tail", "head"])
def test_loss_equals_whole_matrices(readout, dense, monkeypatch):
    """Coordinates by node, the transition matrix of edges to edges, its power and a numerical pseudoinverse."""
    if not dense:
        monkeypatch.setattr(train, "DENSE_NODES", 0)
    one, config = ball(readout=readout)
    x = train.initial(config)
    p = train.unpack(x, config)
    n, m = 7, len(one.src)
    edges = list(zip(one.src.tolist(), one.dst.tolist(), strict=True))
    total = 0.0
    for window in range(len(one.counts)):
        c = np.zeros((n, train.MEMORY))
        for w, node, slot, weight in zip(*one.marks, strict=True):
            if w == one.group[window]:
                c[int(node), int(slot)] += weight
        for layer in range(2):
            new = np.zeros((n, 3))
            for v in range(n):
                into, out = [c[a] for a, b in edges if b == v], [c[b] for a, b in edges if a == v]
                parts = c[v] @ p[f"own{layer}"] + p[f"bias{layer}"]
                parts = parts + (np.mean(into, axis=0) @ p[f"in{layer}"] if into else 0) + (np.mean(out, axis=0) @ p[f"out{layer}"] if out else 0)
                new[v] = np.tanh(parts)
            c = new
        f = np.log1p(one.features)
        z = np.array([np.maximum(np.concatenate([c[a], c[b], f[a], f[b], one.edge_features[e]]) @ p["w1"] + p["b1"], 0) @ p["w2"] + p["b2"][0] for e, (a, b) in enumerate(edges)])
        w = np.array([np.exp(z[e]) / sum(np.exp(z[k]) for k, (c2, _) in enumerate(edges) if c2 == a) for e, (a, _) in enumerate(edges)])
        spread, step = np.zeros((m, n)), np.zeros((m, m))
        weight = dict(zip(edges, w, strict=True))
        for e, (a, b) in enumerate(edges):
            spread[e, a] = w[e]
            for k, (c2, d) in enumerate(edges):
                if c2 == b and d != a:
                    step[k, e] = w[k] / (1 - weight.get((b, a), 0))
        at = np.zeros(n)
        at[one.start] = 1
        if readout == "head":
            mass = np.linalg.matrix_power(step, config.h - 1) @ spread @ at
            got = np.array([mass[[b == v for _, b in edges]].sum() for v in range(n)])
        else:
            mass = np.linalg.matrix_power(step, config.h) @ spread @ at
            got = np.linalg.pinv(spread) @ mass if readout == "pinv" else np.array([mass[[a == v for a, _ in edges]].sum() for v in range(n)])
        total -= one.counts[window] * np.log(got[one.suffixes[window, -1]] + train.EPSILON)
        tape = train.forward(one, p, config, np.arange(len(one.counts)))
        shown = train.node_mass(one, tape["w"], config)[:, tape["column"][window]]
        assert np.allclose(shown, got)
    assert np.isclose(train.loss_and_gradient(one, x, config)[0], total)


@pytest.fixture(scope="module")
def walked(spark):
    """Paths over a graph with ways back, its edge features and nodes."""
    rng = np.random.default_rng(7)
    paths = [[int(n) for n in rng.integers(0, 9, 6)] for _ in range(40)]
    paths = [[n for i, n in enumerate(p) if not i or n != p[i - 1]] for p in paths] + [[3, 1, 2, 1, 4], [1, 2, 1, 4, 1], [2, 50]]
    frame = spark.createDataFrame([(i, p) for i, p in enumerate(paths)], "path_id long, nodes array<long>").cache()
    steps = trajectories.explode_paths(frame)
    edges = graph.build_edges(steps)
    f = features.assemble_edge_features(edges, edges.selectExpr("src", "dst", "0.0D text_sim"), features.click_counts(steps, edges), None, standardize=True)
    return frame, steps, edges, f.cache()


def test_one_epoch_and_balls_equal_the_whole_graph(spark, walked):
    """Loss and gradient of an epoch over balls are those of balls that hold the whole graph; training balls are enough."""
    frame, _, edges, f = walked
    windows = trajectories.windows(frame, horizons=(2,))
    nodes = features.node_features(edges)
    for readout in ("pinv", "head"):
        config = train.ModelConfig(readout=readout, seed=5)
        x = train.initial(config)
        rows = train.ego_graphs(windows, f, nodes, h=2, readout=readout)
        (loss, grad), *_ = train.evaluate(rows, [x], [config])
        e, n = f.collect(), nodes.collect()
        pairs = np.array([[r["src"], r["dst"]] for r in e])
        by: dict = {}
        for r in windows.collect():
            by.setdefault(r["cur"], []).append(r)
        total, g = 0.0, np.zeros(len(x))
        for cur, ws in by.items():
            marks = [[(v, i, 1.0) for i, v in enumerate(w["prefix"][::-1][: train.MEMORY])] for w in ws]
            one = train.Ball(np.array([r["node_id"] for r in n]), np.array([r["f"] for r in n]), pairs, pairs, np.array([r["f"] for r in e]), cur, 2, marks, [w["suffix"] for w in ws], [1] * len(ws)).prepare()
            a, b = train.loss_and_gradient(one, x, config)
            total, g = total + a, g + b
        count = windows.count()
        assert np.isclose(loss, total / count + 0.5 * config.l2 * x @ x, rtol=1e-4) and np.allclose(grad, g / count + config.l2 * x, rtol=1e-3, atol=1e-4)  # single precision


def test_predictions_agree_with_the_walk_and_the_measures(spark, walked):
    """A model whose weights don't depend on the prefix, as a table, gives the same four measures through walk and metrics."""
    frame, steps, edges, f = walked
    nodes = features.node_features(edges)
    exits = edges.groupBy("src").agg(F.min("dst").alias("target")).selectExpr("src AS cur", "target", "array(src) AS prefix", "array(target) AS suffix")
    for h, readout in ((2, "pinv"), (3, "tail"), (3, "head")):
        config = train.ModelConfig(coords="none", layers=0, h=h, readout=readout, seed=3)
        model = train.Model(config, train.initial(config) * 2)
        latent = train.weights_table(train.ego_graphs(exits, f, nodes, h=1, layers=0, readout="head", whole=True), model).cache()
        windows = trajectories.windows(frame, horizons=(h,))
        found = train.predict(train.ego_graphs(windows, f, nodes, h=h, layers=0, readout=readout, whole=True), model).cache()
        got = {r["metric"]: (r["value"], r["support"]) for r in train.measure(found).collect()}
        dist = walk.target_distribution(latent.selectExpr("src AS node_id").distinct(), latent, h=h, how=readout)
        want = {r["metric"]: (r["value"], r["support"]) for r in metrics.all_metrics(dist, windows, latent, graph.node_degrees(edges)).collect()}
        assert {k: (round(a, 9), b) for k, (a, b) in got.items()} == {k: (round(a, 9), b) for k, (a, b) in want.items()}
        path = {r["window_id"]: r["p"] for r in walk.suffix_probability(windows, latent).collect()}
        shown = {(tuple(r["prefix"]), tuple(r["suffix"])): r["p_path"] for r in found.collect()}
        for r in windows.collect():
            assert math.isclose(shown[(tuple(r["prefix"][-train.MEMORY :]), tuple(r["suffix"]))], path[r["window_id"]], abs_tol=1e-9)
        top = train.top_nodes(found)
        assert top.where("place > 5 or p <= 0").count() == 0 and top.count() > 0
    rival = train.predict(train.ego_graphs(trajectories.windows(frame, horizons=(2,)), f, nodes, h=2, layers=0, whole=True), train.Model(train.ModelConfig(coords="none", layers=0), train.initial(train.ModelConfig(coords="none", layers=0))), suffixes=1000)
    for r in rival.select("rivals").collect():
        assert not r["rivals"] or sum(x["p"] for x in r["rivals"]) < 1 + 1e-9


def test_walk_over_a_dense_ball_holds_no_pairs_of_edges():
    """The mass of each step equals the sum over pairs of edges, and a ball's size follows its edges, not those pairs."""
    n = 40
    rng = np.random.default_rng(4)
    edges = np.array([(a, b) for a in range(n) for b in range(n) if a != b and rng.random() < 0.9] + [(n, 0), (0, n), (n + 1, n)])
    nodes = np.arange(n + 2)
    ball = train.Ball(nodes, np.ones((n + 2, 2)), edges, edges, np.ones((len(edges), 1)), n, 2, [[(n, 0, 1.0)]], [[0, 1]], [1])
    assert len(pickle.dumps(ball, protocol=5)) < 100 * len(edges)
    ball.prepare()
    w = rng.random((len(edges), 3))
    w /= np.stack([np.bincount(ball.src, x, n + 2) for x in w.T], 1)[ball.src]
    room = train._rooms(ball, w)
    want = np.where((ball.src == n)[:, None], w, 0)
    for got in train.walk_mass(ball, w, 2):
        assert np.allclose(got, want, rtol=1e-9, atol=0)
        step = np.zeros_like(w)
        for e in range(len(edges)):
            for f in np.flatnonzero((ball.src == ball.dst[e]) & (ball.dst != ball.src[e])):
                step[f] += np.where(room[e] > train.EPSILON, want[e] * w[f] / np.maximum(room[e], train.EPSILON), 0)
        want = step


def crowded(n=60, windows=40):
    """A ball over a nearly complete graph whose windows all differ in their marks."""
    rng = np.random.default_rng(8)
    edges = np.array([(a, b) for a in range(n) for b in range(n) if a != b and rng.random() < 0.95])
    marks = [[(0, 0, 1.0), (1 + k % (n - 1), 1, 1.0), (1 + k // 2 % (n - 1), 2, 1.0)] for k in range(windows)]
    suffixes = [[int(x) for x in rng.integers(1, n, 2)] for _ in range(windows - 1)] + [[1, 0]]
    one = train.Ball(np.arange(n), rng.random((n, 2)) * 9, edges, edges, rng.random((len(edges), 2)), 0, 2, marks, suffixes, rng.integers(1, 5, windows).tolist())
    return one.prepare(), train.ModelConfig(layers=1, seed=2)


def test_a_pass_holds_no_array_of_edges_by_windows_by_hidden_units():
    one, config = crowded()
    x = train.initial(config).astype(np.float32)
    train.loss_and_gradient(one, x, config)
    tracemalloc.start()
    train.loss_and_gradient(one, x, config)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 2 * 4 * len(one.src) * len(one.counts) * config.hidden


def test_blocks_change_no_result(monkeypatch):
    one, config = crowded(20, 6)
    x = train.initial(config)
    want = train.loss_and_gradient(one, x, config)
    kinds = set()
    for numbers in (1, 16 * 6 * 3, 16 * 6 * 15, 16 * 6 * 50):
        monkeypatch.setattr(train, "BLOCK_NUMBERS", numbers)
        again = crowded(20, 6)[0]
        got = train.loss_and_gradient(again, x, config)
        assert np.isclose(got[0], want[0]) and np.allclose(got[1], want[1], atol=1e-9)
        blocks = again.blocks(16 * 6)
        assert [b.at.start for b in blocks] == [0, *(b.at.stop for b in blocks[:-1])] and blocks[-1].at.stop == len(again.src)
        kinds |= {(b.tail is None, b.by_dst is None, b.stretches is None) for b in blocks}
    assert len(kinds) > 2


@pytest.mark.parametrize("layers", [1, 2])
def test_hidden_units_of_one_sign_are_summed_by_products(layers, monkeypatch):
    """On a dense ball few hidden units are computed one by one, and loss, gradient and weights are those of computing all."""
    one, config = crowded()
    config.layers = layers
    x, windows = train.initial(config), np.arange(40)
    tape = train.forward(one, train.unpack(x, config), config, windows)
    singly = tape["units"].above.size + sum(a.size for _, a in tape["units"].changing)
    assert 0 < singly < 0.25 * len(one.src) * tape["w"].shape[1] * config.hidden
    got = train.loss_and_gradient(one, x, config)
    monkeypatch.setattr(train, "RUN_GROUPS", 10**9)
    again = crowded()[0]
    want = train.loss_and_gradient(again, x, config)
    assert np.isclose(got[0], want[0], rtol=1e-12) and np.allclose(got[1], want[1], rtol=1e-8, atol=1e-9)
    other = train.forward(again, train.unpack(x, config), config, windows)
    assert "units" not in other and np.allclose(tape["w"], other["w"], rtol=1e-9)


@pytest.mark.parametrize("readout", ["pinv", "tail"])
def test_loss_from_the_edges_at_targets_equals_that_from_all_edges(readout):
    one, config = crowded(20, 12)
    config.readout = readout
    windows = np.arange(12)
    tape = train.forward(one, train.unpack(train.initial(config), config), config, windows)
    near, far, room = (np.zeros_like(tape["w"]) for _ in range(3))
    losses = train._near_target_loss(one, tape, config, windows, near), train._target_loss(one, tape, config, windows, far, room)
    has = one.back >= 0
    far[one.back[has]] -= room[has]
    assert np.isclose(*losses) and np.allclose(near, far)


def test_training_lowers_the_loss_and_models_survive_saving(spark, walked, tmp_path):
    frame, _, edges, f = walked
    rows = train.ego_graphs(trajectories.windows(frame, horizons=(2,)), f, features.node_features(edges), h=2).cache()
    for optimizer in ("adam", "lbfgs"):
        model = train.fit(rows, train.ModelConfig(optimizer=optimizer, epochs=8, lr=0.05))
        assert model.history[-1][1] < model.history[0][1]
    again = train.fit_many(rows, [train.ModelConfig(optimizer="lbfgs", epochs=8, lr=0.05)])[0]
    assert np.allclose(again.params, model.params)
    one, two = train.fit_many(rows, [train.ModelConfig(epochs=3, seed=s) for s in (1, 2)])
    assert np.allclose(two.params, train.fit(rows, train.ModelConfig(epochs=3, seed=2)).params) and not np.allclose(one.params, two.params)
    train.save_model(spark, model, str(tmp_path / "m"))
    assert np.allclose(train.load_model(spark, str(tmp_path / "m")).params, model.params)


def test_observations_fall_with_distance(spark):
    nodes = spark.createDataFrame([(1,), (2,)], "node_id long")
    near = spark.createDataFrame([(1, 5, 0, 0.5), (1, 6, 1, -0.2), (1, 7, 2, 0.1)], "src long, dst long, pos int, sim double")
    got = {(r["node_id"], r["seen"]): r["weight"] for r in trajectories.nearest_nodes(nodes, near, k_nearest=3).collect()}
    assert got == {(1, 1): 1 / 1.5, (1, 5): 0.5 / 1.5, (1, 6): 0.0, (2, 2): 1.0}


def test_an_experiment_predicts_once(spark, monkeypatch):
    from types import SimpleNamespace

    from hyperpath.plans import experiments

    passes = spark.sparkContext.accumulator(0)

    def predicted(batches):
        passes.add(1)
        yield from batches

    schema = "model int, features string, seed int, count long, p_target double, rank long, choices array<struct<degree:long,hit:boolean>>"
    rows = spark.createDataFrame([(0, "original", 1, 2, 0.5, 1, [(3, True), (4, False)])], schema).coalesce(1)
    monkeypatch.setattr(experiments, "trained", lambda *_, **__: [])
    monkeypatch.setattr(experiments, "predictions", lambda *_: rows.mapInArrow(predicted, schema))
    got = {r["metric"]: r["value"] for r in experiments.run_experiment(SimpleNamespace(spark=spark, sf_dir="none", which="once")).collect()}
    assert len(got) == 4 and got["target_probability"] == 0.5 and got["precision_top1"] == 1.0
    assert passes.value == 1
