"""The dual hypergraph: edges become nodes, nodes become hyperedges; and the edge features read off it.

The matrix forms are quadratic in the degree of hubs. Both features have closed forms over degrees, so the matrices never
exist: a hub costs one row per edge.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..schemas import FeatureGraph
from .graph import node_degrees


def incidence(edges: DataFrame, *, directed: bool = False) -> DataFrame:
    """(node_id, src, dst, sign): both ends of each edge; directed: -1 at its tail, 1 at its head. Map-only."""
    ends = F.array(F.struct(F.col("src").alias("node_id"), F.lit(-1 if directed else 1).alias("sign")), F.struct(F.col("dst").alias("node_id"), F.lit(1).alias("sign")))
    rows = edges.select("*", F.explode(ends).alias("_e"))
    return rows.select("_e.node_id", *(c for c in ("edge_id", "src", "dst") if c in edges.columns), "_e.sign")


def dual(graph: FeatureGraph) -> FeatureGraph:
    """Node and edge features trade places and the incidence is read the other way; no data moves."""
    return FeatureGraph(graph.edge_features, graph.incidence, graph.node_features, graph.edge_key, graph.node_key)


def roundtrip_differences(graph: FeatureGraph) -> DataFrame:
    """(part, differences): rows by which the dual of the dual differs from the graph; all zero."""
    again = dual(dual(graph))
    parts = []
    for name in ("node_features", "incidence", "edge_features"):
        x, y = getattr(graph, name), getattr(again, name)
        parts.append(x.exceptAll(y).unionAll(y.exceptAll(x)).agg(F.count("*").alias("differences")).select(F.lit(name).alias("part"), "differences"))
    return parts[0].unionAll(parts[1]).unionAll(parts[2])


def hyperedges(edges: DataFrame) -> DataFrame:
    """(hyperedge_id, edge_id, sign): the members of each hyperedge, one row each, so no size limit."""
    return incidence(edges, directed=True).select(F.col("node_id").alias("hyperedge_id"), "edge_id", "sign")


def hyperedge_sizes(edges: DataFrame) -> DataFrame:
    return incidence(edges).groupBy("node_id").agg(F.count("*").alias("size"))


def _pairs(edges: DataFrame) -> DataFrame:
    return edges.select(F.least("src", "dst").alias("lo"), F.greatest("src", "dst").alias("hi"))


def hyperedge_similarity(edges: DataFrame, *, reciprocal: str = "keep") -> DataFrame:
    """(src, dst, hyper_sim): cosine of the incidence rows of an edge's ends.

    Two nodes share exactly the columns of the edges between them: one, or two if the link back exists and has its
    own column ("keep"; "collapse" makes one of both). So the cosine is shared / sqrt(degree * degree).
    """
    edges = edges.select("src", "dst")
    if reciprocal == "collapse":
        undirected = _pairs(edges).distinct().select(F.col("lo").alias("src"), F.col("hi").alias("dst"))
        shared = F.lit(1)
    else:
        undirected, shared = edges, F.when(F.col("back").isNotNull(), 2).otherwise(1)
    degree = hyperedge_sizes(undirected)
    du, dv = (degree.select(F.col("node_id").alias(c), F.col("size").alias(f"d_{c}")) for c in ("src", "dst"))
    rows = edges.join(du, "src").join(dv, "dst")
    if reciprocal == "keep":
        back = edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), F.lit(1).alias("back"))
        rows = rows.join(back, ["src", "dst"], "left")
    return rows.select("src", "dst", (shared / F.sqrt(F.col("d_src").cast("double") * F.col("d_dst"))).alias("hyper_sim"))


def dual_node_degree(edges: DataFrame, *, normalize: bool = True, dmax: str = "joint", exclude_backtrack: bool = False) -> DataFrame:
    """(src, dst, dual_in, dual_out): edge-to-edge continuations into and out of an edge seen as a node.

    A continuation out of an edge is an edge that leaves its head, so the count is a degree lookup; likewise into it.
    """
    edges = edges.select("src", "dst")
    degree = node_degrees(edges)
    tail = degree.select(F.col("node_id").alias("src"), F.col("in_degree").alias("dual_in"))
    head = degree.select(F.col("node_id").alias("dst"), F.col("out_degree").alias("dual_out"))
    rows = edges.join(tail, "src").join(head, "dst")
    if exclude_backtrack:
        back = edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), F.lit(1).alias("back"))
        rows = rows.join(back, ["src", "dst"], "left").select("src", "dst", *((F.col(c) - F.coalesce("back", F.lit(0))).alias(c) for c in ("dual_in", "dual_out")))
    rows = rows.select("src", "dst", "dual_in", "dual_out")
    if not normalize:
        return rows
    top = rows.agg(F.max("dual_in").alias("_i"), F.max("dual_out").alias("_o"))
    top = top.select(*((F.greatest("_i", "_o") if dmax == "joint" else F.col(c)).cast("double").alias(c) for c in ("_i", "_o")))
    scaled = rows.crossJoin(F.broadcast(top))  # one row
    share = lambda c, m: F.when(F.col(m) > 0, F.col(c) / F.col(m)).otherwise(F.lit(0.0)).alias(c)
    return scaled.select("src", "dst", share("dual_in", "_i"), share("dual_out", "_o"))


def dual_features(edges: DataFrame, *, reciprocal: str = "keep", dmax: str = "joint") -> DataFrame:
    """(src, dst, hyper_sim, dual_in, dual_out): both features from one table of degrees."""
    if reciprocal == "collapse":
        return hyperedge_similarity(edges, reciprocal=reciprocal).join(dual_node_degree(edges, dmax=dmax), ["src", "dst"])
    edges = edges.select("src", "dst")
    degree = node_degrees(edges)
    tail = degree.select(F.col("node_id").alias("src"), F.col("in_degree").alias("dual_in"), (F.col("in_degree") + F.col("out_degree")).alias("_du"))
    head = degree.select(F.col("node_id").alias("dst"), F.col("out_degree").alias("dual_out"), (F.col("in_degree") + F.col("out_degree")).alias("_dv"))
    back = edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), F.lit(1).alias("_back"))
    rows = edges.join(tail, "src").join(head, "dst").join(back, ["src", "dst"], "left")
    # The largest count is that of an edge: in-degrees of tails, out-degrees of heads.
    has_out, has_in = degree.where("out_degree > 0"), degree.where("in_degree > 0")
    top = has_out.agg(F.max("in_degree").alias("_i")).crossJoin(has_in.agg(F.max("out_degree").alias("_o")))  # two rows of one
    top = top.select(*((F.greatest("_i", "_o") if dmax == "joint" else F.col(c)).cast("double").alias(c) for c in ("_i", "_o")))
    rows = rows.crossJoin(F.broadcast(top))
    shared = F.when(F.col("_back").isNotNull(), 2).otherwise(1)
    share = lambda c, m: F.when(F.col(m) > 0, F.col(c) / F.col(m)).otherwise(F.lit(0.0)).alias(c)
    return rows.select("src", "dst", (shared / F.sqrt(F.col("_du").cast("double") * F.col("_dv"))).alias("hyper_sim"), share("dual_in", "_i"), share("dual_out", "_o"))


def dual_adjacency(edges: DataFrame, *, nodes: DataFrame | None = None, salts: int = 16) -> DataFrame:
    """(src, through, dst): pairs of edges that continue one another through a node; with nodes, through those only.

    A hub's arrivals are dealt over salts, and its departures repeated for each, so no task gets all of its pairs.
    """
    into = edges.select("src", F.col("dst").alias("through"))
    out = edges.select(F.col("src").alias("through"), "dst")
    if nodes is not None:
        keep = nodes.select(F.col("node_id").alias("through"))
        into, out = into.join(keep, "through", "left_semi"), out.join(keep, "through", "left_semi")
    into = into.withColumn("_salt", F.pmod(F.xxhash64("src"), F.lit(salts)))
    out = out.withColumn("_salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long"))))
    return into.join(out, ["through", "_salt"]).select("src", "through", "dst")
