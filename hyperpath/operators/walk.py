"""Non-backtracking walks over latent weights: spreading, transitions, horizons and readouts.

The transition matrix of edges to edges is never built: mass on edges is a table, a transition is a join of the heads of
edges with the tails of others. As weights don't depend on the prefix here, walks start once per node, not per window.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .weights import with_back

EPSILON = 1e-12


def spread(x: DataFrame, latent: DataFrame) -> DataFrame:
    """x(start, node_id, p) -> edge mass (start, src, dst, p)."""
    rows = x.withColumnRenamed("node_id", "src").join(latent.select("src", "dst", "w"), "src")
    return rows.select("start", "src", "dst", (F.col("p") * F.col("w")).alias("p"))


def nb_step(mass: DataFrame, latent: DataFrame, *, dead_end: str = "drop", nb: bool = True) -> DataFrame:
    """One transition: the mass of i->j goes on to j->l, l other than i, by w(j->l) / (1 - w(j->i)).

    dead_end: where the only exit leads back, mass is dropped, or goes back with "allow_backtrack". nb False: a plain walk.
    """
    exits = latent.select(F.col("src").alias("via"), F.col("dst").alias("next"), F.col("w").alias("w_next"))
    if not nb:
        joined = mass.withColumnRenamed("dst", "via").join(exits, "via").select("start", F.col("via").alias("src"), F.col("next").alias("dst"), (F.col("p") * F.col("w_next")).alias("p"))
        return joined.groupBy("start", "src", "dst").agg(F.sum("p").alias("p"))
    back = latent.select(F.col("dst").alias("src"), F.col("src").alias("dst"), F.col("w").alias("w_back"))
    rows = mass.join(back, ["src", "dst"], "left").withColumn("room", 1 - F.coalesce("w_back", F.lit(0.0)))
    rows = rows.withColumnRenamed("src", "origin").withColumnRenamed("dst", "via").join(exits, "via")
    go = F.when(F.col("next") != F.col("origin"), F.when(F.col("room") > EPSILON, F.col("w_next") / F.col("room")))
    if dead_end == "allow_backtrack":
        go = F.when(F.col("room") > EPSILON, go).otherwise(F.when(F.col("next") == F.col("origin"), F.lit(1.0)))
    rows = rows.select("start", F.col("via").alias("src"), F.col("next").alias("dst"), (F.col("p") * go).alias("p")).where("p is not null")
    return rows.groupBy("start", "src", "dst").agg(F.sum("p").alias("p"))


def _printed_step(mass: DataFrame, latent: DataFrame) -> DataFrame:
    """The transition in the other orientation: mass moves from j->l back to i->j; kept for comparison only."""
    full = with_back(latent)
    into = full.select(F.col("src").alias("origin"), F.col("dst").alias("via"), F.col("w_back"))
    own = mass.join(latent.select("src", "dst", "w"), ["src", "dst"]).withColumnRenamed("src", "via")
    rows = own.join(into, "via").where("origin <> dst").withColumn("room", 1 - F.coalesce("w_back", F.lit(0.0))).where(F.col("room") > EPSILON)
    return rows.select("start", F.col("origin").alias("src"), F.col("via").alias("dst"), (F.col("p") * F.col("w") / F.col("room")).alias("p")).groupBy("start", "src", "dst").agg(F.sum("p").alias("p"))


def propagate(mass: DataFrame, latent: DataFrame, *, h: int, orientation: str = "forward", dead_end: str = "drop", nb: bool = True, prune: float | None = None, topk: int | None = None) -> DataFrame:
    """h transitions. prune drops mass below a bound, topk keeps each start's heaviest edges; what goes shows as lost mass."""
    for _ in range(h):
        mass = _printed_step(mass, latent) if orientation == "printed" else nb_step(mass, latent, dead_end=dead_end, nb=nb)
        if prune is not None:
            mass = mass.where(F.col("p") >= prune)
        if topk is not None:
            order = Window.partitionBy("start").orderBy(F.desc(F.round("p", 9)), "src", "dst")
            mass = mass.withColumn("_r", F.row_number().over(order)).where(F.col("_r") <= topk).drop("_r")
    return mass


def readout(mass: DataFrame, latent: DataFrame | None = None, *, how: str = "tail", normalize: bool = False) -> DataFrame:
    """Edge mass to node mass (start, node_id, p).

    tail: sum by origin. head: sum by end. pinv: the least-squares inverse of the spread; the columns of the spread
    have no edge in common, so it is the sum of mass times weight over the sum of squared weights of a node's exits.
    """
    if how == "pinv":
        squares = latent.groupBy("src").agg(F.sum(F.col("w") * F.col("w")).alias("_ww"))
        rows = mass.join(latent.select("src", "dst", "w"), ["src", "dst"]).groupBy("start", "src").agg(F.sum(F.col("p") * F.col("w")).alias("_pw"))
        out = rows.join(squares, "src").select("start", F.col("src").alias("node_id"), (F.col("_pw") / F.col("_ww")).alias("p"))
    else:
        end = "src" if how == "tail" else "dst"
        out = mass.groupBy("start", F.col(end).alias("node_id")).agg(F.sum("p").alias("p"))
    if normalize:
        total = out.groupBy("start").agg(F.sum("p").alias("_all"))
        out = out.join(total, "start").select("start", "node_id", (F.col("p") / F.col("_all")).alias("p"))
    return out


def one_hot(nodes: DataFrame) -> DataFrame:
    """x(start, node_id, p) with all mass on the start."""
    return nodes.select(F.col("node_id").alias("start"), "node_id", F.lit(1.0).alias("p"))


def target_distribution(starts: DataFrame, latent: DataFrame, *, h: int, how: str = "tail", normalize: bool = False, dead_end: str = "drop", nb: bool = True, orientation: str = "forward") -> DataFrame:
    """(start, node_id, p): where an agent that is at start will be after h steps. starts(node_id) is distinct.

    tail and pinv read the origin of the edge after h transitions; head reads the end after h - 1, which counts sinks too.
    """
    mass = spread(one_hot(starts), latent)
    steps = h - 1 if how == "head" else h
    mass = propagate(mass, latent, h=steps, dead_end=dead_end, nb=nb, orientation=orientation)
    return readout(mass, latent, how=how, normalize=normalize)


def lost_mass(dist: DataFrame) -> DataFrame:
    """(start, lost): what dead ends and pruning took."""
    return dist.groupBy("start").agg((F.lit(1.0) - F.sum("p")).alias("lost"))


def diffuse(x: DataFrame, edges: DataFrame, *, layers: int = 2) -> DataFrame:
    """Coordinates without parameters: layers rounds of averaging x(start, node_id, p) over a node and its in- and out-neighbours."""
    both = edges.select(F.col("src").alias("node_id"), F.col("dst").alias("to")).unionByName(edges.select(F.col("dst").alias("node_id"), F.col("src").alias("to")))
    both = both.distinct()
    degree = both.groupBy(F.col("to")).agg((F.count("*") + 1).alias("_d"))
    for _ in range(layers):
        moved = x.join(both, "node_id").select("start", F.col("to").alias("node_id"), "p").unionByName(x.select("start", "node_id", "p"))
        x = moved.groupBy("start", "node_id").agg(F.sum("p").alias("p")).join(degree.withColumnRenamed("to", "node_id"), "node_id").select("start", "node_id", (F.col("p") / F.col("_d")).alias("p"))
    return x


def suffix_steps(windows: DataFrame) -> DataFrame:
    """(window_id, path_id, i, before, src, dst): the moves of each suffix; before is the node that can't be gone back to."""
    rows = windows.select("window_id", "path_id", "h", F.col("prefix"), F.concat(F.array("cur"), "suffix").alias("_s"))
    rows = rows.select("*", F.posexplode(F.slice("_s", F.lit(1), F.col("h"))).alias("i", "src"))
    before = F.when(F.col("i") > 0, F.get(F.col("_s"), F.col("i") - 1)).otherwise(F.when(F.size("prefix") > 1, F.element_at("prefix", -2)))
    return rows.select("window_id", "path_id", "h", "i", before.alias("before"), "src", F.get(F.col("_s"), F.col("i") + 1).alias("dst"))


def suffix_probability(windows: DataFrame, latent: DataFrame, *, anchor: str = "node") -> DataFrame:
    """(window_id, p): probability of each window's suffix; anchor "node" leaves the first move free, "edge" bars the way back."""
    moves = suffix_steps(windows)
    if anchor == "node":
        moves = moves.withColumn("before", F.when(F.col("i") > 0, F.col("before")))
    w = latent.select("src", "dst", "w")
    back = latent.select("src", F.col("dst").alias("before"), F.col("w").alias("w_back"))
    rows = moves.join(w, ["src", "dst"], "left").join(back, ["src", "before"], "left")
    room = 1 - F.coalesce("w_back", F.lit(0.0))
    p = F.when(F.col("w").isNull() | F.coalesce(F.col("dst") == F.col("before"), F.lit(False)), F.lit(0.0)).when(room > EPSILON, F.col("w") / room).otherwise(F.lit(0.0))
    # A product as one aggregation: a zero anywhere makes it zero.
    return rows.withColumn("_p", p).groupBy("window_id").agg(F.when(F.min("_p") > 0, F.exp(F.sum(F.when(F.col("_p") > 0, F.log("_p"))))).otherwise(F.lit(0.0)).alias("p"))


def top_suffixes(starts: DataFrame, latent: DataFrame, *, h: int, k: int = 2, beam: int | None = None, min_prob: float = 0.0) -> DataFrame:
    """(start, suffix, p, rank): the k likeliest suffixes of each start; exact without a beam. suffix joins nodes by ">"."""
    full = with_back(latent)
    exits = full.select("src", F.col("dst").alias("next"), F.col("w").alias("w_next"))
    backs = latent.select(F.col("src").alias("at"), F.col("dst").alias("origin"), F.col("w").alias("w_back"))
    rows = starts.select(F.col("node_id").alias("start"), F.col("node_id").alias("at"), F.lit(None).cast("long").alias("origin"), F.lit("").alias("suffix"), F.lit(1.0).alias("p"))
    for i in range(h):
        known = rows.join(backs, ["at", "origin"], "left") if i else rows.withColumn("w_back", F.lit(None).cast("double"))
        moved = known.join(exits, F.col("at") == F.col("src")).where("origin is null or next <> origin").withColumn("_room", 1 - F.coalesce("w_back", F.lit(0.0))).where(F.col("_room") > EPSILON)
        text = F.when(F.col("suffix") == "", F.col("next").cast("string")).otherwise(F.concat_ws(">", "suffix", F.col("next").cast("string")))
        rows = moved.select("start", F.col("next").alias("at_"), F.col("at").alias("origin"), text.alias("suffix"), (F.col("p") * F.col("w_next") / F.col("_room")).alias("p")).withColumnRenamed("at_", "at").where(F.col("p") >= min_prob)
        if beam is not None:
            order = Window.partitionBy("start").orderBy(F.desc(F.round("p", 9)), "suffix")
            rows = rows.withColumn("_r", F.row_number().over(order)).where(F.col("_r") <= beam).drop("_r")
    order = Window.partitionBy("start").orderBy(F.desc(F.round("p", 9)), "suffix")
    return rows.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("start", "suffix", "p", "rank")


def sample_suffix(starts: DataFrame, latent: DataFrame, *, h: int, n: int = 1, seed: int = 42) -> DataFrame:
    """(start, draw, suffix): n continuations per start; each move is drawn by a hash against the running sum of the exits."""
    from ..functions.columns import hash8

    rows = starts.select(F.col("node_id").alias("start"), F.explode(F.sequence(F.lit(1), F.lit(n))).alias("draw"), F.col("node_id").alias("at"), F.lit(None).cast("long").alias("origin"), F.array().cast("array<bigint>").alias("suffix"))
    exits = latent.groupBy(F.col("src").alias("at")).agg(F.array_sort(F.collect_list(F.struct("dst", "w"))).alias("exits"))  # a node's exits
    for i in range(h):
        free = F.filter(F.coalesce("exits", F.array().cast("array<struct<dst:bigint,w:double>>")), lambda e: F.coalesce(e["dst"] != F.col("origin"), F.lit(True)))
        drawn = rows.join(exits, "at", "left").withColumn("_f", free).withColumn("_all", F.aggregate("_f", F.lit(0.0), lambda s, e: s + e["w"]))
        u = hash8(str(seed), F.col("start"), F.col("draw"), F.lit(i)) / F.lit(float(1 << 32)) * F.col("_all")
        drawn = drawn.withColumn("_u", u)
        pick = F.aggregate("_f", F.struct(F.lit(0.0).alias("s"), F.lit(None).cast("long").alias("d")), lambda acc, e: F.struct((acc["s"] + e["w"]).alias("s"), F.when(acc["d"].isNull() & (F.col("_u") < acc["s"] + e["w"]), e["dst"]).otherwise(acc["d"]).alias("d")))["d"]
        drawn = drawn.withColumn("_next", pick)
        rows = drawn.select("start", "draw", F.coalesce("_next", "at").alias("at"), F.when(F.col("_next").isNotNull(), F.col("at")).otherwise(F.col("origin")).alias("origin"), F.when(F.col("_next").isNotNull(), F.concat("suffix", F.array("_next"))).otherwise(F.col("suffix")).alias("suffix"))
    return rows.select("start", "draw", "suffix")
