"""Relational operators around the methods: each takes tables and gives a table."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .store import stored


def cold_edges(train: DataFrame, test: DataFrame) -> DataFrame:
    """Edges of test paths that no training path takes."""
    return test.select("src", "dst").distinct().join(train.select("src", "dst"), ["src", "dst"], "left_anti")


def warm_edges(train: DataFrame, test: DataFrame) -> DataFrame:
    return test.select("src", "dst").distinct().join(train.select("src", "dst"), ["src", "dst"], "left_semi")


def edge_set_ops(a: DataFrame, b: DataFrame, *, op: str) -> DataFrame:
    """op: union, intersect, except, or their bag forms union_all, intersect_all, except_all."""
    a, b = a.select("src", "dst"), b.select("src", "dst")
    return {
        "union": lambda: a.union(b).distinct(), "union_all": lambda: a.union(b), "intersect": lambda: a.intersect(b), "intersect_all": lambda: a.intersectAll(b),
        "except": lambda: a.subtract(b), "except_all": lambda: a.exceptAll(b),
    }[op]()


def degree_full_outer(edges: DataFrame) -> DataFrame:
    """(node_id, in_degree, out_degree) by a full outer join of two counts."""
    out = edges.groupBy(F.col("src").alias("node_id")).agg(F.count("*").alias("out_degree"))
    into = edges.groupBy(F.col("dst").alias("node_id")).agg(F.count("*").alias("in_degree"))
    return out.join(into, "node_id", "full").select("node_id", F.coalesce("in_degree", F.lit(0)).alias("in_degree"), F.coalesce("out_degree", F.lit(0)).alias("out_degree"))


def asof_last(events: DataFrame, probes: DataFrame) -> DataFrame:
    """probes(agent, us, probe_id) with node_id: of the agent's last event(agent, us, node_id) before it. Union and one window: no range join."""
    both = events.select("agent", "us", F.lit(0).alias("kind"), "node_id", F.lit(None).cast("long").alias("probe_id")).unionByName(
        probes.select("agent", "us", F.lit(-1).alias("kind"), F.lit(None).cast("long").alias("node_id"), "probe_id")
    )  # a probe sorts before events of its own instant
    last = F.last("node_id", ignorenulls=True).over(Window.partitionBy("agent").orderBy("us", "kind").rowsBetween(Window.unboundedPreceding, Window.currentRow))
    return both.withColumn("last_node", last).where("probe_id is not null").select("probe_id", "agent", "last_node")


def interval_pairs(first: DataFrame, second: DataFrame, *, hours: float) -> DataFrame:
    """(first_id, second_id): events of one agent, the second at most so many hours after the first.

    The equi-join key has the time slot too, and each first event is in its slot and the next, so a busy agent's events
    don't all meet.
    """
    span = int(hours * 3_600_000_000)
    slot = F.floor(F.col("us") / span).cast("long")
    a = first.select(F.col("event_id").alias("first_id"), "agent", F.col("us").alias("us1"), F.explode(F.array(slot, slot + 1)).alias("slot"))
    b = second.select(F.col("event_id").alias("second_id"), "agent", F.col("us").alias("us2"), slot.alias("slot"))
    return a.join(b, ["agent", "slot"]).where((F.col("us2") > F.col("us1")) & (F.col("us2") <= F.col("us1") + span)).select("first_id", "second_id")


def range_bands(events: DataFrame, bands: DataFrame, *, width: float) -> DataFrame:
    """(event_id, band): events whose value is in a band(band, lo, hi), lo <= value < hi, by an equi-join on cells of a width and a residual test."""
    cells = bands.select("band", "lo", "hi", F.explode(F.sequence(F.floor(F.col("lo") / width), F.floor(F.col("hi") / width))).alias("cell"))
    return events.withColumn("cell", F.floor(F.col("value") / width)).join(cells, "cell").where("value >= lo and value < hi").select("event_id", "band")


def theta_pairs(steps: DataFrame) -> DataFrame:
    """(path_id, earlier, later): ordered pairs of a path's steps; paths are short."""
    a = steps.select("path_id", F.col("step").alias("s1"), F.col("node_id").alias("earlier"))
    b = steps.select("path_id", F.col("step").alias("s2"), F.col("node_id").alias("later"))
    return a.join(b, "path_id").where("s1 < s2").select("path_id", "earlier", "later")


def with_attributes(steps: DataFrame, part: DataFrame, *, broadcast_rows: int = 1_000_000) -> DataFrame:
    """Steps with the attributes of their part; the part table is broadcast if it is counted to be small."""
    attrs = part.select(F.col("p_partkey").alias("node_id"), "p_brand", "p_type")
    small = attrs.limit(broadcast_rows + 1).count() <= broadcast_rows
    return steps.join(F.broadcast(attrs) if small else attrs, "node_id")


def path_owners(steps: DataFrame, orders: DataFrame) -> DataFrame:
    """(path_id, agent, length): a sort-merge join of paths with their orders."""
    length = steps.groupBy("path_id").agg(F.count("*").alias("length"))
    return length.join(orders.select(F.col("o_orderkey").alias("path_id"), F.col("o_custkey").alias("agent")).hint("merge"), "path_id")


def path_cube(paths: DataFrame) -> DataFrame:
    return paths.cube("status", "priority", "length").agg(F.count("*").alias("paths"), F.grouping_id().alias("gid"))


def region_rollup(visits: DataFrame) -> DataFrame:
    """visits(region, nation, supplier, path_id)."""
    return visits.rollup("region", "nation", "supplier").agg(F.count_distinct("path_id").alias("paths"), F.grouping_id().alias("gid"))


def global_rows(df: DataFrame, order: list) -> DataFrame:
    """df with row, its number from 1 in this order: ranges are sorted on their own, then the counts of the ranges before are added."""
    own = stored(df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("_at", F.monotonically_increasing_id()), "ranges")
    part, place = F.shiftright("_at", 33), F.col("_at").bitwiseAND(F.lit((1 << 33) - 1))
    sizes = own.groupBy(part.alias("_part")).agg((F.max(place) + 1).alias("_n"))  # a row per range
    before = sizes.select("_part", F.coalesce(F.sum("_n").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_before"))
    return own.withColumn("_part", part).join(F.broadcast(before), "_part").withColumn("row", F.col("_before") + place + 1).drop("_at", "_part", "_before")


def degree_bands(degrees: DataFrame, *, bands: int = 4) -> DataFrame:
    """Ranks of all nodes by degree, without a window over all of them.

    Everything but the place among equals follows from the histogram of degrees, which has 2 * sqrt(edges) rows at most: k different
    degrees sum up to k * k / 2 or more, and all degrees to twice the edges. So its window may be one task.
    """
    rows = degrees.select("node_id", (F.col("in_degree") + F.col("out_degree")).alias("degree"))
    above = Window.orderBy(F.desc("degree"))
    hist = rows.groupBy("degree").agg(F.count("*").alias("_n"))
    upto = F.sum("_n").over(above.rowsBetween(Window.unboundedPreceding, Window.currentRow))
    hist = hist.select("degree", "_n", upto.alias("_upto"), F.row_number().over(above).alias("dense"), F.sum("_n").over(Window.partitionBy()).alias("_all"))
    placed = global_rows(rows, [F.desc("degree"), F.col("node_id")]).join(F.broadcast(hist), "degree")
    size, more = F.floor(F.col("_all") / bands), F.col("_all") % bands
    head = more * (size + 1)
    band = F.when(F.col("row") <= head, F.floor((F.col("row") - 1) / (size + 1)) + 1).otherwise(more + F.floor((F.col("row") - 1 - head) / F.greatest(size, F.lit(1))) + 1)
    rank = F.col("_upto") - F.col("_n") + 1
    return placed.select(
        "node_id", "degree", band.cast("int").alias("band"), rank.cast("int").alias("rank"), F.col("dense").cast("int").alias("dense"),
        F.round(F.when(F.col("_all") > 1, (rank - 1) / (F.col("_all") - 1)).otherwise(F.lit(0.0)), 6).alias("percent"), F.round(F.col("_upto") / F.col("_all"), 6).alias("cume"),
    )


def running_clicks(events: DataFrame, *, hours: int = 24) -> DataFrame:
    """(event_id, so_far, recent, last_three): clicks of an agent up to each event, within some hours, and the value sum of three rows."""
    by = Window.partitionBy("agent").orderBy("us", "event_id")
    recent = Window.partitionBy("agent").orderBy("us").rangeBetween(-hours * 3_600_000_000, 0)
    return events.select(
        "event_id", F.count("*").over(by.rowsBetween(Window.unboundedPreceding, Window.currentRow)).alias("so_far"), F.count("*").over(recent).alias("recent"),
        F.round(F.sum("value").over(by.rowsBetween(-2, 0)), 4).alias("last_three"), F.first("event_id").over(by.rowsBetween(Window.unboundedPreceding, Window.currentRow)).alias("first_event"),
        F.nth_value("event_id", 2).over(by.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("second_event"),
    )


def topk_per_group(edges: DataFrame, *, k: int = 3) -> DataFrame:
    """edges(src, dst, nof) -> the k most clicked exits of each node."""
    order = Window.partitionBy("src").orderBy(F.desc("nof"), "dst")
    return edges.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("src", "dst", "nof", "rank")


def two_hop(edges: DataFrame) -> DataFrame:
    """(src, dst, ways): nodes two steps away, with the number of ways; pairs are pre-aggregated by the join's output keys."""
    second = edges.select(F.col("src").alias("via"), F.col("dst").alias("end"))
    return edges.select("src", F.col("dst").alias("via")).join(second, "via").groupBy("src", F.col("end").alias("dst")).agg(F.count("*").alias("ways"))


def reach(edges: DataFrame, start: int, *, h: int) -> DataFrame:
    """(node_id, hops): nodes within h steps of start and the least number of steps, by rounds of semi-naive joins, each stored."""
    spark = edges.sparkSession
    seen = frontier = spark.createDataFrame([(start, 0)], "node_id long, hops int")
    links = edges.select(F.col("src").alias("node_id"), "dst")
    for i in range(1, h + 1):
        fresh = frontier.join(links, "node_id").select(F.col("dst").alias("node_id")).distinct().join(seen, "node_id", "left_anti").withColumn("hops", F.lit(i))
        frontier = stored(fresh, "frontier")
        seen = stored(seen.unionByName(frontier), "seen")
    return seen


def reach_sql(edges: DataFrame, start: int, *, h: int) -> DataFrame:
    """The same as a recursive common table expression."""
    return edges.sparkSession.sql(
        """WITH RECURSIVE r(node_id, hops) AS (
               SELECT CAST(:start AS BIGINT), 0 UNION ALL SELECT DISTINCT e.dst, r.hops + 1 FROM r JOIN {edges} e ON e.src = r.node_id WHERE r.hops < :h
           ) SELECT node_id, min(hops) AS hops FROM r GROUP BY node_id""",
        args={"start": start, "h": h}, edges=edges,
    )


def stratified_sample(rows: DataFrame, key: str, stratum: str, percent: dict[str, int]) -> DataFrame:
    """Rows of each stratum by the hash of their key; strata that percent doesn't name are left out."""
    from ..functions.columns import hash8

    share = F.lit(0)
    for value, p in percent.items():
        share = F.when(F.col(stratum) == value, F.lit(p)).otherwise(share)
    return rows.where(hash8(F.lit("stratum"), F.col(key)) % 100 < share)


def page_of(rows: DataFrame, order: list, *, size: int, page: int) -> DataFrame:
    """One page of an ordered list."""
    return rows.orderBy(*order).offset(size * page).limit(size)


def approximate(rows: DataFrame, key: str, value: str, *, deviation: float = 0.02, accuracy: int = 10_000) -> DataFrame:
    """(distinct_values, quartiles): sketches of bounded size, merged across tasks."""
    return rows.agg(F.approx_count_distinct(key, deviation).alias("distinct_values"), F.percentile_approx(value, [0.25, 0.5, 0.75], accuracy).alias("quartiles"))


def hash_sample(paths: DataFrame, *, percent: int) -> DataFrame:
    from ..functions.columns import hash8

    return paths.where(hash8(F.lit("sample"), F.col("path_id")) % 100 < percent)


def json_and_urls(events: DataFrame) -> DataFrame:
    parsed = F.from_json("props", "k long")
    return events.select("event_id", parsed["k"].alias("k"), F.upper(F.substring("event_type", 1, 3)).alias("short"), F.length("props").alias("size"), F.to_json(F.struct(F.col("event_type").alias("t"), parsed["k"].alias("k"))).alias("packed"))
