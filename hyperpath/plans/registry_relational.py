"""Relational and streaming queries beside those of the registry: global ranks, recursion, sketches, hints, samples, late data."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import graph, relational, trajectories
from ..operators.store import stored
from ..sources import tables
from ..streaming import events as stream
from . import workloads
from .registry import _CLOSED, _order_paths, _PATHS, _text, part_edges, query
from .sql import hash8
from .workloads import START, Crawl, load


@query(
    "q66_degree_bands",
    """SELECT node_id, degree, CAST(ntile(4) OVER w AS INTEGER) AS band, CAST(rank() OVER g AS INTEGER) AS rank, CAST(dense_rank() OVER g AS INTEGER) AS dense, round(percent_rank() OVER g, 6) AS percent, round(cume_dist() OVER g, 6) AS cume
       FROM (SELECT node_id, in_degree + out_degree AS degree FROM degrees_part) x WINDOW w AS (ORDER BY degree DESC, node_id), g AS (ORDER BY degree DESC)""",
)
def q66(spark, d):
    return relational.degree_bands(graph.node_degrees(part_edges(spark, d)))


@query("q68b_page_of_hubs", "SELECT node_id, in_degree + out_degree AS degree FROM degrees_part ORDER BY degree DESC, node_id LIMIT 25 OFFSET 50")
def q68b(spark, d):
    rows = graph.node_degrees(part_edges(spark, d)).select("node_id", (F.col("in_degree") + F.col("out_degree")).alias("degree"))
    return relational.page_of(rows, [F.desc("degree"), F.col("node_id")], size=25, page=2)


@query("q69e_reach_recursive", "SELECT node_id, CAST(min(hops) AS INTEGER) AS hops FROM (WITH RECURSIVE r(node_id, hops) AS (SELECT CAST(0 AS BIGINT), 0 UNION SELECT e.dst, r.hops + 1 FROM r JOIN edges_dense e ON e.src = r.node_id WHERE r.hops < 4) SELECT * FROM r) x GROUP BY node_id")
def q69e(spark, d):
    return relational.reach_sql(stored(Crawl(spark, d).edges, "reach_edges"), START, h=4)


_SHARES = {"F": 50, "O": 20, "P": 100}


@query("q69f_stratified_sample", f"SELECT path_id, status FROM order_paths WHERE {hash8(chr(39) + 'stratum|' + chr(39) + ' || path_id')} % 100 < CASE status WHEN 'F' THEN 50 WHEN 'O' THEN 20 WHEN 'P' THEN 100 ELSE 0 END", _PATHS)
def q69f(spark, d):
    return relational.stratified_sample(_order_paths(spark, d).select("path_id", "status"), "path_id", "status", _SHARES)


@query("q12b_approximate_counts", "SELECT TRUE AS distinct_close, TRUE AS quartiles_close")
def q12b(spark, d):
    """Sketches against exact values: distinct parts within five deviations, quartiles of the price within the accuracy in rank."""
    lines = load(spark, d, "lineitem")
    near = relational.approximate(lines, "l_partkey", "l_extendedprice").first()
    share = [F.avg((F.col("l_extendedprice") <= x).cast("double")).alias(f"s{i}") for i, x in enumerate(near["quartiles"])]
    exact = lines.agg(F.count_distinct("l_partkey").alias("n"), *share)
    close = F.abs(F.col("n") - near["distinct_values"]) <= 0.1 * F.col("n")
    ranks = [F.abs(F.col(f"s{i}") - q) <= 0.001 for i, q in enumerate((0.25, 0.5, 0.75))]
    return exact.select(close.alias("distinct_close"), (ranks[0] & ranks[1] & ranks[2]).alias("quartiles_close"))


@query("q62b_shuffle_hash_join", "SELECT s.path_id, s.length, o.o_custkey AS agent FROM (SELECT path_id, count(*) AS length FROM steps_part GROUP BY path_id) s JOIN orders o ON o.o_orderkey = s.path_id")
def q62b(spark, d):
    """The smaller side is hashed within each partition, so neither side is sorted."""
    length = trajectories.path_lengths(workloads.order_steps(spark, d)).hint("shuffle_hash")
    return length.join(load(spark, d, "orders").select(F.col("o_orderkey").alias("path_id"), F.col("o_custkey").alias("agent")), "path_id")


@query("q60b_theta_nested_loop", "SELECT event_id, b.name AS band FROM clicks, (VALUES ('rise', 1.0, 0.0), ('flat', 0.0, 20.0), ('fall', -1.0, 45.0)) b(name, slope, base) WHERE value > slope * node_id + base")
def q60b(spark, d):
    """A join on an inequality alone; the small side is three literal rows, which is what makes a nested loop right."""
    lines = spark.createDataFrame([("rise", 1.0, 0.0), ("flat", 0.0, 20.0), ("fall", -1.0, 45.0)], "name string, slope double, base double")
    rows = tables.clicks(load(spark, d, "events"))
    return rows.join(F.broadcast(lines), F.col("value") > F.col("slope") * F.col("node_id") + F.col("base")).select("event_id", F.col("name").alias("band"))


# ---------------------------------------------------------------- streams


@query(
    "q73b_stream_sliding",
    """SELECT node_id, strftime(make_timestamp(w), '%Y-%m-%d %H:%M:%S.%f') AS start, count(*) AS n FROM
        (SELECT node_id, (us // 21600000000) * 21600000000 - k * 21600000000 AS w FROM clicks, (VALUES (0), (1), (2), (3)) v(k)) x, mark WHERE make_timestamp(w) + INTERVAL 1 DAY <= cutoff GROUP BY node_id, w""",
    _CLOSED,
)
def q73b(spark, d):
    return stream.replay(stream.visit_windows(stream.stream_events(spark, d), size="1 day", slide="6 hours")).select("node_id", _text("start"), "n")


_LATE = {
    "dealt": f"SELECT *, {hash8(chr(39) + 'batch|' + chr(39) + ' || event_id')} % 4 AS batch, date_trunc('day', ts) + INTERVAL 1 DAY AS closes FROM clicks",
    # A batch drops by the mark of the batch before it, which rests on the batches before that.
    "marks": "SELECT b.batch, max(e.ts) - INTERVAL 1 HOUR AS mark FROM (SELECT DISTINCT batch FROM dealt) b LEFT JOIN dealt e ON e.batch < b.batch - 1 GROUP BY b.batch",
}


@query(
    "q74_stream_late",
    """SELECT event_type, CAST(sum(CASE WHEN m.mark IS NULL OR closes > m.mark THEN 1 ELSE 0 END) AS BIGINT) AS kept, CAST(sum(CASE WHEN closes <= m.mark THEN 1 ELSE 0 END) AS BIGINT) AS dropped
       FROM dealt JOIN marks m ON m.batch = dealt.batch GROUP BY event_type""",
    _LATE,
)
def q74(spark, d):
    """The events dealt to four files in no order of time, a file a batch: what comes after its day has closed is dropped."""
    folder = stream.shuffled_files(load(spark, d, "events"), 4)
    rows = stream.file_batches(spark, folder)
    counted = rows.groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count("*").alias("n"))
    counted = counted.select(F.col("w.start").alias("start"), "event_type", "n")
    kept = stream.latest(stream.replay(counted, mode="update"), ["start", "event_type"]).groupBy("event_type").agg(F.sum("n").alias("kept"))
    return tables.clicks(load(spark, d, "events")).groupBy("event_type").agg(F.count("*").alias("_all")).join(kept, "event_type", "left").select("event_type", F.coalesce("kept", F.lit(0)).alias("kept"), (F.col("_all") - F.coalesce("kept", F.lit(0))).alias("dropped"))
