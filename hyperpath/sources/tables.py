"""Reading the given tables, and adapters that turn them into trajectories and links."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One table; projections and filters on it reach the Parquet scan."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def micros(ts: str) -> Column:
    """Microseconds of a timestamp without zone, whatever the session's time zone."""
    return F.expr(f"timestampdiff(MICROSECOND, TIMESTAMP_NTZ '1970-01-01 00:00:00', `{ts}`)")


def clicks(events: DataFrame) -> DataFrame:
    """event_id, us, agent, event_type, value, node_id of the events table."""
    node = F.get_json_object("props", "$.k").cast("long")
    return events.select("event_id", micros("ts").alias("us"), F.col("user_id").alias("agent"), "event_type", "value", node.alias("node_id"))


def _without_repeats(rows: DataFrame, order: list) -> DataFrame:
    """rows(path_id, node_id, ...) in order within a path, without consecutive repeats, numbered by step from 0.

    Both windows share the partitioning by path_id, so there is one shuffle.
    """
    by_path = Window.partitionBy("path_id").orderBy(*order)
    fresh = rows.withColumn("_before", F.lag("node_id").over(by_path)).where("_before is null or _before <> node_id")
    return fresh.withColumn("step", (F.row_number().over(by_path) - 1).cast("int")).drop("_before")


def from_orders(lineitem: DataFrame, *, node: str = "part", min_len: int = 4, max_len: int = 7) -> DataFrame:
    """steps(path_id, step, node_id): the parts, or suppliers, of an order's lines; orders of min_len to max_len lines."""
    key = {"part": "l_partkey", "supplier": "l_suppkey"}[node]
    order = ["l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice"]
    rows = lineitem.select(F.col("l_orderkey").alias("path_id"), *order, F.col(key).alias("node_id"))
    rows = rows.withColumn("_n", F.count("*").over(Window.partitionBy("path_id"))).where(F.col("_n").between(min_len, max_len))
    return _without_repeats(rows, order).select("path_id", "step", "node_id")


def from_events(events: DataFrame, *, gap_hours: float = 12) -> DataFrame:
    """steps(path_id, agent, step, node_id, outcome): a user's events until a gap of more than gap_hours.

    path_id is the id of the session's first event; a session is completed if its last event is a purchase,
    abandoned if it is an error, else open.
    """
    rows = clicks(events).drop("value")
    by_user = Window.partitionBy("agent").orderBy("us", "event_id")
    starts = rows.withColumn("_start", F.when(F.coalesce(F.col("us") - F.lag("us").over(by_user) > int(gap_hours * 3_600_000_000), F.lit(True)), F.col("event_id")))
    starts = starts.withColumn("path_id", F.last("_start", ignorenulls=True).over(by_user))
    ends = Window.partitionBy("agent", "path_id").orderBy("us", "event_id").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    last = F.last("event_type").over(ends)
    named = starts.withColumn("outcome", F.when(last == "purchase", "completed").when(last == "error", "abandoned").otherwise("open"))
    steps = _without_repeats(named.where("node_id is not null"), ["us", "event_id"])
    return steps.select("path_id", "agent", "step", "node_id", "outcome")


def from_conversations(conversations: DataFrame) -> DataFrame:
    """steps over the three-node graph of roles: 0 system, 1 user, 2 assistant."""
    role = F.when(F.col("role") == "system", 0).when(F.col("role") == "user", 1).otherwise(2).cast("long")
    rows = conversations.select(F.col("conv_id").alias("path_id"), "turn", role.alias("node_id"))
    return _without_repeats(rows, ["turn"]).select("path_id", "step", "node_id")
