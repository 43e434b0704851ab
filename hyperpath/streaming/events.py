"""Structured Streaming over the events table: incremental clicks, sessions, windows, late data, prediction, joins, dedup.

The time column is a timestamp without zone, which watermarks refuse; it is cast, so run with session time zone UTC. Every
operator takes the stream and gives a stream; replay() runs one over all files that are there and returns what it wrote.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from ..operators.store import shared_dir

EVENT_SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def stream_events(spark: SparkSession, sf_dir: str, *, watermark: str = "1 hour") -> DataFrame:
    rows = spark.readStream.schema(EVENT_SCHEMA).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return shaped(rows).withWatermark("ts", watermark)


def shuffled_files(events: DataFrame, n: int) -> str:
    """Write events to n files by the hash of their id, one after the other; the folder they are in."""
    import uuid

    from ..functions.columns import hash8

    path = f"{shared_dir(events.sparkSession)}/files-{uuid.uuid4().hex}"
    for i in range(n):
        events.where(hash8(F.lit("batch"), F.col("event_id")) % n == i).coalesce(1).write.parquet(f"{path}/b={i}")
    return path


def file_batches(spark: SparkSession, folder: str, *, watermark: str = "1 hour") -> DataFrame:
    """The events of a folder, a file a batch, oldest file first."""
    rows = spark.readStream.schema(EVENT_SCHEMA).option("maxFilesPerTrigger", 1).parquet(f"{folder}/*")
    return shaped(rows).withWatermark("ts", watermark)


def shaped(events: DataFrame) -> DataFrame:
    """event_id, ts (with zone), agent, event_type, value, node_id; the same for batch and stream."""
    return events.select("event_id", F.col("ts").cast("timestamp").alias("ts"), F.col("user_id").alias("agent"), "event_type", "value", F.get_json_object("props", "$.k").cast("long").alias("node_id"))


def replay(stream: DataFrame, *, mode: str = "append", tag: str = "stream") -> DataFrame:
    """Run over what is there and return the result as a batch table, written with a checkpoint to the shared folder.

    update and complete mode go through foreachBatch, each batch in a folder of its own, so that a retried batch overwrites itself.
    """
    import uuid

    spark = stream.sparkSession
    path = f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{path}/checkpoint").trigger(availableNow=True)
    if mode == "append":
        writer.format("parquet").option("path", f"{path}/out").start().awaitTermination()
    else:
        def save(batch: DataFrame, batch_id: int) -> None:
            batch.withColumn("batch_id", F.lit(batch_id)).write.mode("overwrite").parquet(f"{path}/out/b={batch_id}")

        writer.foreachBatch(save).start().awaitTermination()
        return spark.read.schema(f"{_ddl(stream)}, batch_id int").parquet(f"{path}/out/*")
    return spark.read.schema(_ddl(stream)).parquet(f"{path}/out")


def _ddl(df: DataFrame) -> str:
    return ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema.fields)


def latest(updates: DataFrame, keys: list[str]) -> DataFrame:
    """Of the rows an update stream wrote, the last of each key."""
    order = Window.partitionBy(*keys).orderBy(F.desc("batch_id"))
    return updates.withColumn("_r", F.row_number().over(order)).where("_r = 1").drop("_r", "batch_id")


class PreviousNode(StatefulProcessor):
    """Per agent, the node of the last event; emits a move for each event after the first. Rows of a batch are sorted by id."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.last = handle.getValueState("last", "node_id long")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timer_values) -> Iterator[pd.DataFrame]:
        frame = pd.concat(list(rows)).sort_values("event_id")
        nodes = frame["node_id"].tolist()
        held = self.last.get() if self.last.exists() else None
        before = [held[0] if held is not None else None, *nodes[:-1]]
        self.last.update((int(nodes[-1]),))
        moves = [(a, b) for a, b in zip(before, nodes, strict=True) if a is not None and a != b]
        yield pd.DataFrame({"src": pd.Series([a for a, _ in moves], dtype="int64"), "dst": pd.Series([b for _, b in moves], dtype="int64")})

    def close(self) -> None:
        pass


def moves(stream: DataFrame) -> DataFrame:
    """(src, dst) of each agent's consecutive events."""
    return stream.select("agent", "event_id", "node_id").groupBy("agent").transformWithStateInPandas(PreviousNode(), "src long, dst long", "append", "none")


def moves_by_list(spark: SparkSession, stream: DataFrame) -> DataFrame:
    """The same with applyInPandasWithState, where the state store that the other needs isn't set up."""
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def step(key, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        frame = pd.concat(list(frames)).sort_values("event_id")
        nodes = frame["node_id"].tolist()
        before = [state.get[0] if state.exists else None, *nodes[:-1]]
        state.update((int(nodes[-1]),))
        pairs = [(a, b) for a, b in zip(before, nodes, strict=True) if a is not None and a != b]
        yield pd.DataFrame({"src": pd.Series([a for a, _ in pairs], dtype="int64"), "dst": pd.Series([b for _, b in pairs], dtype="int64")})

    rows = stream.select("agent", "event_id", "node_id")
    return rows.groupBy("agent").applyInPandasWithState(step, "src long, dst long", "node_id long", "append", GroupStateTimeout.NoTimeout)


def sessions(stream: DataFrame, *, gap: str = "12 hours") -> DataFrame:
    """(agent, start, stop, n) of sessions that have ended by the watermark."""
    return stream.groupBy("agent", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n")).select("agent", F.col("w.start").alias("start"), F.col("w.end").alias("stop"), "n")


def visit_windows(stream: DataFrame, *, size: str = "1 day", slide: str | None = None) -> DataFrame:
    """(node_id, start, n): visits per node in tumbling, or with slide sliding, windows."""
    return stream.groupBy("node_id", F.window("ts", size, slide).alias("w")).agg(F.count("*").alias("n")).select("node_id", F.col("w.start").alias("start"), "n")


def interval_join(stream: DataFrame, other: DataFrame, *, hours: int = 24) -> DataFrame:
    """(first_id, second_id): views followed by a purchase of the same agent within some hours; both sides have watermarks."""
    a = stream.where("event_type = 'view'").select(F.col("event_id").alias("first_id"), F.col("agent").alias("a1"), F.col("ts").alias("t1"))
    b = other.where("event_type = 'purchase'").select(F.col("event_id").alias("second_id"), F.col("agent").alias("a2"), F.col("ts").alias("t2"))
    return a.join(b, F.expr(f"a1 = a2 AND t2 > t1 AND t2 <= t1 + INTERVAL {hours} HOURS")).select("first_id", "second_id")


def first_visits(stream: DataFrame) -> DataFrame:
    """(agent, node_id): a node re-visited within the watermark is dropped."""
    return stream.dropDuplicatesWithinWatermark(["agent", "node_id"]).select("agent", "node_id", "event_id")


def predict_next(stream: DataFrame, weights: DataFrame, *, k: int = 3) -> DataFrame:
    """(event_id, node_id, rank) : the k heaviest exits of each event's node, by a stream-static join with ranked weights(src, dst, rank)."""
    best = weights.where(F.col("rank") <= k).select(F.col("src").alias("node_id"), "dst", "rank")
    return stream.select("event_id", "node_id").join(best, "node_id").select("event_id", "dst", "rank")
