"""Streams over files that arrive one by one: late rows, restarts, and the stateful operators."""

import datetime as dt

import pytest
from pyspark.sql import functions as F

from hyperpath.operators.graph import transitions
from hyperpath.streaming import events as stream

DAY = dt.datetime(2024, 1, 1)


def arrive(spark, folder, n, rows):
    """File n of the table: rows are (event id, hours, user, node)."""
    data = [(e, DAY + dt.timedelta(hours=h), u, "view", 1.0, f'{{"k": {k}}}') for e, h, u, k in rows]
    spark.createDataFrame(data, stream.EVENT_SCHEMA).coalesce(1).write.mode("append").parquet(f"{folder}/{n}")


def reading(spark, folder, watermark="1 hour"):
    rows = spark.readStream.schema(stream.EVENT_SCHEMA).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").option("pathGlobFilter", "*.parquet").parquet(str(folder))
    return stream.shaped(rows).withWatermark("ts", watermark)


def drain(df, folder, mode="append"):
    """One run over what has arrived, with a checkpoint that the next run goes on from."""
    df.writeStream.outputMode(mode).option("checkpointLocation", f"{folder}/checkpoint").format("parquet").option("path", f"{folder}/out").trigger(availableNow=True).start().awaitTermination()
    return df.sparkSession.read.parquet(f"{folder}/out")


def test_late_rows_are_dropped_and_a_restart_goes_on(spark, tmp_path):
    source, sink = tmp_path / "in", tmp_path / "sink"
    arrive(spark, source, 1, [(1, 0, 7, 5), (2, 1, 7, 5)])
    visits = lambda: stream.visit_windows(reading(spark, source), size="6 hours").withColumn("start", F.date_format("start", "HH"))
    drain(visits(), sink)
    arrive(spark, source, 2, [(3, 20, 7, 5)])
    drain(visits(), sink)
    arrive(spark, source, 3, [(4, 2, 7, 5), (5, 40, 7, 5)])  # the first is 18 hours late: its window is closed
    drain(visits(), sink)
    arrive(spark, source, 4, [(6, 41, 7, 6)])
    got = sorted((r["node_id"], r["start"], r["n"]) for r in drain(visits(), sink).collect())
    assert got == [(5, "00", 2), (5, "18", 1)]


@pytest.mark.parametrize("how", ["list", "processor"])
def test_previous_node_state_equals_batch(spark, tmp_path, how):
    source, sink = tmp_path / "in", tmp_path / "sink"
    rows = [(i, i, i % 3, (i * 7) % 5) for i in range(30)]
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider" if how == "processor" else "org.apache.spark.sql.execution.streaming.state.HDFSBackedStateStoreProvider")
    try:
        for n, part in enumerate((rows[:10], rows[10:])):
            arrive(spark, source, n, part)
            live = reading(spark, source)
            moves = stream.moves(live) if how == "processor" else stream.moves_by_list(spark, live)
            got = drain(moves, sink)
    finally:
        spark.conf.unset("spark.sql.streaming.stateStore.providerClass")
    steps = spark.createDataFrame([(u, e, k) for e, _, u, k in rows], "path_id long, step int, node_id long")
    want = sorted((r["src"], r["dst"]) for r in transitions(steps).collect())
    assert sorted((r["src"], r["dst"]) for r in got.collect()) == want


def test_duplicates_within_the_watermark(spark, tmp_path):
    arrive(spark, tmp_path / "in", 1, [(1, 0, 7, 5), (2, 1, 7, 5), (3, 2, 8, 5)])
    got = drain(stream.first_visits(reading(spark, tmp_path / "in", "2 days")), tmp_path / "sink")
    assert sorted((r["agent"], r["node_id"]) for r in got.collect()) == [(7, 5), (8, 5)]
