"""Shared pieces of the text operators: word rules, shared storage, hashing, graph components."""

from __future__ import annotations

import atexit
import ctypes
import os
import shutil
import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: A word is a run of anything but ASCII blank, tab, \n, \v, \f, \r.
WORD_PATTERN = r"[^\x20\x09-\x0D]+"
#: Java regex for the gaps between words.
GAP_PATTERN = r"[\x20\x09-\x0D]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

SHINGLE_WORDS = 5
SIMILARITY = 0.75

IS_GAP = np.zeros(256, dtype=bool)
IS_GAP[[9, 10, 11, 12, 13, 32]] = True
ASCII_LOWER = np.arange(256, dtype=np.uint8)
ASCII_LOWER[65:91] += 32

_made: list[str] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir, or one of our own where that is unset (local runs)."""
    root = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        root = held.get() if held.isDefined() else None
    if not root:
        root = "file://" + tempfile.mkdtemp(prefix="hyperpath-")
        _made.append(root[7:])
        spark.sparkContext.setCheckpointDir(root)
    return root.rstrip("/")


@atexit.register
def _sweep() -> None:
    for path in _made:
        shutil.rmtree(path, ignore_errors=True)


def shared_path(spark: SparkSession, tag: str) -> str:
    path = f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"
    if path.startswith(("file:/", "/")):
        _made.append("/" + path.removeprefix("file:").lstrip("/"))
    return path


def materialize(df: DataFrame, tag: str = "stage") -> DataFrame:
    """Write df as Parquet to the shared folder and read it back: the lineage ends there, lost executors lose nothing."""
    spark = df.sparkSession
    path = shared_path(spark, tag)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def drop_materialized(df: DataFrame) -> None:
    """Delete what materialize() wrote for df, when no later plan reads it (local or shared mounts only)."""
    for f in df.inputFiles()[:1]:
        folder = os.path.dirname(f.removeprefix("file:").replace("///", "/"))
        if folder in _made:
            shutil.rmtree(folder, ignore_errors=True)


def trimmed(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """run for mapInArrow; what it freed goes back to the system when it ends. Python workers wait for more tasks, and would hold it beside those that work."""

    def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from run(batches)
        finally:
            release_memory()

    return whole


def release_memory() -> None:
    pa.default_memory_pool().release_unused()
    if trim := getattr(ctypes.CDLL(None), "malloc_trim", None):  # glibc only
        trim(0)


def with_row_key(df: DataFrame, name: str) -> DataFrame:
    """A unique key per row, the same in every evaluation of a scan: partition number and place in it."""
    return df.withColumn(name, F.monotonically_increasing_id())


def ranked(df: DataFrame, order: list[str], name: str) -> DataFrame:
    """df with its global rank from 0 in this order: ranges are sorted on their own, then counts of the ranges before are added."""
    own = materialize(df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("_at", F.monotonically_increasing_id()), "ranked")
    part, place = F.shiftright("_at", 33), F.col("_at").bitwiseAND(F.lit((1 << 33) - 1))
    sizes = own.groupBy(part.alias("_part")).agg(F.max(place).alias("_last"))  # a row per range
    before = sizes.select("_part", F.coalesce(F.sum(F.col("_last") + 1).over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_before"))
    return own.withColumn("_part", part).join(F.broadcast(before), "_part").withColumn(name, F.col("_before") + place).drop("_at", "_part", "_before")


#: Keys that hold a larger part of the rows than one in so many are joined by broadcast: there are no more of them than this.
HOT_KEYS, HOT_LEAST = 2000, 500


def hot_join(left: DataFrame, right: DataFrame, by: list[str], count: str) -> DataFrame:
    """left joined with right, which has one row per key and, in count, the rows of left with that key. No task gets a hot key's rows:
    those keys, whose number is bounded by their size, are broadcast, and only the others are shuffled. Both sides are read twice."""
    total = right.agg(F.coalesce(F.sum(count), F.lit(0))).first()[0]
    large = F.col(count) > max(HOT_LEAST, total // HOT_KEYS)
    hot, others = F.broadcast(right.where(large).drop(count)), right.where(~large).drop(count)
    return left.join(hot, by).unionByName(left.join(F.broadcast(right.where(large).select(*by)), by, "left_anti").join(others, by))


def free_name(df: DataFrame, base: str) -> str:
    """base, or base with underscores before it, so that it clashes with no column of df (any case)."""
    taken = {c.lower() for c in df.columns}
    while base.lower() in taken:
        base = "_" + base
    return base


# ---------------------------------------------------------------- hashing in numpy

_U = np.uint64
_BASE, _STEP = _U(0x9E3779B97F4A7C15 | 1), _U(0xD6E8FEB86659FD93 | 1)
_INV_BASE = _U(pow(int(_BASE), -1, 1 << 64))
_powers: dict[str, np.ndarray] = {}


def _power(which: str, n: int) -> np.ndarray:
    held = _powers.get(which)
    if held is None or len(held) < n:
        base = _BASE if which == "up" else _INV_BASE
        grown = np.full(max(n, 1 << 16), base, dtype=np.uint64)
        grown[0] = 1
        held = _powers[which] = np.multiply.accumulate(grown)
    return held[:n]


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser."""
    x = x ^ (x >> _U(30))
    x = x * _U(0xBF58476D1CE4E5B9)
    x = x ^ (x >> _U(27))
    x = x * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


_BYTE = mix64(np.arange(1, 257, dtype=np.uint64) * _U(0x9E3779B97F4A7C15))


def word_bounds(raw: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Byte offsets at which the words of a text start and end."""
    inside = np.zeros(len(raw) + 2, dtype=np.int8)
    inside[1:-1] = ~IS_GAP[raw]
    edge = np.diff(inside)
    return np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)


def word_hashes(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit hash of each word, by one rolling polynomial over the text."""
    sums = np.zeros(len(raw) + 1, dtype=np.uint64)
    np.cumsum(_BYTE[raw] * _power("up", len(raw)), out=sums[1:])
    return mix64((sums[ends] - sums[starts]) * _power("down", len(raw) + 1)[starts] + (ends - starts).astype(np.uint64))


def roll(words: np.ndarray, n: int) -> np.ndarray:
    """Rolling hash of each run of n word hashes."""
    if len(words) < n:
        return words[:0]
    out = words[: len(words) - n + 1].copy()
    for j in range(1, n):
        out = out * _STEP + words[j : len(words) - n + 1 + j]
    return mix64(out)


def shingle_set(text: bytes, n: int = SHINGLE_WORDS) -> np.ndarray:
    """Sorted distinct hashes of the n-word shingles of a text, A-Z lower-cased; all words as one if fewer than n."""
    raw = ASCII_LOWER[np.frombuffer(text, dtype=np.uint8)]
    starts, ends = word_bounds(raw)
    if not len(starts):
        return np.empty(0, dtype=np.uint64)
    words = word_hashes(raw, starts, ends)
    return np.unique(roll(words, min(n, len(words))) if len(words) >= n else roll(words, len(words)) ^ _U(len(words)))


# ---------------------------------------------------------------- components


def components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, component): the smallest node reachable over undirected edges, for every node that has an edge.

    Each round hooks every root to its smallest neighbouring root (partial aggregation, so that a hub costs one
    row per task), halves the chains, and rewrites the edges to roots; all tables are written between rounds.
    """
    edges = materialize(
        edges.select(F.least(a, b).alias("a"), F.greatest(a, b).alias("b")).where("a <> b").distinct(), "edges"
    )
    label = None
    while not edges.isEmpty():
        both = edges.select(F.col("a").alias("node"), F.col("b").alias("to")).union(edges.select("b", "a"))
        hook = materialize(both.groupBy("node").agg(F.least("node", F.min("to")).alias("up")), "hook")
        while True:
            above = hook.select(F.col("node").alias("up"), F.col("up").alias("top"))
            jumped = materialize(hook.join(above, "up").select("node", F.col("top").alias("up"), (F.col("top") != F.col("up")).alias("moved")), "jump")
            more = not jumped.where("moved").isEmpty()
            hook = jumped.select("node", "up")
            if not more:
                break
        if label is None:
            label = hook
        else:
            root = hook.select(F.col("node").alias("up"), F.col("up").alias("top"))
            label = materialize(label.join(root, "up", "left").select("node", F.coalesce("top", "up").alias("up")), "label")
        ra, rb = (hook.select(F.col("node").alias(x), F.col("up").alias(f"r{x}")) for x in "ab")
        edges = materialize(
            edges.join(ra, "a").join(rb, "b").where("ra <> rb")
            .select(F.least("ra", "rb").alias("a"), F.greatest("ra", "rb").alias("b")).distinct(),
            "edges",
        )
    if label is None:
        return edges.select(F.col("a").alias("node"), F.col("b").alias("component"))
    return label.select("node", F.col("up").alias("component"))
