"""Chat formatting of reply trees.

Messages form trees by a parent id. Self-joins of pointer tables that double their reach each round give every message
its root, depth and the score of the branch above it, in as many rounds as the depth has binary digits; the leaves of a
root are ranked by branch score, and the chosen root-to-leaf paths are enumerated by the same tables. Each path is
formatted as one conversation: turns are marked, control strings inside texts are escaped so that they can be read back,
and the spans under the loss mask (assistant texts) are noted.

A path is formatted as a stream of its rows, sorted by depth.

Defined results: a null text is an empty text and a null role is an empty role; messages whose parent is missing are
roots; messages on a cycle have no root and are in no path; ties of score go to the smaller leaf id; turns of equal
number are ordered by role and text; repeated rows are turns of their own.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import materialize

#: The template's control strings.
OPEN, CLOSE = "<|im_start|>", "<|im_end|>"
#: Every "<|", with any run of "~" between, gets one "~" more; so no text holds a control string, and all can be read back.
_ESCAPE, _UNESCAPE = re.compile(r"<(~*)\|"), re.compile(r"<~(~*)\|")
#: Line feeds in a role would end it early.
_ROLE_ESCAPES = (("%", "%25"), ("\n", "%0A"), ("\r", "%0D"))


def escape(text: str) -> str:
    return _ESCAPE.sub(r"<~\1|", text)


def unescape(text: str) -> str:
    return _UNESCAPE.sub(r"<\1|", text)


def format_turn(role: str, text: str) -> str:
    for a, b in _ROLE_ESCAPES:
        role = role.replace(a, b)
    return f"{OPEN}{escape(role)}\n{escape(text)}{CLOSE}\n"


def read_turns(formatted: str) -> Iterator[tuple[str, str, tuple[int, int]]]:
    """(role, text, span of the escaped text) of each turn."""
    at = 0
    while at < len(formatted):
        if not formatted.startswith(OPEN, at):
            raise ValueError(f"no turn starts at {at}")
        line = formatted.index("\n", at)
        stop = formatted.index(CLOSE + "\n", line)
        role = unescape(formatted[at + len(OPEN) : line])
        for a, b in reversed(_ROLE_ESCAPES):
            role = role.replace(b, a)
        yield role, unescape(formatted[line + 1 : stop]), (line + 1, stop)
        at = stop + len(CLOSE) + 1


# ---------------------------------------------------------------- trees


def _jump_tables(nodes: DataFrame) -> tuple[DataFrame, list[DataFrame]]:
    """(node, root, depth, total), and for each j the table (node, up): the message 2**j above."""
    state = materialize(
        nodes.select("node", F.col("parent").alias("up"), F.lit(1).cast("long").alias("hops"), F.col("score").alias("total")), "jump"
    )
    tables: list[DataFrame] = []
    n = state.count()
    done = state.where("up is null").select("node", F.col("node").alias("root"), F.lit(0).cast("long").alias("depth"), "total")
    state = state.where("up is not null")
    while not state.isEmpty():
        tables.append(state.select("node", "up"))
        # What lies above: either still going up (its own state) or finished.
        above = state.select(F.col("node").alias("up"), F.col("up").alias("next"), F.lit(None).cast("long").alias("root"), F.col("hops").alias("more"), F.col("total").alias("plus")).unionByName(
            done.select(F.col("node").alias("up"), F.lit(None).cast("long").alias("next"), "root", F.col("depth").alias("more"), F.col("total").alias("plus"))
        )
        joined = materialize(
            state.join(above, "up").select("node", F.col("next").alias("up"), "root", (F.col("hops") + F.col("more")).alias("hops"), (F.col("total") + F.col("plus")).alias("total")), "jump"
        )
        done = materialize(done.unionByName(joined.where("root is not null").select("node", "root", F.col("hops").alias("depth"), "total")), "rooted")
        state = joined.where("up is not null").drop("root")
        if 1 << len(tables) > n:  # longer than any path: what is left runs in cycles
            break
    return done, tables


def best_paths(messages: DataFrame, *, top: int = 1) -> DataFrame:
    """messages(node, parent, score) -> (path, root, rank, depth, node): the top branches of each root, row by row.

    A branch's score is the sum of its messages' scores; path is the id of its leaf.
    """
    clean = messages.select("node", "parent", F.coalesce(F.col("score").cast("double"), F.lit(0.0)).alias("score"))
    known = clean.select(F.col("node").alias("parent"), F.lit(True).alias("known"))
    nodes = clean.join(known, "parent", "left").select("node", F.when(F.col("known"), F.col("parent")).alias("parent"), "score")
    rooted, tables = _jump_tables(materialize(nodes, "tree"))
    leaves = rooted.join(clean.select(F.col("parent").alias("node")).where("node is not null").distinct(), "node", "left_anti")
    order = Window.partitionBy("root").orderBy(F.desc("total"), "node")
    chosen = leaves.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= top)
    rows = materialize(chosen.select(F.col("node").alias("path"), "root", "rank", "depth", "node"), "paths")
    for j in range(len(tables) - 1, -1, -1):  # every distance above the leaf is one sum of powers of two
        up = rows.join(tables[j], "node").select("path", "root", "rank", (F.col("depth") - (1 << j)).alias("depth"), F.col("up").alias("node"))
        rows = materialize(rows.unionByName(up), "paths")
    return rows


def conversation_messages(conversations: DataFrame, *, conv_col: str = "conv_id", turn_col: str = "turn", role_col: str = "role", text_col: str = "text") -> DataFrame:
    """A conversation as a chain of replies: (node, parent, score, conv, role, text); each turn answers the one before it."""
    rows = conversations.select(
        F.col(conv_col).alias("conv"), F.col(turn_col).alias("turn"), F.coalesce(F.col(role_col), F.lit("")).alias("role"), F.coalesce(F.col(text_col), F.lit("")).alias("text")
    )
    rows = materialize(rows.withColumn("node", F.monotonically_increasing_id()), "messages")
    order = Window.partitionBy("conv").orderBy(F.col("turn").asc_nulls_first(), "role", "text", "node")
    links = rows.select("node", F.lag("node").over(order).alias("parent"))
    return rows.join(links, "node").withColumn("score", F.lit(1.0))


def format_paths(paths: DataFrame, messages: DataFrame) -> DataFrame:
    """One row per path: conv, path, n_turns, formatted, loss_spans (start, end in formatted, escaped text)."""
    lines = paths.join(messages.select("node", "conv", "role", "text"), "node").select("conv", "path", "depth", "role", "text")
    dealt = lines.repartition("path").sortWithinPartitions("path", "depth")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, conv, parts, spans, at = None, None, [], [], 0
        out: list[tuple] = []
        for batch in batches:
            for c, path, _, role, text in zip(*(x.to_pylist() for x in batch.columns), strict=True):
                if path != now:
                    if parts:
                        out.append((conv, now, len(parts), "".join(parts), spans))
                    now, conv, parts, spans, at = path, c, [], [], 0
                turn = format_turn(role, text)
                if role == "assistant":
                    start = at + turn.index("\n") + 1
                    spans.append({"start": start, "end": at + len(turn) - len(CLOSE) - 1})
                at += len(turn)
                parts.append(turn)
            if out:
                yield pack(out)
                out = []
        if parts:
            yield pack([*out, (conv, now, len(parts), "".join(parts), spans)])

    def pack(rows: list[tuple]) -> pa.RecordBatch:
        kinds = (pa.int64(), pa.int64(), pa.int64(), pa.large_string() if big else pa.string(), pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())])))
        names = ("conv", "path", "n_turns", "formatted", "loss_spans")
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=list(names))

    big = paths.sparkSession.conf.get("spark.sql.execution.arrow.useLargeVarTypes", "false") == "true"
    return dealt.mapInArrow(run, "conv long, path long, n_turns long, formatted string, loss_spans array<struct<start:long,end:long>>")


def format_conversations(conversations: DataFrame, *, top: int = 1, **columns: str) -> DataFrame:
    """Every conversation as one formatted text; see format_paths."""
    messages = materialize(conversation_messages(conversations, **columns), "messages")
    return format_paths(best_paths(messages.select("node", "parent", "score"), top=top), messages)


def read_back(formatted: DataFrame) -> DataFrame:
    """From the formatted texts and their spans alone: turns and loss digests."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for conv, text, spans in zip(*(x.to_pylist() for x in batch.columns), strict=True):
                turns, loss, n, chars = hashlib.sha256(), hashlib.sha256(), 0, 0
                for role, said, _ in read_turns(text):
                    turns.update(f"{role}\n{said}\n".encode("utf-8", "surrogatepass"))
                    n += 1
                for s in spans:
                    said = unescape(text[s["start"] : s["end"]])
                    loss.update(said.encode("utf-8", "surrogatepass"))
                    chars += len(said)
                out.append((conv, n, turns.hexdigest(), chars, loss.hexdigest(), len(text)))
            kinds = (pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64())
            names = ["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out, strict=True) if out else [()] * 6, kinds, strict=True)], names=names)

    return formatted.select("conv", "formatted", "loss_spans").mapInArrow(
        run, "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long"
    )
