"""Line dedup: runs of lines that occur earlier in the corpus are deleted from their later copies.

Each text is a sequence of line ids; blank lines are not part of it. Equal lines get one id, lines found once none, as no repeated run
holds them. Prefix doubling over the whole corpus then ranks longer runs: the rank of a run of 2**(k+1) lines is that of the pair of ranks
of its halves, and pairs found once drop out, so each round is two joins over ever fewer places. Places of equal rank are an interval
of the suffix array whose common prefix has 2**k lines at least; the interval of a length between two powers is that of a pair of ranks that
overlap. The smallest document id of an interval has the first copy, and the others are later ones.

A run counts if it has min_words words. It is enough to look at the shortest runs that do, from each line on and up to each line: a line
in a longer repeated run that counts is in such a short one inside it, and the maximal repeated runs are what these cover together.
No more than min_words lines are in one, so the rounds end with the longest of them. Earlier means in a document of smaller id, or further
up in the same text.

Defined results: a null text stays null; a null id counts as the largest; rows of equal id are one document, so their lines
are no copies of each other; lines are compared as they are; a blank line goes if the lines with words before and after it go; a document that
loses its last line with a word is left out (keep_empty keeps it with what blank lines it has left). Columns of any name are kept.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import IS_GAP, drop_materialized, free_name, hot_join, materialize, trimmed

MIN_WORDS = 10
_LAST = (1 << 63) - 1
_BLANK = bytes(i for i in range(256) if IS_GAP[i])
#: A place packs the number of the line and the lines of the shortest runs from it on and up to it, 16 bits each; more words than this
#: can't be asked for.
LARGEST = (1 << 16) - 1


def shortest_runs(words: list[int], least: int) -> tuple[list[int], list[int]]:
    """Lines of the shortest run with least words from each line on, and up to each line; 0 where there is none."""
    n = len(words)
    ahead, behind = [0] * n, [0] * n
    total = end = 0
    for i in range(n):
        while end < n and total < least:
            total += words[end]
            end += 1
        if total < least:
            break
        ahead[i] = end - i
        total -= words[i]
    total, start = 0, 0
    for i in range(n):
        total += words[i]
        while total - words[start] >= least:
            total -= words[start]
            start += 1
        behind[i] = i - start + 1 if total >= least else 0
    return ahead, behind


def _sequence(text: bytes) -> tuple[list[bytes], list[int], list[int]]:
    """All lines; which of them have words, and how many."""
    lines = text.split(b"\n")
    words = [len(x.split()) for x in lines]
    at = [i for i, w in enumerate(words) if w]
    return lines, at, [words[i] for i in at]


def _keys(docs: DataFrame, id_col: str, text_col: str) -> list:
    """Document and row: rows of one document with equal texts are the same."""
    doc = F.coalesce(F.col(f"`{id_col}`").cast("long"), F.lit(_LAST))
    return [doc, F.xxhash64(doc, F.col(f"`{text_col}`"))]


def line_places(docs: DataFrame, *, id_col: str, text_col: str, min_words: int) -> DataFrame:
    """(doc, row, place, a, b): the lines with words, in 128 bits; place as LARGEST says."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: list[list] = [[], [], [], [], []]

            def flush(out: list[list] = out) -> pa.RecordBatch:
                return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in out], names=["doc", "row", "place", "a", "b"])

            for doc, row, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2).cast(pa.binary()).to_pylist(), strict=True):
                if not text:
                    continue
                lines, at, words = _sequence(text)
                ahead, behind = shortest_runs(words, min_words)
                for i, line in enumerate(at):
                    name = xxhash.xxh3_128_digest(lines[line])
                    out[2].append(i << 32 | ahead[i] << 16 | behind[i])
                    out[3].append(int.from_bytes(name[:8], "little", signed=True))
                    out[4].append(int.from_bytes(name[8:], "little", signed=True))
                out[0] += [doc] * len(at)
                out[1] += [row] * len(at)
                if len(out[0]) > 200_000:
                    yield flush()
                    for c in out:
                        c.clear()
            if out[0]:
                yield flush()

    doc, row = _keys(docs, id_col, text_col)
    return docs.select(doc.alias("doc"), row.alias("row"), F.col(f"`{text_col}`").alias("text")).mapInArrow(trimmed(run), "doc long, row long, place long, a long, b long")


def _ranked(places: DataFrame, by: list[str], tag: str) -> DataFrame:
    """places with the id of their key, where the key is found twice or more. Partial aggregation first, so a hot key is a row per task."""
    many = places.groupBy(*by).agg(F.count("*").alias("_n")).where("_n > 1").select(*by, "_n", F.monotonically_increasing_id().alias("id"))
    return materialize(hot_join(places, materialize(many, "ranks"), by, "_n").drop(*by), tag)


def repeated_runs(docs: DataFrame, *, id_col: str, text_col: str, min_words: int) -> DataFrame:
    """(doc, row, start, size): the shortest runs that count of which an earlier document has a copy; start counts lines with words."""
    if not 0 < min_words <= LARGEST:
        raise ValueError(f"min_words must be from 1 to {LARGEST}")
    places = materialize(line_places(docs, id_col=id_col, text_col=text_col, min_words=min_words), "places")
    one = _ranked(places, ["a", "b"], "lines")
    drop_materialized(places)
    mask = F.lit((1 << 16) - 1)
    one = one.select("doc", "row", F.shiftright("place", 32).alias("at"), F.shiftright("place", 16).bitwiseAND(mask).alias("ahead"), F.col("place").bitwiseAND(mask).alias("behind"), "id")
    windows = one.where("ahead > 0").select("doc", "row", F.col("at").alias("start"), F.col("ahead").alias("size")).unionByName(
        one.where("behind > 1").select("doc", "row", (F.col("at") - F.col("behind") + 1).alias("start"), F.col("behind").alias("size"))
    )
    longest = one.agg(F.greatest(F.max("ahead"), F.max("behind"))).first()[0] or 0
    found = []
    # A run of more lines has light ones but at one end; where two heavy lines meet, none goes on.
    level = one.select("doc", "row", "at", "id", (F.col("ahead") == 1).alias("heavy_first"), (F.col("ahead") == 1).alias("heavy_last"))
    length = 1
    while length <= longest:
        wanted = windows.where((F.col("size") >= length) & (F.col("size") < 2 * length))
        head = level.select("doc", "row", F.col("at").alias("start"), F.col("id").alias("x"))
        runs = wanted.join(head, ["doc", "row", "start"])
        if length > 1:
            tail = level.select("doc", "row", F.col("at").alias("_end"), F.col("id").alias("y"))
            runs = runs.withColumn("_end", F.col("start") + F.col("size") - length).join(tail, ["doc", "row", "_end"]).drop("_end")
        else:
            runs = runs.withColumn("y", F.lit(0).cast("long"))
        found.append(_later_copies(materialize(runs, "runs")))
        if 2 * length > longest:
            break
        half = level.select("doc", "row", (F.col("at") - length).alias("at"), F.col("id").alias("next"), F.col("heavy_first").alias("_f"), F.col("heavy_last").alias("_l"))
        pairs = level.where(~F.col("heavy_first") | ~F.col("heavy_last")).join(half, ["doc", "row", "at"]) if length > 1 else level.join(half, ["doc", "row", "at"])
        pairs = pairs.where(~(F.col("heavy_last") & F.col("_f"))).select("doc", "row", "at", "id", "next", "heavy_first", F.col("_l").alias("heavy_last"))
        pairs = pairs.withColumnRenamed("id", "_id")
        level = _ranked(materialize(pairs, "pairs"), ["_id", "next"], "level")
        length *= 2
    if not found:
        return windows
    return reduce(DataFrame.unionByName, found)


def _later_copies(runs: DataFrame) -> DataFrame:
    """runs(doc, row, start, size, x, y) of which a document of smaller id has a copy."""
    by = ["size", "x", "y"]
    first = runs.groupBy(*by).agg(F.min("doc").alias("first"), F.max("doc").alias("last"), F.count("*").alias("_n")).where("first < last").drop("last")
    return hot_join(runs, materialize(first, "firsts"), by, "_n").where("doc > first").select("doc", "row", "start", "size")


def dedup_lines(
    docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", min_words: int = MIN_WORDS, keep_empty: bool = False, report: bool = False,
) -> DataFrame:
    """docs with the texts that are left, or with report: id, n_lines, n_deleted, n_runs (maximal runs deleted), text_left."""
    gone = materialize(repeated_runs(docs, id_col=id_col, text_col=text_col, min_words=min_words), "gone")
    doc, row, runs, doc_r, row_r = (free_name(docs, x) for x in ("_doc", "_row", "_runs", "_doc_r", "_row_r"))
    # The runs of one text: twice as many as it has lines, at most.
    packed = gone.groupBy("doc", "row").agg(F.collect_set(F.col("start") * (1 << 16) + F.col("size")).alias(runs)).select(F.col("doc").alias(doc_r), F.col("row").alias(row_r), runs)
    keys = _keys(docs, id_col, text_col)
    joined = docs.select("*", keys[0].alias(doc), keys[1].alias(row)).join(packed, (F.col(doc) == F.col(doc_r)) & (F.col(row) == F.col(row_r)), "left")
    kept = [*docs.columns]
    at = kept.index(text_col)
    joined = joined.select(*(F.col(f"`{c}`") for c in kept), runs)

    def clean(text: bytes, marks: list[int] | None) -> tuple[bytes, int, int, int]:
        lines, at, words = _sequence(text)
        gone = [False] * len(at)
        for mark in marks or ():
            start, size = mark >> 16, mark & LARGEST
            gone[start : start + size] = [True] * size
        ahead, behind = shortest_runs(words, min_words)
        own = {(i, n) for i, n in enumerate(ahead) if n} | {(i - n + 1, n) for i, n in enumerate(behind) if n}
        seen: dict[tuple, int] = {}
        for start, size in sorted(own):  # copies further up in the same text
            key = tuple(lines[i] for i in at[start : start + size])
            if seen.setdefault(key, start) < start:
                gone[start : start + size] = [True] * size
        deleted = [False] * len(lines)
        for k, i in enumerate(at):
            deleted[i] = gone[k]
            if k and gone[k] and gone[k - 1]:
                deleted[at[k - 1] : i] = [True] * (i - at[k - 1])
        left = b"\n".join(x for x, d in zip(lines, deleted, strict=True) if not d)
        return left, len(lines), sum(deleted), sum(g and not (k and gone[k - 1]) for k, g in enumerate(gone))

    def rebuild(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column(at).cast(pa.binary()).to_pylist()
            done = [None if t is None else clean(t, x) for t, x in zip(texts, batch.column(len(kept)).to_pylist(), strict=True)]
            left = pa.array([None if d is None else d[0].decode("utf-8", "surrogatepass") for d in done], pa.string())
            if report:
                counts = [pa.array([0 if d is None else d[j] for d in done], pa.int64()) for j in (1, 2, 3)]
                yield pa.RecordBatch.from_arrays([batch.column(kept.index(id_col)), *counts, left], names=[id_col, "n_lines", "n_deleted", "n_runs", "text_left"])
                continue
            out = pa.RecordBatch.from_arrays([left if j == at else batch.column(j) for j in range(len(kept))], names=kept)
            if not keep_empty:
                out = out.filter(pa.array([d is None or not d[2] or bool(d[0].strip(_BLANK)) for d in done], pa.bool_()))
            yield out

    if report:
        return joined.mapInArrow(trimmed(rebuild), f"`{id_col}` {docs.schema[id_col].dataType.simpleString()}, n_lines long, n_deleted long, n_runs long, text_left string")
    return joined.mapInArrow(trimmed(rebuild), docs.schema)
