"""Sparse-suffix dedup: passages of MIN_WORDS words or more that repeat across the corpus.

Of every text only the suffixes at minimiser positions are kept: the place of the smallest k-gram hash in every window of
w places. Two copies of a passage select the same places inside it, so each run of MIN_WORDS words has a kept suffix with
BEGIN words or more of the run after it. No suffix array is sorted: equal beginnings meet by their hash. A repeated beginning
alone says nothing about what stands around it (a common clause has many continuations), so every run of MIN_WORDS words
whose own kept suffix has a repeated beginning is then compared as a whole, again by hash. Of equal runs all but the first by
(document, place) are later copies; overlapping ones are merged, which gives the repeats at full length.

Two passes over the texts: the first sends hashes and ids of beginnings, as sorted blobs; suffixes whose beginning is found
once end there. The second reads the documents that have repeated beginnings and sends their runs, as blobs, too. A task sends
only the first of equal runs it holds (the others are later copies already), so a passage that a third of all documents
share is a few entries of a bucket, and no bucket is cut.

Defined results: null and short texts have no suffixes; a null id counts as the largest; rows of equal id are one document;
later copies inside one document are reported as well; of a repeat, the copy in the smallest id, furthest up, is not reported.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import drop_materialized, materialize, mix64, roll, word_bounds, word_hashes
from .jaccard import _MASK40, _U, FLUSH, _by_bucket, _release, pack_sorted, unpack_sorted

MIN_WORDS = 50
#: k-gram of the minimisers, window of places, words of the beginnings; window + beginning - 1 <= MIN_WORDS.
GRAM, PLACES, BEGIN = 8, 18, 32
#: Runs travel in blobs by the top bits of their hash.
RUN_BITS = 12
_LAST = (1 << 63) - 1


def anchors(text: bytes) -> tuple[np.ndarray, np.ndarray]:
    """(hash of the BEGIN words at each place, minimiser place of each run of MIN_WORDS words)."""
    raw = np.frombuffer(text, dtype=np.uint8)
    words = word_hashes(raw, *word_bounds(raw))
    if len(words) < MIN_WORDS:
        return words[:0], np.empty(0, dtype=np.int64)
    view = np.lib.stride_tricks.sliding_window_view(roll(words, GRAM), PLACES)[: len(words) - MIN_WORDS + 1]
    return roll(words, BEGIN), view.argmin(axis=1) + np.arange(len(view))


def run_hashes(begins: np.ndarray) -> np.ndarray:
    """Hash of the MIN_WORDS words at each place: of the two beginnings that cover them."""
    apart = MIN_WORDS - BEGIN
    return mix64(mix64(begins[:-apart]) + begins[apart:])


def repeated_beginnings(docs: DataFrame) -> DataFrame:
    """docs(doc, text) -> (doc, key): 48-bit hashes of beginnings in doc that occur twice or more in the corpus."""

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[int, np.ndarray]] = []
        size = 0

        def flush() -> pa.RecordBatch:
            keys = np.concatenate([k for _, k in held])
            ids = np.repeat(np.array([d for d, _ in held], dtype=np.int64), [len(k) for _, k in held])
            order = np.argsort(keys, kind="stable")
            keys, ids = keys[order], ids[order]
            parts = _by_bucket(keys)
            return pa.RecordBatch.from_arrays(
                [pa.array([b for b, _, _ in parts], pa.int32()), pa.array([pack_sorted(keys[s:e] & _MASK40) for _, s, e in parts], pa.binary()), pa.array([ids[s:e].tobytes() for _, s, e in parts], pa.binary())],
                names=["bucket", "keys", "ids"],
            )

        for batch in batches:
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1).cast(pa.binary()).to_pylist(), strict=True):
                begins, places = anchors(text or b"")
                if len(places):
                    keys = begins[np.unique(places)] >> _U(16)
                    held.append((doc, keys))
                    size += len(keys)
                if size >= FLUSH:
                    yield flush()
                    held, size = [], 0
        if held:
            yield flush()

    def match(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list[tuple]] = {}
        for batch in batches:
            for bucket, keys, ids in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                held.setdefault(bucket, []).append((keys, ids))
        for bucket in list(held):
            blobs = held.pop(bucket)
            keys = np.concatenate([unpack_sorted(k) for k, _ in blobs]) | (_U(bucket) << _U(40))
            ids = np.concatenate([np.frombuffer(x, dtype=np.int64) for _, x in blobs])
            order = np.argsort(keys, kind="stable")
            keys = keys[order]
            twin = np.zeros(len(keys), dtype=bool)
            same = keys[1:] == keys[:-1]
            twin[1:] |= same
            twin[:-1] |= same
            keys, ids = keys[twin], ids[order[twin]]
            order = np.lexsort((ids, keys))
            keys, ids = keys[order], ids[order]
            fresh = np.ones(len(keys), dtype=bool)
            fresh[1:] = (keys[1:] != keys[:-1]) | (ids[1:] != ids[:-1])
            keys, ids = keys[fresh], ids[fresh]
            if not len(keys):
                continue
            for at in range(0, len(keys), 200_000):
                part = slice(at, at + 200_000)
                yield pa.RecordBatch.from_arrays([pa.array(ids[part]), pa.array(keys[part].astype(np.int64))], names=["doc", "key"])

    return docs.mapInArrow(send, "bucket int, keys binary, ids binary").repartition("bucket").mapInArrow(match, "doc long, key long")


def _planes(values: np.ndarray) -> bytes:
    """Integers as byte planes, which shuffle compression shrinks."""
    return np.ascontiguousarray(values.view(np.uint8).reshape(len(values), -1).T).tobytes()


def _whole(blobs: list[bytes], kind: str) -> np.ndarray:
    width = np.dtype(kind).itemsize
    return np.concatenate([np.ascontiguousarray(np.frombuffer(b, dtype=np.uint8).reshape(width, -1).T).view(kind).ravel() for b in blobs])


def _split_runs(keys: np.ndarray, docs: np.ndarray, places: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(entries that are the first of equal runs, entries that are later copies); the same place of a document is no copy."""
    order = np.argsort(keys, kind="stable")
    k = keys[order]
    twin = np.zeros(len(k), dtype=bool)
    same = k[1:] == k[:-1]
    twin[1:] |= same
    twin[:-1] |= same
    alone, order = order[~twin], order[twin]
    order = order[np.lexsort((places[order], docs[order], keys[order]))]
    k = keys[order]
    head = np.ones(len(k), dtype=bool)
    head[1:] = k[1:] != k[:-1]
    first = order[head]
    own = np.repeat(first, np.diff(np.append(np.flatnonzero(head), len(k))))
    later = (docs[order] != docs[own]) | (places[order] != places[own])
    return np.concatenate((alone, first)), order[later]


def _spans(docs: np.ndarray, places: np.ndarray) -> list[np.ndarray]:
    """Columns doc, start, stop: the runs at these places, merged where they overlap or touch."""
    order = np.lexsort((places, docs))
    docs, places = docs[order], places[order].astype(np.int64)
    head = np.ones(len(docs), dtype=bool)
    head[1:] = (docs[1:] != docs[:-1]) | (places[1:] - places[:-1] > MIN_WORDS)
    tail = np.append(head[1:], True)[: len(head)]
    return [docs[head], places[head], places[tail] + MIN_WORDS]


def later_copies(docs: DataFrame, repeated: DataFrame) -> DataFrame:
    """(doc, start, stop): the runs of docs(doc, text) that an earlier document or place has, too; spans may overlap."""
    # As many as the text has minimisers at most.
    own = repeated.groupBy("doc").agg(F.sort_array(F.collect_set("key")).alias("own"))
    joined = docs.join(own, "doc").select("doc", "text", "own")
    kinds = [pa.int32(), pa.binary(), pa.binary(), pa.binary(), pa.int64(), pa.int64(), pa.int64()]
    names = ["bucket", "keys", "docs", "places", "doc", "start", "stop"]

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, int, np.ndarray]] = []
        size = 0

        def flush() -> Iterator[pa.RecordBatch]:
            keys = np.concatenate([k for k, _, _ in held])
            ids = np.repeat(np.array([d for _, d, _ in held], dtype=np.int64), [len(k) for k, _, _ in held])
            places = np.concatenate([p for _, _, p in held])
            first, later = _split_runs(keys, ids, places)
            if len(later):
                found = _spans(ids[later], places[later])
                none = pa.nulls(len(found[0]), pa.binary())
                bucket = (found[0] % (1 << RUN_BITS)).astype(np.int32)
                yield pa.RecordBatch.from_arrays([pa.array(bucket), none, none, none, *map(pa.array, found)], names=names)
            first = first[np.argsort(keys[first], kind="stable")]
            keys, ids, places = keys[first], ids[first], places[first]
            ends = np.searchsorted(keys >> _U(64 - RUN_BITS), np.arange(1 << RUN_BITS, dtype=np.uint64), side="right")
            starts = np.concatenate(([0], ends[:-1]))
            parts = [(b, slice(x, y)) for b, (x, y) in enumerate(zip(starts.tolist(), ends.tolist(), strict=True)) if y > x]
            rows = [(b, keys[p].tobytes(), _planes(ids[p]), _planes(places[p]), None, None, None) for b, p in parts]
            for at in range(0, len(rows), 512):
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows[at : at + 512], strict=True), kinds, strict=True)], names=names)

        for batch in batches:
            for doc, text, own in zip(batch.column(0).to_pylist(), batch.column(1).cast(pa.binary()).to_pylist(), batch.column(2), strict=True):
                begins, kept = anchors(text or b"")
                if not len(kept):
                    continue
                wanted = own.values.to_numpy(zero_copy_only=False)
                short = (begins[kept] >> _U(16)).astype(np.int64)
                places = np.flatnonzero(wanted[np.minimum(np.searchsorted(wanted, short), len(wanted) - 1)] == short)
                if len(places):
                    held.append((run_hashes(begins)[places], doc, places.astype(np.uint32)))
                    size += len(places)
                if size >= FLUSH:
                    yield from flush()
                    held, size = [], 0
        if held:
            yield from flush()

    def match(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held = None, []

        def flush() -> pa.RecordBatch:
            keys = np.concatenate([np.frombuffer(k, dtype=np.uint64) for k, _, _ in held])
            ids, places = _whole([d for _, d, _ in held], "<i8"), _whole([p for _, _, p in held], "<u4")
            later = _split_runs(keys, ids, places)[1]
            return pa.RecordBatch.from_arrays(list(map(pa.array, _spans(ids[later], places[later]))), names=names[4:])

        for batch in batches:
            known = batch.filter(batch.column(1).is_null())
            if len(known):
                yield known.select(names[4:])
            for bucket, *blob in zip(*(c.to_pylist() for c in batch.columns[:4]), strict=True):
                if blob[0] is None:
                    continue
                if bucket != now:
                    if held:
                        yield flush()
                    now, held = bucket, []
                held.append(blob)
        if held:
            yield flush()

    sent = joined.mapInArrow(send, "bucket int, keys binary, docs binary, places binary, doc long, start long, stop long")
    return sent.repartition("bucket").sortWithinPartitions("bucket").mapInArrow(match, "doc long, start long, stop long")


def repeated_passages(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, word_start, word_stop, n_words): merged spans of later copies, in words counted from 0."""
    source = docs.select(F.coalesce(F.col(id_col).cast("long"), F.lit(_LAST)).alias("doc"), F.col(text_col).alias("text"))
    repeated = materialize(repeated_beginnings(source), "beginnings")
    found = materialize(later_copies(source, repeated), "copies")
    drop_materialized(repeated)
    _release(docs.sparkSession)
    spans = found.repartition("doc").sortWithinPartitions("doc", "start", "stop")

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now: list[int] | None = None
        for batch in batches:
            out: list[tuple] = []
            for doc, start, stop in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if now and now[0] == doc and start <= now[2]:
                    now[2] = max(now[2], stop)
                    continue
                if now:
                    out.append(tuple(now))
                now = [doc, start, stop]
            if out:
                yield pack(out)
        if now:
            yield pack([tuple(now)])

    def pack(rows: list[tuple]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows, strict=True)], names=["doc", "word_start", "word_stop"])

    merged = spans.mapInArrow(merge, "doc long, word_start long, word_stop long")
    return merged.select(F.when(F.col("doc") != _LAST, F.col("doc")).alias("doc_id"), "word_start", "word_stop", (F.col("word_stop") - F.col("word_start")).alias("n_words"))
