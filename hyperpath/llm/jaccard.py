"""N-gram Jaccard join: documents whose sets of five-word shingles are similar, and their components.

Exact. Documents with equal sets are one node (the signature of the set), so exact copies never meet as pairs. Shingles have a
global order, rare ones first; two similar sets share shingles in their prefixes. Shingles are counted in one pass; those
found often form the frequent class, which is sent as a table of levels by cell. Its size follows the corpus: shingles of many documents
in the rare class would tie unrelated texts into one group. Prefixes are extended, and indexed by single
shingles of the rare class and by combinations of two of the frequent class, which are dealt to subclasses so that the
combinations stay few: with g subclasses, prefixes longer by g share a rare shingle or two of one frequent subclass. The number of
subclasses depends on the size level of the smaller set, and sets near a level's edge are indexed for both.

Counts and index travel as blobs of sorted, delta-coded hashes, two to twelve bytes an entry. A bucket of the index gives all its pairs if
it is small; a large one gives pairs with its first member and with the next four of a fixed order, a number linear in
its size. Pairs whose sketches show that their sets can't be similar go first; the others are verified on whole texts, and linked nodes form components. All pairs within large buckets are then considered, block against block by matrix products in
bounded tasks, which return the links that connect components and the number of links of each node; so no link is lost or
left uncounted, and no pair becomes a row. The products of a group of many near texts grow with the square of the group.

Defined results: null and empty texts, and texts without words, have an empty set, link with nothing and are their own
component; rows of equal id are documents of their own with one id; all whole texts are used, none is cut.
"""

from __future__ import annotations

import gc
from collections import OrderedDict
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import SHINGLE_WORDS, components, drop_materialized, free_name, materialize, mix64, shingle_set, trimmed

_U = np.uint64
#: Two sets link when 100 * intersection >= PERCENT * union.
PERCENT = 75
#: Blobs by the top bits of a hash.
BUCKET_BITS = 8
BUCKETS = 1 << BUCKET_BITS
#: Hashes counted or indexed before a task sends blobs.
FLUSH = 1_500_000
#: The frequent class: shingles in so many documents at least, and so many shingles at most (the most frequent ones), which is
#: more than 50 GB of text have. The class only sets the order, so its size bounds no result.
FREQUENT_DOCS, FREQUENT_LIMIT = 8, 1 << 24
#: Levels of counts, per factor of e.
HISTOGRAM_CELLS = 16
#: The table of the class has 8 to 16 cells of a byte per shingle, within these bits. A rare shingle in a taken cell counts as
#: frequent wherever it is, so no link is lost.
CELL_BITS = 16, 27
#: Buckets of more nodes give a linear number of pairs at first.
SMALL_BUCKET, NEIGHBOURS = 16, 4
#: The index is dealt to its buckets in so many parts, one after the other: beside the index the disk holds the shuffle of one part.
PARTS = 4
#: Cells of a sketch per shingle, rounded up to a power of two.
SKETCH_CELLS = 4
#: Blocks of the exact rest: rows and shingles at most, about.
BLOCK_ROWS, BLOCK_SHINGLES = 400, 200_000
BROADCAST_CLASSES = 100_000
#: Sets from 64 shingles on have subclasses: 16 on the first level; sizes and subclasses grow by 8 per level.
LEVEL_SIZE, LEVEL_CLASSES, LEVEL_FACTOR = 64, 16, 8


# ---------------------------------------------------------------- blobs


def pack_sorted(values: np.ndarray) -> bytes:
    """Sorted uint64 values below 2**40 as byte planes of their differences, which shuffle compression shrinks."""
    gaps = np.diff(values, prepend=_U(0)).astype("<u8").view(np.uint8).reshape(-1, 8)[:, :5]
    return np.ascontiguousarray(gaps.T).tobytes()


def unpack_sorted(blob: bytes) -> np.ndarray:
    planes = np.frombuffer(blob, dtype=np.uint8).reshape(5, -1)
    out = np.zeros((planes.shape[1], 8), dtype=np.uint8)
    out[:, :5] = planes.T
    return np.cumsum(out.view("<u8").ravel(), dtype=np.uint64)


def _by_bucket(keys: np.ndarray) -> list[tuple[int, int, int]]:
    """(bucket, start, end) of sorted 48-bit keys."""
    ends = np.searchsorted(keys, np.arange(1, BUCKETS + 1, dtype=np.uint64) << _U(40))
    starts = np.concatenate(([0], ends[:-1]))
    return [(b, s, e) for b, (s, e) in enumerate(zip(starts.tolist(), ends.tolist(), strict=True)) if e > s]


_MASK40 = _U((1 << 40) - 1)


# ---------------------------------------------------------------- counting


def levels(tokens: np.ndarray, table: np.ndarray) -> np.ndarray:
    """The level of each shingle hash in the table of the frequent class: 0 if rare, else by the logarithm of its documents."""
    return table[tokens >> _U(16) >> _U(48 - (len(table).bit_length() - 1))]


def frequent_shingles(docs: DataFrame, text_col: str, *, least: int = FREQUENT_DOCS, limit: int = FREQUENT_LIMIT) -> np.ndarray:
    """The table of the frequent class: levels by the top bits of the hash; all documents are counted."""

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []
        size = 0

        def flush() -> pa.RecordBatch:
            keys = np.sort(np.concatenate(held))
            parts = _by_bucket(keys)
            return pa.RecordBatch.from_arrays(
                [pa.array([b for b, _, _ in parts], pa.int32()), pa.array([pack_sorted(keys[s:e] & _MASK40) for _, s, e in parts], pa.binary())], names=["bucket", "blob"]
            )

        for batch in batches:
            for text in batch.column(0).cast(pa.binary()):
                t = shingle_set(text.as_py() or b"") >> _U(16)
                if len(t):
                    held.append(t)
                    size += len(t)
                if size >= FLUSH:
                    yield flush()
                    held, size = [], 0
        if held:
            yield flush()

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list[np.ndarray]] = {}
        for batch in batches:
            for bucket, blob in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                held.setdefault(bucket, []).append(unpack_sorted(blob))
        for bucket in list(held):
            token, n = np.unique(np.concatenate(held.pop(bucket)), return_counts=True)
            often = n >= least
            token = token[often] | (_U(bucket) << _U(40))
            yield pa.RecordBatch.from_arrays([pa.array(token.astype(np.int64)), pa.array(n[often].astype(np.int64))], names=["token", "docs"])

    blobs = docs.select(text_col).mapInArrow(trimmed(send), "bucket int, blob binary").repartition("bucket")
    counted = materialize(blobs.mapInArrow(trimmed(count), "token long, docs long"), "counts")
    # The least count with which the class fits its limit, from a histogram of at most some hundred cells.
    step = F.least(F.floor(F.log("docs") * HISTOGRAM_CELLS) + 1, F.lit(255)).cast("int")
    cells = {r["cell"]: r["n"] for r in counted.groupBy(step.alias("cell")).agg(F.count("*").alias("n")).collect()}
    total, lowest = 0, None
    for cell in sorted(cells, reverse=True):
        if total + cells[cell] > limit:
            break
        total, lowest = total + cells[cell], cell
    if lowest is None:
        return np.zeros(1, dtype=np.uint8)
    bits = min(max(CELL_BITS[0], total.bit_length() + 3), CELL_BITS[1])

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = batch.column(0).to_numpy().astype(np.uint64) >> _U(48 - bits)
            yield pa.RecordBatch.from_arrays([pa.array([at.astype("<u4").tobytes()], pa.binary()), pa.array([batch.column(1).to_numpy().astype(np.uint8).tobytes()], pa.binary())], names=["at", "level"])

    table = np.zeros(1 << bits, dtype=np.uint8)
    for r in counted.where(step >= lowest).select("token", step.alias("level")).mapInArrow(place, "at binary, level binary").collect():  # five bytes a shingle
        np.maximum.at(table, np.frombuffer(r["at"], dtype="<u4"), np.frombuffer(r["level"], dtype=np.uint8))
    drop_materialized(counted)
    return table


# ---------------------------------------------------------------- signatures


def _level(n: int) -> int:
    level, edge = 0, LEVEL_SIZE
    while n >= edge:
        level, edge = level + 1, edge * LEVEL_FACTOR
    return level


def index_keys(tokens: np.ndarray, frequent: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """Distinct 48-bit index keys of a sorted set of shingle hashes. frequent: 48 bits of those in the frequent class (others may be there), ascending; counts: what orders them."""
    n = len(tokens)
    least = -(-PERCENT * n // 100)  # shingles shared with any similar set
    if len(frequent):
        short = tokens >> _U(16)
        at = np.minimum(np.searchsorted(frequent, short), len(frequent) - 1)
        often = frequent[at] == short
        rare, common = tokens[~often], tokens[often]
        if len(common):
            common = common[np.lexsort((common, counts[at[often]]))]
    else:
        rare, common = tokens, tokens[:0]
    out = []
    for level in range(_level(least), _level(n) + 1):
        classes = LEVEL_CLASSES * LEVEL_FACTOR ** (level - 1) if level else 0
        length = n - least + 1 + classes
        salt = _U(level * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF)
        single, pairs = rare[:length], common[: max(0, length - len(rare))]
        if not level:
            single, pairs = np.concatenate((single, pairs)), pairs[:0]
        out.append(mix64(single ^ salt))
        if len(pairs) > 1:
            kind = pairs % _U(classes)
            order = np.lexsort((pairs, kind))
            pairs, kind = pairs[order], kind[order]
            step = 1
            while True:
                same = np.flatnonzero(kind[step:] == kind[:-step])
                if not len(same):
                    break
                out.append(mix64(mix64(pairs[same] ^ salt) + pairs[same + step]))
                step += 1
                if step >= len(pairs):
                    break
    return np.unique(np.concatenate(out) >> _U(16))


def signature(tokens: np.ndarray) -> int:
    """64 bits of a set, as a signed integer."""
    folded = np.bitwise_xor.reduce(mix64(tokens), keepdims=True) + np.add.reduce(tokens, keepdims=True)
    return int(mix64(folded + np.array([len(tokens)], dtype=np.uint64)).view(np.int64)[0])


def build_index(docs: DataFrame, id_col: str, text_col: str, frequent: np.ndarray) -> DataFrame:
    """Rows of two kinds: documents (doc, n, node) and blobs (bucket, keys, nodes, sizes)."""
    spark = docs.sparkSession
    table = spark.sparkContext.broadcast(frequent)  # 2**CELL_BITS[1] bytes at most
    kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.binary(), pa.binary(), pa.binary()]
    names = ["doc", "n", "node", "bucket", "keys", "nodes", "sizes"]

    def batch_of(rows: list[tuple]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cells = table.value
        held: list[tuple[np.ndarray, int, int]] = []
        size = 0

        def flush() -> pa.RecordBatch:
            keys = np.concatenate([k for k, _, _ in held])
            lengths = [len(k) for k, _, _ in held]
            nodes = np.repeat(np.array([x for _, x, _ in held], dtype=np.int64), lengths)
            sizes = np.repeat(np.array([x for _, _, x in held], dtype=np.uint32), lengths)
            order = np.argsort(keys, kind="stable")
            keys, nodes, sizes = keys[order], nodes[order], sizes[order]
            rows = []
            for b, s, e in _by_bucket(keys):
                planes = np.ascontiguousarray(sizes[s:e].view(np.uint8).reshape(-1, 4).T).tobytes()
                rows.append((None, None, None, b, pack_sorted(keys[s:e] & _MASK40), nodes[s:e].tobytes(), planes))
            return batch_of(rows)

        seen: set[int] = set()  # exact copies within a flush are indexed once
        for batch in batches:
            rows = []
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1).cast(pa.binary()).to_pylist(), strict=True):
                tokens = shingle_set(text or b"")
                if not len(tokens):
                    rows.append((doc, 0, None, None, None, None, None))
                    continue
                node = signature(tokens)
                rows.append((doc, len(tokens), node, None, None, None, None))
                if node not in seen:
                    seen.add(node)
                    level = levels(tokens, cells)
                    often = level > 0
                    keys = index_keys(tokens, tokens[often] >> _U(16), level[often])
                    held.append((keys, node, len(tokens)))
                    size += len(keys)
                    if size >= FLUSH:
                        yield flush()
                        held, size = [], 0
                        seen = set()
            if rows:
                yield batch_of(rows)
        if held:
            yield flush()

    return docs.select(F.col(id_col).cast("long"), F.col(text_col)).mapInArrow(trimmed(run), "doc long, n long, node long, bucket int, keys binary, nodes binary, sizes binary")


def candidates(blobs: DataFrame) -> DataFrame:
    """Rows (key, a, b, n): pairs of nodes (key null), and members a of large buckets (b null, n the size of the set)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list[tuple]] = {}
        for batch in batches:
            for bucket, *blob in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                held.setdefault(bucket, []).append(blob)
        for bucket in list(held):
            blobs = held.pop(bucket)
            keys = np.concatenate([unpack_sorted(k) for k, _, _ in blobs]) | (_U(bucket) << _U(40))
            nodes = np.concatenate([np.frombuffer(x, dtype=np.int64) for _, x, _ in blobs])
            sizes = np.concatenate([np.ascontiguousarray(np.frombuffer(x, dtype=np.uint8).reshape(4, -1).T).view("<u4").ravel() for _, _, x in blobs]).astype(np.int64)
            del blobs
            order = np.argsort(keys, kind="stable")  # most keys have one entry: these go first
            k = keys[order]
            twin = np.zeros(len(k), dtype=bool)
            same = k[1:] == k[:-1]
            twin[1:] |= same
            twin[:-1] |= same
            order = order[twin]
            order = order[np.lexsort((nodes[order], sizes[order], keys[order]))]
            keys, nodes, sizes = keys[order], nodes[order], sizes[order]
            if len(keys) < 2:
                continue
            fresh = np.ones(len(keys), dtype=bool)
            fresh[1:] = (keys[1:] != keys[:-1]) | (nodes[1:] != nodes[:-1])
            keys, nodes, sizes = keys[fresh], nodes[fresh], sizes[fresh]
            first = np.flatnonzero(np.concatenate(([True], keys[1:] != keys[:-1])))
            length = np.diff(np.append(first, len(keys)))
            group = np.repeat(np.arange(len(first)), length)
            large = length[group] > SMALL_BUCKET
            left, right = [], []
            for step in range(1, SMALL_BUCKET):
                i = np.flatnonzero(keys[step:] == keys[:-step])
                if step > NEIGHBOURS:
                    i = i[~large[i]]
                if not len(i):
                    break
                left.append(i)
                right.append(i + step)
            i = np.flatnonzero(large & (first[group] != np.arange(len(keys))))
            left.append(first[group[i]])
            right.append(i)
            i, j = np.concatenate(left), np.concatenate(right)
            fits = 100 * np.minimum(sizes[i], sizes[j]) >= PERCENT * np.maximum(sizes[i], sizes[j])
            a, b = np.minimum(nodes[i[fits]], nodes[j[fits]]), np.maximum(nodes[i[fits]], nodes[j[fits]])
            pairs = np.unique(np.stack((a, b), axis=1), axis=0) if len(a) else np.empty((0, 2), dtype=np.int64)
            pairs = pairs[pairs[:, 0] != pairs[:, 1]]
            none = pa.nulls(len(pairs), pa.int64())
            yield pa.RecordBatch.from_arrays([none, pa.array(pairs[:, 0]), pa.array(pairs[:, 1]), none], names=["key", "a", "b", "n"])
            if large.any():
                k = pa.array(keys[large].astype(np.int64))
                yield pa.RecordBatch.from_arrays([k, pa.array(nodes[large]), pa.nulls(len(k), pa.int64()), pa.array(sizes[large])], names=["key", "a", "b", "n"])

    return blobs.repartition("bucket").mapInArrow(trimmed(run), "key long, a long, b long, n long")


# ---------------------------------------------------------------- verification


def similar(x: np.ndarray, y: np.ndarray) -> bool:
    both = len(np.intersect1d(x, y, assume_unique=True))
    return 100 * both >= PERCENT * (len(x) + len(y) - both)


def sketch(tokens: np.ndarray) -> bytes:
    """A bit per cell of the hashes' top bits: set if a shingle falls there."""
    bits = max(3, (SKETCH_CELLS * len(tokens) - 1).bit_length())
    cells = np.zeros(1 << bits, dtype=np.uint8)
    cells[tokens >> _U(64 - bits)] = 1
    return np.packbits(cells).tobytes()


def may_link(x: bytes, y: bytes, n: int, m: int) -> bool:
    """False only if sets of n and m shingles with these sketches can't be similar: a cell that one of them has alone holds a shingle that it has alone."""
    p, q = (np.unpackbits(np.frombuffer(b, dtype=np.uint8)) for b in (x, y))
    while len(p) > len(q):
        p = p[::2] | p[1::2]
    while len(q) > len(p):
        q = q[::2] | q[1::2]
    both = min(n - np.count_nonzero(p > q), m - np.count_nonzero(q > p))
    return 100 * both >= PERCENT * (n + m - both)


def promising(pairs: DataFrame, texts: DataFrame) -> DataFrame:
    """The pairs (a, b) of nodes but for those that their sketches rule out, so that few texts travel; texts(node, n, sketch) has one row per node."""
    sa, sb = (texts.select(F.col("node").alias(x), F.col("n").alias(f"n_{x}"), F.col("sketch").alias(f"sketch_{x}")) for x in "ab")
    joined = pairs.join(sa, "a").join(sb, "b").select("a", "b", "sketch_a", "sketch_b", "n_a", "n_b")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = [may_link(*row) for row in zip(*(c.to_pylist() for c in batch.columns[2:]), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], names=["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return joined.mapInArrow(trimmed(run), "a long, b long")


def verify(pairs: DataFrame, texts: DataFrame) -> DataFrame:
    """The pairs (a, b) of nodes whose sets are similar; texts(node, text) has one row per node."""
    ta, tb = (texts.select(F.col("node").alias(x), F.col("text").alias(f"text_{x}")) for x in "ab")
    joined = pairs.join(ta, "a").join(tb, "b").select("a", "b", "text_a", "text_b")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: OrderedDict[int, np.ndarray] = OrderedDict()
        size = 0

        def of(node: int, text: str) -> np.ndarray:
            nonlocal size
            if node in held:
                held.move_to_end(node)
                return held[node]
            held[node] = out = shingle_set(text.encode("utf-8", "surrogatepass"))
            size += len(out)
            while size > 4_000_000 and len(held) > 1:
                size -= len(held.popitem(last=False)[1])
            return out

        for batch in batches:
            links = [similar(of(a, x), of(b, y)) for a, b, x, y in zip(*(c.to_pylist() for c in batch.columns), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], names=["a", "b"]).filter(pa.array(links, pa.bool_()))

    return joined.mapInArrow(trimmed(run), "a long, b long")


def _release(spark: SparkSession) -> None:
    """Let Spark's cleaner delete the shuffles of plans that are done."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def _degrees(links: DataFrame, groups: DataFrame, hits: DataFrame) -> DataFrame:
    """(node, n_links): verified links, but for those within one of groups(node, grp), whose links are counted in hits(node, hits)."""
    ga, gb = (groups.select(F.col("node").alias(x), F.col("grp").alias(f"grp_{x}")) for x in "ab")
    apart = links.select("a", "b").distinct().join(ga, "a", "left").join(gb, "b", "left").where("grp_a IS NULL OR grp_b IS NULL OR grp_a <> grp_b")
    both = apart.select(F.explode(F.array("a", "b")).alias("node"), F.lit(1).cast("long").alias("hits")).unionByName(hits)
    return both.groupBy("node").agg(F.sum("hits").alias("n_links"))


def _block_links(members: DataFrame, label: DataFrame, texts: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(node, grp) of the members of large buckets, and rows of two kinds: links (a, b) that join components (hits null), and
    parts of the number of links of node a within its group (b null). All pairs of a group are considered, each once.

    Buckets that share members form groups. A group is dealt into blocks by size class (sizes in one class, or in two
    adjoining ones, can be similar) and, within a class, by a hash into blocks of bounded rows and shingles. A task gets
    two blocks and finds all intersections by products of their incidence matrices; it returns how many links each node has
    in it, and those that connect components, one less than the rows it has at most. So rows stay linear in the group, times
    its blocks.
    """
    placed = materialize(members.join(label, "node", "left").select("key", "node", "n", F.coalesce("component", "node").alias("part")), "placed")
    hub = placed.groupBy("key").agg(F.min("node").alias("hub"))
    groups = components(placed.join(hub, "key").where("node <> hub").select(F.col("hub").alias("a"), F.col("node").alias("b")).distinct())
    nodes = placed.select("node", "n", "part").distinct().join(groups.select("node", F.col("component").alias("grp")), "node")
    nodes = materialize(nodes.withColumn("size", F.floor(F.log("n") / np.log(100 / PERCENT)).cast("long")), "grouped")
    room = nodes.groupBy("grp", "size").agg(F.greatest(F.ceil(F.sum("n") / BLOCK_SHINGLES), F.ceil(F.count("*") / BLOCK_ROWS)).alias("blocks"))
    dealt = nodes.join(F.broadcast(room) if room.count() <= BROADCAST_CLASSES else room, ["grp", "size"])
    dealt = materialize(dealt.withColumn("block", F.pmod(F.xxhash64("node"), "blocks")).join(texts, "node").select("grp", "size", "block", "node", "n", "part", "text"), "blocks")
    blocks = dealt.select("grp", "size", "block").distinct()
    x, y = (blocks.select("grp", F.col("size").alias(f"size_{i}"), F.col("block").alias(f"block_{i}")) for i in "xy")
    tasks = x.join(y, "grp").where("(size_x = size_y AND block_x <= block_y) OR size_y = size_x + 1")
    task = ["grp", "size_x", "block_x", "size_y", "block_y"]
    sides = [tasks.join(dealt.select("grp", F.col("size").alias(f"size_{i}"), F.col("block").alias(f"block_{i}"), "node", "part", "text"), ["grp", f"size_{i}", f"block_{i}"]).select(*task, F.lit(i).alias("side"), "node", "part", "text") for i in "xy"]
    rows = sides[0].unionByName(sides[1].where("size_x <> size_y OR block_x <> block_y"))

    def compare(frame: pd.DataFrame) -> pd.DataFrame:
        sets = [shingle_set(t.encode("utf-8", "surrogatepass")) for t in frame["text"]]
        node, part = frame["node"].to_numpy(np.int64), frame["part"].to_numpy(np.int64)
        sizes = np.array([len(x) for x in sets], dtype=np.int64)
        owner = np.repeat(np.arange(len(sets)), sizes)
        token, column, seen = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
        often = seen[column] > 1
        order = np.argsort(column[often], kind="stable")
        column, owner = column[often][order], owner[often][order]
        both = np.zeros((len(sets), len(sets)), dtype=np.float32)
        start = np.flatnonzero(np.concatenate(([True], column[1:] != column[:-1]))) if len(column) else np.empty(0, dtype=np.int64)
        dense = np.cumsum(np.concatenate(([0], (column[1:] != column[:-1]).astype(np.int64)))) if len(column) else column
        for low in range(0, len(start), 4096):  # a slice of the shingles at a time
            first, last = start[low], start[low + 4096] if low + 4096 < len(start) else len(column)
            m = np.zeros((len(sets), 4096), dtype=np.float32)
            m[owner[first:last], dense[first:last] - low] = 1
            both += m @ m.T
        both = np.rint(both).astype(np.int64)
        hit = 100 * both >= PERCENT * (sizes[:, None] + sizes[None, :] - both)
        np.fill_diagonal(hit, False)
        side = (frame["side"] == "y").to_numpy()
        if side.any():  # two blocks: pairs of one block have a task of their own
            hit &= side[:, None] != side[None, :]
        hits = hit.sum(axis=1)
        i, j = np.nonzero(np.triu(hit & (part[:, None] != part[None, :]), 1))
        up: dict[int, int] = {}

        def root(k: int) -> int:
            while up.get(k, k) != k:
                up[k] = k = up.get(up[k], up[k])
            return k

        out = []
        for k, l in zip(i.tolist(), j.tolist(), strict=True):
            p, q = root(int(part[k])), root(int(part[l]))
            if p != q:
                up[max(p, q)] = min(p, q)
                out.append((min(node[k], node[l]), max(node[k], node[l]), None))
        out += [(node[k], None, hits[k]) for k in np.flatnonzero(hits).tolist()]
        return pd.DataFrame({c: pd.array([r[k] for r in out], dtype="Int64") for k, c in enumerate(("a", "b", "hits"))})

    return nodes.select("node", "grp"), rows.groupBy(*task).applyInPandas(compare, "a long, b long, hits long")


def similarity_components(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_shingles, component_id, n_links): component_id is the smallest id reachable by links; n_links is
    the number of other texts (sets of shingles) that link with the document's."""
    spark = docs.sparkSession
    frequent = frequent_shingles(docs, text_col)
    _release(spark)
    index = materialize(build_index(docs, id_col, text_col, frequent), "index")
    rows = index.where("bucket is null").select("doc", "n", "node")
    parts = []
    for i in range(PARTS):
        blobs = index.where(F.col("bucket") % PARTS == i).select("bucket", "keys", "nodes", "sizes")
        parts.append(materialize(candidates(blobs), "candidates"))
        del blobs
        _release(spark)
    found = reduce(DataFrame.unionByName, parts)
    rows = materialize(rows, "nodes")
    drop_materialized(index)
    pairs = found.where("key is null").select("a", "b").distinct()
    members = found.where("key is not null").select("key", F.col("a").alias("node"), "n")
    first = rows.where("node is not null").groupBy("node").agg(F.min("doc").alias("doc"))
    wanted = found.select(F.explode(F.array("a", "b")).alias("node")).where("node is not null").distinct()
    wanted = first.join(wanted, "node", "left_semi").select("node", F.col("doc").alias("_doc"))
    texts = docs.select(F.col(id_col).cast("long").alias("_doc"), F.col(text_col).alias("text")).join(wanted, "_doc")

    def own(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sets = [shingle_set((x or "").encode("utf-8", "surrogatepass")) for x in batch.column(1).to_pylist()]
            keep = [len(t) > 0 and signature(t) == node for node, t in zip(batch.column(0).to_pylist(), sets, strict=True)]  # rows of equal id may have other texts
            more = pa.array([len(t) for t in sets], pa.int64()), pa.array([sketch(t) if k else None for k, t in zip(keep, sets, strict=True)], pa.binary())
            yield pa.RecordBatch.from_arrays([*batch.columns, *more], names=["node", "text", "n", "sketch"]).filter(pa.array(keep, pa.bool_()))

    texts = materialize(texts.select("node", "text").mapInArrow(trimmed(own), "node long, text string, n long, sketch binary"), "texts")
    if texts.count() != wanted.count():
        texts = materialize(texts.groupBy("node").agg(F.first("text").alias("text"), F.first("n").alias("n"), F.first("sketch").alias("sketch")), "texts")
    _release(spark)
    pairs = materialize(promising(pairs, texts), "pairs")
    _release(spark)
    whole = texts.select("node", "text")
    links = materialize(verify(pairs, whole), "links")
    _release(spark)
    label = components(links)
    if members.isEmpty():
        degrees = links.select(F.explode(F.array("a", "b")).alias("node")).groupBy("node").agg(F.count("*").alias("n_links"))
    else:
        # Exact rest: whatever the members of large buckets have in common.
        groups, more = _block_links(members, label, whole)
        more = materialize(more, "more")
        degrees = _degrees(links, groups, more.where("hits IS NOT NULL").select(F.col("a").alias("node"), "hits"))
        joining = more.where("b IS NOT NULL").select("a", "b").distinct()
        if not joining.isEmpty():
            label = components(links.unionByName(joining))
    label = materialize(label.join(degrees, "node"), "label")
    for done in (texts, *parts):  # the large tables: no later plan reads them
        drop_materialized(done)
    labelled = rows.join(label, "node", "left").select("doc", "n", F.coalesce("component", "node").alias("part"), F.coalesce("n_links", F.lit(0)).alias("n_links"))
    labelled = materialize(labelled, "labelled")
    least = labelled.where("part is not null").groupBy("part").agg(F.min("doc").alias("least"))
    joined = labelled.join(least, "part", "left")
    return joined.select(F.col("doc").alias("doc_id"), F.col("n").alias("n_shingles"), F.when(F.col("n") > 0, F.col("least")).otherwise(F.col("doc")).alias("component_id"), "n_links")


def keep_first(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs with one document of each component: the one with the smallest id. Rows of equal id stay or go together."""
    parts = similarity_components(docs, id_col=id_col, text_col=text_col)
    key = free_name(docs, "_gone")
    gone = materialize(parts.where("component_id <> doc_id").select(F.col("doc_id").alias(key)).distinct(), "gone")
    return docs.join(gone, docs[id_col].cast("long") == gone[key], "left_anti")


__all__ = ["SHINGLE_WORDS", "candidates", "frequent_shingles", "index_keys", "keep_first", "similar", "similarity_components", "verify"]
