"""Benchmark decontamination: documents that hold a near copy of a benchmark item.

Windows are sized by the items. A passage as long as an item, whose weighted shingles are similar enough, can differ from it only so
much: what it loses and what it adds must fit a quarter of the item's weight. From the item's own weights follow the most edits inside
and the most words lost at its ends, and so the stretch of words that must be left unchanged (unchanged_stretch): for an item of distinct
words three quarters of it, half of it from 32 words on. The item's window is the largest power of two that fits the stretch;
items are dealt into size classes by it, and documents are probed once per class, at a stride that no such stretch can slip through.

A window's SimHash is the bitwise majority of its word hashes, counted by adders on whole 64-bit words (windows over 32 words: of 32 of their
words, evenly spaced). RADIUS + 1 blocks index the fingerprints of all item windows: two fingerprints within the Hamming radius agree
on a block, so the index finds all within it, equal windows first of all. A hit places the item in the document; every alignment of the
two around that place is then compared exactly, by shingles weighted by their rarity among the items.

Only DataFrame functions. Documents are read once per class and not shuffled: the items' index is broadcast in parts of bounded size.

Defined results: null and empty texts and items match nothing. Items of fewer than five words are one shingle; a document shorter
than an item is compared as a whole. Equal rows match alike and give one row per (document id, item id); ties of similarity go
to the earliest place. What the stretch doesn't cover: edits whose new shingles repeat each other or occur elsewhere in the item.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import GAP_PATTERN, SHINGLE_WORDS, SIMILARITY, free_name, materialize

RADIUS = 3
#: Words of a window that its fingerprint counts.
COUNTED = 32
#: Item windows in one broadcast table (RADIUS + 1 rows of about 60 bytes each).
BROADCAST_WINDOWS = 200_000


def _words(text: Column) -> Column:
    return F.array_remove(F.split(F.lower(text), GAP_PATTERN), "")


def _add(a: list[str], b: list[str]) -> list[Column]:
    """The sum of two numbers per bit position, each a list of bit planes, lowest first."""
    out, carry = [], None
    for x, y in zip(map(F.col, a), map(F.col, b), strict=True):
        either = x.bitwiseXOR(y)
        out.append(either if carry is None else either.bitwiseXOR(carry))
        carry = x.bitwiseAND(y) if carry is None else x.bitwiseAND(y).bitwiseOR(carry.bitwiseAND(either))
    return [*out, carry]


def fingerprints(df: DataFrame, hashes: str, at: str, window: int) -> DataFrame:
    """df with fp: the SimHash of the window words (a power of two) from place at. Each round of sums is a projection of its own."""
    base = df.columns
    counted = min(window, COUNTED)
    numbers = [[f"_p{j}_0"] for j in range(counted)]
    df = df.select(*base, *(F.get(F.col(hashes), F.col(at) + j * (window // counted)).alias(f"_p{j}_0") for j in range(counted)))
    while len(numbers) > 1:
        sums = [_add(a, b) for a, b in zip(numbers[::2], numbers[1::2], strict=True)]
        numbers = [[f"_p{j}_{k}" for k in range(len(planes))] for j, planes in enumerate(sums)]
        df = df.select(*base, *(c.alias(n) for names, planes in zip(numbers, sums, strict=True) for n, c in zip(names, planes, strict=True)))
    planes = [F.col(c) for c in numbers[0]]
    fp = planes[0] if counted == 1 else planes[-1].bitwiseOR(planes[-2])
    # Never null, so that no filter on nulls is pushed down through the sums, which would multiply them.
    return df.select(*base, F.coalesce(fp, F.lit(0).cast("long")).alias("fp"))


def _block_keys(fp: Column, radius: int) -> Column:
    """radius + 1 keys, of the blocks of a fingerprint."""
    cuts = [64 * j // (radius + 1) for j in range(radius + 2)]
    blocks = [F.shiftrightunsigned(fp, a).bitwiseAND(F.lit((1 << (b - a)) - 1)) if b - a < 64 else fp for a, b in zip(cuts, cuts[1:], strict=False)]
    return F.array(*(F.struct(F.lit(j).alias("block"), b.alias("bits")) for j, b in enumerate(blocks)))


def _shingles(words: Column, n: Column) -> Column:
    """Every run of n words, in order. Safe with too few words, too, as Catalyst may evaluate this before the filter on sizes."""
    return F.transform(F.sequence(F.lit(1), F.greatest(F.lit(1), F.size(words) - n + 1)), lambda i: F.array_join(F.slice(words, i, n), " "))


def unchanged_stretch(similarity: float) -> Column:
    """Words in a row that any passage this similar to the item leaves unchanged; of columns size, n, least, total, unknown, plain.

    (1 - similarity) of the item's weight pays for the shingles lost and, times the similarity, for those added. An edit inside
    loses and adds four shingles at least, a word at an end loses one. An item that repeats shingles guarantees one shingle only.
    """
    room = F.col("total") * (1 - similarity) + 1e-9
    inside = (F.col("least") + F.col("unknown") * similarity) * (SHINGLE_WORDS - 1)
    left = lambda q: F.ceil((F.col("size") - q - F.floor((room - inside * q) / F.col("least"))) / (q + 1))
    worst = F.array_min(F.transform(F.sequence(F.lit(0), F.floor(room / inside).cast("int")), left))
    return F.when(F.col("plain"), F.greatest(F.col("n"), worst)).otherwise(F.col("n")).cast("int")


def item_table(items: DataFrame, *, id_col: str, text_col: str, similarity: float) -> DataFrame:
    """One row per distinct item: key, item, w (words), size, n (words of a shingle), weights (a map), total, unknown (weight of other shingles), window, stretch."""
    words = items.select(F.col(id_col).alias("item"), _words(F.col(text_col)).alias("w")).where(F.size("w") > 0).dropDuplicates(["item", "w"])
    words = words.select(F.monotonically_increasing_id().alias("key"), "item", "w", F.size("w").alias("size"), F.least(F.size("w"), F.lit(SHINGLE_WORDS)).alias("n"))
    words = materialize(words, "items")
    shingles = words.select("key", F.explode(F.array_distinct(_shingles(F.col("w"), F.col("n")))).alias("shingle"))
    df = shingles.groupBy("shingle").agg(F.count("*").alias("df"))
    count = float(words.count())
    weighted = shingles.join(df, "shingle").withColumn("weight", F.log(1 + F.lit(count) / F.col("df")))
    weights = weighted.groupBy("key").agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct("shingle", "weight")))).alias("weights"), F.min("weight").alias("least"))
    table = words.join(weights, "key").withColumn("total", F.aggregate(F.map_values("weights"), F.lit(0.0), lambda a, x: a + x)).withColumn("unknown", F.log(F.lit(1 + count)))
    table = table.withColumn("plain", F.size("weights") == F.col("size") - F.col("n") + 1).withColumn("stretch", unchanged_stretch(similarity))
    return materialize(table.withColumn("window", F.pow(F.lit(2.0), F.floor(F.log2("stretch"))).cast("int")).drop("least", "plain"), "weights")


def item_index(table: DataFrame, window: int, radius: int) -> DataFrame:
    """(key, item_at, item_fp, k): the fingerprints of all windows of the items of a size class, once per block key."""
    placed = table.where(F.col("window") == window).select("key", F.transform("w", lambda x: F.xxhash64(x)).alias("h"), F.explode(F.sequence(F.lit(0), F.greatest(F.lit(0), F.col("size") - window))).alias("item_at"))
    return fingerprints(placed, "h", "item_at", window).select("key", "item_at", F.col("fp").alias("item_fp"), F.explode(_block_keys(F.col("fp"), radius)).alias("k"))


def find_leaks(
    docs: DataFrame, items: DataFrame, *, doc_id: str = "doc_id", doc_text: str = "text", item_id: str = "item_id", item_text: str = "text",
    similarity: float = SIMILARITY, radius: int = RADIUS,
) -> DataFrame:
    """(doc_id, item_id, word_start, similarity): the best match of each document and item whose similarity is enough."""
    table = item_table(items, id_col=item_id, text_col=item_text, similarity=similarity)
    words = docs.select(F.col(doc_id).alias("doc"), _words(F.col(doc_text)).alias("w")).where(F.size("w") > 0)
    hashed = words.select("doc", "w", F.size("w").alias("len"), F.transform("w", lambda x: F.xxhash64(x)).alias("h"))
    sizes = table.select("key", F.col("size").cast("int").alias("size"))
    hits = []
    classes = table.groupBy("window").agg(F.min(F.col("stretch") - F.col("window") + 1).alias("stride"), F.sum(F.col("size") - F.col("window") + 1).alias("windows")).orderBy("window")
    for window, stride, n in classes.collect():  # powers of two: a few rows
        placed = hashed.where(F.col("len") >= window).select("*", F.explode(F.sequence(F.lit(0), F.greatest(F.lit(0), F.col("len") - window), F.lit(stride))).alias("at"))
        probes = fingerprints(placed, "h", "at", window).select("doc", "w", "len", "at", "fp", F.explode(_block_keys(F.col("fp"), radius)).alias("k"))
        index = item_index(table, window, radius).join(F.broadcast(sizes) if n <= BROADCAST_WINDOWS else sizes, "key")
        index = index.select("key", "size", "item_at", "item_fp", F.col("k.block").alias("block"), F.col("k.bits").alias("bits"))
        probes = probes.select("doc", "w", "len", "at", "fp", F.col("k.block").alias("block"), F.col("k.bits").alias("bits"))
        index = materialize(index, "index")
        parts = max(1, -(-n // BROADCAST_WINDOWS))
        for part in range(parts):
            own = index if parts == 1 else index.where(F.pmod(F.xxhash64("key"), F.lit(parts)) == part)
            near = probes.join(F.broadcast(own), ["block", "bits"]).where(F.bit_count(F.col("fp").bitwiseXOR(F.col("item_fp"))) <= radius)
            # All alignments around the hit: the words from a size before the item's place to a size after its end.
            base = F.greatest(F.lit(0), F.col("at") - F.col("item_at") - F.col("size"))
            hits.append(near.select("doc", "key", "len", base.alias("base"), F.slice("w", base + 1, F.col("size") * 3).alias("region")))
    if not hits:
        return docs.select(F.col(doc_id).alias("doc_id")).where("false").crossJoin(items.select(F.col(item_id).alias("item_id")).where("false")).select("doc_id", "item_id", F.lit(0).cast("long").alias("word_start"), F.lit(0.0).alias("similarity"))
    regions = reduce(DataFrame.unionByName, hits).dropDuplicates(["doc", "key", "base", "region"])
    compared = regions.join(table.select("key", "item", "size", "n", "weights", "total", "unknown", _shingles(F.col("w"), F.col("n")).alias("own")), "key")
    compared = compared.where(F.size("region") >= F.col("n")).withColumn("s", _shingles(F.col("region"), F.col("n")))
    last = F.greatest(F.lit(0), F.col("len") - F.col("size"))
    at_shingle = lambda x, i: F.transform(
        F.filter(F.sequence(F.lit(0), F.size("own") - 1), lambda o: F.get("own", o) == x), lambda o: F.greatest(F.lit(0), F.least(F.col("base") + i - o, last))
    )
    starts = F.array_distinct(F.flatten(F.transform("s", lambda x, i: F.when(F.map_contains_key("weights", x), at_shingle(x, i)).otherwise(F.array().cast("array<int>")))))
    compared = compared.withColumn("start", F.explode(starts)).where("start >= base")
    inside = F.array_distinct(F.slice("s", F.col("start") - F.col("base") + 1, F.greatest(F.lit(1), F.least(F.col("size"), F.col("len")) - F.col("n") + 1)))
    compared = compared.withColumn("inside", inside)
    both = F.aggregate(F.filter("inside", lambda x: F.map_contains_key("weights", x)), F.lit(0.0), lambda a, x: a + F.element_at("weights", x))
    extra = F.size(F.filter("inside", lambda x: ~F.map_contains_key("weights", x))) * F.col("unknown")
    compared = compared.withColumn("sim", F.round(both / (F.col("total") + extra), 6)).where(F.col("sim") >= similarity)
    best = compared.groupBy("doc", "item").agg(F.max(F.struct("sim", (-F.col("start")).alias("place"))).alias("best"))
    return best.select(F.col("doc").alias("doc_id"), F.col("item").alias("item_id"), (-F.col("best.place")).cast("long").alias("word_start"), F.col("best.sim").alias("similarity"))


def drop_leaks(docs: DataFrame, items: DataFrame, *, doc_id: str = "doc_id", **options: object) -> DataFrame:
    """docs without the rows whose id has a leak; rows with a null id stay only if no row with a null id has one."""
    leaks = find_leaks(docs, items, doc_id=doc_id, **options)
    key = free_name(docs, "_leak")
    ids = materialize(leaks.select(F.col("doc_id").alias(key)).distinct(), "leaks")
    return docs.join(ids, docs[doc_id].eqNullSafe(ids[key]), "left_anti")
