"""Document operators against brute force, with nulls, empty and long texts, ties, repeated rows and clashing columns."""

import random
import re
from collections import defaultdict
from pathlib import Path

import numpy as np
import pytest
from pyspark.sql import functions as F
from hypothesis import given, settings
from hypothesis import strategies as st

from hyperpath.llm import decontam, jaccard, lines, mixing, quality, suffix
from hyperpath.llm.common import components, shingle_set, trimmed

WORDS = re.compile(r"[^\x20\x09-\x0D]+")


def docs_of(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, text string")


def words_of(text):
    return WORDS.findall(text or "")


# ---- repetition coverage


def brute_profile(text):
    words = words_of(text)
    repeated = [False] * len(words)
    where = defaultdict(list)
    for i in range(len(words) - 4):
        where[tuple(words[i : i + 5])].append(i)
    for places in where.values():
        if len(places) > 1:
            for i in places:
                repeated[i : i + 5] = [True] * 5
    seen, dups = set(), 0
    for line in (text or "").split("\n"):
        dups += bool(words_of(line)) and line in seen
        seen.add(line)
    n, r = len(words), sum(repeated)
    return n, sum(map(len, words)), sum(c in "#*$%&|<>" for c in text or ""), dups, r, n < 10 or 100 * r > 20 * n


TEXTS = st.text(st.sampled_from("ab \n\t \x1c#|é日🙂"), max_size=120)


@settings(max_examples=300, deadline=None)
@given(TEXTS)
def test_repetition_counts_equal_brute_force(text):
    got = quality.measure(text.encode(), quality.RepetitionRules())
    assert (*got[:5], got[7]) == brute_profile(text)
    assert not (got[7] and got[8])


def brute_verdict(text):
    """(largest n-gram share, line share, kept) by sets of words, with the production limits."""
    words = words_of(text)
    total, rules = sum(map(len, words)), quality.RepetitionRules()
    if brute_profile(text)[5]:
        kept = False
    else:
        kept = True
    worst = 0.0
    for n, limit in rules.ngram_limits.items():
        seen, copies = set(), set()
        for i in range(len(words) - n + 1):
            key = tuple(words[i : i + n])
            if key in seen:
                copies.update(range(i, i + n))
            seen.add(key)
        share = sum(len(words[i]) for i in copies) / total if total else 0.0
        worst = max(worst, share)
        kept &= len(copies) < rules.copy_words or share <= limit
    seen, chars, count = set(), 0, 0
    for line in (text or "").split("\n"):
        if line in seen:
            chars, count = chars + sum(map(len, words_of(line))), count + len(words_of(line))
        seen.add(line)
    kept &= count < rules.copy_words or chars <= rules.line_limit * total
    return worst, chars / total if total else 0.0, kept


@settings(max_examples=150, deadline=None)
@given(st.lists(st.lists(st.sampled_from("abcdefghijklm"), min_size=1, max_size=12), max_size=25))
def test_repetition_verdicts_equal_brute_force(parts):
    text = "\n".join(" ".join(p) for p in parts)
    worst, lines_share, kept = brute_verdict(text)
    got = quality.measure(text.encode(), quality.RepetitionRules())
    assert abs(got[5] - worst) < 1e-12 and abs(got[6] - lines_share) < 1e-12 and got[8] == kept


def test_repetition_verdicts_on_planted_copies():
    fresh = lambda n, tag: " ".join(f"{tag}{i}" for i in range(n))
    cases = [(fresh(200, "a"), True), (fresh(92, "a") + "\n" + fresh(8, "a"), True), (fresh(150, "a") + " " + fresh(14, "a"), False), (fresh(400, "a") + " " + fresh(14, "a"), True)]
    for text, kept in cases:
        assert quality.measure(text.encode(), quality.RepetitionRules())[8] == kept == brute_verdict(text)[2]


def test_repetition_edge_cases(spark):
    long = " ".join(f"w{i}" for i in range(60_000))
    rows = [(1, None), (2, ""), (3, long), (3, long), (None, "a b c d e f g h i j"), (5, " ".join(["a b c d e"] * 9))]
    got = quality.repetition_profile(docs_of(spark, rows)).collect()
    assert len(got) == 6
    by = {(r["doc_id"], r["n_words"]): r for r in got}
    assert by[(1, 0)]["base_failed"] and not by[(2, 0)]["kept"] and by[(3, 60_000)]["kept"] and by[(None, 10)]["kept"] and by[(5, 45)]["n_repeat_words"] == 45
    clash = docs_of(spark, rows).selectExpr("doc_id", "text", "1 AS kept", "2 AS n_words")
    left = quality.filter_repetitive(clash)
    assert left.columns == clash.columns and sorted(str(r["doc_id"]) for r in left.collect()) == ["3", "3", "None"]
    assert quality.repetition_profile(docs_of(spark, [])).count() == 0


# ---- line runs


def brute_lines(rows, min_words):
    """Texts left, by the definition: lines in any run of min_words words or more that an earlier document has, or the same text further up."""
    where = {}
    parsed = []
    for doc, text in rows:
        ls = (text or "").split("\n")
        at = [i for i, x in enumerate(ls) if words_of(x)]
        runs = []
        for i in range(len(at)):
            total = 0
            for j in range(i, len(at)):
                total += len(words_of(ls[at[j]]))
                if total >= min_words:
                    runs.append((i, j + 1, tuple(ls[k] for k in at[i : j + 1])))
        key = (1 << 62) if doc is None else doc
        for i, _, run in runs:
            where.setdefault(run, []).append((key, text, i))
        parsed.append((key, text, ls, at, runs))
    out = []
    for key, text, ls, at, runs in parsed:
        gone = [False] * len(at)
        for i, j, run in runs:
            if any(d < key or (d == key and t == text and k < i) for d, t, k in where[run]):
                gone[i:j] = [True] * (j - i)
        deleted = {at[k] for k, g in enumerate(gone) if g}
        for k in range(1, len(at)):
            if gone[k] and gone[k - 1]:
                deleted.update(range(at[k - 1], at[k]))
        out.append(text if not text else "\n".join(x for i, x in enumerate(ls) if i not in deleted))
    return out


@settings(max_examples=300, deadline=None)
@given(st.lists(st.integers(1, 12), max_size=30), st.integers(1, 12))
def test_shortest_runs(words, least):
    ahead, behind = lines.shortest_runs(words, least)
    for i in range(len(words)):
        assert ahead[i] == next((j - i for j in range(i + 1, len(words) + 1) if sum(words[i:j]) >= least), 0)
        assert behind[i] == next((i - j + 1 for j in range(i, -1, -1) if sum(words[j : i + 1]) >= least), 0)


@pytest.mark.parametrize("min_words", [1, 4, 7, 10])
def test_line_runs_equal_brute_force(spark, min_words):
    rng = random.Random(min_words)
    pool = ["a b c", "d e", "f", "", "  ", "g h i j", "k l m n o", "é ü", "p"]
    passage = ["p", "f", "d e", "p", "x", "f", "é ü", "y z", "f", "p", "f", "q", "a b c"]
    rows = [(i, "\n".join(rng.choice(pool) for _ in range(rng.randrange(1, 12)))) for i in range(60)]
    rows += [(70 + i, "\n".join([f"own {i}", *passage[i % 3 : 13 - i % 2], "", f"more {i}"])) for i in range(6)]
    rows += [(100, None), (101, ""), (None, "g h i j\nx"), (None, "g h i j\ny"), (80, "\n".join(passage * 2)), (5, rows[5][1]), (5, rows[5][1])]
    got = lines.dedup_lines(docs_of(spark, rows), min_words=min_words, keep_empty=True)
    want = brute_lines(rows, min_words)
    assert sorted((str(r["doc_id"]), str(r["text"])) for r in got.collect()) == sorted((str(d), str(w)) for (d, _), w in zip(rows, want, strict=True))


def test_line_dedup_edge_cases(spark):
    same = "one two three four five six seven eight nine ten"
    frame = spark.createDataFrame([(1, same, "x"), (2, same, "y"), (1, same, "z"), (3, f"{same}\nmore", "w")], "doc_id long, text string, _names string").withColumnRenamed("_names", "_DOC").withColumn("_Row", F.lit(1)).withColumn("_docr", F.lit(2)).withColumn("_rowr", F.lit(2))
    got = lines.dedup_lines(frame)
    assert got.columns == frame.columns
    assert sorted((r["doc_id"], r["text"], r["_DOC"]) for r in got.collect()) == [(1, same, "x"), (1, same, "z"), (3, "more", "w")]
    assert lines.dedup_lines(docs_of(spark, [])).count() == 0
    long = "\n".join(f"line {i} of a long text" for i in range(30_000))
    report = {r["doc_id"]: r for r in lines.dedup_lines(docs_of(spark, [(1, long), (2, f"{long}\nend")]), report=True).collect()}
    assert report[1]["n_deleted"] == 0 and (report[2]["n_deleted"], report[2]["n_runs"], report[2]["text_left"]) == (30_000, 1, "end")


# ---- suffixes


def covered_by_brute_force(rows, n=50):
    seen, out = set(), {}
    for doc, text in sorted((r for r in rows if r[0] is not None), key=lambda r: r[0]):
        w, c = words_of(text), set()
        for i in range(len(w) - n + 1):
            key = tuple(w[i : i + n])
            if key in seen:
                c.update(range(i, i + n))
            seen.add(key)
        if c:
            out[doc] = c
    return out


def test_suffix_matches_equal_brute_force(spark):
    rng = random.Random(2)
    word = lambda: rng.choice("abcdefgh") + rng.choice("abcdefgh") + rng.choice("abcdefgh")
    shared = [[word() for _ in range(k)] for k in (49, 50, 51, 80, 300)]
    rows = []
    for i in range(40):
        parts = [[word() for _ in range(rng.randrange(5, 120))]]
        for _ in range(rng.randrange(3)):
            parts += [rng.choice(shared), [word() for _ in range(rng.randrange(0, 60))]]
        rows.append((i, " ".join(x for p in parts for x in p)))
    rows += [(50, rows[0][1]), (51, None), (52, ""), (53, "a " * 400)]
    got = defaultdict(set)
    for r in suffix.repeated_passages(docs_of(spark, rows)).collect():
        assert r["n_words"] == r["word_stop"] - r["word_start"] >= 50
        got[r["doc_id"]].update(range(r["word_start"], r["word_stop"]))
    want = covered_by_brute_force(rows)
    assert dict(got) == want and 50 in got and 53 in got
    assert suffix.repeated_passages(docs_of(spark, [])).count() == 0


def test_suffix_hot_clauses_with_many_continuations(spark):
    """Equal beginnings of 32 words and more that go on differently must not hide the two that go on alike."""
    rng = random.Random(12)
    fresh = iter(range(10**6))
    words = lambda n: [f"u{next(fresh)}" for _ in range(n)]
    docs = [words(20) for _ in range(30)]
    for _ in range(40):
        clause, after = words(45), words(10)
        alike = rng.sample(range(30), 2)
        for i, doc in enumerate(docs):
            doc += words(3) + clause + (after if i in alike else []) + words(30)
    rows = [(i, " ".join(d)) for i, d in enumerate(docs)]
    got = defaultdict(set)
    for r in suffix.repeated_passages(docs_of(spark, rows)).collect():
        got[r["doc_id"]].update(range(r["word_start"], r["word_stop"]))
    assert dict(got) == covered_by_brute_force(rows) and sum(map(len, got.values())) == 40 * 55


@pytest.mark.parametrize("partitions", [1, 7, 61])
def test_suffix_result_is_the_same_for_any_number_of_partitions(spark, partitions):
    rng = random.Random(13)
    words = lambda n: [f"v{rng.randrange(10**9)}" for _ in range(n)]
    docs = [words(40) for _ in range(60)]
    for _ in range(150):
        passage = words(50)
        for i in rng.sample(range(60), 2):
            docs[i] += passage + words(4)
    rows = [(i, " ".join(d)) for i, d in enumerate(docs)]
    names = {"spark.sql.shuffle.partitions": str(partitions), "spark.sql.adaptive.coalescePartitions.enabled": "false"}
    before = {n: spark.conf.get(n) for n in names}
    try:
        for n, v in names.items():
            spark.conf.set(n, v)
        found = suffix.repeated_passages(docs_of(spark, rows)).collect()
    finally:
        for n, v in before.items():
            spark.conf.set(n, v)
    got = defaultdict(set)
    for r in found:
        got[r["doc_id"]].update(range(r["word_start"], r["word_stop"]))
    assert dict(got) == covered_by_brute_force(rows)


def test_suffix_repeated_rows_and_null_ids(spark):
    text = " ".join(f"w{i}" for i in range(70))
    got = suffix.repeated_passages(docs_of(spark, [(1, text), (1, text), (None, text)])).collect()
    assert [(r["doc_id"], r["n_words"]) for r in got] == [(None, 70)]


# ---- similarity join


def brute_components(rows):
    sets = []
    for _, text in rows:
        w = [x.translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")) for x in words_of(text)]
        sets.append({tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set()))
    up = list(range(len(rows)))

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for i in range(len(rows)):
        for j in range(i):
            both = len(sets[i] & sets[j])
            if sets[i] and sets[j] and 100 * both >= 75 * (len(sets[i]) + len(sets[j]) - both):
                up[root(i)] = root(j)
    least = {}
    for i, (doc, _) in enumerate(rows):
        least[root(i)] = min(least.get(root(i), doc), doc)
    return sorted((doc, len(sets[i]), least[root(i)]) for i, (doc, _) in enumerate(rows))


def near(rng, words, changes):
    words = list(words)
    for _ in range(changes):
        at, kind = rng.randrange(len(words)), rng.randrange(3)
        words[at : at + (kind != 1)] = [f"n{rng.randrange(1000)}"] if kind else []
    return words


def test_join_equals_brute_force(spark):
    rng = random.Random(4)
    rows, i = [], 0
    for size in (1, 3, 5, 6, 9, 30, 64, 80, 150, 600):
        for _ in range(3):
            base = [f"w{rng.randrange(3000)}" for _ in range(size)]
            for _ in range(rng.randrange(1, 30)):  # chains and large groups
                rows.append((i, " ".join(base)))
                i += 1
                if rng.random() < 0.5:
                    base = near(rng, base, max(1, size // 40)) or ["x"]
    hot = " ".join(f"h{k}" for k in range(40))
    rows += [(i + k, f"{hot} " + " ".join(f"u{k}x{j}" for j in range(20))) for k in range(60)]
    rows += [(9000, None), (9001, ""), (9002, " \n "), (9003, "A b C"), (9004, "a B c"), (9004, "a B c"), (9005, "a b")]
    got = sorted((r["doc_id"], r["n_shingles"], r["component_id"]) for r in jaccard.similarity_components(docs_of(spark, rows)).collect())
    assert got == brute_components(rows)
    left = jaccard.keep_first(docs_of(spark, rows).selectExpr("doc_id", "text", "1 AS part", "2 AS node"))
    assert left.columns == ["doc_id", "text", "part", "node"]
    assert sorted(r["doc_id"] for r in left.collect()) == sorted(d for d, _, c in brute_components(rows) if d == c)


def brute_links(rows):
    sets = {doc: frozenset(shingle_set(text.encode()).tolist()) for doc, text in rows}
    texts = set(sets.values()) - {frozenset()}
    return {doc: sum(x != y and 100 * len(x & y) >= 75 * len(x | y) for y in texts) if x else 0 for doc, x in sets.items()}


def test_links_are_counted_in_small_and_large_buckets(spark):
    rng = random.Random(6)
    rows = []
    for size, copies, changes in ((100, 20, 1), (100, 17, 2), (60, 16, 1), (200, 90, 6), (30, 5, 1), (80, 500, 1)):
        base = [f"w{rng.randrange(10**6)}" for _ in range(size)]
        rows += [(len(rows) + k, " ".join(near(rng, base, changes))) for k in range(copies)]
    rows += [(5000, rows[0][1]), (5001, rows[0][1].upper()), (5002, ""), (5003, "x y")]
    got = {r["doc_id"]: r["n_links"] for r in jaccard.similarity_components(docs_of(spark, rows)).collect()}
    want = brute_links(rows)
    assert got == want and want[0] >= 18


def test_join_of_nothing(spark):
    assert jaccard.similarity_components(docs_of(spark, [])).count() == 0


def test_frequent_class_changes_no_link():
    """With any frequent table, two similar sets share an index key."""
    rng = np.random.default_rng(3)
    for n in (5, 40, 64, 70, 200, 515, 600, 4100):
        base = np.unique(rng.integers(1 << 30, 1 << 63, n, dtype=np.uint64))
        other = np.unique(np.concatenate((base[len(base) // 8 :], rng.integers(1 << 30, 1 << 63, len(base) // 9, dtype=np.uint64))))
        assert jaccard.similar(base, other) or n < 9
        for share in (0.0, 0.4, 1.0):
            table = np.unique((base >> np.uint64(16))[rng.random(len(base)) < share])
            counts = rng.integers(8, 99, len(table))
            if jaccard.similar(base, other):
                assert len(np.intersect1d(jaccard.index_keys(base, table, counts), jaccard.index_keys(other, table, counts)))


def test_frequent_class_follows_the_corpus(spark):
    """No shingle of many texts is left in the rare class because others are frequent, too; rare ones stay rare, most of them."""
    often, rare = (" ".join(f"{x}{k}" for k in range(n)) for x, n in (("w", 300_000), ("r", 50_000)))
    rows = [(k, often) for k in range(jaccard.FREQUENT_DOCS)] + [(100, rare)]
    table = jaccard.frequent_shingles(docs_of(spark, rows).repartition(4), "text")
    assert (jaccard.levels(shingle_set(often.encode()), table) > 0).all()
    assert (jaccard.levels(shingle_set(rare.encode()), table) == 0).mean() > 0.8
    assert not jaccard.levels(shingle_set(rare.encode()), jaccard.frequent_shingles(docs_of(spark, [(1, rare)]), "text")).any()


def test_blobs_round_trip_and_shingles():
    x = np.sort(np.random.default_rng(1).integers(0, 1 << 40, 1000, dtype=np.uint64))
    assert (jaccard.unpack_sorted(jaccard.pack_sorted(x)) == x).all() and not len(jaccard.unpack_sorted(jaccard.pack_sorted(x[:0])))


def test_sketches_rule_out_no_similar_pair():
    rng = np.random.default_rng(5)
    ruled_out = 0
    for n in (1, 3, 8, 60, 64, 65, 300, 1024, 5000):
        base = np.unique(rng.integers(0, 2**64, n, dtype=np.uint64))
        for changed in (0, n // 10, n // 7, n // 6, n // 4, n // 2, n):
            for extra in (0, n // 5, n // 3):
                other = np.unique(np.concatenate((base[changed:], rng.integers(0, 2**64, extra + changed // 2, dtype=np.uint64))))
                if not len(other):
                    continue
                may = jaccard.may_link(jaccard.sketch(base), jaccard.sketch(other), len(base), len(other))
                assert may == jaccard.may_link(jaccard.sketch(other), jaccard.sketch(base), len(other), len(base))
                assert may or not jaccard.similar(base, other)
                ruled_out += not may
    assert ruled_out > 40


def test_join_moves_only_promising_texts_and_leaves_no_large_tables(spark, tmp_path, monkeypatch):
    """Of many pairs with a common passage the texts don't travel, and what the join wrote of texts and index is gone when it returns."""
    rng = random.Random(3)
    passage = " ".join(f"p{k}" for k in range(12))
    rows = [(k, passage + " " + " ".join(f"w{rng.randrange(10**6)}" for _ in range(40))) for k in range(7)]
    rows.append((10, rows[0][1] + " end"))
    seen, made = [], []
    verify, materialize = jaccard.verify, jaccard.materialize
    monkeypatch.setattr(jaccard, "verify", lambda pairs, texts: seen.append(pairs.count()) or verify(pairs, texts))
    monkeypatch.setattr(jaccard, "materialize", lambda df, tag="stage": made.append((tag, out := materialize(df, tag), out.inputFiles()[:1])) or out)
    got = {r["doc_id"]: r["component_id"] for r in jaccard.similarity_components(docs_of(spark, rows)).collect()}
    assert got == {k: 0 if k == 10 else k for k, _ in rows}
    assert seen == [1]
    large = [f for tag, _, files in made if tag in ("index", "candidates", "texts") for f in files]
    assert large and not [f for f in large if Path(f.removeprefix("file:").replace("///", "/")).exists()]


def test_trimmed_mappers_pass_all_rows(spark):
    ended = []
    def double(batches):
        yield from (b for x in batches for b in (x, x))
        ended.append(1)
    assert list(trimmed(double)(iter([1, 2]))) == [1, 1, 2, 2] and ended
    assert spark.range(1000).mapInArrow(trimmed(lambda batches: batches), "id long").count() == 1000
    assert (shingle_set(b"A b  c\nd e F") == shingle_set(b"a B c d e f")).all() and len(shingle_set(b"a b c d e f")) == 2
    assert len(shingle_set(b" \t")) == 0 and len(shingle_set(b"a b")) == 1


def test_components_of_a_long_chain_and_a_star(spark):
    rows = [(i, i + 1) for i in range(60)] + [(100, i) for i in range(101, 140)]
    got = {r["node"]: r["component"] for r in components(spark.createDataFrame(rows, "a long, b long")).collect()}
    assert all(got[i] == 0 for i in range(61)) and all(got[i] == 100 for i in range(100, 140))
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


# ---- decontamination


def test_leaks(spark):
    rng = random.Random(8)
    text = lambda n: " ".join(f"q{rng.randrange(500)}" for _ in range(n))
    items = [(i, text(n)) for i, n in enumerate((15, 20, 37, 57))] + [(8, None), (9, ""), (10, "no such words"), (11, text(7))]
    one = items[2][1].split()
    one[2] = "changed"
    rows = [(1, f"{text(30)} {items[0][1]} {text(40)}"), (2, text(300)), (3, f"x {' '.join(one)}"), (4, items[3][1].upper()), (5, None), (6, ""), (7, "a b"), (8, items[2][1][: len(items[2][1]) // 2]), (9, f"{text(3)} {items[1][1]}"), (9, f"{text(3)} {items[1][1]}")]
    docs = docs_of(spark, rows)
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = {(r["doc_id"], r["item_id"]): (r["word_start"], r["similarity"]) for r in decontam.find_leaks(docs, bench).collect()}
    assert got[(1, 0)] == (30, 1.0) and got[(4, 3)] == (0, 1.0) and got[(9, 1)] == (3, 1.0) and got[(3, 2)][0] == 1 and 0.75 <= got[(3, 2)][1] < 1
    assert set(got) == {(1, 0), (3, 2), (4, 3), (9, 1)}
    left = decontam.drop_leaks(docs.selectExpr("doc_id", "text", "1 AS _leak"), bench)
    assert sorted(r["doc_id"] for r in left.collect()) == [2, 5, 6, 7, 8] and left.columns == ["doc_id", "text", "_leak"]
    assert decontam.find_leaks(docs_of(spark, []), bench).count() == 0 and decontam.find_leaks(docs, bench.where("false")).count() == 0


def leaks_by_sql(rows, items):
    import duckdb
    import pandas as pd

    from hyperpath.llm.queries import ORACLE_SQL

    con = duckdb.connect()
    con.register("documents", pd.DataFrame(rows, columns=["doc_id", "text"]))
    con.register("benchmark", pd.DataFrame(items, columns=["item_id", "text"]))
    return sorted(con.execute(ORACLE_SQL["op1_decontaminate"]).fetchall())


def found_leaks(spark, rows, items):
    got = decontam.find_leaks(docs_of(spark, rows), spark.createDataFrame(items, "item_id long, text string"))
    return sorted((r["doc_id"], r["item_id"], r["word_start"], r["similarity"]) for r in got.collect())


def test_leaks_with_a_common_opening_equal_sql(spark):
    """Forty items of ten words with one opening, each planted with one word changed at four alignments."""
    rng = random.Random(12)
    items = [(i, " ".join(["which", "is", "the", "best", "of", "all", *(f"v{i}x{j}" for j in range(4))])) for i in range(40)]
    rows = []
    for i, text in items:
        for lead in range(4):
            w = text.split()
            w[0] = "changed"
            rows.append((len(rows), " ".join([*(f"f{rng.randrange(999)}" for _ in range(20 + lead)), *w, *(f"f{rng.randrange(999)}" for _ in range(9))])))
    got = found_leaks(spark, rows, items)
    assert got == leaks_by_sql(rows, items) and len(got) == 160


@pytest.mark.parametrize("seed", [1, 2])
def test_leaks_of_all_sizes_equal_sql(spark, seed):
    rng = random.Random(seed)
    word = lambda: f"q{min(int(rng.expovariate(0.01)), 900)}"
    items = [(n, " ".join(word() for _ in range(n))) for n in (*range(1, 40), 55, 70, 90)]
    items += [(100 + i, items[30 + i][1].rsplit(" ", 5)[0] + " other end of this one") for i in range(4)]
    rows = []
    for _ in range(400):
        w = rng.choice(items)[1].split()
        for _ in range(rng.choice((0, 0, 1, 1, 2, 3))):
            at, kind = rng.randrange(len(w)), rng.randrange(3)
            w[at : at + (kind < 2)] = [] if kind == 0 else [word()]
            w = w or ["x"]
        if rng.random() < 0.2:
            w = w[rng.randrange(len(w)) :]
        rows.append((len(rows), " ".join([*(word() for _ in range(rng.choice((0, 3, 17)))), *w, *(word() for _ in range(rng.choice((0, 5))))])))
    got, want = found_leaks(spark, rows, items), leaks_by_sql(rows, items)
    assert got == want and len({d for d, *_ in want}) > 150


def test_leaks_in_long_texts(spark):
    item = " ".join(f"i{j}" for j in range(200))
    long = " ".join(f"w{j}" for j in range(60_000))
    rows = [(1, f"{long} {item} {long}"), (2, long), (3, item.replace("i100 ", "")), (4, item)]
    assert [(d, s) for d, _, s, _ in found_leaks(spark, rows, [(7, item), (8, "i5 i6 i7 i8 i9 i10")])] == [(1, 60_000), (1, 60_005), (3, 0), (3, 5), (4, 0), (4, 5)]


# ---- mixing


def test_shortages_go_to_siblings_first(spark):
    plan = mixing.MixPlan(weights={"domain": {"a": 3, "b": 1}}, budget_parts=(1, 1), max_epochs=1)
    leaves = spark.createDataFrame([("a", "x", "1", 10), ("a", "x", "2", 400), ("a", "y", "3", 30), ("b", "x", "4", 560)], "domain string, lang string, source string, tokens long")
    full = {r["source"]: r["budget"] for r in mixing.leaf_budgets(leaves, plan).collect()}
    assert full == {"1": 10, "2": 400, "3": 30, "4": 560}
    half = mixing.MixPlan(weights={"domain": {"a": 3, "b": 1}}, budget_parts=(1, 2), max_epochs=1)
    got = {r["source"]: r["budget"] for r in mixing.leaf_budgets(leaves, half).collect()}
    # 375 to a and 125 to b; y can't use its half, so x takes 345, of which source 1 can give 10.
    assert got == {"1": 10, "2": 335, "3": 30, "4": 125}


def test_mix_takes_prefixes_of_seeded_epochs(spark):
    rows = [(i, "w " * (1 + i % 7), "en" if i % 3 else "de", f"src{i % 5}") for i in range(400)] + [(500, None, None, None), (501, "", "en", ""), (7, "w w", "en", "src2")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string").withColumn("epoch", mixing.F.lit("kept"))
    out = mixing.mix(docs, mixing.MixPlan(budget_parts=(5, 4), max_epochs=3))
    assert out.columns == [*docs.columns, "domain", "n_tokens", "_epoch"]
    got = out.collect()
    total = sum(len(words_of(t)) for _, t, _, _ in rows)
    assert 0.9 * total * 5 / 4 < sum(r["n_tokens"] for r in got) <= total * 5 / 4
    assert max(r["_epoch"] for r in got) <= 3 and sorted(r["doc_id"] for r in got) == sorted(r["doc_id"] for r in mixing.mix(docs, mixing.MixPlan(budget_parts=(5, 4), max_epochs=3)).collect())
    assert mixing.mix(docs.where("false")).count() == 0


# ---- clashing names


def test_helper_names_clash_with_no_column(spark):
    text = " ".join(f"w{i}" for i in range(40))
    names = ["_mix_id", "_MIX_tokens", "_mix_epochs", "_mix_bound", "_mix_times", "_leaf_lang", "_gone", "_leak", "_doc", "n_tokens", "epoch"]
    docs = spark.createDataFrame([(1, text, "en", "s1"), (2, text, "en", "s1"), (3, "a b c", None, None)], "doc_id long, text string, lang string, source string")
    docs = docs.select("*", *(F.lit(i).alias(n) for i, n in enumerate(names)))
    assert mixing.mix(docs).count() > 0
    left = jaccard.keep_first(docs)
    assert left.columns == docs.columns and sorted(r["doc_id"] for r in left.collect()) == [1, 3]
    assert jaccard.similarity_components(docs.withColumn("node", F.lit(1)).withColumn("n_links", F.lit(2))).count() == 3
    assert suffix.repeated_passages(docs.withColumn("doc", F.lit(1)).withColumn("own", F.lit(2))).count() == 0
