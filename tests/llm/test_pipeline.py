"""The pipeline against a brute-force version on a fixture, and the queries that have SQL."""

import duckdb
import pytest

import corpus_pipeline
from hyperpath.llm import quality
from hyperpath.llm.queries import MIX_SQL, ORACLE_SQL, QUERIES

from test_documents import brute_components, brute_lines, words_of


@pytest.fixture(scope="module")
def fixture(spark, small, tmp_path_factory):
    """150 documents with copies, near copies, repeated lines and leaks."""
    folder = tmp_path_factory.mktemp("corpus")
    docs = spark.read.parquet(f"{small}/documents.parquet").orderBy("doc_id").limit(150).collect()
    items = [r["text"] for r in spark.read.parquet(f"{small}/benchmark.parquet").collect()]
    rows = [tuple(r) for r in docs]
    rows += [(1000 + i, r[1], *r[2:]) for i, r in enumerate(rows[:5])]
    rows += [(1100 + i, " ".join([*words_of(r[1])[:-1], "changed"]), *r[2:]) for i, r in enumerate(rows[5:12])]
    rows += [(1200 + i, f"{rows[20 + i][1]} {items[i]}", *rows[20 + i][2:]) for i in range(4)]
    rows += [(1300, None, "en", "src1", 0), (1301, "", "en", None, 0), (1302, "few words", None, "src2", 9)]
    spark.createDataFrame(rows, docs[0].__fields__ and "doc_id long, text string, lang string, source string, n_chars long").coalesce(2).write.parquet(f"{folder}/documents.parquet")
    spark.read.parquet(f"{small}/benchmark.parquet").write.parquet(f"{folder}/benchmark.parquet")
    return str(folder), rows, items


def shingles(text):
    w = words_of(text.lower())
    return {tuple(w[i : i + 5]) for i in range(len(w) - 4)}


def test_pipeline_equals_brute_force(spark, fixture):
    folder, rows, items = fixture
    kept = [r for r in rows if quality.measure((r[1] or "").encode(), quality.RepetitionRules())[-1]]
    left = brute_lines([r[:2] for r in kept], 10)
    lined = [(r[0], t, *r[2:]) for r, t in zip(kept, left, strict=True) if words_of(t)]
    first = {d for d, _, c in brute_components([r[:2] for r in lined]) if d == c}
    single = [r for r in lined if r[0] in first]
    clean = [r for r in single if not any(shingles(i) and shingles(i) <= shingles(r[1]) for i in items)]
    con = duckdb.connect()
    con.execute("CREATE TABLE clean (doc_id BIGINT, text VARCHAR, lang VARCHAR, source VARCHAR)")
    con.executemany("INSERT INTO clean VALUES (?, ?, ?, ?)", [list(r[:4]) for r in clean])
    want = sorted((r[0], r[5]) for r in con.execute("SELECT doc_id, lang, source, domain, n_tokens, epoch FROM (" + MIX_SQL.format(table="clean") + ") x").fetchall())
    got = corpus_pipeline.run(spark, folder)
    assert sorted((r["doc_id"], r["epoch"]) for r in got.collect()) == want
    texts = {r[0]: r[1] for r in clean}
    assert all(texts[r["doc_id"]] == r["text"] and r["n_chars"] == len(r["text"]) for r in got.collect())


def test_stages_keep_the_columns(spark, fixture):
    folder, *_ = fixture
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality_rules", "line_dedup", "jaccard_join", "decontamination", "mixing_to_weights"]
    for _, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, folder)
        assert out.columns == docs.columns
        assert stage(spark, docs.where("false"), folder).count() == 0


@pytest.mark.parametrize("name", sorted(ORACLE_SQL))
def test_queries_equal_their_sql(spark, small, name):
    con = duckdb.connect()
    for t in ("documents", "pages", "benchmark", "conversations"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{small}/{t}.parquet'")
    df = QUERIES[name](spark, small)
    cursor = con.execute(ORACLE_SQL[name])
    columns = sorted(c[0] for c in cursor.description)
    order = [[c[0] for c in cursor.description].index(c) for c in columns]
    assert sorted(df.columns) == columns
    assert sorted(map(str, (tuple(r[c] for c in columns) for r in df.collect()))) == sorted(str(tuple(r[i] for i in order)) for r in cursor.fetchall())
