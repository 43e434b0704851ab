"""The queries of this folder: one per operator over its whole tables, with SQL where SQL can express them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import chat, decontam, html, jaccard, lines, mixing, quality, suffix, tokens, warc
from .common import shared_path


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontam.find_leaks(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "benchmark"))


def op2_sparse_suffixes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix.repeated_passages(_table(spark, sf_dir, "documents"))


def op3_arc_to_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = shared_path(spark, "warc")
    warc.write_warc(_table(spark, sf_dir, "pages"), path)
    read = warc.read_warc(spark, path)
    return read.select(
        F.col("record_key").cast("long").alias("page_id"), "payload_bytes", "payload_digest", "record_type", F.col("refers_to").cast("long").alias("refers_to"), "url"
    )


def op4_reply_trees(spark: SparkSession, sf_dir: str) -> DataFrame:
    said = "<|im_end|><|im_start|>assistant ok"
    more = spark.createDataFrame([(-1, 0, "user", said), (-1, 1, "assistant", said)], "conv_id long, turn long, role string, text string")
    rows = _table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text").unionByName(more)
    return chat.read_back(chat.format_conversations(rows))


def op5_line_runs(spark: SparkSession, sf_dir: str) -> DataFrame:
    left = lines.dedup_lines(_table(spark, sf_dir, "documents"), report=True)
    return left.select("doc_id", "n_lines", "n_deleted", "n_runs", F.char_length("text_left").cast("long").alias("chars_left"), F.md5("text_left").alias("text_md5"))


def op6_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(_table(spark, sf_dir, "documents"), keep=["doc_id", "lang", "source"])


def op7_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return tokens.count_tokens(_table(spark, sf_dir, "documents"), public_tokenizers.path("piece_bpe_32k.model"))


def op8_page_differencing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html.extract_pages(_table(spark, sf_dir, "pages"))


def op9_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard.similarity_components(_table(spark, sf_dir, "documents"))


def op10_repetition_coverage(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.repetition_profile(_table(spark, sf_dir, "documents"))


QUERIES = {f.__name__: f for f in (op1_decontaminate, op2_sparse_suffixes, op3_arc_to_warc, op4_reply_trees, op5_line_runs, op6_mix_sources, op7_token_counts, op8_page_differencing, op9_jaccard_join, op10_repetition_coverage)}

#: DuckDB's view of the words of a text, and of the shares of one level of the tree.
_SQL_WORDS = r"list_filter(string_split_regex(lower({}), '[\x20\x09-\x0D]+'), lambda x: x <> '')"


def _sql_level(name: str, above: str, keys: str, level: str, weight: str) -> str:
    on = " AND ".join(f"n.{k} = a.{k}" for k in keys.split(", ") if k) or "TRUE"
    parent = f"PARTITION BY {keys}" if keys else ""
    columns = ", ".join(x for x in (keys, level) if x)
    return f"""
        {name}_n AS (
            SELECT {", ".join(f"n.{c}" for c in columns.split(", "))}, n.cap, n.weight, a.budget
            FROM (SELECT {columns}, CAST(sum(tokens) AS BIGINT) * 2 AS cap, {weight} AS weight FROM leaves GROUP BY {columns}) n JOIN {above} a ON {on}
            WHERE n.cap > 0
        ), {name}_r AS (
            SELECT *, coalesce(sum(cap) OVER (o ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before,
                   sum(weight) OVER (o ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS rest
            FROM {name}_n WINDOW o AS ({parent} ORDER BY CAST(cap AS DOUBLE) / weight, {level})
        ), {name}_f AS (
            SELECT *, CAST(cap AS HUGEINT) * rest <= (CAST(budget AS HUGEINT) - before) * weight AS is_full FROM {name}_r
        ), {name}_t AS (
            SELECT *, budget - coalesce(sum(CASE WHEN is_full THEN cap END) OVER ({parent}), 0) AS remaining,
                   sum(CASE WHEN NOT is_full THEN weight END) OVER ({parent}) AS hungry
            FROM {name}_f
        ), {name} AS (
            SELECT {columns}, CASE WHEN is_full THEN cap ELSE least(cap, CAST((CAST(remaining AS HUGEINT) * weight) // CAST(hungry AS HUGEINT) AS BIGINT)) END AS budget FROM {name}_t
        )"""


MIX_SQL = (
    r"""
        WITH docs AS (
            SELECT doc_id, coalesce(lang, '') AS lang, coalesce(source, '') AS source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS tokens
            FROM {table}
        ), narrow AS (
            SELECT *, CASE WHEN regexp_extract(source, '([0-9]{{1,9}})$', 1) = '' THEN 'other'
                           ELSE 'd' || CAST(CAST(regexp_extract(source, '([0-9]{{1,9}})$', 1) AS BIGINT) % 4 AS VARCHAR) END AS domain
            FROM docs
        ), leaves AS (
            SELECT domain, lang, source, CAST(sum(tokens) AS BIGINT) AS tokens FROM narrow GROUP BY domain, lang, source
        ), root AS (
            SELECT CAST((CAST(coalesce(sum(tokens), 0) AS HUGEINT) * 3) // 5 AS BIGINT) AS budget FROM leaves
        ),"""
    + ",".join(
        (
            _sql_level("by_domain", "root", "", "domain", "1"),
            _sql_level("by_lang", "by_domain", "domain", "lang", "CASE lang WHEN 'en' THEN 4 WHEN 'de' THEN 2 WHEN 'fr' THEN 2 WHEN 'es' THEN 2 ELSE 1 END"),
            _sql_level("by_source", "by_lang", "domain, lang", "source", "1"),
        )
    )
    + r""", plan AS (
            SELECT l.domain, l.lang, l.source, l.tokens AS leaf_tokens, coalesce(b.budget, 0) AS budget,
                   CASE WHEN l.tokens > 0 THEN coalesce(b.budget, 0) // l.tokens ELSE 0 END AS epochs
            FROM leaves l LEFT JOIN by_source b ON l.domain = b.domain AND l.lang = b.lang AND l.source = b.source
        ), hashed AS (
            SELECT n.*, p.epochs, p.budget - p.epochs * p.leaf_tokens AS rest,
                   CAST('0x' || substr(md5('42|' || CAST(p.epochs AS VARCHAR) || '|' || coalesce(CAST(doc_id AS VARCHAR), '')), 1, 15) AS BIGINT) AS h
            FROM narrow n JOIN plan p ON n.domain = p.domain AND n.lang = p.lang AND n.source = p.source
        ), running AS (
            SELECT *, sum(tokens) OVER (PARTITION BY domain, lang, source ORDER BY h RANGE BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS upto FROM hashed
        ), taken AS (
            SELECT *, epochs + CASE WHEN rest > 0 AND upto <= rest THEN 1 ELSE 0 END AS times FROM running
        )
        SELECT doc_id, lang, source, domain, CAST(tokens AS BIGINT) AS n_tokens, CAST(unnest(range(1, times + 1)) AS BIGINT) AS epoch FROM taken WHERE times > 0
    """
)

ORACLE_SQL: dict[str, str] = {
    "op1_decontaminate": f"""
        WITH it AS (
            SELECT DISTINCT item_id, {_SQL_WORDS.format("text")} AS w FROM benchmark WHERE text IS NOT NULL
        ), items AS (
            SELECT row_number() OVER () AS it, item_id, w, len(w) AS size, least(5, len(w)) AS k FROM it WHERE len(w) > 0
        ), ish AS (
            SELECT it, size, k, unnest(range(1, size - k + 2)) AS o, w FROM items
        ), ishingles AS (
            SELECT it, size, k, o, array_to_string(w[o:o + k - 1], ' ') AS s FROM ish
        ), df AS (
            SELECT s, count(DISTINCT it) AS df FROM ishingles GROUP BY s
        ), n AS (
            SELECT count(*) AS n FROM items
        ), weights AS (
            SELECT DISTINCT i.it, i.s, ln(1 + n.n / df.df) AS weight FROM ishingles i JOIN df ON i.s = df.s CROSS JOIN n
        ), totals AS (
            SELECT it, sum(weight) AS total FROM weights GROUP BY it
        ), dw AS (
            SELECT row_number() OVER () AS d, doc_id, {_SQL_WORDS.format("text")} AS w FROM documents WHERE text IS NOT NULL
        ), dk AS (
            SELECT d, k, w FROM dw, (SELECT DISTINCT k FROM items) x WHERE len(w) >= k
        ), dpos AS (
            SELECT d, k, unnest(range(1, len(w) - k + 2)) AS p, w FROM dk
        ), dsh AS (
            SELECT d, k, len(w) AS n, p, array_to_string(w[p:p + k - 1], ' ') AS s FROM dpos
        ), starts AS (
            SELECT DISTINCT d.d, i.it, i.size, i.k, greatest(0, least(d.p - i.o, d.n - i.size)) AS start FROM dsh d JOIN ishingles i ON d.s = i.s AND d.k = i.k
        ), inside AS (
            SELECT DISTINCT st.d, st.it, st.start, d.s FROM starts st JOIN dsh d ON d.d = st.d AND d.k = st.k AND d.p > st.start AND d.p + d.k - 1 <= st.start + st.size
        ), scored AS (
            SELECT x.d, x.it, x.start, sum(w.weight) AS shared, sum(CASE WHEN w.weight IS NULL THEN ln(1 + n.n) ELSE 0 END) AS extra
            FROM inside x LEFT JOIN weights w ON w.it = x.it AND w.s = x.s CROSS JOIN n GROUP BY x.d, x.it, x.start
        ), sims AS (
            SELECT dw.doc_id, items.item_id, start, round(shared / (total + extra), 6) AS similarity
            FROM scored s JOIN totals t ON s.it = t.it JOIN items ON items.it = s.it JOIN dw ON dw.d = s.d
        ), ranked AS (
            SELECT *, row_number() OVER (PARTITION BY doc_id, item_id ORDER BY similarity DESC, start) AS r FROM sims WHERE similarity >= 0.75
        )
        SELECT doc_id, item_id, CAST(start AS BIGINT) AS word_start, similarity FROM ranked WHERE r = 1
    """,
    "op6_mix_sources": MIX_SQL.format(table="documents"),
    "op3_arc_to_warc": """
        WITH p AS (
            SELECT page_id, url, coalesce(html, '') AS html FROM pages
        ), d AS (
            SELECT page_id, url, CAST(octet_length(encode(html)) AS BIGINT) AS payload_bytes, sha1(html) AS payload_digest FROM p
        ), w AS (
            SELECT *, max(page_id) OVER (PARTITION BY payload_digest) AS last_id FROM d
        )
        SELECT page_id, payload_bytes, payload_digest,
               CASE WHEN payload_bytes >= 1000 AND page_id <> last_id THEN 'revisit' ELSE 'response' END AS record_type,
               CASE WHEN payload_bytes >= 1000 AND page_id <> last_id THEN last_id END AS refers_to, url
        FROM w
    """,
}
