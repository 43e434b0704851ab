"""TF-IDF of articles and the text similarity of linked articles."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.columns import WORD


def tfidf(texts: DataFrame, *, id_col: str = "node_id", text_col: str = "text", smooth: str = "none", min_df: int = 1, max_terms: int | None = None) -> DataFrame:
    """(node_id, term, tf, df, tfidf): raw counts times ln(N / df), or ln((N + 1) / (df + 1)) with smooth "plus_one".

    max_terms keeps each article's heaviest terms. Terms are counted per article first, so df is an aggregation of
    distinct terms, not of words.
    """
    words = F.regexp_extract_all(F.lower(text_col), F.lit(WORD), F.lit(0))
    tf = texts.select(F.col(id_col).alias("node_id"), F.explode(words).alias("term")).groupBy("node_id", "term").agg(F.count("*").alias("tf"))
    df = tf.groupBy("term").agg(F.count("*").alias("df")).where(F.col("df") >= min_df)
    n = texts.agg(F.count("*").cast("double").alias("_n"))
    rows = tf.join(df, "term").crossJoin(F.broadcast(n))  # one row
    idf = F.log((F.col("_n") + 1) / (F.col("df") + 1)) if smooth == "plus_one" else F.log(F.col("_n") / F.col("df"))
    out = rows.select("node_id", "term", "tf", "df", (F.col("tf") * idf).alias("tfidf"))
    if max_terms is not None:
        out = out.withColumn("_r", F.row_number().over(Window.partitionBy("node_id").orderBy(F.desc("tfidf"), "term"))).where(F.col("_r") <= max_terms).drop("_r")
    return out


def edge_text_similarity(edges: DataFrame, weights: DataFrame) -> DataFrame:
    """(src, dst, text_sim): cosine of the ends' vectors, for existing edges only; 0 where a text is missing or weightless."""
    norms = weights.groupBy("node_id").agg(F.sqrt(F.sum(F.col("tfidf") * F.col("tfidf"))).alias("norm"))
    own = weights.where("tfidf <> 0").select(F.col("node_id").alias("src"), "term", F.col("tfidf").alias("x"))
    other = weights.where("tfidf <> 0").select(F.col("node_id").alias("dst"), "term", F.col("tfidf").alias("y"))
    edges = edges.select("src", "dst")
    dots = edges.join(own, "src").join(other, ["dst", "term"]).groupBy("src", "dst").agg(F.sum(F.col("x") * F.col("y")).alias("dot"))
    ns, nd = (norms.select(F.col("node_id").alias(c), F.col("norm").alias(f"n_{c}")) for c in ("src", "dst"))
    rows = edges.join(dots, ["src", "dst"], "left").join(ns, "src", "left").join(nd, "dst", "left")
    size = F.col("n_src") * F.col("n_dst")
    return rows.select("src", "dst", F.coalesce(F.when(size > 0, F.col("dot") / size), F.lit(0.0)).alias("text_sim"))
