"""Bundles of tables, graph markup, edge lists, and a paced source of pages."""

from __future__ import annotations

import time
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: The tables of a published graph.
BUNDLE = ("paths", "nodes", "steps", "categories", "edges", "hyperedges", "observations", "path_lengths")


def write_bundle(tables: dict[str, DataFrame], path: str) -> None:
    missing = set(BUNDLE) - set(tables)
    if missing:
        raise ValueError(f"a bundle needs {sorted(missing)} too")
    for name in BUNDLE:
        tables[name].write.mode("overwrite").parquet(f"{path}/{name}")


def read_bundle(spark: SparkSession, path: str) -> dict[str, DataFrame]:
    return {name: spark.read.parquet(f"{path}/{name}") for name in BUNDLE}


def bucketed(df: DataFrame, table: str, key: str, *, buckets: int = 64) -> DataFrame:
    """df as a table bucketed and sorted by key, so that later joins on the key don't shuffle it."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(table)
    return df.sparkSession.table(table)


def write_graphml(nodes: DataFrame, edges: DataFrame, path: str) -> None:
    """Graph markup as text: header, nodes, edges, footer, each part in files that sort in this order."""
    spark = nodes.sparkSession
    title = F.col("title") if "title" in nodes.columns else F.lit(None).cast("string")
    safe = F.regexp_replace(F.regexp_replace(F.regexp_replace(F.coalesce(title, F.lit("")), "&", "&amp;"), "<", "&lt;"), ">", "&gt;")
    safe = F.regexp_replace(safe, r"[\r\n]", " ")
    head = ['<?xml version="1.0" encoding="UTF-8"?>', '<graphml xmlns="http://graphml.graphdrawing.org/xmlns">', '<key id="title" for="node" attr.name="title" attr.type="string"/>', '<graph edgedefault="directed">']
    parts = [
        spark.createDataFrame([(0, i, x) for i, x in enumerate(head)], "part int, i long, value string"),
        nodes.select(F.lit(1).alias("part"), F.col("node_id").alias("i"), F.format_string('<node id="%d"><data key="title">%s</data></node>', F.col("node_id"), safe).alias("value")),
        edges.select(F.lit(2).alias("part"), F.col("src").alias("i"), F.format_string('<edge source="%d" target="%d"/>', "src", "dst").alias("value")),
        spark.createDataFrame([(3, i, x) for i, x in enumerate(("</graph>", "</graphml>"))], "part int, i long, value string"),
    ]
    rows = parts[0].unionByName(parts[1]).unionByName(parts[2]).unionByName(parts[3])
    rows.repartitionByRange("part", "i").sortWithinPartitions("part", "i").select("value").write.mode("overwrite").text(path)


def read_graphml(spark: SparkSession, path: str) -> tuple[DataFrame, DataFrame]:
    lines = spark.read.text(path)
    node = lines.where(F.col("value").startswith("<node ")).select(F.regexp_extract("value", r'id="(-?\d+)"', 1).cast("long").alias("node_id"), F.regexp_extract("value", r">([^<]*)</data>", 1).alias("title"))
    for code, sign in (("&lt;", "<"), ("&gt;", ">"), ("&amp;", "&")):
        node = node.withColumn("title", F.regexp_replace("title", code, sign))
    edge = lines.where(F.col("value").startswith("<edge ")).select(*(F.regexp_extract("value", rf'{a}="(-?\d+)"', 1).cast("long").alias(c) for a, c in (("source", "src"), ("target", "dst"))))
    return node, edge



def write_edges(edges: DataFrame, path: str, *, fmt: str = "csv") -> None:
    writer = edges.select("src", "dst").write.mode("overwrite")
    writer.option("header", True).csv(path) if fmt == "csv" else writer.json(path)


def read_edges(spark: SparkSession, path: str, *, fmt: str = "csv") -> DataFrame:
    reader = spark.read.schema("src long, dst long")
    return reader.option("header", True).csv(path) if fmt == "csv" else reader.json(path)


def paced_source(spark: SparkSession) -> None:
    """Register the format paced_pages: rows (host, page_id) of the option pages ("host=id,id;host=id"), with at least delay_s
    between two requests to one host; a partition per host."""
    from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

    class Host(InputPartition):
        def __init__(self, host: str, ids: list[int]) -> None:
            self.host, self.ids = host, ids

    class Reader(DataSourceReader):
        def __init__(self, options: dict) -> None:
            self.delay, self.pages = float(options.get("delay_s", 1.0)), options.get("pages", "")

        def partitions(self) -> list:
            parts = [x.partition("=") for x in self.pages.split(";") if x]
            return [Host(h, [int(i) for i in ids.split(",") if i]) for h, _, ids in parts]

        def read(self, partition) -> Iterator[tuple]:
            for n, page in enumerate(partition.ids):
                if n:
                    time.sleep(self.delay)
                yield partition.host, page, float(n * self.delay)

    class PacedPages(DataSource):
        @classmethod
        def name(cls) -> str:
            return "paced_pages"

        def schema(self) -> str:
            return "host string, page_id long, due_s double"

        def reader(self, schema) -> DataSourceReader:
            return Reader(self.options)

    spark.dataSource.register(PacedPages)
