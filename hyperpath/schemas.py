"""Fixed schemas of the tables that operators exchange."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql.types import ArrayType, DoubleType, IntegerType, LongType, StringType, StructField, StructType


def _table(*columns: tuple[str, object]) -> StructType:
    return StructType([StructField(name, kind) for name, kind in columns])


NODES = _table(("node_id", LongType()), ("title", StringType()), ("text", StringType()), ("category", StringType()))
LINKS = _table(("src", LongType()), ("dst", LongType()), ("pos", IntegerType()))
EDGES = _table(("edge_id", LongType()), ("src", LongType()), ("dst", LongType()))
STEPS = _table(("path_id", LongType()), ("step", IntegerType()), ("node_id", LongType()))
PATHS = _table(("path_id", LongType()), ("nodes", ArrayType(LongType())), ("length", IntegerType()), ("outcome", StringType()))
INCIDENCE = _table(("node_id", LongType()), ("edge_id", LongType()), ("sign", IntegerType()))
OBSERVATIONS = _table(("path_id", LongType()), ("step", IntegerType()), ("node_id", LongType()), ("weight", DoubleType()))


@dataclass(frozen=True)
class FeatureGraph:
    """A graph, or hypergraph, as three tables: what its nodes carry, which node is in which edge, what its edges carry.

    node_key and edge_key name the id columns; incidence has both, and sign.
    """

    node_features: DataFrame
    incidence: DataFrame
    edge_features: DataFrame
    node_key: str = "node_id"
    edge_key: str = "edge_id"
