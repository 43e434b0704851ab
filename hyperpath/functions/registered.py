"""SQL functions that Catalyst inlines, and the few Python functions that SQL can't express."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def register_sql(spark: SparkSession) -> None:
    """is_valid_title(title), nb_transition(weight, back_weight), hyper_cosine(common, degree_u, degree_v)."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION is_valid_title(title STRING) RETURNS BOOLEAN RETURN coalesce(NOT (title RLIKE 'Talk|User|File|ISO|[%#:]') AND NOT (title RLIKE '^[0-9]*$'), false)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION nb_transition(weight DOUBLE, back_weight DOUBLE) RETURNS DOUBLE RETURN CASE WHEN 1 - coalesce(back_weight, 0) > 1e-12 THEN weight / (1 - coalesce(back_weight, 0)) ELSE 0 END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION hyper_cosine(common DOUBLE, degree_u DOUBLE, degree_v DOUBLE) RETURNS DOUBLE RETURN common / sqrt(degree_u * degree_v)")


def edge_mlp(params: dict[str, np.ndarray]):
    """A scalar Arrow UDF: feature arrays -> the score of a one-hidden-layer perceptron with these parameters."""
    w1, b1, w2, b2 = (np.asarray(params[k], dtype=float) for k in ("w1", "b1", "w2", "b2"))

    @F.pandas_udf("double")
    def score(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for features in batches:
            x = np.stack(features.to_numpy()) if len(features) else np.empty((0, len(w1)))
            yield pd.Series(np.maximum(x @ w1 + b1, 0) @ w2 + b2[0])

    return score


def modularity_check(name: str = "modularity_check"):
    """A grouped-aggregate pandas UDF over (inner share, degree share) of communities; used to check the DataFrame form."""

    @F.pandas_udf("double")
    def total(inner: pd.Series, degree: pd.Series) -> float:
        return float((inner - degree**2).sum())

    return total


def walks_from(adjacency: dict[int, list[int]]):
    """A Python table function walks_from(node, h): every walk of h steps, for small graphs given as a dict."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="walk string, length int")
    class Walks:
        def eval(self, node: int, h: int):
            walks = [[node]]
            for _ in range(h):
                walks = [[*w, n] for w in walks for n in adjacency.get(w[-1], ())]
            for w in walks:
                yield ">".join(map(str, w)), len(w) - 1

    return Walks


