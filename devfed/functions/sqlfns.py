"""Functions for SQL users: temporary SQL functions, a grouped-aggregate, and a table function."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SQL_FUNCTIONS = {
    "fed_sigmoid": "(z DOUBLE) RETURNS DOUBLE RETURN 1e0 / (1e0 + exp(-greatest(least(z, 30e0), -30e0)))",
    "fed_dist2": "(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN sqrt(aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0e0, (s, x) -> s + x))",
    "fed_dot": "(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> x * y), 0e0, (s, x) -> s + x)",
}


def vec_wavg():
    """A grouped aggregate: the weighted mean of vectors; a few vectors a group (its twin without Python is operators.weighting)."""

    @F.pandas_udf("array<double>")
    def weighted_mean(vectors: pd.Series, weights: pd.Series) -> list[float]:
        w = weights.to_numpy(float)
        return (np.stack(vectors.to_list()) * w[:, None]).sum(axis=0) / w.sum()

    return weighted_mean


@F.udtf(returnType="threshold double, fpr double, tpr double")
class RocPoints:
    """The ROC points of one small group of scores and labels, or of counted levels of them; operators.metrics.roc is for large ones."""

    def eval(self, scores: list, labels: list, counts: list = None) -> Iterator[tuple]:
        s, y, n = np.array(scores, float), np.array(labels, int), np.array(counts if counts is not None else [1] * len(scores), float)
        positives, negatives = n[y == 1].sum(), n[y == 0].sum()
        yield float("inf"), 0.0, 0.0
        if positives and negatives:
            for t in np.unique(s)[::-1]:
                yield float(t), float(n[(s >= t) & (y == 0)].sum() / negatives), float(n[(s >= t) & (y == 1)].sum() / positives)


def federated_train(df: DataFrame | str, features: list[str], key: list[str], options: dict | None = None, three_tier: bool = False, spark: SparkSession | None = None, **split_options) -> DataFrame:
    """The method on a table (a DataFrame or a view's name) with client_id, label and features: (method, round, w) of every round.

    options are FedConfig's fields; split_options go to the splitter.
    """
    from ..operators import rounds

    if isinstance(df, str):
        df = (spark or SparkSession.active()).table(df)
    result = rounds.fit(df, features, key, rounds.FedConfig(**(options or {})), three_tier, **split_options)
    return result.history(df.sparkSession, "federated")


def register(spark: SparkSession) -> None:
    for name, body in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name} {body}")
    spark.udf.register("fed_vec_wavg", vec_wavg())
    spark.udtf.register("fed_roc_points", RocPoints)
