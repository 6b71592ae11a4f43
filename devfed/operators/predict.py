"""Scores and classes of rows."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import vec


def score(df: DataFrame, features: Sequence[str], w: Sequence[float], threshold: float = 0.5, intercept: bool = True) -> DataFrame:
    """Adds ``score`` (probability) and ``predicted`` (score >= threshold), in generated code."""
    return df.withColumn("score", vec.sigmoid(vec.margin(features, w, intercept))).withColumn("predicted", F.when(F.col("score") >= threshold, 1).otherwise(0))


def score_history(df: DataFrame, features: Sequence[str], history: DataFrame, intercept: bool = True, keep: Sequence[str] = ("label",)) -> DataFrame:
    """Rows scored by every round's vector: (round, kept columns, score). The history is a stated set of few vectors that meets the rows by broadcast."""
    x = F.array(*([F.lit(1.0)] if intercept else []), *(F.col(c).cast("double") for c in features))
    return df.select(*keep, x.alias("__x")).crossJoin(F.broadcast(history.select("round", "w"))).select("round", *keep, vec.sigmoid(vec.dot(F.col("__x"), F.col("w"))).alias("score"))
