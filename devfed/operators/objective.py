"""The training objective: the mean loss over all rows is the share-weighted mean of the clients' mean losses."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import vec


def logloss(features: Sequence[str], w: Sequence[float], label: str = "label", intercept: bool = True) -> Column:
    """A row's logistic loss, with the margin clipped."""
    z = vec.margin(features, w, intercept)
    z = F.greatest(F.least(z, F.lit(vec.CLIP)), F.lit(-vec.CLIP))
    return F.log1p(F.exp(-z)) + (F.lit(1.0) - F.col(label)) * z


def by_client(df: DataFrame, features: Sequence[str], w: Sequence[float], label: str = "label", intercept: bool = True) -> DataFrame:
    """(client_id, n_rows, loss)."""
    return df.groupBy("client_id").agg(F.count("*").alias("n_rows"), F.avg(logloss(features, w, label, intercept)).alias("loss"))


def decompose(df: DataFrame, features: Sequence[str], w: Sequence[float], label: str = "label", intercept: bool = True) -> DataFrame:
    """One row: the pooled loss, the share-weighted sum of client losses (they agree), and the unweighted mean."""
    clients = by_client(df, features, w, label, intercept)
    sums = clients.agg(F.sum("n_rows").alias("n_rows"), (F.sum(F.col("n_rows") * F.col("loss")) / F.sum("n_rows")).alias("weighted"), F.avg("loss").alias("unweighted"))
    pooled = df.agg(F.avg(logloss(features, w, label, intercept)).alias("pooled"))
    return sums.crossJoin(F.broadcast(pooled))
