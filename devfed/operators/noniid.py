"""How unlike the clients are."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def report(df: DataFrame, features: Sequence[str], label: str = "label") -> DataFrame:
    """One row: clients, least and largest client, range and deviation of label rates, and the largest spread of client means in units of the overall deviation."""
    own = df.groupBy("client_id").agg(F.count("*").alias("n"), F.avg(label).alias("rate"), *(F.avg(c).alias(f"m_{c}") for c in features))
    overall = df.agg(*(F.stddev_samp(c).alias(f"s_{c}") for c in features))
    figures = own.agg(
        F.count("*").alias("clients"), F.min("n").alias("least_rows"), F.max("n").alias("most_rows"), F.min("rate").alias("least_rate"), F.max("rate").alias("most_rate"), F.stddev_samp("rate").alias("rate_sd"), *(F.stddev_samp(f"m_{c}").alias(f"d_{c}") for c in features)
    )
    spread = F.greatest(*(F.col(f"d_{c}") / F.col(f"s_{c}") for c in features)) if len(features) > 1 else F.col(f"d_{features[0]}") / F.col(f"s_{features[0]}")
    return figures.crossJoin(F.broadcast(overall)).select("clients", "least_rows", "most_rows", "least_rate", "most_rate", "rate_sd", spread.alias("mean_spread"))


def histogram_distance(df: DataFrame, column: str, low: float, high: float, bins: int = 20) -> DataFrame:
    """(client_id, distance): half the absolute difference of a client's histogram and that of all rows, from 0 (alike) to 1."""
    at = F.width_bucket(F.col(column), F.lit(low), F.lit(high), F.lit(bins))
    cells = df.groupBy("client_id", at.alias("bin")).agg(F.count("*").alias("n"))
    totals = cells.groupBy("client_id").agg(F.sum("n").alias("total"))
    every = cells.groupBy("bin").agg(F.sum("n").alias("all_n"))
    overall = every.crossJoin(F.broadcast(every.agg(F.sum("all_n").alias("all_total")))).withColumn("q", F.col("all_n") / F.col("all_total")).select("bin", "q")
    # bins that a client doesn't have add their whole share
    shared = cells.join(totals, "client_id").join(overall, "bin").groupBy("client_id").agg(F.sum(F.abs(F.col("n") / F.col("total") - F.col("q"))).alias("d"), F.sum("q").alias("met"))
    return shared.select("client_id", ((F.col("d") + 1.0 - F.col("met")) / 2).alias("distance"))
