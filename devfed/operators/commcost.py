"""What a run costs: messages and bytes by tier, gradient evaluations, rounds to a target."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def ledger(spark: SparkSession, rounds: int, clients: int, width: int, subservers: int | None = None, sub_rounds: int = 1, quorum: float | None = None) -> DataFrame:
    """(round, tier, direction, messages, bytes). A round has one download and one upload for each edge of the tree that takes part; a vector is 8 bytes a parameter."""
    taking_part = clients if quorum is None else max(1, int(-(-quorum * clients // 1)))
    tiers = [("centre", taking_part)] if subservers is None else [("centre", subservers), ("edge", taking_part * sub_rounds)]
    edges = spark.createDataFrame([(t, d, n) for t, n in tiers for d in ("down", "up")], "tier string, direction string, messages long")
    return spark.range(1, rounds + 1).withColumnRenamed("id", "round").crossJoin(F.broadcast(edges)).withColumn("bytes", F.col("messages") * F.lit(8 * width))


def ledger_of(tree: DataFrame, rounds: int, width: int, sub_rounds: int = 1) -> DataFrame:
    """``ledger`` of three tiers whose edges are those of a table (client_id, subserver_id), counted where it lies."""
    edges = tree.agg(F.countDistinct("subserver_id").alias("centre"), (F.countDistinct("client_id") * sub_rounds).alias("edge"))
    tiers = edges.select(F.explode(F.array(*(F.struct(F.lit(t).alias("tier"), F.lit(d).alias("direction"), F.col(t).alias("messages")) for t in ("centre", "edge") for d in ("down", "up")))).alias("e")).select("e.*")
    return tree.sparkSession.range(1, rounds + 1).withColumnRenamed("id", "round").crossJoin(F.broadcast(tiers)).withColumn("bytes", F.col("messages") * F.lit(8 * width))


def ledger_rollup(table: DataFrame) -> DataFrame:
    """Totals by tier and direction, by tier, and overall; level counts what is summed over."""
    return table.rollup("tier", "direction").agg(F.sum("messages").alias("messages"), F.sum("bytes").alias("bytes"), F.grouping_id().cast("long").alias("level"))


def rounds_to_target(history: DataFrame, metric: str, target: float, by: list[str] | None = None, smaller: bool = False) -> DataFrame:
    """The first round at which an indicator reaches a target (null if never)."""
    hit = F.col(metric) <= target if smaller else F.col(metric) >= target
    return history.groupBy(*(by or ["method"])).agg(F.min(F.when(hit, F.col("round"))).alias("first_round"), F.max("round").alias("rounds"))


def compute(df: DataFrame, epochs: int, rounds: int) -> DataFrame:
    """Gradient evaluations of a run by client and in all: a row is used once an epoch."""
    own = df.groupBy("client_id").agg((F.count("*") * epochs * rounds).alias("evaluations"))
    return own.rollup("client_id").agg(F.sum("evaluations").alias("evaluations"))
