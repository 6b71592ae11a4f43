"""The experiments' inputs, re-expressed on the given tables."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import replace

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import features, metrics, partitioners, rounds
from ..operators.rounds import FedConfig, FedResult
from ..sources.tables import table

KEY = ["k1", "k2", "k3", "k4", "k5"]
ALL_FEATURES = [f"x{k}" for k in range(1, 12)]
FEW_FEATURES = ["x1", "x2", "x6", "x7"]


def mix() -> Column:
    return F.col("k1") * 7919 + F.col("k2") * 104729 + F.col("k3") * 1299709 + F.col("k4") * 15485863


def late_shipment(spark: SparkSession, sf_dir: str, few: bool = False) -> DataFrame:
    """Late shipment of order lines: keys k1-k5, x1-x11 (or four of them), label (15 % flipped), clean label, ``is_test``, and l_linestatus, l_shipdate."""
    lines = table(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_linestatus", "l_shipdate"])
    orders = table(spark, sf_dir, "orders", ["o_orderkey", "o_orderdate", "o_totalprice"])
    joined = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    if not few:
        joined = joined.join(table(spark, sf_dir, "part", ["p_partkey", "p_size", "p_retailprice"]), F.col("l_partkey") == F.col("p_partkey"))
    late = F.col("l_shipdate") > F.col("o_orderdate")
    flipped = (F.col("l_orderkey") * 31 + F.col("l_linenumber") * 7 + F.col("l_suppkey") * 13 + F.col("l_partkey")) % 100 < 15
    spec: dict[str, Column | str] = {"x1": "l_quantity", "x2": "l_extendedprice", "x6": features.days_since("l_shipdate"), "x7": features.days_since("o_orderdate")}
    if not few:
        spec |= {"x3": "l_discount", "x4": "l_tax", "x5": "l_linenumber", "x8": "o_totalprice", "x9": "p_size", "x10": "p_retailprice", "x11": features.encode("l_linestatus", {"F": 1.0}, 0.0)}
    keys = {"k1": "l_orderkey", "k2": "l_partkey", "k3": "l_suppkey", "k4": "l_linenumber", "k5": "l_extendedprice"}
    named = joined.withColumns({k: F.col(c) for k, c in keys.items()} | {"clean_label": F.when(late, 1.0).otherwise(0.0), "label": F.when(late != flipped, 1.0).otherwise(0.0)})
    out = features.assemble(named, spec, keep=[*KEY, "l_linestatus", "l_shipdate", "clean_label", "label"])
    return partitioners.train_test(out, mix())


def scaled(df: DataFrame, columns: Sequence[str], scale: str = "global") -> DataFrame:
    """Features scaled over all training rows, within each client, or not at all."""
    if scale == "none":
        return df
    if scale == "client":
        return features.standardize(df, columns, ["client_id"])
    if scale != "global":
        raise ValueError("scale is 'none', 'global' or 'client'")
    found = features.moments(df.where("NOT is_test"), columns)
    joined = df.crossJoin(F.broadcast(found))
    return joined.withColumns({c: F.when(F.col(f"{c}__s") > 0, (F.col(c) - F.col(f"{c}__m")) / F.col(f"{c}__s")).otherwise(0.0) for c in columns}).drop(*(f"{c}__{k}" for c in columns for k in "ms"))


def dealt(df: DataFrame, scheme: str, k: int) -> DataFrame:
    """Rows with client_id by one of the schemes."""
    if scheme == "attribute":
        return partitioners.by_attribute(df, "l_linestatus", k, KEY)
    if scheme == "natural":
        return partitioners.by_key(df, "k3")
    if scheme == "range":
        return partitioners.by_range(df, "x6", k, KEY)
    if scheme == "label":
        return partitioners.by_label(df, k, KEY)
    if scheme == "iid":
        return partitioners.iid(df, k, mix())
    if scheme == "unequal":
        return partitioners.unequal(df, k, mix())
    raise ValueError("no such scheme")


SCHEMES = ("attribute", "natural", "range", "label", "iid", "unequal")


def late_shipment_run(spark: SparkSession, sf_dir: str, configs: dict[str, FedConfig], scheme: str = "attribute", k: int = 100, q: int | None = None, scale: str = "global", columns: Sequence[str] = tuple(ALL_FEATURES), split: bool = True, only_last: bool = False, shared: dict | None = None, kept: dict | None = None, **split_options) -> tuple[dict[str, FedResult], DataFrame]:
    """Trains every configuration on one partition of the rows; results by name, and the indicators of all rounds on the test rows.

    shared: an empty dict that keeps the dealt and split rows for the next run on the same partition, which differs in q or configs alone;
    kept: one that keeps the joined and scaled rows for the next partition, with the same scale. Who gives them calls ``dropped``.
    """
    columns = list(columns)
    if shared:
        return trained(spark, None, None, columns, KEY, configs, q is not None, split, only_last, shared, q or 1, **split_options)
    if kept:
        (rows,) = kept["rows"]
    else:
        rows = scaled(late_shipment(spark, sf_dir), columns, "none" if scale == "client" else scale)
    if kept is not None and not kept:
        kept["rows"] = (rows := rows.drop("l_shipdate", "clean_label").persist(),)
    train = dealt(rows.where("NOT is_test"), scheme, k)
    if scale == "client":
        train = features.standardize(train, columns, ["client_id"])
    return trained(spark, train, rows.where("is_test"), columns, KEY, configs, q is not None, split, only_last, shared, q or 1, **split_options)


def dropped(shared: dict) -> None:
    """Gives up what runs have shared."""
    for df in shared.pop("rows", ()):
        df.unpersist()


def trained(spark: SparkSession, train: DataFrame | None, test: DataFrame | None, columns: Sequence[str], key: Sequence[str], configs: dict[str, FedConfig], three_tier: bool = False, split: bool = True, only_last: bool = False, shared: dict | None = None, q: int | None = None, **split_options) -> tuple[dict[str, FedResult], DataFrame]:
    """Every configuration on one split of the same training rows; results by name, and the indicators of all rounds, or of the last alone, on the test rows. q: sub-servers by the owner's remainder, in place of the rows' own."""
    columns, base = list(columns), next(iter(configs.values()))
    if shared:
        held, test = shared["rows"]
    else:
        held = rounds.prepare(train, columns, key, replace(base, split=split), **split_options).persist()
        test = test.select(*columns, "label").persist()
    if shared is not None:
        shared["rows"] = held, test
    base_rows = held
    if q is not None:
        held = held.withColumn("subserver_id", F.pmod("client_id", F.lit(q)).cast("int"))
    try:
        results = rounds.simulate(held, len(columns) + 1, configs, three_tier)
        # all rounds of all configurations are scored together, and told apart by a running number
        numbers = [(name, result.first_round + k) for name, result in results.items() for k in range(len(result.vectors) - 1 if only_last else 0, len(result.vectors))]
        vectors = np.concatenate([result.vectors[-1:] if only_last else result.vectors for result in results.values()])
        scored = metrics.evaluate_rounds(test, columns, np.arange(len(vectors)), vectors)
        named = spark.createDataFrame([(k, *n) for k, n in enumerate(numbers)], "at long, method string, number long")
        history = scored.withColumnRenamed("round", "at").join(F.broadcast(named), "at").select("method", F.col("number").alias("round"), *scored.columns[1:])
        history = spark.createDataFrame(history.collect(), history.schema)
    finally:
        if shared is None:
            base_rows.unpersist()
            test.unpersist()
    return results, history


def compare(spark: SparkSession, rows: DataFrame, columns: Sequence[str], key: Sequence[str], configs: dict[str, FedConfig], three_tier: bool = False, scale: str = "global", **split_options) -> tuple[dict[str, FedResult], DataFrame]:
    """``trained`` for rows with client_id and is_test, whose features are scaled by the training rows."""
    rows = scaled(rows, list(columns), scale)
    return trained(spark, rows.where("NOT is_test"), rows.where("is_test"), columns, key, configs, three_tier, **split_options)


def document_quality(spark: SparkSession, sf_dir: str, target: str = "quality") -> DataFrame:
    """Labelled documents: six text ratios; the source is the client and the language the tier."""
    docs = table(spark, sf_dir, "documents", ["doc_id", "text", "lang", "source", "n_chars"])
    labels = table(spark, sf_dir, "labels", ["doc_id", target])
    rows = docs.join(labels, "doc_id")
    ratios = features.text_ratios("text", "n_chars")
    servers = F.expr("CASE lang WHEN 'en' THEN 0 WHEN 'fr' THEN 1 WHEN 'de' THEN 2 ELSE 3 END")
    return rows.select("doc_id", "source", "lang", F.regexp_extract("source", "([0-9]+)$", 1).cast("int").alias("client_id"), servers.alias("subserver_id"), *(c.alias(f"x{k}") for k, c in enumerate(ratios.values(), 1)), F.col(target).cast("double").alias("label"), (F.col("doc_id") % 7 == 0).alias("is_test"))


def embedding_one_vs_rest(spark: SparkSession, sf_dir: str, positive: int = 0) -> DataFrame:
    """Embeddings with label = (label is the positive one); clients hold pairs of the original labels."""
    df = table(spark, sf_dir, "embeddings", ["vec_id", "embedding", "label"])
    return df.select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("features"), F.when(F.col("label") == positive, 1.0).otherwise(0.0).alias("target"), F.floor(F.col("label") / 2).cast("int").alias("client_id"))


def wide(df: DataFrame, vector: str, width: int, prefix: str = "x") -> DataFrame:
    """One column for each place of a vector."""
    return df.select(*(c for c in df.columns if c != vector), *(F.col(vector)[k].alias(f"{prefix}{k + 1}") for k in range(width)))


def activity(spark: SparkSession, sf_dir: str, clients: int = 10) -> DataFrame:
    """One row per user: events by type, sum and mean of values, active days, mean of a JSON property; label: purchases' share above 1 / types."""
    events = table(spark, sf_dir, "events", ["user_id", "ts", "event_type", "value", "props"])
    k = F.from_json("props", "k int")["k"]
    by_user = events.groupBy("user_id").agg(F.count("*").alias("n_events"), F.sum(F.when(F.col("event_type") == "purchase", 1).otherwise(0)).alias("n_purchases"), F.sum("value").alias("sum_value"), F.avg("value").alias("mean_value"), F.countDistinct(F.to_date("ts")).alias("active_days"), F.avg(k).alias("mean_k"))
    share = F.col("n_purchases") / F.col("n_events")
    return by_user.withColumns({"label": F.when(share > 0.2, 1.0).otherwise(0.0), "client_id": F.pmod(F.col("user_id"), F.lit(clients)).cast("int")})


def siting_demand(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Purchase-heavy users and their activity by nation, the demand for facilities there."""
    customers = table(spark, sf_dir, "customer", ["c_custkey", "c_nationkey"])
    nations = table(spark, sf_dir, "nation", ["n_nationkey", "n_name"])
    users = activity(spark, sf_dir).join(customers, F.col("user_id") == F.col("c_custkey")).join(F.broadcast(nations), F.col("c_nationkey") == F.col("n_nationkey"))
    return users.groupBy("n_name").agg(F.count("*").alias("n_users"), F.sum("label").cast("long").alias("n_heavy"), F.sum("n_events").alias("n_events"))


def natural_tiers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Suppliers as clients, regions as sub-servers."""
    s, n, r = table(spark, sf_dir, "supplier", ["s_suppkey", "s_nationkey"]), table(spark, sf_dir, "nation", ["n_nationkey", "n_regionkey"]), table(spark, sf_dir, "region", ["r_regionkey"])
    joined = s.join(F.broadcast(n), F.col("s_nationkey") == F.col("n_nationkey")).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey"))
    return joined.select(F.col("s_suppkey").cast("int").alias("client_id"), F.col("r_regionkey").cast("int").alias("subserver_id"))


def summary(history: DataFrame) -> DataFrame:
    """The published tables' layout: five figures of each indicator across rounds, by method."""
    return metrics.round_summary(history, ["accuracy", "precision", "recall", "f1", "ks"])
