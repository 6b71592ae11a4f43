"""Merging of members' vectors below each parent, by how far they deviate from their weighted mean.

s_i is a member's share of its parent's rows, m the share-weighted mean, r_i the distance of the
member's vector from m, R the sum of the distances. Weights by rule:

  proportional  r_i / R
  inverse       (1 / r_i) / sum(1 / r_j), r_i at least eps * (1 + R)
  complement    (1 - r_i / R) / (members - 1)
  samples       s_i
  uniform       1 / members

With R <= eps, or one member, the weights are s_i. share="global" divides by the rows of all
parents for m alone (a literal reading of one formula of the three-tier form).
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

RULES = ("proportional", "inverse", "complement", "samples", "uniform")
EPS = 1e-12


def _check(rule: str) -> None:
    if rule not in RULES:
        raise ValueError(f"rule is one of {RULES}")


def weights_np(vectors: np.ndarray, rows: np.ndarray, rule: str = "proportional", eps: float = EPS, total: float | None = None) -> np.ndarray:
    """Weights of the members of one parent; total: what the shares are taken of for the mean, if not of these rows."""
    _check(rule)
    share, n = rows / rows.sum(), len(rows)
    if rule == "samples":
        return share
    if rule == "uniform":
        return np.full(n, 1 / n)
    mean = (vectors * (rows / (total or rows.sum()))[:, None]).sum(axis=0)
    r = np.sqrt(((vectors - mean) ** 2).sum(axis=1))
    every = r.sum()
    if n == 1 or every <= eps:
        return share
    if rule == "proportional":
        return r / every
    if rule == "complement":
        return (1 - r / every) / (n - 1)
    r = 1 / np.maximum(r, eps * (1 + every))
    return r / r.sum()


def merge_np(vectors: np.ndarray, rows: np.ndarray, rule: str = "proportional", eps: float = EPS, total: float | None = None) -> np.ndarray:
    return weights_np(vectors, rows, rule, eps, total) @ vectors


def _with_sums(df: DataFrame, parents: list[str], *sums: Column) -> DataFrame:
    """df with grouped sums of its own, joined back: one row a parent, so that no parent's members gather in one task."""
    found = df.groupBy(*parents).agg(*sums)
    return df.join(found, parents) if parents else df.crossJoin(F.broadcast(found))


def weigh(df: DataFrame, parents: Sequence[str] = (), vector: str = "w", rows: str = "n_rows", rule: str = "proportional", eps: float = EPS, share: str = "local") -> DataFrame:
    """Members with ``share``, ``deviation`` and ``weight``, below each parent. d-wide vectors are summed by position; a parent's members never meet in one row or task.

    df is read several times: members that are costly to compute are materialised before.
    """
    _check(rule)
    parents = list(parents)
    base = _with_sums(df, parents, F.sum(rows).cast("double").alias("__own"), F.count("*").alias("__members"))
    if share != "local":
        base = base.crossJoin(F.broadcast(df.agg(F.sum(rows).cast("double").alias("__total"))))
    total = F.col("__own" if share == "local" else "__total")
    parts = base.select(*parents, F.posexplode(vector).alias("__k", "__x"), (F.col(rows) / total).alias("__s"))
    means = parts.groupBy(*parents, "__k").agg(F.sum(F.col("__x") * F.col("__s")).alias("__m")).groupBy(*parents)
    means = means.agg(F.transform(F.array_sort(F.collect_list(F.struct("__k", "__m"))), lambda s: s["__m"]).alias("__mean"))
    joined = base.join(means, parents) if parents else base.crossJoin(F.broadcast(means))
    square = F.aggregate(F.zip_with(vector, "__mean", lambda x, m: (x - m) * (x - m)), F.lit(0.0), lambda s, x: s + x)
    out = joined.withColumns({"share": F.col(rows) / F.col("__own"), "deviation": F.sqrt(square)}).drop("__mean", "__total", "__own")
    n, r, every = F.col("__members"), F.col("deviation"), F.col("__every")
    if rule in ("samples", "uniform"):
        return out.withColumn("weight", F.col("share") if rule == "samples" else 1.0 / n).drop("__members")
    out = _with_sums(out, parents, F.sum("deviation").alias("__every"))
    if rule == "inverse":
        out = out.withColumn("__near", 1.0 / F.greatest(r, F.lit(eps) * (1.0 + every)))
        out = _with_sums(out, parents, F.sum("__near").alias("__nears"))
    chosen = {"proportional": lambda: r / every, "inverse": lambda: F.col("__near") / F.col("__nears"), "complement": lambda: (1.0 - r / every) / (n - 1)}[rule]()
    return out.withColumn("weight", F.when((n == 1) | (every <= eps), F.col("share")).otherwise(chosen)).drop("__every", "__near", "__nears", "__members")


def merge(df: DataFrame, parents: Sequence[str] = (), vector: str = "w", rows: str = "n_rows", rule: str = "proportional", eps: float = EPS, share: str = "local") -> DataFrame:
    """One row per parent: merged vector and rows. All tables here have a row for each member, never rows of data."""
    parents = list(parents)
    weighed = weigh(df, parents, vector, rows, rule, eps, share)
    parts = weighed.select(*parents, F.posexplode(vector).alias("__k", "__x"), "weight")
    merged = parts.groupBy(*parents, "__k").agg(F.sum(F.col("__x") * F.col("weight")).alias("__v")).groupBy(*parents)
    merged = merged.agg(F.transform(F.array_sort(F.collect_list(F.struct("__k", "__v"))), lambda s: s["__v"]).alias(vector))
    counts = df.groupBy(*parents).agg(F.sum(rows).alias(rows))
    return merged.join(counts, parents) if parents else merged.crossJoin(counts)
