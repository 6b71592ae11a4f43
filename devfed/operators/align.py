"""Matching one entity's rows across parties by a salted hash of the key. Plain hashing, not a cryptographic protocol."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def hashed(key: Column | str, salt: str) -> Column:
    return F.sha2(F.concat(F.lit(salt), (F.col(key) if isinstance(key, str) else key).cast("string")), 256)


def hashed_inner(a: DataFrame, b: DataFrame, key_a: str, key_b: str, salt: str) -> DataFrame:
    """Rows of both parties that share a key; the key itself doesn't leave either side."""
    left = a.withColumn("alias_key", hashed(key_a, salt)).drop(key_a)
    return left.join(b.withColumn("alias_key", hashed(key_b, salt)).drop(key_b), "alias_key")


def aligned(a: DataFrame, b: DataFrame, key_a: str, key_b: str, salt: str) -> DataFrame:
    """a's rows whose key b has too."""
    return a.withColumn("alias_key", hashed(key_a, salt)).join(b.select(hashed(key_b, salt).alias("alias_key")), "alias_key", "left_semi")


def unaligned(a: DataFrame, b: DataFrame, key_a: str, key_b: str, salt: str) -> DataFrame:
    """a's rows whose key b lacks."""
    return a.withColumn("alias_key", hashed(key_a, salt)).join(b.select(hashed(key_b, salt).alias("alias_key")), "alias_key", "left_anti")
