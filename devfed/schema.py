"""Checks of a workload's rows before training."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

POLICIES = ("fail", "drop", "zero")


def validate(df: DataFrame, features: list[str], label: str = "label", nulls: str = "fail") -> DataFrame:
    """df with finite features and labels in {0, 1}.

    nulls: "fail" raises if a feature is null, NaN or infinite, "drop" leaves such rows out, "zero"
    puts 0 there. A label outside {0, 1} always raises. The check is one aggregation.
    """
    if nulls not in POLICIES:
        raise ValueError(f"nulls is one of {POLICIES}")
    missing = [c for c in (*features, label) if c not in df.columns]
    if missing:
        raise ValueError(f"no such columns: {missing}")
    wrong = lambda c: F.col(c).isNull() | F.isnan(F.col(c).cast("double")) | (F.abs(F.col(c).cast("double")) == float("inf"))
    found = df.agg(F.count_if(F.col(label).isNull() | ~F.col(label).isin(0, 1)).alias("__label"), *(F.count_if(wrong(c)).alias(c) for c in features)).first().asDict()
    if found.pop("__label"):
        raise ValueError(f"{label} has values other than 0 and 1")
    bad = [c for c, n in found.items() if n]
    if not bad:
        return df
    if nulls == "fail":
        raise ValueError(f"null, NaN or infinite values in {bad}")
    if nulls == "drop":
        for c in bad:
            df = df.where(~wrong(c))
        return df
    return df.withColumns({c: F.when(wrong(c), F.lit(0.0)).otherwise(F.col(c)) for c in bad})
