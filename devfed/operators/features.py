"""From attributes to feature columns: projection, coding, standardisation, text ratios."""

from __future__ import annotations

from collections.abc import Mapping, Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def assemble(df: DataFrame, spec: Mapping[str, Column | str], keep: Sequence[str] = (), vector: str | None = None) -> DataFrame:
    """One projection of the named features (as doubles), the kept columns, and, if asked for, one array of them."""
    columns = {name: (F.col(c) if isinstance(c, str) else c).cast("double") for name, c in spec.items()}
    out = df.select(*keep, *(c.alias(name) for name, c in columns.items()))
    return out.withColumn(vector, F.array(*columns)) if vector else out


def encode(column: Column | str, mapping: Mapping[str, float], other: float | None = None) -> Column:
    """Numbers for an ordinal or boolean attribute; what isn't mapped becomes other."""
    column = F.col(column) if isinstance(column, str) else column
    out = F.lit(other).cast("double")
    for value, number in mapping.items():
        out = F.when(column == value, F.lit(float(number))).otherwise(out)
    return out


def days_since(column: str, origin: str = "1995-01-01") -> Column:
    return F.datediff(F.col(column).cast("date"), F.lit(origin).cast("date"))


def clip(column: Column | str, low: float, high: float) -> Column:
    column = F.col(column) if isinstance(column, str) else column
    return F.greatest(F.least(column, F.lit(high)), F.lit(low))


def moments(df: DataFrame, columns: Sequence[str], by: Sequence[str] = ()) -> DataFrame:
    """Mean and sample deviation of each column, for each group."""
    return df.groupBy(*by).agg(*(f(c).alias(f"{c}__{n}") for c in columns for f, n in ((F.avg, "m"), (F.stddev_samp, "s"))))


def standardize(df: DataFrame, columns: Sequence[str], by: Sequence[str] = (), axis: str = "attribute", prefix: str = "") -> DataFrame:
    """Each attribute less its mean, divided by its sample deviation, within each group of by (all rows if empty).

    A constant attribute, or a group of one row, gives 0. axis="row" takes mean and deviation over the attributes
    of one row instead. The moments are one row a group and meet the rows in a join that the engine may broadcast
    below its own size limit.
    """
    if axis == "row":
        n = len(columns)
        m = sum((F.col(c) for c in columns), F.lit(0.0)) / n
        s = F.sqrt(sum(((F.col(c) - m) * (F.col(c) - m) for c in columns), F.lit(0.0)) / (n - 1))
        return df.withColumns({prefix + c: F.when(s > 0, (F.col(c) - m) / s).otherwise(0.0) for c in columns})
    if axis != "attribute":
        raise ValueError("axis is 'attribute' or 'row'")
    found = moments(df, columns, by)
    joined = df.join(found, list(by)) if by else df.crossJoin(F.broadcast(found))
    scaled = {prefix + c: F.when(F.col(f"{c}__s") > 0, (F.col(c) - F.col(f"{c}__m")) / F.col(f"{c}__s")).otherwise(0.0) for c in columns}
    return joined.withColumns(scaled).drop(*(f"{c}__{k}" for c in columns for k in "ms"))


def text_ratios(text: str, n_chars: str) -> dict[str, Column]:
    """Six figures of a text: length and shares of upper case, punctuation, digits, line breaks, distinct words (ASCII classes)."""
    t, n = F.col(text), F.greatest(F.col(n_chars).cast("double"), F.lit(1.0))
    share = lambda pattern: F.regexp_count(t, F.lit(pattern)) / n
    words = F.split(F.trim(F.regexp_replace(t, "[ \t\n]+", " ")), " ")
    return {"log_chars": F.log1p(F.col(n_chars).cast("double")), "upper": share("[A-Z]"), "punct": share("[.,;:!?#*$%&|<>]"), "digits": share("[0-9]"), "breaks": share("\n"), "distinct": F.size(F.array_distinct(words)) / F.size(words)}


def rank_in(df: DataFrame, by: Sequence[str], order: Sequence[Column | str], name: str = "rank") -> DataFrame:
    return df.withColumn(name, F.row_number().over(Window.partitionBy(*by).orderBy(*order)))
