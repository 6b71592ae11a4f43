"""Dealing rows out to clients in ways that are more or less alike, tiers of clients, and train and test rows."""

from __future__ import annotations

import math
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..sources.checkpoints import materialised

#: Rows that are sorted in one task, about.
RANGE_ROWS = 2_000_000


def _range_of(column: Column, bounds: list[float]) -> Column:
    """The number of bounds below or equal to a value, as a balanced tree of comparisons."""

    def tree(low: int, high: int) -> Column:
        if low == high:
            return F.lit(low)
        middle = (low + high) // 2
        return F.when(column < F.lit(bounds[middle]), tree(low, middle)).otherwise(tree(middle + 1, high))

    return tree(0, len(bounds))


def global_rank(df: DataFrame, order: Sequence[str], name: str = "rank", range_rows: int = RANGE_ROWS) -> DataFrame:
    """Adds 0-based ranks in the order of some columns, and ``total``.

    No window runs over the table: rows are dealt out by ranges of the whole key, as many as their number asks for, sorted
    there and numbered in generated code. The numbered rows are written before the ranges are counted, so that both agree
    whatever is lost; a row for each range, with the rows before it, joins them.
    """
    total = df.count()
    ranges = max(int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), math.ceil(total / range_rows))
    dealt = df.repartitionByRange(ranges, *order).sortWithinPartitions(*order)
    # the id holds the number of the partition above bit 33 and the row's place in it below
    numbered = materialised(dealt.withColumn("__id", F.monotonically_increasing_id()).withColumn("__range", F.shiftright("__id", 33)))
    sizes = numbered.groupBy("__range").agg(F.count("*").alias("__n"))
    # one row for each range
    before = sizes.select("__range", (F.sum("__n").over(Window.orderBy("__range")) - F.col("__n")).alias("__before"))
    place = F.col("__before") + F.col("__id") - F.shiftleft("__range", 33)
    return numbered.join(F.broadcast(before), "__range").withColumns({name: place, "total": F.lit(total).cast("long")}).select(*df.columns, name, "total")


def _tile(rank: Column, total: Column, k: int) -> Column:
    """The tile (from 0) of a rank if a total is cut into k parts, the first ones larger by one."""
    small, large = F.floor(total / k), F.pmod(total, F.lit(k))
    edge = large * (small + 1)
    return F.when(rank < edge, F.floor(rank / (small + 1))).otherwise(large + F.floor((rank - edge) / F.greatest(small, F.lit(1)))).cast("int")


def _shards(df: DataFrame, order: Sequence[str], k: int) -> DataFrame:
    if k < 1:
        raise ValueError("there is at least one client")
    return global_rank(df, order).withColumn("client_id", _tile(F.col("rank"), F.col("total"), k)).drop("rank", "total")


def by_attribute(df: DataFrame, column: str, k: int, key: Sequence[str]) -> DataFrame:
    """Rows ordered by an attribute, cut into k equal shards: clients see one of its values, or few."""
    return _shards(df, [column, *key], k)


def by_label(df: DataFrame, k: int, key: Sequence[str], label: str = "label") -> DataFrame:
    """Shards of rows ordered by the label."""
    return _shards(df, [label, *key], k)


def by_range(df: DataFrame, column: str, k: int, key: Sequence[str]) -> DataFrame:
    """Equal shards of rows ordered by a numeric attribute: strong skew if it goes with the label."""
    return _shards(df, [column, *key], k)


def by_key(df: DataFrame, column: str) -> DataFrame:
    """A client for each value of an integer key: natural owners."""
    return df.withColumn("client_id", F.col(column).cast("int"))


def by_key_bucket(df: DataFrame, column: str, k: int) -> DataFrame:
    """Owners gathered into k clients."""
    return df.withColumn("client_id", F.pmod(F.col(column), F.lit(k)).cast("int"))


def iid(df: DataFrame, k: int, mix: Column) -> DataFrame:
    """A client for each row by a mixed key: the control without skew."""
    return df.withColumn("client_id", F.pmod(F.floor(mix / 7), F.lit(k)).cast("int"))


def unequal(df: DataFrame, k: int, mix: Column, ratio: float = 0.7) -> DataFrame:
    """Clients whose sizes fall geometrically by a ratio."""
    total, edge, bounds = sum(ratio**i for i in range(k)), 0.0, []
    for i in range(k - 1):
        edge += ratio**i / total
        bounds.append(round(edge * 10_000) * 1.0)
    return df.withColumn("client_id", _range_of(F.pmod(F.floor(mix / 7), F.lit(10_000)).cast("double"), bounds).cast("int"))


def salted(df: DataFrame, max_rows: int, mix: Column) -> DataFrame:
    """Splits clients of more than max_rows into sub-clients that train on their own, so that no client must fit one task. Adds ``owner_id``."""
    sizes = df.groupBy("client_id").agg(F.ceil(F.count("*") / max_rows).cast("int").alias("__parts"))
    parts = df.join(sizes, "client_id").withColumns({"owner_id": F.col("client_id"), "__part": F.pmod(F.hash(mix), F.col("__parts")).cast("int")})
    widest = sizes.agg(F.max("__parts")).first()[0] or 1
    return parts.withColumn("client_id", (F.col("owner_id") * widest + F.col("__part")).cast("int")).drop("__parts", "__part")


def tiers(k: int, q: int, how: str = "mod", spark=None) -> DataFrame | dict[int, int]:
    """Which sub-server serves a client: {client: sub-server}, or a DataFrame if a session is given."""
    if not 1 <= q <= k:
        raise ValueError("between one and all clients' number of sub-servers")
    if how not in ("mod", "block"):
        raise ValueError("how is 'mod' or 'block'")
    found = {c: c % q if how == "mod" else c * q // k for c in range(k)}
    return spark.createDataFrame(list(found.items()), "client_id int, subserver_id int") if spark else found


def train_test(df: DataFrame, mix: Column, parts: int = 7) -> DataFrame:
    """Adds ``is_test``, true for one part of the rows by a mixed key."""
    return df.withColumn("is_test", F.pmod(mix, F.lit(parts)) == 0)
