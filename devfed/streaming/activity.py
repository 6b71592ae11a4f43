"""Windows over clients' activity, and joins in event time; the same functions serve batches and streams."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

KINDS = ("tumbling", "sliding", "session")


def counts(events: DataFrame, kind: str = "tumbling", watermark: str | None = None) -> DataFrame:
    """(user_id, start in seconds, n, total) in windows of an hour, of an hour every quarter, or up to a gap of half an hour. Streams need a watermark."""
    if kind not in KINDS:
        raise ValueError(f"kind is one of {KINDS}")
    events = events.withWatermark("ts", watermark) if watermark else events
    span = {"tumbling": lambda: F.window("ts", "1 hour"), "sliding": lambda: F.window("ts", "1 hour", "15 minutes"), "session": lambda: F.session_window("ts", "30 minutes")}[kind]()
    found = events.groupBy("user_id", span.alias("w")).agg(F.count("*").alias("n"), F.sum("value").alias("total"))
    return found.select("user_id", F.unix_timestamp("w.start").alias("start"), "n", "total")


def as_of(events: DataFrame, models: DataFrame) -> DataFrame:
    """(event_id, version): the newest model at or before each event.

    Models are few next to events: for every day the newest model before it is known, so that events and models meet
    by day, and only a day's own models are compared. The calendar is sent to the executors below the engine's own size limit, and
    is otherwise joined by day.
    """
    day = F.to_date("at")
    daily = models.groupBy(day.alias("day")).agg(F.sort_array(F.collect_list(F.struct("at", "version"))).alias("own"))
    spans = daily.agg(F.min("day").alias("a"))
    calendar = events.agg(F.max(F.to_date("ts")).alias("z")).crossJoin(F.broadcast(spans)).where("z >= a").select(F.explode(F.sequence("a", "z")).alias("day"))
    filled = calendar.join(daily, "day", "left").withColumn("before", F.last(F.element_at("own", -1)["version"], ignorenulls=True).over(Window.orderBy("day").rowsBetween(Window.unboundedPreceding, -1)))
    joined = events.withColumn("day", F.to_date("ts")).join(filled, "day", "left")
    today = F.filter("own", lambda m: m["at"] <= F.col("ts"))
    return joined.select("event_id", F.coalesce(F.when(F.size(today) > 0, F.element_at(today, -1)["version"]), F.col("before")).alias("version"))


def count_back(events: DataFrame, by: str, at: str, span: int, name: str = "n") -> DataFrame:
    """Adds how many rows of the same owner lie in the span (microseconds) up to each row, itself and ties included.

    An owner's rows are dealt out by spans of time, each beside copies of the span before it, so that no owner is one task's work.
    """
    span_of = F.floor(F.unix_micros(at) / span)
    rows = events.withColumns({"__at": F.unix_micros(at), "__span": span_of, "__own": F.lit(True)})
    both = rows.unionByName(rows.withColumns({"__span": F.col("__span") + 1, "__own": F.lit(False)}))
    back = Window.partitionBy(by, "__span").orderBy("__at").rangeBetween(-span, 0)
    return both.withColumn(name, F.count("*").over(back)).where("__own").drop("__at", "__span", "__own")
