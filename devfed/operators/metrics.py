"""Indicators of two-class models: confusion counts, accuracy, precision, recall, F, ROC, AUC, KS, and summaries over rounds."""

from __future__ import annotations

import math
from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..sources.checkpoints import materialised

INDICATORS = ("accuracy", "precision", "recall", "f1", "ks")


def confusion(scored: DataFrame, by: Sequence[str] = (), threshold: float = 0.5) -> DataFrame:
    """tp, fp, tn, fn of (score, label) rows, by group; positive from the threshold on."""
    hit, real = F.col("score") >= threshold, F.col("label") == 1
    count = lambda c, name: F.sum(F.when(c, 1).otherwise(0)).alias(name)
    return scored.groupBy(*by).agg(count(hit & real, "tp"), count(hit & ~real, "fp"), count(~hit & ~real, "tn"), count(~hit & real, "fn"))


def indicators(counts: DataFrame) -> DataFrame:
    """Adds accuracy, precision, recall, fpr, f1 (by counts) and f1_harmonic; null where a denominator is 0."""
    over = lambda a, b: F.when(b > 0, a / b)
    tp, fp, tn, fn = (F.col(c).cast("double") for c in ("tp", "fp", "tn", "fn"))
    out = counts.withColumns({"accuracy": over(tp + tn, tp + fp + tn + fn), "precision": over(tp, tp + fp), "recall": over(tp, tp + fn), "fpr": over(fp, fp + tn), "f1": over(2 * tp, 2 * tp + fp + fn)})
    p, r = F.col("precision"), F.col("recall")
    return out.withColumn("f1_harmonic", F.when(p + r > 0, 2 / (1 / p + 1 / r)).when(p.isNotNull() & r.isNotNull(), F.lit(0.0)))


#: Distinct scores up to which one window runs over them; more are dealt out by ranges.
WINDOW_POINTS = 1_000_000


def _points(scored: DataFrame, by: list[str], bins: int | None = None) -> DataFrame:
    """(by, threshold, p, n, tp, fp, all_p, all_n): rows of each class at a score, at or above it, and in all."""
    level = F.floor(F.least(F.col("score"), F.lit(1 - 1e-12)) * bins) / bins if bins else F.col("score")
    points = scored.groupBy(*by, level.alias("threshold")).agg(F.sum(F.when(F.col("label") == 1, 1).otherwise(0)).alias("p"), F.sum(F.when(F.col("label") == 0, 1).otherwise(0)).alias("n"))
    points = materialised(points)
    totals = points.groupBy(*by).agg(F.sum("p").alias("all_p"), F.sum("n").alias("all_n"))
    many, keys = points.count(), [*by, "__range"]
    if many <= WINDOW_POINTS:
        down = Window.partitionBy(*by).orderBy(F.desc("threshold")).rowsBetween(Window.unboundedPreceding, 0)
        points = points.withColumns({"tp": F.sum("p").over(down), "fp": F.sum("n").over(down)})
    else:
        # each range is summed up on its own; what lies above it comes from a row for each range and group
        order = [*by, F.desc("threshold")]
        dealt = points.repartitionByRange(math.ceil(many / WINDOW_POINTS) + 1, *order).sortWithinPartitions(*order)
        dealt = materialised(dealt.withColumn("__range", F.spark_partition_id()))
        above = Window.partitionBy(*by).orderBy("__range").rowsBetween(Window.unboundedPreceding, -1)
        sums = dealt.groupBy(*keys).agg(F.sum("p").alias("p"), F.sum("n").alias("n"))
        sums = sums.select(*keys, *(F.coalesce(F.sum(c).over(above), F.lit(0)).alias(f"__{c}") for c in "pn"))
        own = Window.partitionBy(*keys).orderBy(F.desc("threshold")).rowsBetween(Window.unboundedPreceding, 0)
        points = dealt.join(F.broadcast(sums), keys).withColumns({"tp": F.sum("p").over(own) + F.col("__p"), "fp": F.sum("n").over(own) + F.col("__n")}).drop("__p", "__n", "__range")
    return points.join(totals, by) if by else points.crossJoin(F.broadcast(totals))


def roc(scored: DataFrame, by: Sequence[str] = (), bins: int | None = None) -> DataFrame:
    """ROC points: threshold, tp, fp, tpr, fpr, from (0, 0) at an infinite threshold down to (1, 1). Tied scores make one point.

    With bins the scores are first rounded down to that many equal steps, which bounds the points whatever the rows.
    """
    by = list(by)
    points = _points(scored, by, bins).select(*by, "threshold", "tp", "fp", "all_p", "all_n")
    nothing = F.lit(0).cast("long")
    start = points.groupBy(*by).agg(F.first("all_p").alias("all_p"), F.first("all_n").alias("all_n")).where("all_p IS NOT NULL").select(*by, F.lit(float("inf")).alias("threshold"), nothing.alias("tp"), nothing.alias("fp"), "all_p", "all_n")
    share = lambda c, all_c: F.when(F.col(all_c) > 0, F.col(c) / F.col(all_c))
    return points.unionByName(start).select(*by, "threshold", "tp", "fp", share("tp", "all_p").alias("tpr"), share("fp", "all_n").alias("fpr"))


def auc(scored: DataFrame, by: Sequence[str] = (), method: str = "trapezoid", bins: int | None = None) -> DataFrame:
    """Area under the ROC curve by trapezoids, or as the tie-corrected rank statistic; null if a class is missing."""
    by = list(by)
    if method not in ("trapezoid", "rank"):
        raise ValueError("method is 'trapezoid' or 'rank'")
    points = _points(scored, by, bins if method == "trapezoid" else None)
    p, n, tp, fp, all_p, all_n = (F.col(c).cast("double") for c in ("p", "n", "tp", "fp", "all_p", "all_n"))
    if method == "trapezoid":
        # a step to the right by n rows, at the mean height of its ends
        part = n * (2 * tp - p) / 2
    else:
        # the mean rank from below of a tie's rows, less the least that its positives could have together
        part = p * (all_p + all_n - tp - fp + (p + n + 1) / 2) - p * (all_p + 1) / 2
    both = F.max(all_p) * F.max(all_n)
    return points.groupBy(*by).agg(F.when(both > 0, F.sum(part) / both).alias("auc"))


def ks(scored: DataFrame, by: Sequence[str] = (), bins: int | None = None) -> DataFrame:
    """The largest tpr - fpr over the ROC points, and the (highest) threshold where it is reached."""
    points = roc(scored, by, bins).withColumn("gap", F.col("tpr") - F.col("fpr"))
    return points.groupBy(*by).agg(F.max("gap").alias("ks"), F.max_by("threshold", F.struct("gap", "threshold")).alias("ks_threshold"))


def round_summary(history: DataFrame, metrics: Sequence[str], by: Sequence[str] = ("method",), q3: bool = False) -> DataFrame:
    """Min, first quartile, median, mean, max (and third quartile) of each indicator across rounds; nulls are left out and counted."""
    pairs = ", ".join(f"'{m}', CAST({m} AS DOUBLE)" for m in metrics)
    long = history.select(*by, F.expr(f"stack({len(metrics)}, {pairs}) AS (metric, value)"))
    q = lambda p, name: F.percentile("value", p).alias(name)
    figures = [F.min("value").alias("min"), q(0.25, "q1"), q(0.5, "median"), F.avg("value").alias("mean"), *([q(0.75, "q3")] if q3 else []), F.max("value").alias("max"), F.count_if(F.col("value").isNull()).alias("n_null")]
    return long.groupBy(*by, "metric").agg(*figures)


def curves(history: DataFrame, metric: str, window: int = 10, by: Sequence[str] = ("method",)) -> DataFrame:
    """An indicator by round, with its moving mean and its gain on the round before."""
    along = Window.partitionBy(*by).orderBy("round")
    return history.select(*by, "round", F.col(metric).alias("value"), F.avg(metric).over(along.rowsBetween(1 - window, 0)).alias("smooth"), (F.col(metric) - F.lag(metric).over(along)).alias("gain"))


def stability(history: DataFrame, metric: str, by: Sequence[str] = ("method",)) -> DataFrame:
    """Spread of an indicator over rounds: sample deviation and interquartile range."""
    return history.groupBy(*by).agg(F.stddev_samp(metric).alias("sd"), (F.percentile(metric, 0.75) - F.percentile(metric, 0.25)).alias("iqr"))


#: Bits of a margin's order that make its bin: sign, exponent and six of the mantissa. Cells of rounds and bins that a task holds before it adds up equal ones.
BIN_BITS, HELD_CELLS = 18, 4_000_000


def _order(margins: np.ndarray) -> np.ndarray:
    """Integers in the order of the margins."""
    bits = (margins + 0.0).view(np.int64)
    return np.where(bits < 0, ~(bits & np.int64(2**63 - 1)), bits)


def _margins(part: pa.RecordBatch, w: np.ndarray, intercept: bool) -> tuple[np.ndarray, np.ndarray]:
    """Labels, and a column of margins for each vector; one product after the other, so that equal rows have equal margins in every batch."""
    x = [c.to_numpy(zero_copy_only=False) for c in part.columns]
    at = np.zeros((len(part), len(w)))
    for k, column in enumerate([np.ones(len(part)), *x[:-1]] if intercept else x[:-1]):
        at += column[:, None] * w[:, k]
    return x[-1] == 1, at


def evaluate_rounds(df: DataFrame, features: Sequence[str], rounds: np.ndarray, vectors: np.ndarray, label: str = "label", intercept: bool = True, threshold: float = 0.5) -> DataFrame:
    """Confusion counts, indicators, KS and log loss of all rounds, exact, in two passes over the rows.

    KS is over all distinct margins, which order rows like their scores but don't saturate. The first pass counts rows by class
    and bin of margins (BIN_BITS of their order, so few bins hold any). KS is at least its value at the edges of bins, and
    inside a bin it can't exceed the value at the upper edge plus the bin's share of the positives; the second pass takes the distinct
    margins of those bins alone that may hold more than the best edge.
    """
    w = np.asarray(vectors, float)
    source = df.select(*(F.col(c).cast("double").alias(f"f{k}") for k, c in enumerate(features)), F.col(label).cast("double").alias("y"))
    numbers, bits, most = np.asarray(rounds, int), BIN_BITS, HELD_CELLS
    shift = 64 - bits
    names = ["round", "kind", "at", "n", "p"]

    def sums(r: np.ndarray, kind: str, at: np.ndarray, n: np.ndarray, p: np.ndarray) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(numbers[r]), pa.array([kind] * len(r), pa.string()), pa.array(at.astype(np.int64)), pa.array(n.astype(float)), pa.array(p.astype(float))], names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts, losses, seen, held = np.zeros((len(w), 4)), np.zeros(len(w)), 0, [np.zeros((3, 0), np.int64)]

        def merged() -> np.ndarray:
            cell, n, p = np.concatenate(held, axis=1)
            cell, place = np.unique(cell, return_inverse=True)
            return np.stack([cell, *(np.bincount(place, x, len(cell)).astype(np.int64) for x in (n, p))])

        for batch in batches:
            for part in (batch.slice(i, 2000) for i in range(0, len(batch), 2000)):
                y, at = _margins(part, w, intercept)
                p = 1 / (1 + np.exp(-np.clip(at, -30, 30)))
                hit, real = p >= threshold, y[:, None]
                counts += np.stack([(hit & real).sum(0), (hit & ~real).sum(0), (~hit & ~real).sum(0), (~hit & real).sum(0)], axis=1)
                losses -= np.log(np.where(real, p, 1 - p)).sum(0)
                seen += len(y)
                # round and bin in one number, the bin from its place above the lowest
                cell = (np.arange(len(w), dtype=np.int64) << bits) + (_order(at) >> shift) + (1 << (bits - 1))
                cell, place = np.unique(cell.ravel(), return_inverse=True)
                positive = np.bincount(place.ravel(), np.repeat(y, len(w)), len(cell)).astype(np.int64)
                held.append(np.stack([cell, np.bincount(place.ravel(), minlength=len(cell)) - positive, positive]))
                if sum(h.shape[1] for h in held) > most:
                    held = [merged()]
        if seen:
            cell, n, p = merged()
            yield sums(cell >> bits, "b", cell & ((1 << bits) - 1), n, p)
            for kind, table in (("c", counts), ("l", losses[:, None])):
                r, k = np.nonzero(table)
                yield sums(r, kind, k, table[r, k], np.zeros(len(r)))

    # a row for each round and occupied bin, whatever the rows of df
    cells = materialised(source.mapInArrow(run, "round long, kind string, at long, n double, p double").groupBy("round", "kind", "at").agg(F.sum("n").alias("n"), F.sum("p").alias("p")))
    cell = lambda k: F.coalesce(F.sum(F.when((F.col("kind") == "c") & (F.col("at") == k), F.col("n"))), F.lit(0.0)).cast("long")
    table = cells.groupBy("round").agg(cell(0).alias("tp"), cell(1).alias("fp"), cell(2).alias("tn"), cell(3).alias("fn"), F.sum(F.when(F.col("kind") == "l", F.col("n"))).alias("__loss"))
    whole = Window.partitionBy("round")
    above = whole.orderBy(F.desc("at")).rowsBetween(Window.unboundedPreceding, -1)
    bins = cells.where("kind = 'b'").select("round", "at", "n", "p", F.coalesce(F.sum("p").over(above), F.lit(0.0)).alias("p0"), F.coalesce(F.sum("n").over(above), F.lit(0.0)).alias("n0"), F.nullif(F.sum("p").over(whole), F.lit(0.0)).alias("all_p"), F.nullif(F.sum("n").over(whole), F.lit(0.0)).alias("all_n"))
    bins = bins.withColumns({"upper": F.col("p0") / F.col("all_p") - F.col("n0") / F.col("all_n"), "lower": (F.col("p0") + F.col("p")) / F.col("all_p") - (F.col("n0") + F.col("n")) / F.col("all_n")})
    bins = bins.withColumn("best", F.greatest(F.max("lower").over(whole), F.lit(0.0)))
    # edges of bins of one class only are exact already
    open_bins = bins.where("n > 0 AND p > 0 AND upper + p / all_p > best").select("round", "at", "p0", "n0", "all_p", "all_n")
    wanted = {}
    for row in open_bins.select("round", "at").collect():
        wanted.setdefault(row["round"], []).append(row["at"])
    wanted = {r: np.array(sorted(at)) for r, at in wanted.items()}

    def margins(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in (batch.slice(i, 2000) for i in range(0, len(batch), 2000)):
                y, at = _margins(part, w, intercept)
                for r, number in enumerate(numbers):
                    if int(number) in wanted:
                        order = _order(at[:, r])
                        where = (order >> shift) + (1 << (bits - 1))
                        own = np.isin(where, wanted[int(number)])
                        values, first, place = np.unique(order[own], return_index=True, return_inverse=True)
                        p, every = (np.bincount(place, x, len(values)).astype(float) for x in (y[own], None))
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(values), number)), pa.array(where[own][first]), pa.array(values), pa.array(p), pa.array(every - p)], ["round", "at", "value", "p", "n"])

    edges = bins.groupBy("round").agg(F.max("best").alias("best"))
    if wanted:
        points = source.mapInArrow(margins, "round long, at long, value long, p double, n double").groupBy("round", "at", "value").agg(F.sum("p").alias("p"), F.sum("n").alias("n"))
        down = Window.partitionBy("round", "at").orderBy(F.desc("value"))
        points = points.select("round", "at", F.sum("p").over(down).alias("p"), F.sum("n").over(down).alias("n")).join(open_bins, ["round", "at"])
        inside = points.groupBy("round").agg(F.max((F.col("p0") + F.col("p")) / F.col("all_p") - (F.col("n0") + F.col("n")) / F.col("all_n")).alias("inside"))
        edges = edges.join(inside, "round", "left").withColumn("best", F.greatest("best", "inside"))
    found = indicators(table).join(edges.select("round", F.col("best").alias("ks")), "round", "left")
    return found.withColumn("logloss", F.coalesce("__loss", F.lit(0.0)) / (F.col("tp") + F.col("fp") + F.col("tn") + F.col("fn"))).drop("__loss")
