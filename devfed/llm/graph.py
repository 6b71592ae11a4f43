"""Connected components of edge tables, filters of bounded size, and reliable checkpoints."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..sources.checkpoints import folder as checkpoint_folder  # noqa: F401
from ..sources.checkpoints import materialised as checkpointed


#: Edges up to which components are found in one task; a stated bound of its memory.
ONE_TASK = 1_000_000


def _in_one_task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Union-find over all edges: each node but the smallest of its component, with the smallest."""
    parts = [(b.column(0).to_numpy(), b.column(1).to_numpy()) for b in batches]
    if not parts:
        return
    nodes, place = np.unique(np.concatenate([x for p in parts for x in p]), return_inverse=True)
    a, b = np.split(place, 2) if len(parts) == 1 else (np.concatenate(x) for x in zip(*[np.split(q, 2) for q in np.split(place, np.cumsum([2 * len(p[0]) for p in parts])[:-1])], strict=True))
    label = np.arange(len(nodes))
    while True:
        # every root takes the smallest label beside it, then paths are halved to their ends
        low, new = np.minimum(label[a], label[b]), label.copy()
        np.minimum.at(new, label[a], low)
        np.minimum.at(new, label[b], low)
        while (new != new[new]).any():
            new = new[new]
        new = new[label]
        if (new == label).all():
            break
        label = new
    away = label != np.arange(len(nodes))
    yield pa.RecordBatch.from_arrays([pa.array(nodes[away]), pa.array(nodes[label[away]])], ["a", "b"])


def components(edges: DataFrame) -> DataFrame:
    """(node, component) for every node of edges (a, b), the component being its smallest node.

    Large-star and small-star steps in turn until nothing changes. An edge list is never
    gathered: each step is an aggregation and a join, which skew handling can split. Up to
    ONE_TASK edges a single task does the same by union-find.
    """
    edges = checkpointed(edges.where("a <> b").select(F.greatest("a", "b").cast("long").alias("a"), F.least("a", "b").cast("long").alias("b")).distinct())
    state, n = None, edges.count()
    if n <= ONE_TASK:
        edges = checkpointed(edges.coalesce(1).mapInArrow(_in_one_task, "a long, b long"))
    while n > ONE_TASK:
        both = edges.union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        edges = both.join(least, "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        least = edges.groupBy("a").agg(F.min("b").alias("m"))
        edges = edges.join(least, "a").select(F.explode(F.array(F.struct("b", "m"), F.struct(F.col("a").alias("b"), "m"))).alias("e")).select(F.col("e.b").alias("a"), F.col("e.m").alias("b")).where("a <> b").distinct()
        edges = checkpointed(edges)
        now = edges.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if now == state:
            break
        state = now
    return edges.select(F.col("a").alias("node"), F.col("b").alias("component")).union(edges.select("b", "b").distinct())


#: Least and most bits of a filter that is sent to the executors: 8 MB to 64 MB, however many values it holds.
FILTER_BITS, MOST_FILTER_BITS = 1 << 26, 1 << 29


class Filter:
    """Rows whose value may be among given ones: a bit map of bounded size, of eight bits for each of ``expected`` values if they fit. It loses no row; the fuller it is, the fewer it drops."""

    def __init__(self, values: DataFrame, expected: int = 0) -> None:
        name, self.bits = values.columns[0], min(max(FILTER_BITS, 1 << (8 * expected).bit_length()), MOST_FILTER_BITS)
        at = values.select(self.place(F.col(name)).alias("at"))
        rows = at.groupBy(F.expr("at div 32768").alias("part")).agg(F.bitmap_construct_agg(F.expr("at % 32768")).alias("bits")).collect()
        bits = np.zeros(self.bits // 8, np.uint8)
        for row in rows:
            bits[row["part"] * 4096 : (row["part"] + 1) * 4096] = np.frombuffer(row["bits"], np.uint8)
        self.sent = values.sparkSession.sparkContext.broadcast(bits.tobytes())

    def place(self, column: Column) -> Column:
        return F.pmod(F.xxhash64(column), F.lit(self.bits))

    def of(self, df: DataFrame, name: str) -> DataFrame:
        """The rows of df that may have one of the values in a column."""
        sent, kinds = self.sent, df.schema

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            bits = np.frombuffer(sent.value, np.uint8)
            for batch in batches:
                at = batch.column(batch.num_columns - 1).to_numpy()
                hit = (bits[at >> 3] >> (at & 7).astype(np.uint8)) & 1
                yield pa.RecordBatch.from_arrays(batch.columns[:-1], batch.schema.names[:-1]).filter(pa.array(hit.astype(bool)))

        return df.withColumn("__at", self.place(F.col(name))).mapInArrow(run, kinds)
