"""Rows packed into blocks of contiguous matrices that stay with their client.

The rows are dealt out by client once. A task walks over its clients in order and cuts
each cluster's rows into blocks of at most BLOCK_ROWS, so that no cluster must fit one row
of the block table. From here on only vectors leave a task.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BLOCK_ROWS = 100_000
SCHEMA = "client_id int, cluster_id int, subserver_id int, block int, n long, x binary, y binary"
NAMES = ["client_id", "cluster_id", "subserver_id", "block", "n", "x", "y"]


def block(rows: np.ndarray, key: tuple, number: int, intercept: bool = True) -> pa.RecordBatch:
    """One block of rows (features, then the label) of a (client, cluster, sub-server)."""
    x = np.column_stack([np.ones(len(rows)), rows[:, :-1]]) if intercept else rows[:, :-1]
    values = [pa.array([v], pa.int32()) for v in (*key, number)]
    return pa.RecordBatch.from_arrays([*values, pa.array([len(rows)]), pa.array([np.ascontiguousarray(x).tobytes()], pa.binary()), pa.array([np.ascontiguousarray(rows[:, -1]).tobytes()], pa.binary())], NAMES)


def to_blocks(df: DataFrame, features: Sequence[str], label: str = "label", order: Sequence[str] = (), intercept: bool = True, block_rows: int = BLOCK_ROWS, partitions: int | None = None) -> DataFrame:
    """Blocks of rows with client_id and optionally cluster_id and subserver_id; x is row-major float64, its first column 1 with an intercept."""
    extra = {c: F.lit(0) for c in ("cluster_id", "subserver_id") if c not in df.columns}
    source = df.withColumns(extra) if extra else df
    keys = [F.col(c).cast("int").alias(c) for c in NAMES[:3]]
    source = source.select(*keys, *(F.col(c).cast("double").alias(f"f{k}") for k, c in enumerate(features)), F.col(label).cast("double").alias("y"), *(F.col(c).alias(f"o{k}") for k, c in enumerate(order)))
    dealt = source.repartition(partitions, "client_id") if partitions else source.repartition("client_id")
    sorted_rows = dealt.sortWithinPartitions(*NAMES[:2], *(f"o{k}" for k in range(len(order)))).drop(*(f"o{k}" for k in range(len(order))))
    wide = len(features)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, parts, held, number = None, [], 0, 0

        for batch in batches:
            if not batch.num_rows:
                continue
            ids = np.column_stack([batch.column(k).to_numpy() for k in range(3)])
            rows = np.column_stack([batch.column(k).to_numpy(zero_copy_only=False) for k in range(3, 4 + wide)])
            edges = [0, *(np.flatnonzero((ids[1:, :2] != ids[:-1, :2]).any(axis=1)) + 1), len(ids)]
            for a, b in zip(edges, edges[1:], strict=False):
                own = tuple(int(v) for v in ids[a])
                if key is not None and own[:2] != key[:2]:
                    if held:
                        yield block(np.concatenate(parts), key, number, intercept)
                    parts, held, number = [], 0, 0
                key = own
                while a < b:
                    take = min(b - a, block_rows - held)
                    parts.append(rows[a : a + take])
                    a, held = a + take, held + take
                    if held == block_rows:
                        yield block(np.concatenate(parts), key, number, intercept)
                        parts, held, number = [], 0, number + 1
        if held:
            yield block(np.concatenate(parts), key, number, intercept)

    return sorted_rows.mapInArrow(run, SCHEMA)


def matrices(x: bytes, y: bytes) -> tuple[np.ndarray, np.ndarray]:
    labels = np.frombuffer(y)
    return np.frombuffer(x).reshape(len(labels), -1), labels


def clients(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, int, dict[int, list[tuple[np.ndarray, np.ndarray]]]]]:
    """(client, sub-server, blocks by cluster), client by client, from a task's blocks in order."""
    key, held = None, {}
    for batch in batches:
        for row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
            client, cluster, server, _, _, x, y = row
            if key is not None and client != key[0]:
                yield (*key, held)
                held = {}
            key = (client, server)
            held.setdefault(cluster, []).append(matrices(x, y))
    if key is not None:
        yield (*key, held)
