"""Rounds over a stream of clients' vectors: a sub-server merges when enough of a round's vectors have arrived.

Vectors behind the watermark are dropped by the engine (``dropped_late`` reads how many from a query's progress), repeated ones by
(client, round). A group's state holds the vectors of one (sub-server, round) until the quorum is met; then it holds counts
alone, of what still arrives. When the watermark is ``expiry_ms`` past the group's last arrival the state is removed, and what came
late, or too little for a quorum, is reported in the ledger row of the group.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout
from pyspark.sql.window import Window

from ..operators import weighting

SCHEMA = "ts timestamp, client_id int, subserver_id int, round int, n_rows long, w array<double>"
_OUT = "subserver_id int, round int, n_rows long, members int, complete boolean, late int, w array<double>"
_STATE = "done boolean, late int, clients array<int>, rows array<long>, vectors array<array<double>>"


def quorum_rounds(updates: DataFrame, quorum: int, rule: str = "proportional", watermark: str = "10 minutes", expiry_ms: int = 3_600_000) -> DataFrame:
    """A stream of (subserver_id, round, n_rows, members, complete, late, w).

    A round whose quorum is met gives a row at once (complete, late null) and a ledger row when its state expires (no vector, late:
    the arrivals since); one whose quorum isn't gives a row of what has arrived when it expires (not complete).
    """
    if quorum < 1:
        raise ValueError("a quorum has at least one client")

    def row(key: tuple, n_rows: int, members: int, complete: bool, late: int | None, w: list[float] | None) -> pd.DataFrame:
        return pd.DataFrame({"subserver_id": [key[0]], "round": [key[1]], "n_rows": [n_rows], "members": [members], "complete": [complete], "late": pd.array([late], "Int32"), "w": [w]})

    def merged(key: tuple, clients: list, rows: list, vectors: list, complete: bool) -> pd.DataFrame:
        order = np.argsort(clients)
        counts, stacked = np.array(rows, float)[order], np.array([list(v) for v in vectors], float)[order]
        return row(key, int(counts.sum()), len(clients), complete, None if complete else 0, weighting.merge_np(stacked, counts, rule).tolist())

    def run(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        done, late, clients, rows, vectors = state.get if state.exists else (False, 0, [], [], [])
        clients, rows, vectors = list(clients), list(rows), [list(v) for v in vectors]
        if state.hasTimedOut:
            state.remove()
            if done:
                yield row(key, 0, 0, True, late, None)
            elif clients:
                yield merged(key, clients, rows, vectors, False)
            return
        newest = 0
        for batch in batches:
            newest = max(newest, int(batch["ts"].max().timestamp() * 1000))
            for arrival in batch.sort_values(["ts", "client_id"]).itertuples():
                if done:
                    late += 1
                elif arrival.client_id not in clients:
                    clients.append(int(arrival.client_id))
                    rows.append(int(arrival.n_rows))
                    vectors.append([float(x) for x in arrival.w])
                    if len(clients) == quorum:
                        yield merged(key, clients, rows, vectors, True)
                        done, clients, rows, vectors = True, [], [], []
        state.update((done, late, clients, rows, vectors))
        state.setTimeoutTimestamp(max(newest, state.getCurrentWatermarkMs()) + expiry_ms)

    arrived = updates.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["client_id", "round"])
    return arrived.groupBy("subserver_id", "round").applyInPandasWithState(run, _OUT, _STATE, "append", GroupStateTimeout.EventTimeTimeout)


def dropped_late(query: StreamingQuery) -> int:
    """Vectors that a query has dropped behind the watermark so far, by the progress that it still remembers."""
    return sum(int(o.get("numRowsDroppedByWatermark", 0)) for p in query.recentProgress for o in p["stateOperators"])


def quorum_batch(updates: DataFrame, quorum: int, rule: str = "proportional") -> DataFrame:
    """The same over a table of arrivals, in order of arrival, for comparison and replays."""
    first = updates.groupBy("client_id", "round").agg(F.min(F.struct("ts", "subserver_id", "n_rows", "w")).alias("u")).select("client_id", "round", "u.*")
    arrived = first.withColumn("place", F.row_number().over(Window.partitionBy("subserver_id", "round").orderBy("ts", "client_id")))
    used = arrived.where(F.col("place") <= quorum)
    full = used.groupBy("subserver_id", "round").agg(F.count("*").cast("int").alias("members")).where(F.col("members") == quorum)
    return weighting.merge(used.join(full, ["subserver_id", "round"]), ["subserver_id", "round"], rule=rule).join(full, ["subserver_id", "round"]).select("subserver_id", "round", "n_rows", "members", "w")


def running_moments(rows: DataFrame, columns: list[str]) -> DataFrame:
    """Count, sum and sum of squares by client, for standardisation over a stream (update mode)."""
    return rows.groupBy("client_id").agg(F.count("*").alias("n"), *(F.sum(c).alias(f"{c}__sum") for c in columns), *(F.sum(F.col(c) * F.col(c)).alias(f"{c}__square") for c in columns))


def with_tier(updates: DataFrame, tier_map: DataFrame) -> DataFrame:
    """Arrivals with their sub-server, from a static map of clients."""
    return updates.drop("subserver_id").join(tier_map, "client_id")


def in_round(updates: DataFrame, opened: DataFrame, length: str = "1 hour", watermark: str | None = "10 minutes") -> DataFrame:
    """Arrivals (ts, round, ...) beside the opening (opened_at, round) of their round, those up to a length of time after it: a join of two streams within bounds of time, or, without a watermark, of two tables."""
    if watermark:
        updates, opened = updates.withWatermark("ts", watermark), opened.withWatermark("opened_at", watermark)
    a, b = updates.alias("a"), opened.alias("b")
    within = (F.col("a.round") == F.col("b.round")) & (F.col("a.ts") >= F.col("b.opened_at")) & (F.col("a.ts") < F.col("b.opened_at") + F.expr(f"INTERVAL {length}"))
    return a.join(b, within).select("a.*", "b.opened_at")


def score_stream(rows: DataFrame, features: list[str], newest, out: list) -> object:
    """Scores each micro-batch with the newest vector and appends (batch, rows, accuracy) to out: test, then train. newest() returns a vector."""
    from ..operators import metrics, predict

    def each(batch: DataFrame, number: int) -> None:
        found = metrics.indicators(metrics.confusion(predict.score(batch, features, newest()))).first()
        if found["tp"] is not None:
            out.append((number, found["tp"] + found["fp"] + found["tn"] + found["fn"], found["accuracy"]))

    return rows.writeStream.foreachBatch(each)
