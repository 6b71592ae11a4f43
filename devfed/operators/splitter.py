"""Splitting one client's rows into clusters by max-min distances, with tests that accept or undo a split.

On standardised rows: the first centre is one row, the second the row farthest from it. Then the row
with the largest distance to its nearest centre becomes a centre, as long as that distance exceeds
theta times the gap of the first two and there are fewer than the cap. Every row joins its nearest centre.
Ties fall to the lowest key and the lowest cluster.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator, Sequence

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..sources.checkpoints import materialised
from . import blocks, pairwise

GROWTH = ("one_at_a_time", "single_sweep")
SEEDS = ("first", "hash", "medoid")
ACCEPT = ("spread", "gap", "both", "always")


def _distances(z: np.ndarray, centre: np.ndarray) -> np.ndarray:
    # column by column: sums along the few places of a row cost three times as much
    total = np.zeros(len(z))
    for k in range(z.shape[1]):
        d = z[:, k] - centre[k]
        d *= d
        total += d
    return np.sqrt(total, out=total)


def cap_of(n: int, divisor: int = 50) -> int:
    return max(2, n // divisor)


def first_centre(z: np.ndarray, seed_rule: str = "first", marks: np.ndarray | None = None) -> int:
    """The first row, the one nearest to the mean, or the one with the lowest mark (a hash of its key)."""
    if seed_rule == "first":
        return 0
    if seed_rule == "medoid":
        return int(_distances(z, z.mean(axis=0)).argmin())
    if seed_rule == "hash":
        if marks is None:
            raise ValueError("seed_rule 'hash' needs the rows' marks")
        return int(np.argmin(marks)) if np.asarray(marks).dtype.kind in "iuf" else min(range(len(marks)), key=lambda i: (marks[i], i))
    raise ValueError(f"seed_rule is one of {SEEDS}")


def maxmin(z: np.ndarray, theta: float = 0.5, cap: int | None = None, growth: str = "one_at_a_time", seed_rule: str = "first", marks: np.ndarray | None = None) -> tuple[np.ndarray, list[int]]:
    """(cluster of each row, rows that are centres) for rows in order of their keys; marks: what seed_rule "hash" goes by."""
    if not 0 < theta < 1:
        raise ValueError("theta lies between 0 and 1")
    if growth not in GROWTH:
        raise ValueError(f"growth is one of {GROWTH}")
    cap, z = cap_of(len(z)) if cap is None else cap, np.asfortranarray(z)
    centres = [first_centre(z, seed_rule, marks)]
    nearest = _distances(z, z[centres[0]])
    second = int(nearest.argmax())
    gap = nearest[second]
    if gap == 0 or cap < 2:
        return np.zeros(len(z), int), centres
    label = np.zeros(len(z), int)

    def join(row: int) -> None:
        """Makes a row the next centre, which the rows join that it is nearest to."""
        d = _distances(z, z[row])
        closer = np.flatnonzero(d < nearest)
        label[closer], nearest[closer] = len(centres), d[closer]
        centres.append(row)

    join(second)
    if growth == "single_sweep":
        order = np.lexsort((np.arange(len(z)), -nearest))
        for i in [int(i) for i in order[: cap - 2] if nearest[i] > theta * gap]:
            join(i)
    else:
        while len(centres) < cap:
            far = int(nearest.argmax())
            if not nearest[far] > theta * gap:
                break
            join(far)
    return label, centres


def assign(z: np.ndarray, centres: np.ndarray) -> np.ndarray:
    """The nearest centre of each row; the running minimum keeps one distance a row."""
    label, best, z = np.zeros(len(z), int), np.full(len(z), np.inf), np.asfortranarray(z)
    for j, c in enumerate(centres):
        d = _distances(z, c)
        closer = d < best
        label[closer], best[closer] = j, d[closer]
    return label


def complete_linkage(z: np.ndarray, clusters: int, max_rows: int | None = None) -> np.ndarray:
    """Agglomerative clusters by the largest distance of their rows, along chains of nearest neighbours: 8 n**2 bytes and time like n**2.

    Only where the caller names max_rows, above it an evenly spaced sample is clustered and the others join the nearest mean.
    """
    n = len(z)
    if max_rows is not None and n > max_rows:
        some = np.linspace(0, n - 1, max_rows).astype(int)
        own = complete_linkage(z[some], clusters)
        return assign(z, np.stack([z[some][own == j].mean(axis=0) for j in range(own.max() + 1)]))
    square = np.empty((n, n))
    for i in range(n):
        square[i] = _distances(z, z[i])
    np.fill_diagonal(square, np.inf)
    alive, chain, merges = np.ones(n, bool), [], []
    while len(merges) < n - 1:
        if not chain:
            chain = [int(alive.argmax())]
        while True:
            i, before = chain[-1], chain[-2] if len(chain) > 1 else None
            j = int(square[i].argmin())
            # of equally near ones the chain's last, so that it ends
            if before is not None and square[i, before] <= square[i, j]:
                break
            chain.append(j)
        i, j = sorted(chain[-2:])
        del chain[-2:]
        merges.append((square[i, j], i, j))
        square[i] = np.maximum(square[i], square[j])
        square[:, i] = square[i]
        square[j] = square[:, j] = np.inf
        square[i, i] = np.inf
        alive[j] = False
    label = np.arange(n)
    # the chains find the merges in another order than that of their distances
    for _, i, j in sorted(merges, key=lambda m: m[0])[: max(0, n - max(1, clusters))]:
        label[label == label[j]] = label[i]
    return np.unique(label, return_inverse=True)[1]


def distinct(z: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The different rows, and how often each lies there."""
    order = np.lexsort(z.T)
    ordered = z[order]
    first = np.flatnonzero(np.r_[True, (ordered[1:] != ordered[:-1]).any(axis=1)])
    return ordered[first], np.diff(np.r_[first, len(z)]).astype(float)


def mean_pairwise(z: np.ndarray, limit: int | None = None, block: int = 512) -> float:
    """Mean distance of all pairs, in blocks of rows by rows; 0 for one row. Only where the caller names a limit, above it of an evenly spaced sample.

    Equal rows are measured once and counted as often as they lie there: time like the square of the different rows. Many rows of few
    columns are summed up by cubes (``pairwise``), unless they lie so unevenly that all pairs are cheaper.
    """
    if len(z) < 2:
        return 0.0
    if limit is not None and len(z) > limit:
        z = z[np.linspace(0, len(z) - 1, limit).astype(int)]
    n, (z, times) = len(z), distinct(z)
    if (found := pairwise.total(z, times)) is not None:
        return 2 * found / (n * (n - 1))
    square, one, total = (z**2).sum(axis=1), np.ones(len(z)), 0.0
    # one product gives the squares of a block's distances
    left, right = np.column_stack([-2 * z, one, square]), np.ascontiguousarray(np.column_stack([z, square, one]).T)
    height = max(1, block // 4)
    buffer = np.empty(height * block)
    for i in range(0, len(z), height):
        own, most = left[i : i + height], min(i + height, len(z))
        for j in range(i, len(z), block):
            d = buffer[: len(own) * min(block, len(z) - j)].reshape(len(own), -1)
            np.matmul(own, right[:, j : j + block], out=d)
            np.sqrt(np.maximum(d, 0, out=d), out=d)
            weighed = times[j : j + block].copy()
            if j == i:
                # pairs within the rows of own come up twice, and a row's with itself not at all
                np.fill_diagonal(d, 0)
                weighed[: most - i] /= 2
            total += 2 * float(times[i:most] @ (d @ weighed))
    return total / (n * (n - 1))


def _most_mean(z: np.ndarray) -> float:
    """No mean distance of all pairs is above this: the root of their mean squared distance."""
    # a little more, for what sums round
    return math.sqrt(2 * float(z.var(axis=0).sum()) * len(z) / max(1, len(z) - 1)) * (1 + 1e-9) + 1e-12


#: Cubes, about, and columns that they are cut along, for bounds of mean distances.
BOUND_CUBES, BOUND_WIDTH = 1296, 10


def _least_mean(z: np.ndarray) -> float:
    """No mean distance of all pairs is below this. All rows count: the mean distance from rows to rows is at least that from their means to means, for the rows of cubes, and for single rows and the mean of all."""
    n, width = len(z), min(z.shape[1], BOUND_WIDTH)
    if n < 2:
        return 0.0
    sides, extent = max(2, int(BOUND_CUBES ** (1 / width) + 1e-9)), np.ptp(z, axis=0)
    cell = np.zeros(n, int)
    for k in range(width):
        if extent[k] > 1e-200:
            cell = cell * sides + np.minimum((z[:, k] - z[:, k].min()) * (sides / extent[k]), sides - 1).astype(int)
    counts = np.bincount(cell).astype(float)
    held = counts > 0
    means = np.stack([np.bincount(cell, column)[held] for column in z.T], axis=1) / counts[held, None]
    times, square = counts[held], (means**2).sum(axis=1)
    # one product gives all squares of distances, less what it may round up
    apart = square[:, None] + square - 2 * (means @ means.T) - 1e-13 * (1 + square.max())
    total = float(times @ np.sqrt(np.maximum(apart, 0, out=apart), out=apart) @ times)
    total = max(total, n * float(_distances(z, z.mean(axis=0)).sum()))
    # a little less, for what sums round
    return total / (n * (n - 1)) * (1 - 1e-9)


def _widest(z: np.ndarray, label: np.ndarray, spread: Callable[[np.ndarray], float], whole: bool) -> float:
    """The largest spread of a cluster. Clusters whose bound, the root of their mean squared distance, is below one already found need not be measured; that holds where spreads are of the whole cluster."""
    bounds, found = {j: _most_mean(z[label == j]) for j in np.unique(label)}, 0.0
    for j in sorted(bounds, key=bounds.get, reverse=True):
        if whole and bounds[j] <= found:
            break
        found = max(found, spread(z[label == j]))
    return found


def _gap(centres: np.ndarray) -> float:
    """The smallest distance of two centres."""
    return float(min((_distances(centres[j + 1 :], centres[j]).min() for j in range(len(centres) - 1)), default=0.0))


#: What a report holds beside the decision.
RATIOS = ("spread", "gap")


def figures(z: np.ndarray, label: np.ndarray, centres: np.ndarray, dist: str = "pairwise", limit: int | None = None, overall: float | None = None, ratios: Sequence[str] = RATIOS) -> dict[str, float | None]:
    """What the acceptance tests look at: spread_ratio (largest mean distance within a cluster by that of the client) and gap_ratio (smallest distance of centres by the client's). overall: the client's mean distance, where it is known; ratios: those that are measured."""
    if dist == "pairwise":
        spread = lambda rows: mean_pairwise(rows, limit)
    elif dist == "centroid":
        spread = lambda rows: float(_distances(rows, rows.mean(axis=0)).mean())
    else:
        raise ValueError("dist is 'pairwise' or 'centroid'")
    overall = spread(z) if overall is None else overall
    parts = {"spread": lambda: _widest(z, label, spread, limit is None), "gap": lambda: _gap(centres)}
    return {"overall": overall} | {f"{r}_ratio": (part() / overall if overall else 0.0) if r in ratios else None for r, part in parts.items()}


#: The ratios that each test looks at.
ACCEPTS_BY = {"spread": ("spread",), "gap": ("gap",), "both": ("spread", "gap"), "always": ()}


def accepted(found: dict[str, float | None], accept: str = "spread", spread_factor: float = 1.2, gap_factor: float = 0.5) -> bool:
    if accept not in ACCEPT:
        raise ValueError(f"accept is one of {ACCEPT}")
    tests = {"spread": lambda: found["spread_ratio"] < spread_factor, "gap": lambda: found["gap_ratio"] > gap_factor}
    return all(tests[r]() for r in ACCEPTS_BY[accept])


def settled(z: np.ndarray, label: np.ndarray, centres: np.ndarray, accept: str = "spread", spread_factor: float = 1.2, gap_factor: float = 0.5) -> bool | None:
    """What ``accepted`` says of all pairs' mean distances, where bounds of them tell it, else None: then they are to be measured."""
    if accept not in ACCEPT:
        raise ValueError(f"accept is one of {ACCEPT}")
    if not ACCEPTS_BY[accept]:
        return True
    least, most, said = _least_mean(z), _most_mean(z), []
    if not least > 0:
        return None
    for r in ACCEPTS_BY[accept]:
        if r == "gap":
            gap = _gap(centres)
            said.append(True if gap > gap_factor * most else False if gap < gap_factor * least else None)
        else:
            clusters = [z[label == j] for j in np.unique(label)]
            if max(map(_most_mean, clusters)) < spread_factor * least:
                said.append(True)
            else:
                said.append(False if max(map(_least_mean, clusters)) > spread_factor * most else None)
    return False if False in said else None if None in said else True


def split_rows(z: np.ndarray, thetas: Sequence[float] = (0.5,), min_rows: int = 300, cap_divisor: int = 50, growth: str = "one_at_a_time", seed_rule: str = "first", accept: str = "spread", spread_factor: float = 1.2, gap_factor: float = 0.5, dist: str = "pairwise", limit: int | None = None, method: str = "maxmin", cap: int | None = None, most: int | None = None, marks: np.ndarray | None = None, ratios: Sequence[str] = RATIOS) -> tuple[np.ndarray, dict]:
    """Clusters of one client's standardised rows, and a report. cap bounds the centres in place of cap_divisor, most bounds them beside it. Of several thetas the accepted split with the largest gap ratio counts (then the fewer clusters).

    ratios: what the report must hold. The others are measured only where the test needs them and bounds don't settle it; which split is taken doesn't depend on them.
    """
    n, best, overall, known = len(z), None, None, {}
    report = {"n_rows": n, "n_clusters": 1, "accepted": False, "theta": None, "spread_ratio": None, "gap_ratio": None}
    if n <= min_rows:
        return np.zeros(n, int), report
    bound = cap_of(n, cap_divisor) if cap is None else cap
    for theta in thetas:
        label, centres = maxmin(z, theta, bound if most is None else min(bound, most), growth, seed_rule, marks)
        points, grown = z[centres], tuple(centres)
        if grown not in known:
            if method == "complete_linkage":
                label = complete_linkage(z, len(centres))
                points = np.stack([z[label == j].mean(axis=0) for j in range(label.max() + 1)])
            elif method != "maxmin":
                raise ValueError("method is 'maxmin' or 'complete_linkage'")
            sure = settled(z, label, points, accept, spread_factor, gap_factor) if label.max() and dist == "pairwise" and limit is None and not set(ACCEPTS_BY.get(accept, ())) <= set(ratios) else None
            needed = {*ratios, *(ACCEPTS_BY[accept] if sure is None and accept in ACCEPT else ())}
            found = figures(z, label, points, dist, limit, overall, tuple(needed)) if needed and label.max() else {"overall": overall, "spread_ratio": None, "gap_ratio": None}
            overall = found["overall"]
            # equal centres give equal clusters, which are judged once
            known[grown] = label, found, _gap(points), (accepted(found, accept, spread_factor, gap_factor) if sure is None else sure) if label.max() else False
        label, found, gap, taken = known[grown]
        if label.max() == 0:
            continue
        report |= {"spread_ratio": found["spread_ratio"], "gap_ratio": found["gap_ratio"], "theta": theta}
        if taken:
            # gap ratios are gaps by the client's one mean distance
            rank = (gap, -int(label.max()))
            if best is None or rank > best[0]:
                best = rank, label, theta, found
    if best is None:
        return np.zeros(n, int), report
    _, label, theta, found = best
    return label, report | {"n_clusters": int(label.max()) + 1, "accepted": True, "theta": theta, "spread_ratio": found["spread_ratio"], "gap_ratio": found["gap_ratio"]}


def key_mark(key: Sequence[str]) -> Column:
    """A hash of a row's key, the same wherever the row lies."""
    return F.md5(F.concat_ws("|", *(F.col(c).cast("string") for c in key)))


def _own(df: DataFrame, key: Sequence[str], options: dict) -> tuple[DataFrame, list[str]]:
    """df with the marks of its rows where the first centre goes by them, and its own columns."""
    return (df.withColumn("__mark", key_mark(key)) if options.get("seed_rule") == "hash" else df), df.columns


def _ordered(rows: pd.DataFrame, key: list[str]) -> pd.DataFrame:
    """Rows in order of their keys; numbers are ranked as they are, other keys through their levels."""
    if key and all(rows[c].dtype.kind in "iuf" for c in key):
        return rows.take(np.lexsort([rows[c].to_numpy() for c in reversed(key)]))
    return rows.sort_values(key, kind="stable")


def _split(rows: pd.DataFrame, features: list[str], options: dict) -> tuple[np.ndarray, dict]:
    marks = rows["__mark"].tolist() if "__mark" in rows else None
    return split_rows(standardized(rows[features].to_numpy(float)), marks=marks, **options)


def _by_client(df: DataFrame):
    """Rows grouped by client, in several tasks a core, so that the clients of one task don't keep the others waiting."""
    spark = df.sparkSession
    tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 8 * spark.sparkContext.defaultParallelism)
    return df.repartition(tasks, "client_id").groupBy("client_id")


def split_clients(df: DataFrame, features: Sequence[str], key: Sequence[str], **options) -> DataFrame:
    """Adds ``cluster_id`` within each client. Rows are standardised in the client and ordered by key; one client's rows are one group, so owners too large for a task are salted before (partitioners.salted) or split by ``maxmin_frame``."""
    features, key = list(features), list(key)
    source, names = _own(df, key, options)

    def one(rows: pd.DataFrame) -> pd.DataFrame:
        rows = _ordered(rows, key)
        return rows[names].assign(cluster_id=_split(rows, features, {"ratios": (), **options})[0].astype("int32"))

    schema = f"{', '.join(f'`{f.name}` {f.dataType.simpleString()}' for f in df.schema)}, cluster_id int"
    return _by_client(source).applyInPandas(one, schema).select(*names, "cluster_id")


def split_blocks(df: DataFrame, features: Sequence[str], key: Sequence[str], label: str = "label", intercept: bool = True, block_rows: int = blocks.BLOCK_ROWS, fraction: float = 1.0, seed: int = 0, **options) -> DataFrame:
    """The blocks of ``split_clients``' rows, or of their ``stratified_sample``, packed by the task that splits them: rows are dealt out and ordered once."""
    features, key = list(features), list(key)
    source = _own(df, key, options)[0]
    source = source if "subserver_id" in df.columns else source.withColumn("subserver_id", F.lit(0))
    if fraction < 1:
        source = source.withColumn("__drawn", F.unhex(_sample_mark(key, seed)))

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = pa.Table.from_batches(list(batches))
        if fraction < 1:
            # two numbers in the order of a mark's digits
            marks = np.frombuffer(b"".join(held["__drawn"].to_pylist()), ">u8").reshape(-1, 2)
            held = held.drop_columns(["__drawn"]).append_column("__high", pa.array(marks[:, 0].astype("u8"))).append_column("__low", pa.array(marks[:, 1].astype("u8")))
        rows = _ordered(held.to_pandas(), key)
        drawn = (rows["__low"].to_numpy(), rows["__high"].to_numpy()) if fraction < 1 else ()
        del held
        cluster = _split(rows, features, {"ratios": (), **options})[0]
        client, server, values = int(rows["client_id"].iloc[0]), rows["subserver_id"].to_numpy(), rows[[*features, label]].to_numpy(float)
        del rows
        for c in np.unique(cluster).tolist():
            own = np.flatnonzero(cluster == c)
            if fraction < 1:
                # the lowest marks, of equal ones the lowest key
                own = own[np.sort(np.lexsort([m[own] for m in drawn])[: max(1, math.ceil(len(own) * fraction))])]
            for number, a in enumerate(range(0, len(own), block_rows)):
                yield blocks.block(values[own[a : a + block_rows]], (client, c, int(server[own[0]])), number, intercept)

    return _by_client(source).applyInArrow(pack, blocks.SCHEMA)


def split_report(df: DataFrame, features: Sequence[str], key: Sequence[str], **options) -> DataFrame:
    """One row per client: rows, clusters, whether its split was accepted, and the ratios that decided it."""
    features, key = list(features), list(key)

    def one(rows: pd.DataFrame) -> pd.DataFrame:
        rows = _ordered(rows, key)
        return pd.DataFrame([{"client_id": rows["client_id"].iloc[0], **_split(rows, features, options)[1]}])

    return _by_client(_own(df, key, options)[0]).applyInPandas(one, "client_id int, n_rows long, n_clusters int, accepted boolean, theta double, spread_ratio double, gap_ratio double")


def standardized(x: np.ndarray) -> np.ndarray:
    s = x.std(axis=0, ddof=1) if len(x) > 1 else np.zeros(x.shape[1])
    return np.where(s > 0, (x - x.mean(axis=0)) / np.where(s > 0, s, 1), 0.0)


def maxmin_frame(df: DataFrame, features: Sequence[str], key: Sequence[str], clusters: int, theta: float | None = None, by: str = "client_id") -> DataFrame:
    """The growth one at a time as DataFrame passes, for clients too large for one task. Adds ``cluster_id`` and ``nearest``.

    Only the centres, a row per client, are written between passes: each pass is one scan of df, which meets the centres in one
    join and ends in one aggregate by client, combined before it is shuffled. clusters bounds the number of centres; theta None
    leaves out the threshold.
    """
    width, place = range(len(features)), F.struct(*key)
    point = F.struct(*(F.col(c).cast("double").alias(f"p{k}") for k, c in enumerate(features)))

    def distance(j: int):
        return F.sqrt(sum(((F.col(c) - F.col(f"__c{j}.p{k}")) * (F.col(c) - F.col(f"__c{j}.p{k}")) for k, c in enumerate(features)), F.lit(0.0))) if width else F.lit(0.0)

    def measured(centres: DataFrame, n: int) -> DataFrame:
        # a client that has stopped growing has no further centres, and no distance to them
        rows = df.join(centres, by).withColumns({f"__d{j}": distance(j) for j in range(n)})
        nearest = F.least(*(F.col(f"__d{j}") for j in range(n))) if n > 1 else F.col("__d0")
        return rows.withColumn("nearest", nearest)

    centres = materialised(df.groupBy(by).agg(F.min_by(point, place).alias("__c0")).withColumn("__gap", F.lit(None).cast("double")))
    for j in range(1, clusters):
        # the farthest row, and the lowest key among equals
        far = measured(centres, j).groupBy(by).agg(F.min_by(point, F.struct(-F.col("nearest"), place)).alias("__c"), F.max("nearest").alias("__far"))
        grown = centres.join(far, by, "left").withColumn("__gap", F.coalesce("__gap", "__far"))
        enough = F.col("__far") > (F.col("__gap") * F.lit(theta) if theta and j > 1 else F.lit(0.0))
        before = [f"__c{i}" for i in range(j)]
        # no centre follows one that was too near
        enough = enough & F.col(before[-1]).isNotNull()
        centres = materialised(grown.select(by, *before, F.when(enough, F.col("__c")).alias(f"__c{j}"), "__gap"))
    rows = measured(centres, clusters)
    label = F.coalesce(*(F.when(F.col(f"__d{j}") == F.col("nearest"), F.lit(j)) for j in range(clusters)))
    return rows.withColumn("cluster_id", label).select(*df.columns, "nearest", "cluster_id")


#: Parts into which marks are dealt before rows are ranked, so that no group is ranked in one task.
MARK_PARTS = 4096


def ranked(df: DataFrame, mark: Column, fraction: float, by: Sequence[str] = (), key: Sequence[str] = (), least: int = 1) -> DataFrame:
    """The max(least, ceil(fraction * n)) rows of each group with the lowest marks (md5 texts), with their ``rank`` from 1.

    Rows are ranked within a group's part by the first three digits of the mark; counts by part, a table of at most MARK_PARTS rows a
    group, tell where a part begins and which are needed at all.
    """
    by = list(by)
    rows = df.withColumns({"__mark": mark, "__part": F.conv(F.substring(mark, 1, 3), 16, 10).cast("int")})
    group = Window.partitionBy(*by) if by else Window.partitionBy(F.lit(0))
    parts = rows.groupBy(*by, "__part").agg(F.count("*").alias("__n"))
    parts = parts.withColumns({"__before": F.sum("__n").over(group.orderBy("__part")) - F.col("__n"), "__take": F.greatest(F.lit(least), F.ceil(F.sum("__n").over(group) * F.lit(fraction)))})
    parts = parts.where(F.col("__before") < F.col("__take")).drop("__n")
    own = [f"__by{k}" for k in range(len(by))]
    met = F.col("__part") == F.col("__own")
    for c, name in zip(by, own, strict=True):
        met = met & F.col(c).eqNullSafe(F.col(name))
    rows = rows.join(parts.select(*(F.col(c).alias(n) for c, n in zip(by, own, strict=True)), F.col("__part").alias("__own"), "__before", "__take"), met)
    rows = rows.withColumn("rank", F.col("__before") + F.row_number().over(Window.partitionBy(*by, "__part").orderBy("__mark", *key)))
    return rows.where(F.col("rank") <= F.col("__take")).select(*(c for c in df.columns if c != "rank"), "rank")


def _sample_mark(key: Sequence[str], seed: int) -> Column:
    return F.md5(F.concat_ws("|", F.lit(str(seed)), *(F.col(c).cast("string") for c in key)))


def stratified_sample(df: DataFrame, fraction: float, strata: Sequence[str] = ("client_id", "cluster_id"), key: Sequence[str] = (), seed: int = 0) -> DataFrame:
    """ceil(fraction * n) rows of each stratum, at least one, by rank of a hash of the key: repeatable, and nested in fraction."""
    if fraction >= 1:
        return df
    if fraction <= 0:
        raise ValueError("fraction is above 0")
    return ranked(df, _sample_mark(key, seed), fraction, strata, key).select(*df.columns)


def report(df: DataFrame) -> DataFrame:
    """Split statistics of rows with client_id and cluster_id: clients, split clients, mean and largest number of clusters, cluster sizes."""
    sizes = df.groupBy("client_id", "cluster_id").agg(F.count("*").alias("n"))
    by_client = sizes.groupBy("client_id").agg(F.count("*").alias("j"), F.min("n").alias("least"), F.max("n").alias("most"))
    return by_client.agg(F.count("*").alias("clients"), F.count_if(F.col("j") > 1).alias("split_clients"), F.avg("j").alias("mean_clusters"), F.max("j").alias("most_clusters"), F.min("least").alias("smallest_cluster"), F.max("most").alias("largest_cluster"), F.bool_or(F.col("j") > 1).alias("any_split"))
