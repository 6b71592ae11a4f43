"""Local training: losses, and descent within one owner's cluster, as numpy kernels and as expressions."""

from __future__ import annotations

from collections.abc import Iterable, Sequence

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import vec

CLIP = vec.CLIP


def _logistic(z: np.ndarray, y: np.ndarray) -> np.ndarray:
    # a plain minimum and maximum cost less than clip on the short vectors of a cluster; one buffer holds every step
    out = np.negative(z)
    np.minimum(np.maximum(out, -CLIP, out=out), CLIP, out=out)
    np.exp(out, out=out)
    out += 1
    np.divide(1, out, out=out)
    out -= y
    return out


def _squared(z: np.ndarray, y: np.ndarray) -> np.ndarray:
    return z - y


def _hinge(z: np.ndarray, y: np.ndarray) -> np.ndarray:
    sign = 2 * y - 1
    return np.where(sign * z < 1, -sign, 0.0)


#: The derivative of a sample's loss by its linear score; any finite sum of such losses can be trained.
SLOPES = {"logistic": _logistic, "squared": _squared, "hinge": _hinge}


def gradient(x: np.ndarray, y: np.ndarray, w: np.ndarray, loss: str = "logistic") -> np.ndarray:
    return SLOPES[loss](x @ w, y) @ x / len(y)


def _shuffled(n: int, seed: int, epoch: int) -> np.ndarray:
    return np.random.default_rng((seed, epoch)).permutation(n)


def sgd(x: np.ndarray, y: np.ndarray, w: Sequence[float], epochs: int, lr: float, batch: int | None = None, seed: int = 0, loss: str = "logistic", shuffle: bool = True) -> np.ndarray:
    """Epochs of descent over one cluster's rows, from w: whole, or in batches of a size (the last may be short), shuffled or as the rows lie."""
    w = np.array(w, float)
    for epoch in range(epochs):
        if batch is None or batch >= len(y):
            w -= lr * gradient(x, y, w, loss)
            continue
        order = _shuffled(len(y), seed, epoch) if shuffle else np.arange(len(y))
        for i in range(0, len(y), batch):
            rows = order[i : i + batch]
            w -= lr * gradient(x[rows], y[rows], w, loss)
    return w


def sgd_stream(blocks: Sequence[tuple[np.ndarray, np.ndarray]] | Iterable, w: Sequence[float], epochs: int, lr: float, batch: int | None = None, seed: int = 0, loss: str = "logistic", shuffle: bool = True) -> np.ndarray:
    """The same over a cluster's blocks without joining them: whole epochs add up the blocks' gradients; batches don't cross blocks."""
    w, blocks = np.array(w, float), list(blocks)
    if len(blocks) == 1:
        return sgd(*blocks[0], w, epochs, lr, batch, seed, loss, shuffle)
    n = sum(len(y) for _, y in blocks)
    for epoch in range(epochs):
        if batch is None:
            w -= lr * sum(gradient(x, y, w, loss) * (len(y) / n) for x, y in blocks)
            continue
        for k, (x, y) in enumerate(blocks):
            order = _shuffled(len(y), seed + 7919 * k, epoch) if shuffle else np.arange(len(y))
            for i in range(0, len(y), batch):
                rows = order[i : i + batch]
                w -= lr * gradient(x[rows], y[rows], w, loss)
    return w


#: Bytes of a stack of clusters, which stays in a core's cache over the epochs.
STACK_BYTES = 1 << 19


def stacks(clusters: Sequence[Sequence[tuple[np.ndarray, np.ndarray]]]) -> list[tuple[np.ndarray, ...]]:
    """Clusters of about one size stacked up: their numbers, rows padded to the largest, labels, each row's share of its cluster (0 for padding), sums of rows times half less label, and the largest row's length."""
    whole = [blocks[0] if len(blocks) == 1 else tuple(np.concatenate([b[k] for b in blocks]) for k in (0, 1)) for blocks in clusters]
    sizes = np.array([len(y) for _, y in whole])
    groups, width = [], whole[0][0].shape[1]
    for k in np.argsort(sizes, kind="stable"):
        own = groups[-1] if groups else None
        if own is None or sizes[k] > 1.25 * sizes[own[0]] or (len(own) + 1) * sizes[k] * width * 8 > STACK_BYTES:
            groups.append([])
        groups[-1].append(int(k))
    out = []
    for own in groups:
        if len(own) == 1:
            x, y = whole[own[0]]
            x, y, share = x[None], y[None], np.full((1, len(y)), 1 / len(y))
        else:
            x, y, share = np.zeros((len(own), sizes[own].max(), width)), np.zeros((len(own), sizes[own].max())), np.zeros((len(own), sizes[own].max()))
            for i, k in enumerate(own):
                x[i, : sizes[k]], y[i, : sizes[k]], share[i, : sizes[k]] = *whole[k], 1 / sizes[k]
        out.append((np.array(own), x, y, share, ((0.5 - y)[:, None] @ x)[:, 0], float(np.sqrt(np.einsum("cnd,cnd->cn", x, x).max(initial=0)))))
    return out


#: Scores that are held at once while a stack's epochs run.
STACK_SCORES = 32_768


def _logistic_slopes(x: np.ndarray, now: np.ndarray, labels: np.ndarray, reach: float, step: int) -> np.ndarray:
    """Sums of the logistic loss's slopes over the rows of each cluster, for each table: a probability is half of one more than the hyperbolic tangent of half its score. labels: the sums of rows times half less label."""
    half, total = now / 2, 0.0
    # no score passes the longest row by the longest vector
    clipped = not reach * float(np.sqrt((now * now).sum(axis=1)).max()) < CLIP
    for a in range(0, x.shape[1], step):
        rows = x[:, a : a + step]
        at = rows @ half
        if clipped:
            np.minimum(np.maximum(at, -CLIP / 2, out=at), CLIP / 2, out=at)
        total = total + rows.transpose(0, 2, 1) @ np.tanh(at, out=at)
    return total / 2 + labels[:, :, None]


def sgd_stacked(held: list[tuple[np.ndarray, ...]], w: np.ndarray, epochs: int, lr: float, loss: str = "logistic") -> np.ndarray:
    """Whole epochs of descent in all stacked clusters, each from its own row of w; w may hold several such tables, which share every product."""
    out = np.array(w, float)
    tables = out if out.ndim == 3 else out[None]
    for own, x, y, share, labels, reach in held:
        # (clusters, width, tables)
        now, each = np.ascontiguousarray(tables[:, own].transpose(1, 2, 0)), share[:, :1, None]
        step = max(64, STACK_SCORES // (len(own) * len(tables)))
        for _ in range(epochs):
            # rows of padding are 0 and add nothing to a slope
            if loss == "logistic":
                slopes = _logistic_slopes(x, now, labels, reach, step)
            else:
                slopes = sum(x[:, a : a + step].transpose(0, 2, 1) @ SLOPES[loss](x[:, a : a + step] @ now, y[:, a : a + step, None]) for a in range(0, x.shape[1], step))
            now = now - lr * each * slopes
        tables[:, own] = now.transpose(2, 0, 1)
    return out


def gradients(df: DataFrame, features: Sequence[str], w: Sequence[float], by: Sequence[str], label: str = "label", intercept: bool = True) -> DataFrame:
    """One whole-set logistic gradient at w for each group: one aggregate of the engine, unrolled over features (``g0``, ``g1``, ...)."""
    error = vec.sigmoid(vec.margin(features, w, intercept)) - F.col(label)
    columns = ([F.lit(1.0)] if intercept else []) + [F.col(c) for c in features]
    return df.withColumn("__e", error).groupBy(*by).agg(F.count("*").alias("n_rows"), *(F.avg(F.col("__e") * c).alias(f"g{k}") for k, c in enumerate(columns)))


def hof_step(rows: Column, w: Column, lr: float) -> Column:
    """One whole-set logistic step over an array of (x: array<double>, y: double), in higher-order functions; checks the kernels' parity on small clusters."""
    error = lambda r: vec.sigmoid(vec.dot(r["x"], w)) - r["y"]
    zero = F.transform(w, lambda _: F.lit(0.0))
    total = F.aggregate(rows, zero, lambda s, r: F.zip_with(s, r["x"], lambda a, x: a + error(r) * x))
    return F.zip_with(w, total, lambda a, g: a - F.lit(lr) * g / F.size(rows))


def hof_train(rows: Column, w: Sequence[float], epochs: int, lr: float) -> Column:
    return F.aggregate(F.sequence(F.lit(1), F.lit(epochs)), vec.literal(w), lambda now, _: hof_step(rows, now, lr))
