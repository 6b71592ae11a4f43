"""The sum of all distances between many rows of a few columns, in less time than all pairs take.

Rows are put into cubes. Between cubes that don't touch, the distance of two rows is a polynomial of their places in their cubes:
each cube gives its moments, and sums over all pairs of cubes are correlations, which Fourier transforms yield at once. Between
rows of one cube or of cubes that touch, every distance is measured. No row or pair is left out or drawn; tests compare the sum
with all pairs.
"""

from __future__ import annotations

import math
from functools import cache, lru_cache
from itertools import product

import numpy as np

#: Powers that a polynomial has.
ORDER = 4
#: Offsets of cubes up to which the polynomial is fitted to the distances there; beyond, it is the expansion around the centres, which falls off like the offset's powers.
FITTED = 5
#: Up to so many rows all pairs are measured; columns that cubes are made for; cubes along the longest side.
LEAST, WIDEST, SIDES = 12_500, 4, (4, 6, 8, 10, 12)
#: What the highest powers may change in the sum; higher ones, which are left out, change about a tenth of that.
CHANGE = 1e-6
#: Distances that are held at once.
BUFFER = 262_144
#: Nanoseconds that a pair among all, a measured pair in cubes, a moment's entry in the transforms and a cube cost, about.
PAIR_NS, NEAR_NS, ENTRY_NS, CUBE_NS = 5.0, 2.0, 40.0, 60_000.0


@cache
def _powers(width: int) -> list[tuple[int, ...]]:
    """Exponents of up to ORDER in all, the low ones first."""
    return sorted((a for a in product(range(ORDER + 1), repeat=width) if sum(a) <= ORDER), key=lambda a: (sum(a), a))


@cache
def _pairs(width: int) -> dict[tuple[int, ...], list[tuple[int, int, float]]]:
    """By the sum of their exponents, pairs of moments (each unordered pair once) with their factors."""
    powers, out = _powers(width), {p: [] for p in _powers(width)}
    for i, a in enumerate(powers):
        for j, b in enumerate(powers[: i + 1]):
            both = tuple(x + y for x, y in zip(a, b, strict=True))
            if sum(both) <= ORDER:
                out[both].append((i, j, (-1.0) ** sum(b) * (1 if i == j else 2)))
    return out


def _shape(extent: np.ndarray, sides: int) -> tuple[float, np.ndarray]:
    """The side of a cube, and cubes along each column."""
    h = float(extent.max()) / sides
    return h, np.clip(np.ceil(extent / h - 1e-9), 1, sides).astype(int)


def _cells(z: np.ndarray, low: np.ndarray, h: float, shape: np.ndarray) -> np.ndarray:
    return np.minimum(((z - low) / h).astype(np.int64), shape - 1)


def _near(counts: np.ndarray) -> np.ndarray:
    """Rows in each cube and those that touch it."""
    for k in range(counts.ndim):
        wide, n = np.pad(counts, [(int(k == i),) * 2 for i in range(counts.ndim)]), counts.shape[k]
        counts = sum(np.take(wide, range(a, a + n), axis=k) for a in range(3))
    return counts


def _costs(z: np.ndarray) -> list[tuple[float, int]]:
    """Cubes along the longest side, and their cost, the coarse first, as far as they cost less than all pairs."""
    n, width = z.shape
    if n <= LEAST or not 1 <= width <= WIDEST:
        return []
    low, extent, out = z.min(axis=0), np.ptp(z, axis=0), []
    if not 0 < extent.max() < np.inf:
        return []
    for sides in SIDES:
        h, shape = _shape(extent, sides)
        counts = np.bincount(np.ravel_multi_index(_cells(z, low, h, shape).T, shape), minlength=math.prod(shape)).astype(float)
        near = float(counts @ _near(counts.reshape(shape)).ravel()) / 2
        cost = near * NEAR_NS + (2 * sides) ** width * len(_powers(width)) * ENTRY_NS + np.count_nonzero(counts) * CUBE_NS
        if cost < n * n / 2 * PAIR_NS:
            out.append((cost, sides))
    return out


def _slopes(power: tuple[int, ...], axes: list[np.ndarray], roots: list[np.ndarray]) -> np.ndarray:
    """A coefficient of the expansion at all offsets of cubes, times the factorials of its power; roots: the derivatives of the square root at the squared offsets."""
    terms: dict[int, np.ndarray | float] = {}
    for taken in product(*(range(g // 2 + 1) for g in power)):
        part = 1.0
        for x, g, j in zip(axes, power, taken, strict=True):
            if g:
                part = part * (math.factorial(g) / (math.factorial(j) * math.factorial(g - 2 * j)) * (2 * x) ** (g - 2 * j))
        p = sum(power) - sum(taken)
        terms[p] = terms.get(p, 0.0) + part
    return sum(roots[p] * part for p, part in terms.items())


@cache
def _fits(width: int, order: int = ORDER) -> dict[tuple[int, ...], np.ndarray]:
    """Coefficients (times factorials) by offset, from 0 and ordered, of the polynomial nearest to the distances between two evenly filled cubes."""
    nodes, weights = np.polynomial.legendre.leggauss(8)
    # differences of two places in a cube: both halves of a triangle
    places, heights = np.concatenate([(nodes - 1) / 2, (nodes + 1) / 2]), np.tile(weights / 2, 2)
    heights = heights * (1 - np.abs(places))
    if width > 2:
        # as exact with the nodes of that weight itself
        base = np.vander(places, 11, increasing=True)
        q = np.linalg.qr(base * np.sqrt(heights)[:, None])[0] / np.sqrt(heights)[:, None]
        jacobi = q[:, :10].T @ (heights[:, None] * places[:, None] * q[:, :10])
        places, vectors = np.linalg.eigh(jacobi[:8, :8])
        heights = vectors[0] ** 2 * heights.sum()
    grid = np.stack(np.meshgrid(*[places] * width, indexing="ij"), -1).reshape(-1, width)
    heavy = np.sqrt(math.prod(np.meshgrid(*[heights] * width, indexing="ij")).ravel())
    powers = [p for p in _powers(width) if sum(p) <= order]
    terms = np.stack([np.prod(grid ** np.array(p), axis=1) / math.prod(map(math.factorial, p)) for p in powers], 1)
    solver = np.linalg.pinv(terms * heavy[:, None]) * heavy
    out = {}
    for offset in product(range(FITTED + 1), repeat=width):
        if max(offset) > 1 and tuple(sorted(offset)) == offset:
            out[offset] = solver @ np.sqrt(((grid + np.array(offset)) ** 2).sum(axis=1))
    return out


@lru_cache(4)
def _kernels(width: int, sides: int) -> list[tuple[np.ndarray, np.ndarray]]:
    """For each power the transform of its coefficients at all offsets of cubes that don't touch (real, or imaginary for odd powers), and of what the highest powers change in the fitted ones."""
    padded = (2 * sides,) * width
    line = np.r_[0:sides, -sides:0].astype(float)
    axes = [line.reshape([-1 if i == k else 1 for i in range(width)]) for k in range(width)]
    far = np.broadcast_to(sum((np.abs(x) > 1).astype(int) for x in axes), padded) > 0
    apart = far & (np.broadcast_to(sum((np.abs(x) >= sides).astype(int) for x in axes), padded) == 0)
    squared = np.where(apart, sum(x * x for x in axes), 1.0)
    roots, factor = [], 1.0
    for p in range(ORDER + 1):
        roots.append(np.where(apart, factor * squared ** (0.5 - p), 0.0))
        factor *= 0.5 - p
    close = [o for o in product(range(-min(FITTED, sides - 1), min(FITTED, sides - 1) + 1), repeat=width) if max(map(abs, o)) > 1]
    places = {p: k for k, p in enumerate(_powers(width))}
    signs, turned = np.sign(close), np.argsort(np.abs(close), axis=1, kind="stable")
    # lower fits have no coefficient of the highest powers
    fits = [{o: np.pad(c, (0, len(places) - len(c))) for o, c in _fits(width, n).items()} for n in (ORDER, ORDER - 1)]
    own = [np.array([f[tuple(sorted(map(abs, o)))] for o in close]) for f in fits]
    at, lookup = tuple(np.array(close).T), np.zeros((ORDER + 1,) * width, int)
    for p, k in places.items():
        lookup[p] = k
    # real transforms hold one of two equal halves
    both = np.full(sides + 1, 2.0)
    both[[0, -1]] = 1.0
    out = []
    for power in _powers(width):
        # the fit of the ordered offset, with exponents ordered alike and signs of odd ones
        column, turn = lookup[tuple(np.array(power)[turned].T)], np.prod(np.where(signs < 0, (-1.0) ** np.array(power), 1.0), axis=1)
        high, low = (f[np.arange(len(close)), column] * turn for f in own)
        k = np.broadcast_to(_slopes(power, axes, roots), padded).copy()
        change = np.zeros(padded)
        k[at], change[at] = high, high - low
        out.append(tuple(np.ascontiguousarray((t.imag if sum(power) % 2 else t.real) * both / math.prod(padded)) for t in (np.fft.rfftn(k), np.fft.rfftn(change))))
    return out


def _apart(moments: np.ndarray, sides: int) -> tuple[float, float]:
    """Sum over all ordered pairs of cubes that don't touch, in sides of a cube, and how much the highest powers change in it where they are fitted."""
    width = moments.ndim - 1
    told = [np.fft.rfftn(m, (2 * sides,) * width, axes=tuple(range(width))) for m in moments]
    turned = [t.conj() for t in told]
    kernels, total, part = dict(zip(_powers(width), _kernels(width, sides), strict=True)), np.zeros(2), np.empty_like(told[0])
    for power, pairs in _pairs(width).items():
        spectrum = np.zeros_like(part)
        for i, j, f in pairs:
            np.multiply(told[i], turned[j], out=part)
            part *= f
            spectrum += part
        own = np.ascontiguousarray(spectrum.imag if sum(power) % 2 else spectrum.real)
        total += [np.vdot(k, own) for k in kernels[power]]
    return float(total[0]), abs(float(total[1]))


def _touching(z: np.ndarray, times: np.ndarray, cell: np.ndarray, shape: np.ndarray, kind: type) -> float:
    """Sum over all unordered pairs of rows in one cube or in cubes that touch; z: columns of the rows in order of their cubes; kind: the numbers that distances are taken in."""
    width = len(shape)
    begin = np.searchsorted(cell, np.arange(math.prod(shape) + 1)).tolist()
    steps = [math.prod(shape[k + 1 :].tolist()) for k in range(width)]
    ahead = [d for d in product((-1, 0, 1), repeat=width - 1) if d > (0,) * (width - 1)]
    total = 0.0
    for own in np.unique(cell).tolist():
        at = [own // s % n for s, n in zip(steps, shape.tolist(), strict=True)]
        a, b = begin[own], begin[own + 1]
        # cubes that follow along the last column lie side by side
        low, high = max(at[-1] - 1, 0), min(at[-1] + 1, int(shape[-1]) - 1)
        spans = [(a, begin[own + high - at[-1] + 1])]
        for d in ahead:
            first = [x + y for x, y in zip(at, d, strict=False)]
            if all(0 <= x < n for x, n in zip(first, shape.tolist(), strict=False)):
                base = sum(x * s for x, s in zip(first, steps, strict=False))
                spans.append((begin[base + low], begin[base + high + 1]))
        spans = [s for s in spans if s[1] > s[0]]
        # around the cube's centre, so that little is rounded
        right = np.empty((width + 2, sum(j - i for i, j in spans)), kind)
        np.subtract(np.concatenate([z[:, i:j] for i, j in spans], axis=1), np.array(at)[:, None] + 0.5, out=right[:width], casting="same_kind")
        np.einsum("ij,ij->j", right[:width], right[:width], out=right[width])
        right[width + 1] = 1
        weighed = np.concatenate([times[i:j] for i, j in spans]).astype(kind)
        # pairs within the cube come up twice, and a row's with itself not at all
        weighed[: b - a] /= 2
        left = np.vstack([-2 * right[:width, : b - a], np.ones((1, b - a), kind), right[width : width + 1, : b - a]]).T
        height = max(1, BUFFER // right.shape[1])
        for i in range(0, b - a, height):
            d = left[i : i + height] @ right
            # what rounds below 0; a maximum costs five times as much
            np.sqrt(np.abs(d, out=d), out=d)
            d[np.arange(len(d)), np.arange(i, i + len(d))] = 0
            total += float(times[a + i : a + i + len(d)] @ (d @ weighed))
    return total


def _total(z: np.ndarray, times: np.ndarray, sides: int) -> float | None:
    """The sum by cubes, ``sides`` along the longest column, or None if the highest powers change too much in it."""
    width, low = z.shape[1], z.min(axis=0)
    h, shape = _shape(np.ptp(z, axis=0), sides)
    places = _cells(z, low, h, shape)
    cell = np.ravel_multi_index(places.T, shape)
    order = np.argsort(cell, kind="stable")
    # places in sides of a cube
    z, places, times, cell = np.ascontiguousarray(((z[order] - low) / h).T), places[order].T, times[order], cell[order]
    inner = z - places - 0.5
    held, first = np.unique(cell, return_index=True)
    moments, powers = np.zeros((len(_powers(width)), math.prod(shape))), {}
    for k, power in enumerate(_powers(width)):
        # from the power below along the last column that has one
        c = max((i for i, g in enumerate(power) if g), default=None)
        powers[power] = times if c is None else powers[power[:c] + (power[c] - 1,) + power[c + 1 :]] * inner[c] / power[c]
        moments[k, held] = np.add.reduceat(powers[power], first)
    counts, all_pairs = moments[0].reshape(shape), times.sum() ** 2
    apart, change = _apart(moments.reshape(-1, *shape), sides)
    # the mean distance of rows is at least that from their centre
    spread = float(np.average(np.sqrt(((z - np.average(z, axis=1, weights=times)[:, None]) ** 2).sum(axis=0)), weights=times))
    if change > CHANGE * spread * all_pairs:
        return None
    # single precision rounds a distance by 5e-4 of a cube at most, and by far less between rows that aren't almost equal
    kind = np.float32 if float((counts * _near(counts)).sum()) < 1e-2 * spread * all_pairs else np.float64
    return h * (apart / 2 + _touching(z, times, cell, shape, kind))


def total(z: np.ndarray, times: np.ndarray) -> float | None:
    """The sum of the distances of all unordered pairs of rows, each row lying there ``times``; None where all pairs are to be measured."""
    costs = _costs(z)
    cheapest = min(costs, default=(0.0, 0))[1]
    for _, sides in costs:
        if sides >= cheapest and (found := _total(z, times, sides)) is not None:
            return found
    return None
