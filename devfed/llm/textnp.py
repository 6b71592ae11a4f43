"""Words, lines and rolling hashes of a whole batch of texts in numpy.

All functions work on one byte buffer that holds many texts one after another and
on the offsets of the texts in it, so that their cost does not depend on the
number of texts. Hashes are polynomials modulo 2**64 with an odd base, taken from
prefix sums: the part between two positions is a difference of two prefixes times
the inverse power of the base. A final mix spreads the bits.
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa

#: Bytes of text handled at once; a longer text is handled alone.
SLICE_BYTES = 4 << 20
#: Bytes over which one prefix sum reaches.
SPAN_BYTES = 1 << 18

_U = np.uint64
#: Of the C library, where it has it.
_TRIM = getattr(ctypes.CDLL(None), "malloc_trim", None)
_BYTE_BASE, _WORD_BASE = 0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit values whose output bits all depend on all input bits."""
    x = x ^ (x >> _U(30))
    x = x * _U(0xBF58476D1CE4E5B9)
    x = x ^ (x >> _U(27))
    x = x * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


_VALUES = mix(np.arange(1, 257, dtype=np.uint64) * _U(0xD6E8FEB86659FD93))
_LOWER = _VALUES.copy()
_LOWER[65:91] = _VALUES[97:123]
_SPACE = np.zeros(256, bool)
_SPACE[[32, 9, 10, 11, 12, 13]] = True


def release() -> None:
    """Gives memory that is free back to the system, which a worker would keep between tasks."""
    pa.default_memory_pool().release_unused()
    if _TRIM is not None:
        _TRIM(0)


class _Powers:
    """Powers of an odd base and of its inverse, grown on demand."""

    def __init__(self, base: int) -> None:
        self.base, self.inverse, self.n = base, pow(base, -1, 1 << 64), 0

    def get(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if n > self.n or not self.n:
            self.n = max(1 << 16, 1 << (n - 1).bit_length())
            steps = np.ones((2, self.n + 1), np.uint64)
            steps[:, 1:] = np.array([[self.base], [self.inverse]], np.uint64)
            self.up, self.down = np.cumprod(steps, axis=1)
        return self.up[: n + 1], self.down[: n + 1]


_OF_BYTES, _OF_WORDS = _Powers(_BYTE_BASE), _Powers(_WORD_BASE)


def _prefix(values: np.ndarray) -> np.ndarray:
    out = np.zeros(len(values) + 1, values.dtype)
    np.cumsum(values, out=out[1:])
    return out


class Texts:
    """Texts ``i`` of a buffer: bytes ``offsets[i]`` to ``offsets[i + 1]``."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray, fold_case: bool = False) -> None:
        self.data, self.offsets, self.fold_case = data, offsets, fold_case
        self.n = len(offsets) - 1
        self.in_word = ~_SPACE[data]
        begin, end = self.in_word.copy(), self.in_word.copy()
        begin[1:] &= ~self.in_word[:-1]
        end[:-1] &= ~self.in_word[1:]
        if len(data):
            edges = offsets[(offsets > 0) & (offsets < len(data))]
            begin[edges] = self.in_word[edges]
            end[edges - 1] = self.in_word[edges - 1]
        self.starts, self.ends = np.flatnonzero(begin), np.flatnonzero(end) + 1
        #: Words of text i: word_offsets[i] to word_offsets[i + 1].
        self.word_offsets = np.searchsorted(self.starts, offsets)
        self.n_words = np.diff(self.word_offsets)
        self.doc = np.repeat(np.arange(self.n), self.n_words)

    def per_text(self, flags: np.ndarray) -> np.ndarray:
        """Sums of a value per byte over each text."""
        return np.diff(_prefix(flags.astype(np.int64))[self.offsets])

    def span_hashes(self, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """64-bit hashes of the bytes between positions (starts ascending). Prefix sums reach over SPAN_BYTES, or one longer span, at a time."""
        out, values, i = np.empty(len(starts), np.uint64), _LOWER if self.fold_case else _VALUES, 0
        while i < len(starts):
            j = max(i + 1, int(np.searchsorted(starts, starts[i] + SPAN_BYTES)))
            low, high = starts[i], ends[i:j].max()
            up, down = _OF_BYTES.get(int(high - low))
            sums = _prefix(values[self.data[low:high]] * up[: high - low])
            a, b = starts[i:j] - low, ends[i:j] - low
            out[i:j] = (sums[b] - sums[a]) * down[a] + (b - a).astype(np.uint64) * _U(0xA24BAED4963EE407)
            i = j
        return mix(out)

    def words(self) -> np.ndarray:
        return self.span_hashes(self.starts, self.ends)

    def lines(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        r"""Starts, ends and text of the \n-separated lines; an empty text has one."""
        breaks = np.flatnonzero(self.data == 10)
        doc = np.concatenate([np.arange(self.n), np.searchsorted(self.offsets, breaks, "right") - 1])
        starts, ends = np.concatenate([self.offsets[:-1], breaks + 1]), np.concatenate([breaks, self.offsets[1:]])
        order = np.lexsort((starts, doc))
        # the ends of a text's lines are its breaks and then its own end
        end_doc = np.concatenate([doc[self.n :], np.arange(self.n)])
        return starts[order], ends[np.lexsort((ends, end_doc))], doc[order]


class Windows:
    """Rabin-Karp hashes of windows of words; one prefix sum serves all lengths."""

    def __init__(self, words: np.ndarray, doc: np.ndarray) -> None:
        up, self.down = _OF_WORDS.get(len(words))
        self.sums, self.doc = _prefix(words * up[:-1]), doc

    def of(self, n: int, among: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """First words and hashes of the windows of n words that lie in one text; among: the first words to look at."""
        last = len(self.doc) - n
        at = np.arange(max(last + 1, 0)) if among is None else among[among <= last]
        at = at[self.doc[at] == self.doc[at + n - 1]]
        return at, mix((self.sums[at + n] - self.sums[at]) * self.down[at] + _U(n))


def keyed(hashes: np.ndarray, doc: np.ndarray) -> np.ndarray:
    """Hashes made different in different texts."""
    return mix(hashes ^ (doc.astype(np.uint64) + _U(1)) * _U(0x9FB21C651E98DF25))


def buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets of a string column; a null is an empty text."""
    column = column.cast(pa.large_binary())
    if column.null_count:
        column = column.fill_null(b"")
    offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + len(column) + 1]
    data = column.buffers()[2]
    data = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return data, offsets


def slices(column: pa.Array, fold_case: bool = False, limit: int | None = None) -> Iterator[tuple[int, int, Texts]]:
    """Row ranges of a batch with their texts, of about SLICE_BYTES each."""
    data, offsets = buffers(column)
    i, limit = 0, limit or SLICE_BYTES
    while i < len(column):
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + limit, "right")) - 1)
        yield i, j, Texts(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i], fold_case)
        i = j
