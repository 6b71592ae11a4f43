"""Packing of token sequences into windows of a fixed capacity by Karmarkar-Karp differencing.

Every text becomes its token ids and one end id. Whole windows are cut off first; the
rest is cut into pieces of at most ``piece`` ids. Pieces are gathered into groups that
nearly fill ``GROUP`` windows, and each group is divided by multiway differencing: every
piece begins as a partial partition, and the two partial partitions with the largest
imbalance are merged again and again, the fullest window of one with the emptiest of the
other. The windows come out nearly equal; if one exceeds the capacity, the group is
divided anew with one window more. Groups don't cross tasks, so there is no shuffle, and
a task's last group alone may be smaller.

Defined results: a null or empty text is its end id alone; rows are packed one by one,
whatever their ids; an empty table gives an empty result; only id and text are read.
Memory is bounded by a batch, one group, the longest text and a cache of CACHE words.
"""

from __future__ import annotations

import functools
import heapq
import os
import re
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textnp

CAPACITY, END_ID, PIECE, GROUP = 2048, 1, 384, 64
#: Ids of each window that a full group leaves open, so that slightly unequal windows fit.
SLACK = 8
#: Pieces in each of two generations of a worker's cache.
CACHE = 400_000

#: Characters at which str.split cuts although they aren't white space in Unicode.
_NOT_SPACE = re.compile("[\x1c-\x1f]")
#: Lower-cased texts of ASCII and Latin-1 letters only, and how the tokenizer's own pattern cuts them.
_PLAIN = re.compile("[\t-\r -~\xdf-\xf6\xf8-\xff]*")
_PIECES = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[a-z\xdf-\xf6\xf8-\xff]+|[0-9]|[^\sa-z0-9\xdf-\xf6\xf8-\xff]+")


class WordTokenizer:
    """Ids of whole texts from a tokenizer that lower-cases, drops white space and never joins pieces across it, by a cache.

    Texts of plain letters are cut into the tokenizer's own pieces, others at white space; texts with special tokens or control characters are
    encoded whole.
    """

    def __init__(self, path: str) -> None:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.inner, self.young, self.old = Tokenizer.from_file(path), {}, {}
        self.specials = [t.content for t in self.inner.get_added_tokens_decoder().values()]

    def _ids(self, texts: list[str]) -> list[bytes]:
        return [array("I", e.ids).tobytes() for e in self.inner.encode_batch(texts, add_special_tokens=False)]

    def _parts(self, text: str) -> list[str] | None:
        lower = text.lower()
        if any(s in text for s in self.specials):
            return None
        if _PLAIN.fullmatch(lower):
            return _PIECES.findall(lower)
        return None if _NOT_SPACE.search(text) else text.split()

    def __call__(self, texts: list[str]) -> list[np.ndarray]:
        parts = [self._parts(t) for t in texts]
        found = [p and list(map(self.young.get, p)) for p in parts]
        gaps = [(p, ids) for p, ids in zip(parts, found, strict=True) if p and None in ids]
        missing = {w for p, ids in gaps for w, x in zip(p, ids, strict=True) if x is None}
        if missing:
            fresh = {w: x for w in missing if (x := self.old.get(w)) is not None}
            unknown = list(missing.difference(fresh))
            fresh.update(zip(unknown, self._ids(unknown), strict=True))
            for p, ids in gaps:
                ids[:] = [fresh[w] if x is None else x for w, x in zip(p, ids, strict=True)]
            self.young.update((w, x) for w, x in fresh.items() if len(w) <= 64)
            if len(self.young) >= CACHE:
                self.old, self.young = self.young, {}
        whole = iter(self._ids([t for t, p in zip(texts, parts, strict=True) if p is None]))
        return [np.frombuffer(next(whole) if p is None else b"".join(ids), np.uint32) for p, ids in zip(parts, found, strict=True)]


@functools.lru_cache(maxsize=2)
def word_tokenizer(path: str) -> WordTokenizer:
    return WordTokenizer(path)


def difference(sizes: list[int], k: int) -> list[list[int]]:
    """Items by window, for k windows, by the largest differencing method."""
    if k == 1 or not sizes:
        return [list(range(len(sizes)))] + [[] for _ in range(k - 1)]
    # a partial partition: the windows that hold anything, fullest first; all others are empty
    heap = [(-s, i, [(s, [i])]) for i, s in enumerate(sizes)]
    heapq.heapify(heap)
    n = len(sizes)
    while len(heap) > 1:
        _, _, a = heapq.heappop(heap)
        _, _, b = heapq.heappop(heap)
        over = len(a) + len(b) - k
        if over > 0:
            # the emptiest windows of a take the fullest of b
            keep = len(a) - over
            merged = a[:keep] + [(x + y, p + q) for (x, p), (y, q) in zip(a[keep:], b[len(b) - over :][::-1], strict=True)] + b[: len(b) - over]
        else:
            merged = a + b
        merged.sort(key=lambda w: -w[0])
        low = merged[-1][0] if len(merged) == k else 0
        n += 1
        heapq.heappush(heap, (low - merged[0][0], n, merged))
    windows = [p for _, p in heap[0][2]]
    return windows + [[] for _ in range(k - len(windows))]


def pack_group(sizes: list[int], capacity: int = CAPACITY) -> list[list[int]]:
    """Items by window; as few windows as the total asks for, and one more each time the capacity is exceeded."""
    k = max(1, -(-sum(sizes) // capacity))
    while True:
        windows = difference(sizes, k)
        if all(sum(sizes[i] for i in w) <= capacity for w in windows):
            return [w for w in windows if w]
        k += 1


class Packer:
    """Takes texts' ids one after another and gives back finished pieces."""

    def __init__(self, first_id: int, capacity: int, piece: int, group: int) -> None:
        self.next_id, self.capacity, self.piece, self.group = first_id, capacity, piece, group
        self.open: list[tuple] = []
        self.total, self.full = 0, group * (capacity - SLACK)

    def add(self, doc: object, ids: np.ndarray) -> Iterator[tuple]:
        n, start = len(ids), 0
        while n - start >= self.capacity:
            yield doc, start, n, self.next_id, 0, ids[start : start + self.capacity]
            self.next_id, start = self.next_id + 1, start + self.capacity
        while start < n:
            # equal parts, cut where the group is full
            take = min(-(-(n - start) // -(-(n - start) // self.piece)), self.full - self.total)
            self.open.append((doc, start, n, ids[start : start + take]))
            start, self.total = start + take, self.total + take
            if self.total == self.full:
                yield from self.close()

    def close(self) -> Iterator[tuple]:
        for window in pack_group([len(p[3]) for p in self.open], self.capacity):
            offset = 0
            for doc, start, n, ids in (self.open[i] for i in window):
                yield doc, start, n, self.next_id, offset, ids
                offset += len(ids)
            self.next_id += 1
        self.open, self.total = [], 0


def pack(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", capacity: int = CAPACITY, piece: int = PIECE, group: int = GROUP) -> DataFrame:
    """One row per piece: the id, ``start``, ``length``, ``doc_tokens``, ``sequence_id``, ``offset`` and ``ids`` as little-endian unsigned 32-bit integers (binary).

    sequence_id is unique over all tasks: the task's partition, then a number.
    """
    source = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    names = [id_col, "start", "length", "doc_tokens", "sequence_id", "offset", "ids"]
    kind = source.schema["id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokenize, end = word_tokenizer(path), np.array([END_ID], np.uint32)
        packer = Packer(TaskContext.get().partitionId() << 32, capacity, piece, group)
        id_type = None

        def rows(done: list[tuple]) -> Iterator[pa.RecordBatch]:
            for i in range(0, len(done), 5000):
                doc, start, n, seq, offset, ids = zip(*done[i : i + 5000], strict=True)
                longs = [pa.array(x, pa.int64()) for x in (start, [len(x) for x in ids], n, seq, offset)]
                yield pa.RecordBatch.from_arrays([pa.array(doc, id_type), *longs, pa.array([x.tobytes() for x in ids], pa.binary())], names)

        for batch in batches:
            id_type = batch.column(0).type
            for part in (batch.slice(i, 500) for i in range(0, len(batch), 500)):
                done: list[tuple] = []
                for doc, ids in zip(part.column(0).to_pylist(), tokenize([x or "" for x in part.column(1).to_pylist()]), strict=True):
                    done += packer.add(doc, np.concatenate([ids, end]))
                yield from rows(done)
        if packer.open:
            yield from rows(list(packer.close()))
        textnp.release()

    return source.mapInArrow(run, f"`{id_col}` {kind}, start long, length long, doc_tokens long, sequence_id long, offset long, ids binary")
