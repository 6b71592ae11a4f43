r"""Removal of token windows that occur in an earlier document.

Every window of WINDOW consecutive words gets a Rabin-Karp hash (64 bits). A window is
removed where its word sequence also starts in a document with a smaller id; the words
to remove are the union of such windows, which merge into maximal intervals.

How the hashes are counted: texts are dealt into chunks by a hash of id, text and partition (so that
a row that occurs often is no hot chunk), of about CHUNK_BYTES each. A chunk reduces its windows to distinct hashes, so a passage
that every document holds counts once for each chunk and no key is hot. Two rounds
follow, each from chunks to hash ranges ("buckets") and back:

1. a chunk sends the low 32 bits of its hashes to the bucket of their high bits, and
   gets back one bit each: seen in another chunk or not. As a bucket holds a bounded
   number of hashes, 32 bits within it leave few false hits, and false hits only cost
   work in the next round;
2. for the hashes seen elsewhere it sends the whole hash and its own smallest id, and
   gets back one bit each: whether another chunk has a smaller id.

Windows that a chunk repeats within itself need no message. Spark counts blobs of
hashes, not rows, and reuses one exchange of the texts in all three passes.

Words are ``[^\x20\x09-\x0D]+``. Defined results: a null or empty text, or one with
fewer than WINDOW words, loses nothing; ids are whole numbers (others raise a TypeError, as they
have no order in 64 bits); a null id counts as larger than all others; rows
with equal ids remove nothing from each other; an empty table gives an empty result;
other columns, whatever their names, pass through ``remove`` and aren't read by
``measure``. Equality is that of the 64-bit hashes: n distinct windows have about n**2 / 2**65 equal pairs by
chance, none to be expected for a terabyte of text, some 10**5 windows in 10**13 for a hundred; a chance pair removes 13 words.
Memory is bounded by a chunk, a bucket and the longest text.
"""

from __future__ import annotations

import math
from collections.abc import Callable

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import textnp

WINDOW = 13
#: Text in a chunk, and text whose windows make a bucket (about), in bytes, for tables of up to GROW_BYTES. Beyond, both grow with the
#: square root of the table's bytes, so that the blobs, one from each chunk to each bucket at most, grow as the table does.
CHUNK_BYTES, BUCKET_BYTES, GROW_BYTES = 4 << 20, 16 << 20, 256 << 30

_LARGEST = np.iinfo(np.int64).max


class _Chunk:
    """The windows of a chunk's texts, by distinct hash in ascending order."""

    def __init__(self, ids: pa.ChunkedArray, text: pa.ChunkedArray, window: int) -> None:
        ids = ids.cast(pa.int64())
        self.ids = np.where(ids.is_null().to_numpy(), _LARGEST, ids.fill_null(0).to_numpy())
        column = text.combine_chunks()
        column = column if isinstance(column, pa.Array) else pa.concat_arrays(column.chunks)
        data, offsets = textnp.buffers(column)
        self.texts = textnp.Texts(data[offsets[0] : offsets[-1]], offsets - offsets[0])
        self.at, hashes = textnp.Windows(self.texts.words(), self.texts.doc).of(window)
        order = np.argsort(hashes)
        ranked = hashes[order]
        new = np.ones(len(ranked), bool)
        new[1:] = ranked[1:] != ranked[:-1]
        self.hashes = ranked[new]
        #: The place of each window's hash among the distinct ones.
        self.place = np.empty(len(hashes), np.int64)
        self.place[order] = np.cumsum(new) - 1
        self.id_of = self.ids[self.texts.doc[self.at]]
        first = np.flatnonzero(new)
        self.least = np.minimum.reduceat(self.id_of[order], first) if len(first) else np.zeros(0, np.int64)


def _bucket(hashes: np.ndarray, buckets: int) -> np.ndarray:
    return ((hashes >> np.uint64(32)) * np.uint64(buckets) >> np.uint64(32)).astype(np.int64)


def _blobs(chunk: int, hashes: np.ndarray, buckets: int, pack: Callable[[int, int], bytes]) -> pa.Table:
    """A row for each bucket that any of the (ascending) hashes falls in."""
    edges = np.searchsorted(_bucket(hashes, buckets), np.arange(buckets + 1))
    used = np.flatnonzero(np.diff(edges))
    data = [pack(edges[b], edges[b + 1]) for b in used]
    return pa.table({"chunk": pa.array(np.full(len(used), chunk, np.int32)), "bucket": pa.array(used.astype(np.int32)), "data": pa.array(data, pa.binary())})


def _replies(table: pa.Table, hashes: np.ndarray, buckets: int) -> np.ndarray:
    """The bits that a chunk got back for its hashes, in their order; False where a bucket has sent none."""
    edges = np.searchsorted(_bucket(hashes, buckets), np.arange(buckets + 1))
    out = np.zeros(len(hashes), bool)
    for bucket, bits in zip(table["bucket"].to_pylist(), table["bits"].to_pylist(), strict=True):
        a, b = edges[bucket], edges[bucket + 1]
        out[a:b] = np.unpackbits(np.frombuffer(bits, np.uint8), count=b - a).astype(bool)
    return out


def _low(hashes: np.ndarray, buckets: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct low halves of the hashes by bucket, bucket edges in them, and the place of each hash's own."""
    keys = (_bucket(hashes, buckets).astype(np.uint64) << np.uint64(32)) | (hashes & np.uint64(0xFFFFFFFF))
    distinct, place = np.unique(keys, return_inverse=True)
    return (distinct & np.uint64(0xFFFFFFFF)).astype(np.uint32), np.searchsorted((distinct >> np.uint64(32)).astype(np.int64), np.arange(buckets + 1)), place


def _answer(table: pa.Table, decide: Callable[[list[bytes]], list[np.ndarray]]) -> pa.Table:
    bits = decide(table["data"].to_pylist())
    textnp.release()
    return pa.table({"chunk": table["chunk"], "bucket": table["bucket"], "bits": pa.array([np.packbits(x).tobytes() for x in bits], pa.binary())})


def _seen_twice(data: list[bytes]) -> list[np.ndarray]:
    parts = [np.frombuffer(x, np.uint32) for x in data]
    every = np.concatenate(parts)
    order = np.argsort(every)
    same = np.concatenate([[False], every[order][1:] == every[order][:-1], [False]])
    out = np.zeros(len(every), bool)
    out[order] = same[1:] | same[:-1]
    return np.split(out, np.cumsum([len(p) for p in parts])[:-1])


def _smaller_elsewhere(data: list[bytes]) -> list[np.ndarray]:
    parts = [np.frombuffer(x, np.uint64) for x in data]
    hashes = np.concatenate([p[: len(p) // 2] for p in parts])
    least = np.concatenate([p[len(p) // 2 :] for p in parts]).view(np.int64)
    _, place = np.unique(hashes, return_inverse=True)
    overall = np.full(len(hashes), _LARGEST)
    np.minimum.at(overall, place, least)
    return np.split(overall[place] < least, np.cumsum([len(p) // 2 for p in parts])[:-1])


def sizes(total: float, tasks: int, chunk_bytes: int | None = None) -> tuple[int, int]:
    """Numbers of chunks and of buckets for so many bytes. Small tables get fewer buckets than tasks, as every chunk may send a blob to each."""
    grown = max(1.0, math.sqrt(total / GROW_BYTES))
    return max(math.ceil(total / (chunk_bytes or CHUNK_BYTES * grown)), tasks), max(math.ceil(total / (BUCKET_BYTES * grown)), math.ceil(tasks / 4))


def _sizes(docs: DataFrame, text_col: str, chunk_bytes: int | None) -> tuple[int, int]:
    total = docs.select(F.sum(F.octet_length(text_col).cast("double"))).first()[0] or 0
    return sizes(total, int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), chunk_bytes)


def _exchange(docs: DataFrame, id_col: str, text_col: str, carry: list[str], window: int, chunk_bytes: int | None, finish: Callable[[_Chunk, np.ndarray, pa.Table], pa.Table], schema: str) -> DataFrame:
    """finish gets a chunk, flags of its words to remove, and its rows (i, t, and carry as c0, c1, ...)."""
    if not isinstance(docs.schema[id_col].dataType, T.IntegralType):
        raise TypeError(f"{id_col} holds whole numbers")
    chunks, buckets = _sizes(docs, text_col, chunk_bytes)
    texts = docs.select(
        F.col(id_col).cast("long").alias("i"), F.col(text_col).cast("string").alias("t"), *(F.col(f"`{c}`").alias(f"c{k}") for k, c in enumerate(carry)), F.pmod(F.xxhash64(F.col(id_col), F.col(text_col), F.spark_partition_id()), F.lit(chunks)).cast("int").alias("chunk")
    )

    def own(table: pa.Table) -> _Chunk:
        return _Chunk(table["i"], table["t"], window)

    def send_low(table: pa.Table) -> pa.Table:
        low, edges, _ = _low(own(table).hashes, buckets)
        textnp.release()
        used = np.flatnonzero(np.diff(edges))
        data = [low[edges[b] : edges[b + 1]].tobytes() for b in used]
        return pa.table({"chunk": pa.array(np.full(len(used), table["chunk"][0].as_py(), np.int32)), "bucket": pa.array(used.astype(np.int32)), "data": pa.array(data, pa.binary())})

    def shared(chunk: _Chunk, replies: pa.Table) -> np.ndarray:
        """Places of the hashes that other chunks seem to have."""
        low, edges, place = _low(chunk.hashes, buckets)
        seen = np.zeros(len(low), bool)
        for bucket, bits in zip(replies["bucket"].to_pylist(), replies["bits"].to_pylist(), strict=True):
            a, b = edges[bucket], edges[bucket + 1]
            seen[a:b] = np.unpackbits(np.frombuffer(bits, np.uint8), count=b - a).astype(bool)
        return np.flatnonzero(seen[place])

    def send_least(table: pa.Table, replies: pa.Table) -> pa.Table:
        if not table.num_rows:
            return pa.table({"chunk": pa.array([], pa.int32()), "bucket": pa.array([], pa.int32()), "data": pa.array([], pa.binary())})
        chunk = own(table)
        at = shared(chunk, replies)
        textnp.release()
        hashes, least = chunk.hashes[at], chunk.least[at].view(np.uint64)
        # the places are sent along to no one: the next pass finds them by the hashes
        return _blobs(table["chunk"][0].as_py(), hashes, buckets, lambda a, b: hashes[a:b].tobytes() + least[a:b].tobytes())

    def remove(table: pa.Table, replies: pa.Table, seen: pa.Table) -> pa.Table:
        chunk = own(table)
        at = shared(chunk, seen)
        elsewhere = np.zeros(len(chunk.hashes), bool)
        elsewhere[at] = _replies(replies, chunk.hashes[at], buckets)
        drop = elsewhere[chunk.place] | (chunk.id_of > chunk.least[chunk.place])
        n = len(chunk.texts.starts)
        textnp.release()
        edge = np.zeros(n + 1, np.int64)
        at = chunk.at[drop]
        edge[at] += 1
        np.subtract.at(edge, at + window, 1)
        return finish(chunk, np.cumsum(edge)[:n] > 0, table)

    def last(table: pa.Table, both: pa.Table) -> pa.Table:
        first = pc.equal(both["round"], 1)
        return remove(table, both.filter(pc.invert(first)), both.filter(first))

    blob, bits = "chunk int, bucket int, data binary", "chunk int, bucket int, bits binary"
    by_chunk = texts.groupBy("chunk")
    seen = by_chunk.applyInArrow(send_low, blob).groupBy("bucket").applyInArrow(lambda t: _answer(t, _seen_twice), bits)
    least = by_chunk.cogroup(seen.groupBy("chunk")).applyInArrow(send_least, blob).groupBy("bucket").applyInArrow(lambda t: _answer(t, _smaller_elsewhere), bits)
    both = seen.withColumn("round", F.lit(1)).unionByName(least.withColumn("round", F.lit(2)))
    empty = pa.schema([])
    return by_chunk.cogroup(both.groupBy("chunk")).applyInArrow(lambda t, r: last(t, r) if t.num_rows else empty.empty_table(), schema)


def _cut(texts: textnp.Texts, starts: np.ndarray, ends: np.ndarray, data: np.ndarray) -> pa.Array:
    """The texts made of the bytes between starts and ends (ascending, apart from each other)."""
    edge = np.zeros(len(data) + 1, np.int8)
    np.add.at(edge, starts, 1)
    np.add.at(edge, ends, -1)
    keep = np.cumsum(edge[:-1], dtype=np.int8) > 0
    offsets = textnp._prefix(keep.astype(np.int64))[texts.offsets]
    return pa.LargeStringArray.from_buffers(texts.n, pa.py_buffer(offsets), pa.py_buffer(data[keep])).cast(pa.string())


def kept_words(texts: textnp.Texts, removed: np.ndarray) -> pa.Array:
    """The kept words of each text, joined by one space."""
    kept = np.flatnonzero(~removed)
    ends, doc = texts.ends[kept].copy(), texts.doc[kept]
    inner = np.zeros(len(kept), bool)
    inner[:-1] = doc[1:] == doc[:-1]
    data = texts.data.copy()
    data[ends[inner]] = 32
    return _cut(texts, texts.starts[kept], ends + inner, data)


def spliced(texts: textnp.Texts, removed: np.ndarray) -> pa.Array:
    """The texts without the removed words and the white space after each; a text that loses none stays as it is."""
    gone = np.flatnonzero(removed)
    after = np.append(texts.starts, len(texts.data))[gone + 1]
    after = np.minimum(after, texts.offsets[texts.doc[gone] + 1])
    drop = np.zeros(len(texts.data) + 1, np.int64)
    np.add.at(drop, texts.starts[gone], 1)
    np.add.at(drop, after, -1)
    keep = np.cumsum(drop[:-1]) == 0
    offsets = textnp._prefix(keep.astype(np.int64))[texts.offsets]
    return pa.LargeStringArray.from_buffers(texts.n, pa.py_buffer(offsets), pa.py_buffer(texts.data[keep])).cast(pa.string())


def intervals(texts: textnp.Texts, removed: np.ndarray) -> pa.Array:
    """Maximal intervals of removed words of each text, as word numbers from begin to end (excluded)."""
    doc = texts.doc
    first = removed.copy()
    first[1:] &= ~removed[:-1] | (doc[1:] != doc[:-1])
    final = removed.copy()
    final[:-1] &= ~removed[1:] | (doc[1:] != doc[:-1])
    begin, end = np.flatnonzero(first), np.flatnonzero(final) + 1
    base = texts.word_offsets[doc[begin]]
    offsets = np.searchsorted(doc[begin], np.arange(texts.n + 1)).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(offsets), pa.StructArray.from_arrays([pa.array(begin - base), pa.array(end - base)], ["begin", "end"]))


def measure(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", window: int = WINDOW, chunk_bytes: int | None = None) -> DataFrame:
    """One row per row of ``docs``: its id, ``n_words``, ``n_removed``, ``removed`` (maximal intervals of word numbers) and ``kept`` (the kept words joined by one space)."""

    def finish(chunk: _Chunk, removed: np.ndarray, table: pa.Table) -> pa.Table:
        texts = chunk.texts
        counts = np.bincount(texts.doc[removed], minlength=texts.n).astype(np.int64)
        return pa.table({id_col: table["i"], "n_words": pa.array(texts.n_words.astype(np.int64)), "n_removed": pa.array(counts), "removed": intervals(texts, removed), "kept": kept_words(texts, removed)})

    return _exchange(docs, id_col, text_col, [], window, chunk_bytes, finish, f"`{id_col}` long, n_words long, n_removed long, removed array<struct<begin: long, end: long>>, kept string")


def remove(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", length_col: str | None = "n_chars", window: int = WINDOW, chunk_bytes: int | None = None) -> DataFrame:
    """``docs`` with the removed words cut out of its texts, each with the white space after it. length_col, if it is there, gets the new code points where a text has changed."""
    names = docs.columns
    at, length = names.index(text_col), names.index(length_col) if length_col in names else -1

    def finish(chunk: _Chunk, removed: np.ndarray, table: pa.Table) -> pa.Table:
        texts = chunk.texts
        changed = pa.array(np.bincount(texts.doc[removed], minlength=texts.n) > 0)
        new = spliced(texts, removed)
        columns = [table[f"c{k}"] for k in range(len(names))]
        columns[at] = pc.if_else(changed, new, columns[at])
        if length >= 0:
            columns[length] = pc.if_else(changed, pc.utf8_length(new).cast(columns[length].type), columns[length])
        return pa.table(columns, names=[f"c{k}" for k in range(len(names))])

    schema = ", ".join(f"c{k} {f.dataType.simpleString()}" for k, f in enumerate(docs.schema.fields))
    return _exchange(docs, id_col, text_col, names, window, chunk_bytes, finish, schema).toDF(*names)
