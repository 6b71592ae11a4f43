"""Document fingerprints by one-permutation MinHash with optimal densification.

Each distinct shingle is hashed once; the high bits choose one of BINS bins, and a bin
keeps its smallest hash. An empty bin takes the value of a full one, found by hashing the
bin's number and the number of the attempt, alike for all documents (optimal
densification). Of each bin BITS low-order bits are stored, packed. The share m of equal
bins of two fingerprints has the expectation J + (1 - J) / 2**BITS, which the likeness
corrects for.

``with_next`` compares every document with an edited text, whose last half comes from the
next document in ascending order of id (text among equal ids, null ids first; after the
last the first). Documents are dealt into ranges of ids once; each task reads its range in
order, and the few pairs that cross ranges are made afterwards from the ranges' first and
last rows.

Defined results: texts without words have the fingerprint of zeros with the last bit set
apart: two of them are alike (1), one of them and another aren't (0); null texts are empty;
repeated rows follow one another; a single row is its own next; an empty table gives an
empty result; only id and text are read. Memory is bounded by ROWS texts and the longest.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from . import textnp
from .graph import checkpointed
from .neardup import shingle_rows

BINS, BITS = 512, 4
ROWS = 200
#: Rows of a range, which is one task's work.
TASK_ROWS = 20_000

_U = np.uint64
_EMPTY = np.iinfo(np.uint64).max


def densified(hashes: np.ndarray, doc: np.ndarray, n: int, bins: int = BINS) -> np.ndarray:
    """A row of bins for each of n sets, each bin its smallest hash; rows of empty sets hold _EMPTY."""
    mixed = textnp.mix(hashes ^ _U(0x9D8AF066F3C1E6B5))
    key = doc.astype(np.int64) * bins + ((mixed >> _U(32)) * _U(bins) >> _U(32)).astype(np.int64)
    out = np.full(n * bins, _EMPTY)
    np.minimum.at(out, key, textnp.mix(mixed))
    out = out.reshape(n, bins)
    full = out != _EMPTY
    rows, columns = np.nonzero(~full & full.any(axis=1)[:, None])
    attempt = 0
    while len(rows):
        attempt += 1
        source = (textnp.mix(columns.astype(_U) + _U(attempt << 20)) % _U(bins)).astype(np.int64)
        hit = full[rows, source]
        out[rows[hit], columns[hit]] = out[rows[hit], source[hit]]
        rows, columns = rows[~hit], columns[~hit]
    return out


def fingerprints(texts: list[str], bins: int = BINS, bits: int = BITS) -> np.ndarray:
    """A row of bins of the given bits (as bytes, not yet packed) for each text, and a last column that is 1 for a text without words."""
    column, parts = pa.array(texts, pa.large_string()), []
    for _, _, t in textnp.slices(column, True):
        bins_of = densified(*shingle_rows(t), t.n, bins)
        none = t.n_words == 0
        low = (textnp.mix(bins_of) & _U((1 << bits) - 1)).astype(np.uint8)
        low[none] = 0
        parts.append(np.column_stack([low, none.astype(np.uint8)]))
    return np.concatenate(parts) if parts else np.zeros((0, bins + 1), np.uint8)


def packed(rows: np.ndarray, bits: int = BITS) -> list[bytes]:
    """The bins' bits one after another, and a byte that tells empty texts."""
    flat = (rows[:, :-1, None] >> np.arange(bits - 1, -1, -1, dtype=np.uint8)) & 1
    return [a.tobytes() + b.tobytes() for a, b in zip(np.packbits(flat.reshape(len(rows), -1), axis=1), rows[:, -1:], strict=True)]


def likeness(a: np.ndarray, b: np.ndarray, bits: int = BITS) -> np.ndarray:
    """Estimated similarity of fingerprints, row by row, without the chance hits of the stored bits."""
    chance = 0.5**bits
    share = (a[:, :-1] == b[:, :-1]).mean(axis=1)
    out = np.clip((share - chance) / (1 - chance), 0.0, 1.0)
    return np.where(a[:, -1] != b[:, -1], 0.0, np.where(a[:, -1] == 1, 1.0, out))


def edited(text: str, following: str) -> str:
    """text with its last half (rounded down, in code points) replaced by as much of the start of the next text as there is."""
    half = len(text) // 2
    return text[: len(text) - half] + following[:half]


_NAMES = ["n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"]
_KIND = "n_chars long, edited_sha256 binary, fingerprint binary, edited_fingerprint binary, near_edited double, near_next double"


def _results(texts: list[str], own: np.ndarray | None = None) -> tuple[list[pa.Array], np.ndarray]:
    """Results of all texts but the last, each with the one after it, and the last one's fingerprint."""
    rows = fingerprints(texts if own is None else texts[1:])
    rows = rows if own is None else np.concatenate([own, rows])
    new = [edited(a, b) for a, b in zip(texts, texts[1:], strict=False)]
    other = fingerprints(new)
    columns = [
        pa.array([len(t) for t in texts[:-1]], pa.int64()), pa.array([hashlib.sha256(t.encode()).digest() for t in new], pa.binary()), pa.array(packed(rows[:-1]), pa.binary()), pa.array(packed(other), pa.binary()),
        pa.array(likeness(rows[:-1], other)), pa.array(likeness(rows[:-1], rows[1:])),
    ]
    return columns, rows[-1:]


def with_next(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of ``docs``: the id, n_chars, edited_sha256, fingerprint and edited_fingerprint (binary), near_edited and near_next."""
    source = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    kind = source.schema["id"].dataType.simpleString()
    tasks = max(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-docs.count() // TASK_ROWS))
    in_order = source.repartitionByRange(tasks, "id").sortWithinPartitions("id", "text")
    edge = ["part", "first_text", "last_text"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, texts, own, first, id_type = [], [], None, None, None

        def done() -> pa.RecordBatch:
            columns, last = _results(texts, own)
            n = len(texts) - 1
            return pa.RecordBatch.from_arrays([pa.array(ids[:-1], id_type), *columns, pa.nulls(n, pa.int64()), pa.nulls(n, pa.string()), pa.nulls(n, pa.string())], ["id", *_NAMES, *edge]), last

        for batch in batches:
            id_type = batch.column(0).type
            for i, t in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                ids.append(i)
                texts.append(t or "")
                first = texts[0] if first is None else first
                if len(texts) > ROWS:
                    out, own = done()
                    ids, texts = ids[-1:], texts[-1:]
                    yield out
        if len(texts) > 1:
            out, own = done()
            yield out
        if texts:
            empty = [pa.nulls(1, t) for t in (pa.int64(), pa.binary(), pa.binary(), pa.binary(), pa.float64(), pa.float64())]
            yield pa.RecordBatch.from_arrays([pa.array(ids[-1:], id_type), *empty, pa.array([TaskContext.get().partitionId()], pa.int64()), pa.array([first]), pa.array([texts[-1]])], ["id", *_NAMES, *edge])

    found = checkpointed(in_order.mapInArrow(run, f"id {kind}, {_KIND}, part long, first_text string, last_text string"))
    edges = found.where("part IS NOT NULL")
    parts = edges.select("part")
    follows = parts.select("part", F.lead("part").over(Window.orderBy("part")).alias("following"))
    follows = follows.crossJoin(F.broadcast(parts.agg(F.min("part").alias("least")))).select("part", F.coalesce("following", "least").alias("following"))
    crossing = edges.select("part", "id", "last_text").join(follows, "part").join(edges.select(F.col("part").alias("following"), "first_text"), "following").select("id", "last_text", "first_text")

    def pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(len(batch)):
                columns, _ = _results([batch.column(1)[k].as_py(), batch.column(2)[k].as_py()])
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(k, 1), *columns], ["id", *_NAMES])

    out = found.where("part IS NULL").select("id", *_NAMES).union(crossing.mapInArrow(pairs, f"id {kind}, {_KIND}"))
    return out.withColumnRenamed("id", id_col)
