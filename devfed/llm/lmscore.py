r"""Cross-entropy difference of two matched n-gram language models.

A target model is counted on the documents of a given set of ids and a background model on
all documents. Both are bigram models with the same vocabulary (all words of all documents and
the end mark), order and smoothing: p(w | v) = LAMBDA * c(v w) / c(v) + (1 - LAMBDA) * (c(w) + 1) / (N + V),
where the first part falls away, and the second counts in full, if v was never seen. A text is its
words and an end mark, after a start mark; so c(v) counts v as a history exactly (c of the start mark
is the number of texts with words), and p(. | v) adds up to 1 over the vocabulary. The models match in
all of this, not in size: the background takes every document, as a sample of the target's size would
throw counts away.

No document is scored by counts of its own: they are left out of the background for every document
and of the target for its members. A document's loss is the mean over its words and its end of -log p, and
its score the target's loss minus the background's, in nats: the lower, the more it resembles the target.

Counting: texts are dealt into chunks by a hash of the id. A chunk reduces its words and pairs
to distinct hashes of 64 bits with counts, so that a frequent word is one entry for each chunk, sends
them to buckets by hash, and gets the corpus counts back in the same order; then it scores its
texts. The chunks' texts are exchanged once and read in both passes. Hashes travel as the gaps between
ascending ones, the low 48 bits as they are and the high ones, nearly all 0, deflated like the counts.

Words are ``[^\x20\x09-\x0D]+``. Defined results: a text without words has n_words 0 and null losses;
null texts are empty; a null id is never in the target; ids may be of any type that can be hashed, the
target's are cast to it; repeated rows count as often as they occur, and each leaves out itself only; an
empty target leaves the smoothing alone (c = N = 0); a table without a word or a row gives null losses or
an empty result; only id and text are read. Rows of a null id, and of an id whose rows hold more than a chunk,
are dealt by text and partition too. Memory is bounded by a chunk, a bucket and the longest text.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textnp
from .substring import CHUNK_BYTES, _bucket, _sizes

LAMBDA = 0.7
_START, _END = np.uint64(0x7F4A7C159E3779B9), np.uint64(0x94D049BB1F3779D1)
#: Ids with more text than a chunk, of repeated rows, up to which they are sent to the executors.
HOT_IDS = 10_000
_U = np.uint64


def _grams(text: pa.ChunkedArray) -> tuple[textnp.Texts, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Texts, and for each word and end of a text: its text, and the hashes of the word, of the one before it (or the start mark), and of the pair."""
    column = text.combine_chunks()
    data, offsets = textnp.buffers(column if isinstance(column, pa.Array) else pa.concat_arrays(column.chunks))
    t = textnp.Texts(data[offsets[0] : offsets[-1]], offsets - offsets[0])
    has = (t.n_words > 0).astype(np.int64)
    doc = np.repeat(np.arange(t.n), t.n_words + has)
    words = np.full(len(doc), _END)
    words[np.arange(len(t.doc)) + (np.cumsum(has) - has)[t.doc]] = t.words()
    before = np.full(len(doc), _START)
    before[1:] = np.where(doc[1:] == doc[:-1], words[:-1], _START)
    # words and pairs are told apart by the hash
    return t, doc, textnp.mix(words ^ _U(1)), textnp.mix(before ^ _U(1)), textnp.mix(textnp.mix(before) + words)


def packed(values: np.ndarray, *counts: np.ndarray) -> bytes:
    """Ascending hashes, and columns for them, without loss."""
    gaps = np.diff(values, prepend=_U(0)).view(np.uint8).reshape(-1, 8)
    return gaps[:, :6].tobytes() + zlib.compress(gaps[:, 6:].tobytes() + b"".join(c.tobytes() for c in counts), 1) + len(values).to_bytes(4, "little")


def unpacked(data: bytes) -> tuple[np.ndarray, ...]:
    n = int.from_bytes(data[-4:], "little")
    rest = zlib.decompress(data[6 * n : -4])
    gaps = np.empty((n, 8), np.uint8)
    gaps[:, :6] = np.frombuffer(data, np.uint8, 6 * n).reshape(n, 6)
    gaps[:, 6:] = np.frombuffer(rest, np.uint8, 2 * n).reshape(n, 2)
    return np.cumsum(gaps.view(_U).ravel(), dtype=_U), np.frombuffer(rest, np.uint32, n, 2 * n), np.frombuffer(rest, np.uint32, n, 6 * n), np.frombuffer(rest, np.uint8, n, 10 * n)


def losses(pair: np.ndarray, history: np.ndarray, word: np.ndarray, n: np.ndarray | float, v: float, weight: float = LAMBDA) -> np.ndarray:
    """-log p of each word from its counts."""
    single = (word + 1) / (n + v)
    known = history > 0
    return -np.log(np.where(known, weight * pair / np.maximum(history, 1) + (1 - weight) * single, single))


def replies_of(place: np.ndarray, every: np.ndarray, some: np.ndarray, cuts: np.ndarray) -> list[bytes]:
    """The whole table's two counts of the key at each place, deflated, for each chunk."""
    sums = [np.bincount(place, x).astype(np.uint64) for x in (every, some)]
    return [zlib.compress(b"".join(s[part].tobytes() for s in sums), 1) for part in np.split(place, cuts)]


def counts_in(reply: bytes) -> np.ndarray:
    return np.frombuffer(zlib.decompress(reply), np.uint64).reshape(2, -1)


def _parts(docs: DataFrame, id_col: str, text_col: str, chunk_bytes: int) -> DataFrame | None:
    """(i, parts) of the ids whose rows hold more than a chunk: into how many chunks they are dealt. None where there are none."""
    size = docs.where(F.col(id_col).isNotNull()).groupBy(F.col(id_col).alias("i")).agg(F.sum(F.octet_length(text_col).cast("double")).alias("size"), F.count("*").alias("n"))
    found = size.where((F.col("n") > 1) & (F.col("size") > chunk_bytes)).select("i", F.ceil(F.col("size") / chunk_bytes).cast("int").alias("parts"))
    rows = found.limit(HOT_IDS + 1).collect()
    if not rows:
        return None
    # a bounded number of them is sent to the executors; more meet the texts in a join
    return F.broadcast(docs.sparkSession.createDataFrame(rows, found.schema)) if len(rows) <= HOT_IDS else found


def score(docs: DataFrame, target_ids: DataFrame, id_col: str = "doc_id", text_col: str = "text", weight: float = LAMBDA, chunk_bytes: int | None = None) -> DataFrame:
    """One row per row of ``docs``: the id, ``n_words``, ``target_loss``, ``background_loss`` (means per word and end) and ``score``, their difference. target_ids: one column of ids."""
    chunks, buckets = _sizes(docs, text_col, chunk_bytes)
    kind = docs.schema[id_col].dataType.simpleString()
    source = docs.select(F.col(id_col).alias("i"), F.col(text_col).cast("string").alias("t"))
    target = target_ids.toDF("i").select(F.col("i").cast(kind)).where("i IS NOT NULL").distinct()
    hot = _parts(docs, id_col, text_col, chunk_bytes or CHUNK_BYTES)
    salt = F.when(F.col("i").isNull(), F.xxhash64("t", F.spark_partition_id())).otherwise(0)
    part = F.lit(0).cast("long")
    if hot is not None:
        source, target = source.join(hot, "i", "left"), target.join(hot, "i", "left")
        salt = F.when(F.col("parts").isNotNull(), F.pmod(F.xxhash64("t", F.spark_partition_id()), F.col("parts"))).otherwise(salt)
        part = F.explode(F.sequence(F.lit(0).cast("long"), F.coalesce(F.col("parts").cast("long"), F.lit(1)) - 1))
    texts = source.withColumn("salt", salt.cast("long")).select("i", "t", F.pmod(F.xxhash64("i", "salt"), F.lit(chunks)).cast("int").alias("chunk"))
    nothing = {"bucket": F.lit(None).cast("int"), "data": F.lit(None).cast("binary"), "totals": F.lit(None).cast("array<double>")}
    chosen = target.select("i", part.alias("salt")).select(F.pmod(F.xxhash64("i", "salt"), F.lit(chunks)).cast("int").alias("chunk"), "i").distinct().withColumns(nothing).select("chunk", "i", "bucket", "data", "totals")

    def in_target(table: pa.Table, right: pa.Table) -> np.ndarray:
        wanted = right["i"].drop_null()
        return pc.is_in(table["i"], value_set=wanted.combine_chunks()).to_numpy() if len(wanted) else np.zeros(table.num_rows, bool)

    def keys_of(t: textnp.Texts, word: np.ndarray, pair: np.ndarray, doc: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Distinct keys, the place of each word, pair and text's start mark among them, and the text of each."""
        begun = np.flatnonzero(t.n_words > 0)
        marks = textnp.mix(np.full(len(begun), _START) ^ _U(1))
        values, place = np.unique(np.concatenate([word, pair, marks]), return_inverse=True)
        return values, place, np.concatenate([doc, doc, begun])

    def send(table: pa.Table, right: pa.Table) -> pa.Table:
        if not table.num_rows:
            return pa.table({"chunk": pa.array([], pa.int32()), "bucket": pa.array([], pa.int32()), "data": pa.array([], pa.binary())})
        t, doc, word, _, pair = _grams(table["t"])
        values, place, of = keys_of(t, word, pair, doc)
        own = in_target(table, right)[of]
        every = np.bincount(place, minlength=len(values)).astype(np.uint32)
        some = np.bincount(place[own], minlength=len(values)).astype(np.uint32)
        kind = np.zeros(len(values), np.uint8)
        kind[place[: len(word)]] = 1
        edges = np.searchsorted(_bucket(values, buckets), np.arange(buckets + 1))
        used = np.flatnonzero(np.diff(edges))
        textnp.release()
        data = [packed(*(x[edges[b] : edges[b + 1]] for x in (values, every, some, kind))) for b in used]
        return pa.table({"chunk": pa.array(np.full(len(used), table["chunk"][0].as_py(), np.int32)), "bucket": pa.array(used.astype(np.int32)), "data": pa.array(data, pa.binary())})

    def add_up(table: pa.Table) -> pa.Table:
        parts = [unpacked(x) for x in table["data"].to_pylist()]
        values, every, some, kind = (np.concatenate([p[k] for p in parts]) for k in range(4))
        distinct_values, place = np.unique(values, return_inverse=True)
        data = replies_of(place, every, some, np.cumsum([len(p[0]) for p in parts])[:-1])
        textnp.release()
        word = kind == 1
        is_word = np.zeros(len(distinct_values), bool)
        is_word[place[word]] = True
        # the totals of this bucket's words go along once, with the row of chunk -1
        totals = [float(every[word].sum()), float(some[word].sum()), float(is_word.sum())]
        return pa.table({"chunk": pa.array([*table["chunk"].to_pylist(), -1], pa.int32()), "bucket": pa.array([*table["bucket"].to_pylist(), 0], pa.int32()), "data": pa.array([*data, None], pa.binary()), "totals": pa.array([None] * len(data) + [totals], pa.list_(pa.float64()))})

    def finish(table: pa.Table, right: pa.Table, n_all: float, n_target: float, v: float) -> pa.Table:
        t, doc, word, history, pair = _grams(table["t"])
        values, place, of = keys_of(t, word, pair, doc)
        m = len(word)
        at = place[:m], np.searchsorted(values, history), place[m : 2 * m]
        edges = np.searchsorted(_bucket(values, buckets), np.arange(buckets + 1))
        counts = np.zeros((2, len(values)), np.uint64)
        for bucket, data in zip(right["bucket"].to_pylist(), right["data"].to_pylist(), strict=True):
            if data is not None:
                counts[:, edges[bucket] : edges[bucket + 1]] = counts_in(data)
        # how often each word and pair occurs in its own text; a word is a history as often as it occurs, the start mark once
        _, which, often = np.unique(of[: 2 * m] * max(len(values), 1) + place[: 2 * m], return_inverse=True, return_counts=True)
        own = often[which].astype(float)
        own_history = np.ones(m)
        own_history[1:] = np.where(doc[1:] == doc[:-1], own[: max(m - 1, 0)], 1.0)
        length, member, means = t.n_words + (t.n_words > 0), in_target(table, right).astype(float), []
        for row, n, left_out in ((1, n_target, member), (0, n_all, np.ones(t.n))):
            less = left_out[doc]
            of_word, of_history, of_pair = (counts[row][k].astype(float) for k in at)
            each = losses(of_pair - less * own[m:], of_history - less * own_history, of_word - less * own[:m], (n - left_out * length)[doc], v, weight)
            means.append(np.divide(np.bincount(doc, each, t.n), length, out=np.zeros(t.n), where=length > 0))
        none = t.n_words == 0
        textnp.release()
        return pa.table({id_col: table["i"], "n_words": pa.array(t.n_words.astype(np.int64)), "target_loss": pa.array(means[0], mask=none), "background_loss": pa.array(means[1], mask=none), "score": pa.array(means[0] - means[1], mask=none)})

    by_chunk = texts.groupBy("chunk")
    sent = by_chunk.cogroup(chosen.groupBy("chunk")).applyInArrow(send, "chunk int, bucket int, data binary")
    replies = sent.groupBy("bucket").applyInArrow(add_up, "chunk int, bucket int, data binary, totals array<double>")
    # totals are three numbers of the whole corpus; every chunk gets them in a row of its own
    totals = replies.where("chunk = -1").agg(*(F.coalesce(F.sum(F.col("totals")[k]), F.lit(0.0)).alias(f"n{k}") for k in range(3))).select(F.array("n0", "n1", "n2").alias("totals"))
    every = docs.sparkSession.range(chunks).select(F.col("id").cast("int").alias("chunk")).crossJoin(F.broadcast(totals)).withColumns({"i": F.lit(None).cast(kind), **{k: c for k, c in nothing.items() if k != "totals"}})
    right = replies.where("chunk >= 0").withColumn("i", F.lit(None).cast(kind)).select("chunk", "i", "bucket", "data", "totals").unionByName(every).unionByName(chosen)

    def last(table: pa.Table, other: pa.Table) -> pa.Table:
        if not table.num_rows:
            return pa.schema([]).empty_table()
        return finish(table, other, *other["totals"].drop_null()[0].as_py())

    return by_chunk.cogroup(right.groupBy("chunk")).applyInArrow(last, f"`{id_col}` {kind}, n_words long, target_loss double, background_loss double, score double")
