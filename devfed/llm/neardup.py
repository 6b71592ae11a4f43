r"""Near-duplicate documents by circulant MinHash, banding and exact Jaccard verification.

A document's set holds its distinct shingles of SHINGLE words (A-Z lower-cased, words
``[^\x20\x09-\x0D]+``; fewer words: the whole sequence; no words: empty). Documents are
linked if 100 * intersection >= PERCENT * union; links are decided on full sets of 64-bit
shingle hashes.

1. Signature: one permutation (a bijective mix) scatters the shingles over 2**32 places; a
   second one, shifted circularly by k, gives coordinate k. BANDS bands of ROWS coordinates
   miss a pair at similarity 0.75 with a chance of (1 - 0.75**4)**32 = 5e-6.
2. Documents with equal sets form a class; from here on classes are the nodes, so exact
   copies cost one row each.
3. In each bucket of a band the smallest class leads. Classes are compared with their
   leader by one byte of each coordinate: from LOOSE on they share a candidate cluster, from
   TIGHT on they are done with this bucket, as whatever they may be linked with is at least
   LOOSE to the leader too. The others get a new leader; what is left after ROUNDS rounds
   joins one cluster, unfiltered. So clusters may be too large but split no link.
4. Clusters of up to BLOCK classes are solved exactly, many in a task. Larger ones are
   dealt into blocks: each block by itself, then with the classes of most likeness
   of all blocks ("hubs"). What is then outside the cluster's largest component meets all blocks, where that is
   little, and else the classes that shared a leader with it (its "stars") and no others, in blocks
   of a star; so a cluster that is chained of many small groups costs its groups, not its square.
   Each block gives back a spanning forest of its links, never pairs.

Defined results: null or empty texts have no shingles and are linked with nothing; rows with
equal ids are judged by their own text; a row without an id is linked like any other, and its
component has the smallest id there is in it (null if none); rows equal in id and text are one document; an
empty table gives an empty result; other columns, whatever their names, are not read by ``link``
and pass through ``drop_near_copies``. Memory is bounded by a slice, two blocks of sets and the longest text.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from . import textnp
from .graph import Filter, checkpointed, components

SHINGLE, PERCENT = 5, 75
BANDS, ROWS = 32, 4
LOOSE, TIGHT, ROUNDS = 30, 80, 3
BLOCK, HUBS = 512, 4
#: Copies of a class's set, on average, from which on a cluster is solved by its stars.
COPIES = 2 * BANDS

_U = np.uint64


def shingle_rows(t: textnp.Texts) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all shingles, repeated ones too, and their texts."""
    words = t.words()
    windows = textnp.Windows(words, t.doc)
    at, hashes = windows.of(SHINGLE)
    doc = t.doc[at]
    for n in range(1, SHINGLE):
        some = np.flatnonzero(t.n_words == n)
        if len(some):
            _, short = windows.of(n, t.word_offsets[some])
            hashes, doc = np.concatenate([hashes, short]), np.concatenate([doc, some])
    return hashes, doc


def shingles(t: textnp.Texts) -> tuple[np.ndarray, np.ndarray]:
    """Distinct shingle hashes of all texts, ascending within each text, and their texts."""
    hashes, doc = shingle_rows(t)
    order = np.lexsort((hashes, doc))
    hashes, doc = hashes[order], doc[order]
    new = np.ones(len(hashes), bool)
    new[1:] = (hashes[1:] != hashes[:-1]) | (doc[1:] != doc[:-1])
    return hashes[new], doc[new]


def _mix32(x: np.ndarray) -> np.ndarray:
    x ^= x >> np.uint32(16)
    x *= np.uint32(0x85EBCA6B)
    x ^= x >> np.uint32(13)
    x *= np.uint32(0xC2B2AE35)
    x ^= x >> np.uint32(16)
    return x


def signatures(hashes: np.ndarray, first: np.ndarray, k: int = BANDS * ROWS) -> np.ndarray:
    """Circulant MinHash: a row of k coordinates for each set; first: where each (not empty) set begins."""
    places = (textnp.mix(hashes ^ _U(0x5851F42D4C957F2D)) >> _U(32)).astype(np.uint32)
    out = np.empty((len(first), k), np.uint32)
    for shift in range(k):
        out[:, shift] = np.minimum.reduceat(_mix32(places + np.uint32(shift)), first)
    return out


def _describe(docs: DataFrame) -> DataFrame:
    """(id, key, n, cls, bands, sketch) of rows (id, key, text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, j, t in textnp.slices(batch.column(2), True, 1 << 20):
                hashes, doc = shingles(t)
                n = np.bincount(doc, minlength=t.n).astype(np.int64)
                has = np.flatnonzero(n)
                first = np.searchsorted(doc, has)
                cls, bands, sketch = np.zeros(t.n, _U), [None] * t.n, [None] * t.n
                if len(has):
                    cls[has] = np.add.reduceat(textnp.mix(hashes ^ _U(0x2545F4914F6CDD1D)), first)
                    signature = signatures(hashes, first)
                    keys = np.broadcast_to(np.arange(1, BANDS + 1, dtype=_U), (len(has), BANDS)).copy()
                    for r in range(ROWS):
                        keys = textnp.mix(keys * _U(0x9E3779B97F4A7C15) + signature[:, r::ROWS])
                    keys, low = keys.view(np.int64), (signature & np.uint32(255)).astype(np.uint8)
                    for row, d in enumerate(has):
                        bands[d], sketch[d] = keys[row], low[row].tobytes()
                columns = [pa.array(n), pa.array(cls.view(np.int64), mask=n == 0), pa.array(bands, pa.list_(pa.int64())), pa.array(sketch, pa.binary())]
                yield pa.RecordBatch.from_arrays([*(c.slice(i, j - i) for c in batch.columns[:2]), *columns], ["id", "key", "n", "cls", "bands", "sketch"])
        textnp.release()

    return docs.mapInArrow(run, f"id {docs.schema['id'].dataType.simpleString()}, key long, n long, cls long, bands array<long>, sketch binary")


def _compare(pairs: DataFrame) -> DataFrame:
    """Adds ``like``, the estimated similarity in percent, to (key, cls, sketch, lead, lead_sketch)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                a, b = (np.frombuffer(b"".join(batch.column(c).to_pylist()), np.uint8).reshape(batch.num_rows, -1) for c in (2, 4))
                share = (a == b).mean(axis=1)
                like = np.round(100 * (share - 1 / 256) / (1 - 1 / 256)).astype(np.int32)
                yield pa.RecordBatch.from_arrays([*batch.columns[:4], pa.array(like)], ["key", "cls", "sketch", "lead", "like"])

    return pairs.mapInArrow(run, "key long, cls long, sketch binary, lead long, like int")


def _candidates(described: DataFrame, rows_known: int = 0) -> DataFrame:
    """Edges (a, b) from classes to their leaders: two classes that may be linked share a leader, or one is the other's."""
    rows = described.where("cls IS NOT NULL").select("cls", F.explode("bands").alias("key"))
    # copies of one class are no company; the filter keeps all keys that hold two classes
    shared = rows.groupBy("key").agg(F.min("cls").alias("a"), F.max("cls").alias("z")).where("a < z").select("key")
    active, found = checkpointed(Filter(shared, rows_known).of(rows, "key").distinct()), None
    lead = active.groupBy("key").agg(F.min("cls").alias("lead"), F.max("cls").alias("z")).where("lead < z").select("key", "lead")
    of_these = Filter(active.select("cls"), rows_known).of(described.where("cls IS NOT NULL").select("cls", "sketch"), "cls")
    sketches = checkpointed(of_these.dropDuplicates(["cls"]))
    for k in range(ROUNDS):
        pairs = active.join(lead.join(sketches.toDF("lead", "lead_sketch"), "lead"), "key").where("cls <> lead")
        pairs = pairs.select("key", "cls", "sketch", "lead", "lead_sketch") if k else pairs.join(sketches, "cls").select("key", "cls", "sketch", "lead", "lead_sketch")
        pairs = checkpointed(_compare(pairs))
        edges = pairs.where(F.col("like") >= LOOSE).select(F.col("cls").alias("a"), F.col("lead").alias("b"))
        found = edges if found is None else found.union(edges)
        active = pairs.where(F.col("like") < TIGHT).select("key", "cls", "sketch")
        lead = active.groupBy("key").agg(F.min("cls").alias("lead"), F.max("cls").alias("z")).where("lead < z").select("key", "lead")
    return found.union(active.join(lead, "key").select(F.col("cls").alias("a"), F.col("lead").alias("b"))).distinct()


def _meets(sets: list[np.ndarray], rows: int | None = None) -> np.ndarray:
    """Sizes of all intersections of the sets; rows: only of the first so many with the others."""
    owner = np.repeat(np.arange(len(sets)), [len(s) for s in sets])
    values, place, count = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    column = np.cumsum(count > 1) - 1
    common = count[place] > 1
    owner, place = owner[common], column[place[common]]
    order = np.argsort(place)
    owner, place = owner[order], place[order]
    rows = len(sets) if rows is None else rows
    out, width = np.zeros((rows, len(sets)), np.float32), 8192
    for begin in range(0, int(place[-1]) + 1 if len(place) else 0, width):
        a, b = np.searchsorted(place, [begin, begin + width])
        part = np.zeros((len(sets), width), np.float32)
        part[owner[a:b], place[a:b] - begin] = 1
        out += part[:rows] @ part.T
    return out


def _linked(sets: list[np.ndarray], rows: int | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Which sets are linked, and how alike all are."""
    n = np.array([len(s) for s in sets], np.int64)
    both = np.rint(_meets(sets, rows)).astype(np.int64)
    union = n[: len(both), None] + n - both
    return 100 * both >= PERCENT * union, both / union


def _forest(links: np.ndarray, names: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Edges from each node of a square matrix to the first one of its component."""
    label = np.arange(len(links))
    np.fill_diagonal(links, True)
    while True:
        new = np.where(links, label, len(label)).min(axis=1)
        new = new[new]
        if (new == label).all():
            break
        label = new
    away = label != np.arange(len(label))
    return names[away], names[label[away]]


def _edges(a: np.ndarray, b: np.ndarray) -> pa.Table:
    return pa.table({"a": pa.array(a.astype(np.int64)), "b": pa.array(b.astype(np.int64))})


def _sets(texts: DataFrame) -> DataFrame:
    """(cls, cluster, size, hashes) of rows (cls, cluster, size, text); a row whose text has another set (of an equal id) goes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, j, t in textnp.slices(batch.column(3), True):
                hashes, doc = shingles(t)
                edges = np.searchsorted(doc, np.arange(t.n + 1))
                sums = textnp._prefix(textnp.mix(hashes ^ _U(0x2545F4914F6CDD1D)))
                own = batch.slice(i, j - i)
                right = (sums[edges[1:]] - sums[edges[:-1]]).view(np.int64) == own.column(0).to_numpy(zero_copy_only=False)
                data = [hashes[a:b].tobytes() for a, b in zip(edges, edges[1:], strict=False)]
                yield pa.RecordBatch.from_arrays([*own.columns[:3], pa.array(data, pa.binary())], ["cls", "cluster", "size", "hashes"]).filter(pa.array(right))
        textnp.release()

    return texts.mapInArrow(run, "cls long, cluster long, size long, hashes binary")


def _distinct(table: pa.Table) -> tuple[np.ndarray, list[np.ndarray]]:
    """Classes in ascending order, each once, and their sets."""
    cls, at = np.unique(table["cls"].to_numpy(), return_index=True)
    data = table["hashes"].to_pylist()
    return cls, [np.frombuffer(data[i], _U) for i in at]


def _solve_bin(table: pa.Table) -> pa.Table:
    """Links in each of several whole clusters."""
    cluster = table["cluster"].to_numpy()
    order = np.argsort(cluster, kind="stable")
    found = []
    for rows in np.split(order, np.flatnonzero(np.diff(cluster[order])) + 1):
        names, sets = _distinct(table.take(rows))
        found.append(_forest(_linked(sets)[0], names))
    return _edges(np.concatenate([a for a, _ in found]), np.concatenate([b for _, b in found]))


def _meetings(parts: DataFrame, stars: DataFrame, half: int) -> DataFrame:
    """(cls, star, i, j, left): which classes meet in which block, so that every class outside its cluster's largest component meets all that it may be linked with; parts: (cls, cluster, rest).

    A cluster with few such classes is one star. Where that would copy each of its classes COPIES times or more, they meet in the stars (a, b)
    that hold one of them, of which a class has up to BANDS in each round.
    """
    sizes = parts.groupBy("cluster").agg(F.sum(F.col("rest").cast("long")).alias("n_rest"), F.count("*").alias("n")).where("n_rest > 0")
    copies = F.col("n_rest") * F.ceil(F.col("n") / half) + F.col("n") * F.ceil(F.col("n_rest") / half)
    sizes = checkpointed(sizes.withColumn("whole", copies < COPIES * F.col("n")))
    own = parts.join(sizes.where("whole"), "cluster").select(F.col("cluster").alias("star"), "cls", "rest")
    if sizes.where("NOT whole").limit(1).count():
        chained = parts.join(sizes.where("NOT whole").select("cluster"), "cluster").select("cls", "rest")
        star = stars.select(F.col("b").alias("star"), F.col("a").alias("cls")).union(stars.select("b", "b").distinct())
        own = own.unionByName(star.join(chained, "cls").select("star", "cls", "rest"))
    own = checkpointed(own)
    sizes = own.groupBy("star").agg(F.sum(F.col("rest").cast("long")).alias("n_rest"), F.count("*").alias("n")).where("n_rest > 0")
    own = own.join(sizes.select("star", F.ceil(F.col("n_rest") / half).cast("int").alias("rests"), F.ceil(F.col("n") / half).cast("int").alias("blocks")), "star")
    block = lambda n: F.pmod(F.xxhash64("cls"), F.col(n)).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    left = own.where("rest").select("cls", "star", block("rests").alias("i"), every("blocks").alias("j"), F.lit(True).alias("left"))
    return left.unionByName(own.select("cls", "star", every("rests").alias("i"), block("blocks").alias("j"), F.lit(False).alias("left")))


def _solve_large(sets: DataFrame, stars: DataFrame) -> DataFrame:
    """Links in clusters of more than BLOCK classes, given (cls, cluster, size, hashes) and the candidate edges."""
    half = BLOCK // 2
    n_blocks = F.ceil(F.col("size") / half).cast("int")
    sets = checkpointed(sets.dropDuplicates(["cls"]).withColumn("block", F.pmod(F.xxhash64("cls"), n_blocks).cast("int")))

    def alone(table: pa.Table) -> pa.Table:
        names, own = _distinct(table)
        links, like = _linked(own)
        hubs = np.argsort(-like.sum(axis=1), kind="stable")[:HUBS]
        a, b = _forest(links, names)
        edges = _edges(np.concatenate([a, names[hubs]]), np.concatenate([b, names[hubs]]))
        score = np.concatenate([np.full(len(a), -1.0), like.mean(axis=1)[hubs]])
        return edges.append_column("cluster", pa.array(np.full(len(score), table["cluster"][0].as_py(), np.int64))).append_column("score", pa.array(score))

    first = checkpointed(sets.groupBy("cluster", "block").applyInArrow(alone, "a long, b long, cluster long, score double"))
    hubs = first.where("score >= 0").withColumn("rank", F.row_number().over(Window.partitionBy("cluster").orderBy(F.desc("score"), "a"))).where(F.col("rank") <= half).select(F.col("a").alias("cls"))
    hubs = sets.join(hubs, "cls").withColumn("block", F.explode(F.sequence(F.lit(0), n_blocks - 1)))

    def with_hubs(table: pa.Table) -> pa.Table:
        names, own = _distinct(table)
        return _edges(*_forest(_linked(own)[0], names))

    second = sets.unionByName(hubs).groupBy("cluster", "block").applyInArrow(with_hubs, "a long, b long")
    edges = checkpointed(first.where("score < 0").select("a", "b").union(second))
    parts = sets.join(components(edges).withColumnRenamed("node", "cls"), "cls", "left").withColumn("component", F.coalesce("component", "cls"))
    sizes = parts.groupBy("cluster", "component").count()
    largest = sizes.groupBy("cluster").agg(F.max(F.struct("count", "component")).alias("top")).select("cluster", F.col("top.component").alias("largest"))
    parts = checkpointed(parts.join(largest, "cluster").select("cls", "cluster", (F.col("component") != F.col("largest")).alias("rest")))
    meetings = _meetings(parts, stars, half).join(sets.select("cls", "hashes"), "cls")

    def across(table: pa.Table) -> pa.Table:
        flags = table["left"].to_numpy(zero_copy_only=False)
        (a_names, a), (b_names, b) = _distinct(table.filter(pa.array(flags))), _distinct(table.filter(pa.array(~flags)))
        if not a or not b:
            return _edges(np.zeros(0), np.zeros(0))
        links = _linked(a + b, len(a))[0]
        links[:, : len(a)] = False
        square = np.zeros((links.shape[1],) * 2, bool)
        square[: len(a)], square[:, : len(a)] = links, square[:, : len(a)] | links.T
        return _edges(*_forest(square, np.concatenate([a_names, b_names])))

    third = meetings.groupBy("star", "i", "j").applyInArrow(across, "a long, b long")
    return edges.union(third)


def _linked_rows(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(id, key, n, component_id, stays) of all rows; key tells rows apart by id and text, stays is true for one key of each component."""
    texts = docs.select(F.col(f"`{id_col}`").alias("id"), _key(id_col, text_col).alias("key"), F.col(f"`{text_col}`").cast("string").alias("text"))
    described = checkpointed(_describe(texts))
    rows_known = described.count()
    plain = described.select("id", "key", "n", "cls")
    # the row that stands for a class: of the smallest id, rows without one last
    least = plain.where("cls IS NOT NULL").groupBy("cls").agg(F.min(F.struct(F.col("id").isNull().alias("none"), "id", "key")).alias("rep"))
    candidates = checkpointed(_candidates(described, rows_known))
    clusters = components(candidates).withColumnRenamed("node", "cls").withColumnRenamed("component", "cluster")
    sizes = clusters.groupBy("cluster").agg(F.count("*").alias("size"))
    members = checkpointed(clusters.join(sizes, "cluster").join(least, "cls"))
    large = members.where(F.col("size") > BLOCK).select("cluster").limit(1).count() > 0
    wanted = members.select("cls", "cluster", "size", F.col("rep.key").alias("key"))
    # a row that occurs often is fetched once
    of_these = Filter(wanted.select("key"), rows_known).of(texts.select("key", "text"), "key").dropDuplicates(["key"])
    sets = of_these.join(wanted, "key").select("cls", "cluster", "size", "text")
    small = _sets(sets.where(F.col("size") <= BLOCK))
    bins = max(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")) * 4, members.count() // 2000)
    edges = small.withColumn("bin", F.pmod(F.xxhash64("cluster"), F.lit(bins))).groupBy("bin").applyInArrow(_solve_bin, "a long, b long")
    if large:
        of_large = members.where(F.col("size") > BLOCK).select(F.col("cls").alias("a"))
        edges = edges.union(_solve_large(_sets(sets.where(F.col("size") > BLOCK)), candidates.join(of_large, "a")))
    named = components(edges).withColumnRenamed("node", "cls").join(members.select("cls", "rep"), "cls")
    final = named.join(named.groupBy("component").agg(F.min("rep").alias("first")), "component").select("cls", "first")
    by_class = checkpointed(least.join(final, "cls", "left").select("cls", F.coalesce("first", "rep").alias("first")))
    out = plain.join(by_class, "cls", "left")
    alone = F.col("cls").isNull()
    return out.select("id", "key", "n", F.when(alone, F.col("id")).otherwise(F.col("first.id")).alias("component_id"), (alone | (F.col("key") == F.col("first.key"))).alias("stays"))


def _key(id_col: str, text_col: str) -> Column:
    return F.xxhash64(F.col(f"`{id_col}`"), F.col(f"`{text_col}`").cast("string"))


def link(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of ``docs``: its id, ``n_shingles``, ``component_id`` (the smallest id in its component) and ``kept`` (that id is its own)."""
    found = _linked_rows(docs, id_col, text_col)
    return found.select(F.col("id").alias(id_col), F.col("n").alias("n_shingles"), "component_id", F.col("id").eqNullSafe(F.col("component_id")).alias("kept"))


def drop_near_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One document of each component, that of the smallest id, and all that are linked with nothing. Rows equal in id and text are one document and stay together."""
    gone = _linked_rows(docs, id_col, text_col).where("NOT stays").select(F.col("key").alias("__gone_key")).distinct()
    return docs.join(gone, _key(id_col, text_col) == F.col("__gone_key"), "left_anti")
