"""Near-dedup, substring dedup, LM scores and the pipeline against brute force and on odd rows."""

import math
import random
import re
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from devfed.llm import graph, lmscore, neardup, packing, queries, substring

WORD = re.compile(r"[^\x20\x09-\x0D]+")
FOLD = str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)})


def _docs(spark, rows):
    return spark.createDataFrame([(i, t, "x", 1) for i, t in rows], "doc_id long, text string, cls string, n int").repartition(3)


def _made(seed=1, groups=12):
    """Groups of a text and edits of it, more or less alike, exact copies and short texts."""
    r, out, i = random.Random(seed), [], 100
    for g in range(groups):
        base = [f"w{r.randint(0, 400)}" for _ in range(r.choice([3, 5, 30, 120]))]
        for _ in range(r.choice([1, 2, 4, 9])):
            words = list(base)
            for _ in range(r.choice([0, 0, 1, 2, 3, 6])):
                words[r.randrange(len(words))] = f"e{r.randint(0, 10**6)}"
            i += r.choice([-3, 7])
            out.append((i, r.choice([" ", "\n"]).join(words)))
    seen = {}
    for i, t in out:
        seen[i] = t
    return list(seen.items()) + [(9000, ""), (9001, None), (9002, " \n")]


def _set(text):
    w = WORD.findall((text or "").translate(FOLD))
    return {tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set()


def _components(rows):
    sets, parent = [_set(t) for _, t in rows], list(range(len(rows)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a in range(len(rows)):
        for b in range(a):
            if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b]):
                parent[find(a)] = find(b)
    least = {}
    for k, (i, _) in enumerate(rows):
        least[find(k)] = min(i, least.get(find(k), i))
    return {i: (len(sets[k]), least[find(k)], least[find(k)] == i) for k, (i, _) in enumerate(rows)}


@pytest.mark.parametrize("seed", [1, 2])
def test_near_dedup(spark, seed):
    rows = _made(seed)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"], r["kept"]) for r in neardup.link(_docs(spark, rows)).collect()}
    assert got == _components(rows)
    kept = neardup.drop_near_copies(_docs(spark, rows))
    assert kept.columns == ["doc_id", "text", "cls", "n"] and {r["doc_id"] for r in kept.collect()} == {i for i, v in got.items() if v[2]}


def test_large_clusters_in_blocks(spark, monkeypatch):
    monkeypatch.setattr(neardup, "BLOCK", 8)
    r, base = random.Random(4), [f"w{k}" for k in range(100)]
    rows = [(0, " ".join(base[::-1])), (50, " ".join(base))]
    for i in range(1, 40):
        words = list(base)
        # the base is like every edit, the edits are hardly like each other
        for k in r.sample(range(100), 2 if i % 3 else 3):
            words[k] = f"e{i}_{k}"
        rows.append((i, " ".join(words)))
    rows += [(500 + i, " ".join([f"far{i}_{k}" for k in range(30)] + base[:60])) for i in range(6)]
    rows = list(dict(rows).items())
    got = {x["doc_id"]: (x["n_shingles"], x["component_id"], x["kept"]) for x in neardup.link(_docs(spark, rows)).collect()}
    assert got == _components(rows)


@pytest.mark.parametrize("copies_of_a_class", [8, neardup.COPIES])
def test_chained_clusters_cost_their_groups(spark, monkeypatch, copies_of_a_class):
    monkeypatch.setattr(neardup, "BLOCK", 8)
    monkeypatch.setattr(neardup, "COPIES", copies_of_a_class)
    words = [f"w{k}" for k in range(9000)]
    # each is like the next at about 0.59: candidates all along, hardly a link
    rows = [(i, " ".join(words[25 * i : 25 * i + 100])) for i in range(300)] + [(1000 + i, " ".join(words[25 * i + 2 : 25 * i + 100])) for i in range(0, 300, 50)]
    seen, own = [], neardup._meetings

    def meetings(*a):
        seen.append(out := own(*a).persist())
        return out

    monkeypatch.setattr(neardup, "_meetings", meetings)
    got = {x["doc_id"]: (x["n_shingles"], x["component_id"], x["kept"]) for x in neardup.link(_docs(spark, rows)).collect()}
    assert got == _components(rows) and sum(not v[2] for v in got.values()) == 6
    copies = seen[0].count()
    # one cluster's square of blocks would copy every set 150 times; by stars it is the leaders of each, and a cluster as a whole stays below its bound
    assert 0 < copies < (20 if copies_of_a_class == 8 else neardup.COPIES) * len(rows)


def test_rows_without_ids_are_linked(spark):
    base = [f"w{k}" for k in range(27)]
    near, other = " ".join([*base[:26], "x"]), " ".join(f"v{k}" for k in range(20))
    rows = [(5, " ".join(base)), (None, near), (None, other), (None, other + " y"), (7, ""), (None, None), (9, other[:40]), (3, near), (3, near), (3, " ".join(base) + " z")]
    got = Counter((x["doc_id"], x["n_shingles"], x["component_id"], x["kept"]) for x in neardup.link(_docs(spark, rows)).collect())
    assert got == Counter({(5, 23, 3, False): 1, (None, 23, 3, False): 1, (None, 16, None, True): 1, (None, 17, None, True): 1, (7, 0, 7, True): 1, (None, 0, None, True): 1, (9, len(_set(other[:40])), 9, True): 1, (3, 23, 3, True): 2, (3, 24, 3, True): 1})
    left = [(x["doc_id"], x["text"]) for x in neardup.drop_near_copies(_docs(spark, rows)).collect()]
    # one of the two without an id, one text of id 3 (as often as it occurs)
    assert sum(t in (other, other + " y") for _, t in left) == 1 and len({t for i, t in left if i == 3}) == 1 and not any(i == 5 for i, _ in left)
    assert (7, "") in left and (None, None) in left
    text_ids = _docs(spark, [(1, "a b c d e f g h"), (2, "a b c d e f g h"), (3, "q")]).withColumn("doc_id", F.concat(F.lit("k"), "doc_id"))
    assert {(x["doc_id"], x["component_id"]) for x in neardup.link(text_ids).collect()} == {("k1", "k1"), ("k2", "k1"), ("k3", "k3")}


def test_near_dedup_odd_tables(spark):
    assert neardup.link(_docs(spark, [(1, "a")]).limit(0)).count() == 0
    nulls = _docs(spark, [(1, None), (2, ""), (3, "a b")])
    assert sorted((r["doc_id"], r["n_shingles"], r["kept"]) for r in neardup.link(nulls).collect()) == [(1, 0, True), (2, 0, True), (3, 1, True)]
    twice = _docs(spark, [(1, "a b c d e f"), (1, "a b c d e f"), (None, "q r s")])
    assert neardup.link(twice).count() == 3
    alike = neardup._linked([np.array([1, 2, 3], np.uint64), np.array([1, 2, 3, 4], np.uint64)])[0]
    assert alike[0, 1] and alike[1, 0]


def test_components_both_ways(spark, monkeypatch):
    r = random.Random(5)
    pairs = [(r.randint(0, 300), r.randint(0, 300)) for _ in range(200)] + [(k, k + 1) for k in range(1000, 1030)]
    df = spark.createDataFrame(pairs, "a long, b long")
    small = {x["node"]: x["component"] for x in graph.components(df).collect()}
    monkeypatch.setattr(graph, "ONE_TASK", 0)
    assert small == {x["node"]: x["component"] for x in graph.components(df).collect()}
    assert small[1030] == 1000


def test_circulant_signatures_estimate_likeness():
    r = np.random.default_rng(6)
    a, b = r.integers(0, 2**63, 600).astype(np.uint64), r.integers(0, 2**63, 200).astype(np.uint64)
    both = np.concatenate([a, np.concatenate([a[:400], b])])
    s = neardup.signatures(both, np.array([0, 600]), 1024)
    assert abs((s[0] == s[1]).mean() - 400 / 800) < 0.06


def _removed(rows, n):
    seen, out = {}, {}
    for i, t in sorted(rows, key=lambda x: x[0]):
        w, gone = WORD.findall(t or ""), set()
        for k in range(len(w) - n + 1):
            if seen.setdefault(tuple(w[k : k + n]), i) < i:
                gone |= set(range(k, k + n))
        out[i] = (len(w), len(gone), " ".join(x for k, x in enumerate(w) if k not in gone))
    return out


@pytest.mark.parametrize(("window", "chunk"), [(3, 200), (13, 1 << 20)])
def test_substring_dedup(spark, window, chunk):
    r = random.Random(7)
    passage = [f"p{k}" for k in range(40)]
    rows = [(i, r.choice([" ", "  ", "\n"]).join([f"w{r.randint(0, 60)}" for _ in range(r.randint(0, 30))] + (passage[r.randint(0, 10) :] if i % 3 == 0 else []) + [f"w{r.randint(0, 60)}" for _ in range(r.randint(0, 5))])) for i in range(60)]
    rows += [(90, ""), (91, None), (92, rows[3][1])]
    want = _removed(rows, window)
    got = {x["doc_id"]: x for x in substring.measure(_docs(spark, rows), window=window, chunk_bytes=chunk).collect()}
    for i, (n, gone, kept) in want.items():
        assert (got[i]["n_words"], got[i]["n_removed"], got[i]["kept"]) == (n, gone, kept)
        spans = [(s["begin"], s["end"]) for s in got[i]["removed"]]
        assert sum(b - a for a, b in spans) == gone and all(x[1] < y[0] for x, y in zip(spans, spans[1:], strict=False))
    cut = {x["doc_id"]: x for x in substring.remove(_docs(spark, rows), length_col="n", window=window, chunk_bytes=chunk).collect()}
    for i, text in rows:
        assert WORD.findall(cut[i]["text"] or "") == want[i][2].split(" ") or not want[i][2]
        assert cut[i]["text"] == text if not want[i][1] else cut[i]["n"] == len(cut[i]["text"])


def test_substring_odd_tables(spark):
    words = " ".join(f"w{k}" for k in range(20))
    rows = _docs(spark, [(1, words), (1, words), (None, words), (2, words + " " + words)])
    got = Counter((x["doc_id"], x["n_removed"]) for x in substring.measure(rows).collect())
    # a text twice in a row: the windows over the seam are new, but all words lie in old ones too
    assert got == Counter({(1, 0): 2, (None, 20): 1, (2, 40): 1})
    with pytest.raises(TypeError):
        substring.measure(rows.withColumn("doc_id", F.col("doc_id").cast("string")))
    assert substring.measure(rows.limit(0)).count() == 0 and substring.remove(rows.limit(0)).count() == 0


@pytest.mark.parametrize(("kind", "hot"), [("long", False), ("long", True), ("string", False)])
def test_lm_scores(spark, monkeypatch, kind, hot):
    r = random.Random(8)
    rows = [(i, " ".join(r.choice("abcdefgh" if i % 2 else "hijklmno") for _ in range(r.randint(0, 25)))) for i in range(30)] + [(90, None), (None, "a b")]
    # one id with most of the text, in rows of its own, some of them equal
    rows += [(4, "k l m " * (k % 5)) for k in range(60)] if hot else []
    chosen = {i for i in range(0, 30, 4)}
    target = spark.createDataFrame([(i,) for i in sorted(chosen)] + [(None,)], "x long")
    words = {k: WORD.findall(t or "") for k, (_, t) in enumerate(rows)}

    def counts(which):
        c, h, p = Counter(), Counter(), Counter()
        for k in which:
            before = "<"
            for w in [*words[k], ">"] if words[k] else []:
                c[w] += 1
                h[before] += 1
                p[before, w] += 1
                before = w
        return c, h, p

    members = [k for k, (i, _) in enumerate(rows) if i in chosen]
    every, some = counts(words), counts(members)

    def loss(m, k, left_out):
        c, h, p = (x - y if left_out else x for x, y in zip(m, counts([k]), strict=True))
        n, before, out, w = sum(c.values()), "<", 0.0, [*words[k], ">"]
        for x in w:
            single = (c[x] + 1) / (n + len(every[0]))
            out -= math.log(lmscore.LAMBDA * p[before, x] / h[before] + (1 - lmscore.LAMBDA) * single if h[before] else single)
            before = x
        return out / len(w)

    docs = _docs(spark, rows).withColumn("doc_id", F.col("doc_id").cast(kind))
    got = lmscore.score(docs, target, chunk_bytes=300)
    assert got.schema["doc_id"].dataType.simpleString() == docs.schema["doc_id"].dataType.simpleString()
    tidy = lambda x: None if x is None else round(x, 9)
    want = Counter()
    for k, (i, _) in enumerate(rows):
        a, b = (loss(some, k, i in chosen), loss(every, k, True)) if words[k] else (None, None)
        want[None if i is None else str(i), len(words[k]), tidy(a), tidy(b)] += 1
    assert Counter((None if x["doc_id"] is None else str(x["doc_id"]), x["n_words"], tidy(x["target_loss"]), tidy(x["background_loss"])) for x in got.collect()) == want
    assert lmscore.score(docs.limit(0), target).count() == 0
    if hot:
        monkeypatch.setattr(lmscore, "HOT_IDS", 0)
        assert lmscore.score(docs, target, chunk_bytes=300).count() == len(rows)


def test_lm_scores_without_words_and_of_a_whole_model(spark):
    target = spark.createDataFrame([(1,)], "x long")
    rows = lmscore.score(_docs(spark, [(1, None), (2, ""), (None, " \n"), (1, " ")]), target).collect()
    assert len(rows) == 4 and all(r["n_words"] == 0 and r["score"] is None and r["background_loss"] is None for r in rows)
    # after each word all probabilities add up to one
    pair, history, word = np.array([3.0, 1.0, 0.0]), np.full(3, 4.0), np.array([5.0, 2.0, 3.0])
    assert np.exp(-lmscore.losses(pair, history, word, 10.0, 3.0)).sum() == pytest.approx(1.0)


def test_hashes_travel_whole():
    r = np.random.default_rng(3)
    for values in (np.unique(r.integers(0, 2**64, 5000, dtype=np.uint64)), np.array([0, 2**64 - 1], np.uint64), np.zeros(0, np.uint64)):
        a, b = np.arange(len(values), dtype=np.uint32), np.arange(len(values), dtype=np.uint8)
        back = lmscore.unpacked(lmscore.packed(values, a, a, b))
        assert all((x == y).all() for x, y in zip(back, (values, a, a, b), strict=True))


def test_blobs_grow_as_the_table_does():
    (a, b), (c, d) = substring.sizes(1e12, 1000), substring.sizes(1e14, 1000)
    assert 90 < c * d / (a * b) < 110 and substring.sizes(1e6, 8) == (8, 2) and substring.sizes(1e6, 8, 1000)[0] == 1000


def test_lm_counts_beyond_32_bits():
    # three chunks of keys 0 and 1, 1, 0
    place, most = np.array([0, 1, 1, 0]), 2**32 - 1
    replies = lmscore.replies_of(place, np.array([most, 5, most, most], np.uint32), np.array([3, 0, 0, most], np.uint32), np.array([2, 3]))
    assert [lmscore.counts_in(x).tolist() for x in replies] == [[[2 * most, most + 5], [most + 3, 0]], [[most + 5], [0]], [[2 * most], [most + 3]]]


def test_pipeline(spark, sf_dir):
    import corpus_pipeline
    from devfed.llm import quality

    docs, names = spark.read.parquet(f"{sf_dir}/documents.parquet"), ["quality_rules", "near_dedup", "substring_dedup", "packing"]
    assert [n for n, _ in corpus_pipeline.STAGES] == names and corpus_pipeline.ORACLE_SQL is None
    pieces = corpus_pipeline.run(spark, sf_dir).select("doc_id", "start", "length", "doc_tokens").collect()
    good = {r["doc_id"]: r["text"] for r in docs.collect()}
    keep = {r["doc_id"] for r in quality.measure(docs).where("kept").collect()}
    rows = [(i, t) for i, t in good.items() if i in keep]
    rows = [(i, t) for i, t in rows if _components(rows)[i][2]] if len(rows) < 5 else [x for x, v in zip(rows, _components(rows).values(), strict=True) if v[2]]
    assert {p["doc_id"] for p in pieces} == {i for i, _ in rows}
    assert sum(p["length"] for p in pieces) == sum({p["doc_id"]: p["doc_tokens"] for p in pieces}.values())
    left = _removed(rows, substring.WINDOW)
    import public_tokenizers
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    sizes = {p["doc_id"]: p["doc_tokens"] for p in pieces}
    for i, _ in rows[:40]:
        assert sizes[i] == len(library.encode(left[i][2], add_special_tokens=False).ids) + 1


def test_queries_match_sql(spark, sf_dir):
    import duckdb

    con = duckdb.connect()
    for name in ("documents", "pages", "labels"):
        con.execute(f"CREATE VIEW {name} AS SELECT * FROM '{sf_dir}/{name}.parquet'")
    for name, text in queries.ORACLES.items():
        df, found = queries.QUERIES[name](spark, sf_dir), con.execute(text)
        columns = [d[0] for d in found.description]
        assert sorted(df.columns) == sorted(columns)
        assert sorted(map(str, (tuple(r) for r in df.select(*columns).collect()))) == sorted(map(str, found.fetchall())), name


def test_packing_is_shared_by_queries(spark, sf_dir):
    assert set(queries.QUERIES) == {f"op{k}_{n}" for k, n in enumerate(("packing", "html_text", "byte_bpe", "near_dedup", "url_filter", "fingerprints", "substring_dedup", "lm_scoring", "token_counts", "quality_rules"), 1)}
    assert packing.CAPACITY == 2048
