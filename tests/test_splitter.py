import hashlib
import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from devfed import queries
from devfed.operators import splitter


def test_hand_example():
    z = np.array([[0.0], [1], [2], [10], [11], [20]])
    label, centres = splitter.maxmin(z, 0.4, 10)
    assert centres == [0, 5, 3]
    assert label.tolist() == [0, 0, 0, 2, 2, 1]


def test_growth_rules_on_random_rows():
    z = np.random.default_rng(2).normal(size=(200, 3))
    for theta in (0.3, 0.6, 0.9):
        label, centres = splitter.maxmin(z, theta, 50)
        gap = np.linalg.norm(z[centres[0]] - z[centres[1]])
        for j, c in enumerate(centres[2:], 2):
            assert min(np.linalg.norm(z[c] - z[b]) for b in centres[:j]) > theta * gap
        d = np.stack([np.linalg.norm(z - z[c], axis=1) for c in centres])
        assert (label == d.argmin(axis=0)).all()
        if len(centres) < 50:
            assert d.min(axis=0).max() <= theta * gap
    assert len(splitter.maxmin(z, 0.3, 5, "single_sweep")[1]) <= 5


def test_degenerate_rows():
    assert splitter.maxmin(np.zeros((5, 2)), 0.5)[0].tolist() == [0] * 5
    with pytest.raises(ValueError):
        splitter.maxmin(np.zeros((5, 2)), 1.0)
    for n in (1, 2, 100, 300):
        assert splitter.split_rows(np.random.default_rng(n).normal(size=(n, 2)))[1]["n_clusters"] == 1
    assert splitter.split_rows(np.random.default_rng(1).normal(size=(301, 2)))[1]["accepted"]


def test_accept_tests():
    r = np.random.default_rng(4)
    blobs = np.concatenate([r.normal(size=(60, 2)) * 0.1, r.normal(size=(60, 2)) * 0.1 + 10])
    label, centres = splitter.maxmin(blobs, 0.5, 4)
    found = splitter.figures(blobs, label, blobs[centres])
    assert splitter.accepted(found, "both")
    # a tight blob, and scattered rows that share one cluster
    spread = np.concatenate([r.normal(size=(300, 2)) * 0.01, np.array([[9, 0], [9, 9], [0, 9.5], [13.0, 4]])])
    rejected = np.concatenate([np.zeros(300, int), np.ones(4, int)])
    found = splitter.figures(spread, rejected, np.array([[0.0, 0], [0.001, 0]]))
    assert not splitter.accepted(found, "spread") and not splitter.accepted(found, "gap") and splitter.accepted(found, "always")
    sample = r.normal(size=(3000, 3))
    assert abs(splitter.mean_pairwise(sample, 1000) / splitter.mean_pairwise(sample, 10**6) - 1) < 0.05


def test_complete_linkage_and_best_theta():
    z = np.array([[0.0], [0.1], [5], [5.1], [9], [9.2]])
    label = splitter.complete_linkage(z, 3)
    assert label[0] == label[1] and label[2] == label[3] and label[4] == label[5] and len(set(label)) == 3
    assert len(set(splitter.complete_linkage(np.random.default_rng(0).normal(size=(500, 2)), 4, max_rows=100))) == 4
    rows = np.random.default_rng(6).normal(size=(400, 3))
    best = splitter.split_rows(rows, thetas=(0.5, 0.7, 0.9))[1]
    assert best["theta"] in (0.5, 0.7, 0.9) and best["accepted"]
    assert splitter.split_rows(rows, method="complete_linkage")[1]["n_clusters"] >= 1


def test_all_rows_count_without_a_limit():
    # what an evenly spaced sample of 2000 can't see: every second row lies far off
    z = np.random.default_rng(3).normal(size=(3999, 3))
    z[1::2] += 50
    whole = np.mean([np.sqrt(((z - r) ** 2).sum(axis=1)).sum() / (len(z) - 1) for r in z])
    assert splitter.mean_pairwise(z) == pytest.approx(whole)
    assert splitter.mean_pairwise(z, block=700) == pytest.approx(whole)
    assert splitter.mean_pairwise(z, 2000) < whole / 2
    label = np.arange(len(z)) % 2
    inner = max(splitter.mean_pairwise(z[label == j]) for j in (0, 1))
    assert splitter.figures(z, label, z[:2])["spread_ratio"] == pytest.approx(inner / whole)


def test_complete_linkage_takes_all_rows():
    def greedy(z, clusters):
        d, groups = np.sqrt(((z[:, None] - z[None]) ** 2).sum(axis=2)), [[k] for k in range(len(z))]
        while len(groups) > clusters:
            _, a, b = min((d[np.ix_(groups[a], groups[b])].max(), a, b) for a in range(len(groups)) for b in range(a))
            groups[b] += groups.pop(a)
        return {frozenset(g) for g in groups}

    for seed in range(4):
        z = np.random.default_rng(seed).normal(size=(40, 2))
        label = splitter.complete_linkage(z, 5)
        assert {frozenset(np.flatnonzero(label == j).tolist()) for j in set(label)} == greedy(z, 5)
    # one far row that a sample would miss
    z = np.random.default_rng(5).normal(size=(2501, 2))
    z[4] = 1000
    label = splitter.complete_linkage(z, 2)
    assert (label == label[4]).sum() == 1
    assert splitter.complete_linkage(np.zeros((4, 2)), 2).max() == 1


def test_frame_and_kernel_agree_and_samples_nest(spark):
    r = np.random.default_rng(8)
    rows = [(int(i), int(i % 3), *map(float, v)) for i, v in enumerate(r.normal(size=(300, 2)))]
    df = spark.createDataFrame(rows, "k long, client_id int, x1 double, x2 double")
    found = splitter.maxmin_frame(df, ["x1", "x2"], ["k"], 5, theta=0.4).toPandas().sort_values("k")
    for c in range(3):
        own = found[found["client_id"] == c]
        label, _ = splitter.maxmin(own[["x1", "x2"]].to_numpy(), 0.4, 5)
        assert label.tolist() == own["cluster_id"].tolist()
    split = splitter.split_clients(df, ["x1", "x2"], ["k"], min_rows=50)
    a = {x["k"] for x in splitter.stratified_sample(split, 0.2, key=["k"]).collect()}
    b = {x["k"] for x in splitter.stratified_sample(split, 0.5, key=["k"]).collect()}
    assert a < b
    assert splitter.report(split).first()["clients"] == 3


def test_splitter_queries_take_all_training_rows(spark, sf_dir):
    rows = queries._trained(spark, sf_dir).toPandas()
    sizes = rows.groupby("client_id").size().to_dict()
    assert sum(sizes.values()) == queries._base(spark, sf_dir).where("NOT is_test").count()
    run = lambda name: queries.QUERIES[name](spark, sf_dir).toPandas()
    assert len(run("maxmin_assign")) == len(run("maxmin_kernel")) == len(run("maxmin_single_sweep")) == len(rows)
    kernel, spread, gap = run("maxmin_kernel").groupby("client_id")["cluster_id"].nunique(), *(run(n).set_index("client_id") for n in ("split_accept_spread", "split_accept_gap"))
    assert set(sizes) == set(kernel.index) == set(spread.index) == set(gap.index)
    for client, own in rows.sort_values(queries.KEY).groupby("client_id"):
        x = own[queries.FEW].to_numpy(float)
        z = (x - x.mean(axis=0)) / x.std(axis=0, ddof=1)
        pairs = np.sqrt(((z[:, None] - z[None]) ** 2).sum(axis=2))
        # the farthest row from all centres, by brute force
        centres = [0]
        while len(centres) < 8 and (len(centres) == 1 or pairs[centres].min(axis=0).max() > 0.6 * pairs[0].max()):
            centres.append(int(pairs[centres].min(axis=0).argmax()))
        assert kernel[client] == len(centres)
        label, three = splitter.maxmin(z, 1e-9, 3)
        overall, mean = pairs.sum() / (len(z) * (len(z) - 1)), lambda d: d.sum() / max(1, len(d) * (len(d) - 1))  # noqa: B023
        assert spread.loc[client, "ratio"] == pytest.approx(max(mean(pairs[np.ix_(label == j, label == j)]) for j in range(3)) / overall, abs=2e-6)
        assert gap.loc[client, "ratio"] == pytest.approx(min(pairs[a, b] for a in three for b in three if a < b or a > b) / overall, abs=2e-6)


def test_queries_change_with_the_kernel(spark, sf_dir, monkeypatch):
    run = lambda name: sorted(map(tuple, queries.QUERIES[name](spark, sf_dir).collect()))
    names = ("maxmin_kernel", "maxmin_single_sweep")
    before = [run(n) for n in names]
    # what the workers get is the function of this name
    monkeypatch.setattr(splitter, "_split", lambda rows, features, options: (np.zeros(len(rows), int), {}))
    assert all(run(n) != b for n, b in zip(names, before, strict=True))


def test_whole_method_splits_below_its_gate_too(spark, sf_dir, monkeypatch):
    import duckdb

    # half of the owners have more rows than the gate
    gate = int(queries._trained(spark, sf_dir).groupBy("client_id").count().toPandas()["count"].median())
    monkeypatch.setattr(queries, "GATE", gate)
    con = duckdb.connect()
    for t in ("lineitem", "orders"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    report = queries.split_report(spark, sf_dir)
    assert report.where("accepted").count() > 0 and report.where("NOT accepted").count() > 0
    source, rows = queries._split_ctes_at(gate)
    found = con.execute(queries.sql.training(2, 1, source=source, rows=rows)).fetchall()
    got = [tuple(r) for r in queries._whole(rounds=2, epochs=1)(spark, sf_dir).collect()]
    assert np.allclose(sorted(found), sorted(got), atol=2e-6)


def test_frame_growth_scans_once_a_centre(spark):
    df = spark.range(200).selectExpr("id AS k", "CAST(id % 3 AS INT) AS client_id", "rand(1) AS x1", "rand(2) AS x2")
    scans = lambda n: splitter.maxmin_frame(df, ["x1", "x2"], ["k"], n)._jdf.queryExecution().optimizedPlan().toString().count("Range (")
    assert scans(2) == scans(6) == 1


def test_ranks_by_mark_are_those_of_one_window(spark):
    rows = spark.range(3000).selectExpr("id AS k", "CAST(CASE WHEN id % 10 < 7 THEN NULL ELSE id % 4 END AS INT) AS g")
    found = splitter.ranked(rows, F.md5(F.col("k").cast("string")), 0.13, ["g"], ["k"]).toPandas()
    everyone = rows.toPandas()
    everyone["mark"] = [hashlib.md5(str(k).encode()).hexdigest() for k in everyone["k"]]
    for _, own in everyone.groupby("g", dropna=False):
        want = own.sort_values("mark")["k"].tolist()[: math.ceil(len(own) * 0.13)]
        got = found[found["k"].isin(own["k"])].sort_values("rank")
        assert got["k"].tolist() == want and got["rank"].tolist() == list(range(1, len(want) + 1))


def test_first_centres(spark):
    z = np.random.default_rng(1).normal(size=(50, 2)) + 3
    assert splitter.first_centre(z, "medoid") == int(np.linalg.norm(z - z.mean(axis=0), axis=1).argmin())
    assert splitter.first_centre(z, "hash", [f"{97 * k % 50:02d}" for k in range(50)]) == 0
    with pytest.raises(ValueError):
        splitter.maxmin(z, seed_rule="hash")
