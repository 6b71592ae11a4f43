import numpy as np
import pytest

from devfed import schema
from devfed.operators import commcost, features, metrics, partitioners
from devfed.sources import tables


def _scored(spark, rows):
    return spark.createDataFrame([(float(s), int(y)) for s, y in rows], "score double, label int")


def test_hand_matrix(spark):
    df = _scored(spark, [(0.9, 1), (0.8, 0), (0.5, 1), (0.4, 1), (0.1, 0)])
    found = metrics.indicators(metrics.confusion(df)).first()
    assert (found["tp"], found["fp"], found["tn"], found["fn"]) == (2, 1, 1, 1)
    assert found["accuracy"] == pytest.approx(0.6) and found["f1"] == pytest.approx(found["f1_harmonic"]) == pytest.approx(2 / 3)


def test_curves_of_perfect_constant_reversed_and_tied_scores(spark):
    cases = {"perfect": ([(0.9, 1), (0.8, 1), (0.2, 0)], 1.0, 1.0), "constant": ([(0.5, 1), (0.5, 0), (0.5, 0)], 0.5, 0.0), "reversed": ([(0.1, 1), (0.9, 0)], 0.0, 0.0), "tied": ([(0.5, 1), (0.5, 0), (0.9, 1), (0.1, 0)], 0.875, 0.5)}
    for rows, area, gap in cases.values():
        df = _scored(spark, rows)
        assert metrics.auc(df).first()["auc"] == pytest.approx(area)
        assert metrics.auc(df, method="rank").first()["auc"] == pytest.approx(area)
        assert metrics.ks(df).first()["ks"] == pytest.approx(gap)
    one_class = _scored(spark, [(0.4, 1), (0.6, 1)])
    assert metrics.auc(one_class).first()["auc"] is None and metrics.auc(one_class, method="rank").first()["auc"] is None
    found = metrics.indicators(metrics.confusion(_scored(spark, [(0.1, 0)]))).first()
    assert found["precision"] is None and found["recall"] is None and found["f1"] is None


def test_binned_curve_is_close(spark):
    r = np.random.default_rng(1)
    df = _scored(spark, zip(r.random(500), r.integers(0, 2, 500), strict=True))
    assert metrics.auc(df, bins=1000).first()["auc"] == pytest.approx(metrics.auc(df).first()["auc"], abs=5e-3)


def test_curves_over_ranges_equal_those_of_one_window(spark, monkeypatch):
    r = np.random.default_rng(6)
    rows = [(int(g), float(np.round(v, 2)), int(v + e > 0.5)) for g, v, e in zip(r.integers(0, 3, 2000), r.random(2000), r.normal(size=2000) * 0.3, strict=True)]
    df = spark.createDataFrame(rows, "g int, score double, label int")
    run = lambda by: [sorted(map(tuple, f(df, by).collect())) for f in (metrics.roc, metrics.auc, lambda d, b: metrics.auc(d, b, "rank"), metrics.ks)]
    before = run([]), run(["g"])
    monkeypatch.setattr(metrics, "WINDOW_POINTS", 20)
    assert (run([]), run(["g"])) == before
    assert before[0][1][0][0] == pytest.approx(before[0][2][0][0])


def test_summary_and_targets(spark):
    h = spark.createDataFrame([("a", i, float(v)) for i, v in enumerate([0.1, 0.2, 0.4, 0.8], 1)], "method string, round int, accuracy double")
    s = metrics.round_summary(h, ["accuracy"], q3=True).first()
    assert (s["min"], s["q1"], s["median"], s["max"]) == pytest.approx((0.1, 0.175, 0.3, 0.8)) and s["q3"] == pytest.approx(0.5)
    assert commcost.rounds_to_target(h, "accuracy", 0.4).first()["first_round"] == 3
    assert commcost.rounds_to_target(h, "accuracy", 0.9).first()["first_round"] is None


def test_standardize_and_ranks(spark):
    df = spark.createDataFrame([(i, i % 2, float(i), 5.0) for i in range(20)], "k long, g int, a double, b double")
    z = features.standardize(df, ["a", "b"], ["g"]).toPandas()
    for _, own in z.groupby("g"):
        assert own["a"].mean() == pytest.approx(0) and own["a"].std() == pytest.approx(1) and (own["b"] == 0).all()
    ranked = partitioners.global_rank(df, ["g", "k"]).toPandas().sort_values(["g", "k"])
    assert ranked["rank"].tolist() == list(range(20))
    rows = features.standardize(df, ["a", "b"], axis="row").toPandas()
    assert rows["a"].iloc[0] == pytest.approx(-rows["b"].iloc[0])


def test_partitions_cover_all_rows(spark):
    from pyspark.sql import functions as F

    df = spark.createDataFrame([(i, i * 31 % 97, float(i % 5), i % 2) for i in range(503)], "k1 long, k2 long, x double, label int")
    for dealt in (partitioners.by_attribute(df, "label", 7, ["k1", "k2"]), partitioners.by_range(df, "x", 7, ["k1"]), partitioners.iid(df, 7, F.col("k1") * 7919), partitioners.unequal(df, 7, F.col("k1") * 7919)):
        sizes = [r["count"] for r in dealt.groupBy("client_id").count().orderBy("client_id").collect()]
        assert sum(sizes) == 503 and len(sizes) == 7
    assert sorted(sizes, reverse=True)[0] > 2 * min(sizes)
    salted = partitioners.salted(df.withColumn("client_id", F.lit(3)), 100, F.col("k1"))
    assert salted.select("client_id").distinct().count() == 6 and salted.count() == 503
    assert partitioners.tiers(10, 3)[4] == 1 and partitioners.tiers(10, 5, "block")[9] == 4
    with pytest.raises(ValueError):
        partitioners.tiers(3, 4)


def test_validation(spark):
    good = spark.createDataFrame([(1.0, 1.0), (2.0, 0.0)], "x double, label double")
    assert schema.validate(good, ["x"]).count() == 2
    bad = spark.createDataFrame([(1.0, 1.0), (None, 0.0), (float("nan"), 1.0), (float("inf"), 0.0)], "x double, label double")
    with pytest.raises(ValueError):
        schema.validate(bad, ["x"])
    assert schema.validate(bad, ["x"], nulls="drop").count() == 1
    assert schema.validate(bad, ["x"], nulls="zero").where("x = 0").count() == 3
    with pytest.raises(ValueError):
        schema.validate(good.withColumn("label", good["label"] + 2), ["x"])


def test_client_layout_reads_few_buckets(spark, tmp_path):
    df = spark.createDataFrame([(i % 20, float(i)) for i in range(200)], "client_id int, x double")
    tables.write_clients(df, str(tmp_path / "c"), buckets=8)
    assert tables.read_clients(spark, str(tmp_path / "c"), [3, 4], buckets=8).count() == 20


def test_ks_of_rounds_counts_saturated_scores(spark):
    r = np.random.default_rng(1)
    x, noise = r.normal(size=400) * 50 + 100, r.normal(size=400) * 20
    y = (x + noise > 100).astype(float)
    df = spark.createDataFrame([(float(a), float(b)) for a, b in zip(x, y, strict=True)] * 2, "x1 double, label double").repartition(3)
    vectors = np.array([[0.0, 1.0], [500.0, 3.0], [0.0, -1.0], [0.0, 0.0]])
    got = {q["round"]: q["ks"] for q in metrics.evaluate_rounds(df, ["x1"], np.arange(1, 5), vectors).collect()}
    for k, (b, a) in enumerate(vectors, 1):
        m = b + a * x
        want = max(0.0, *((m[y == 1] >= t).mean() - (m[y == 0] >= t).mean() for t in m))
        assert abs(got[k] - want) < 1e-12
    # one class only
    alone = metrics.evaluate_rounds(df.where("label = 1"), ["x1"], np.arange(1, 5), vectors).collect()
    assert all(q["ks"] == 0 and q["tn"] == 0 for q in alone)


def test_ks_looks_into_few_bins_and_adds_up_cells(spark, monkeypatch):
    r = np.random.default_rng(2)
    x = np.concatenate([r.normal(size=3000), r.normal(size=3000) + 0.4, np.zeros(50)])
    y = np.concatenate([np.zeros(3000), np.ones(3000), r.integers(0, 2, 50)])
    df = spark.createDataFrame([(float(a), float(b)) for a, b in zip(x, y, strict=True)], "x1 double, label double").repartition(3)
    vectors = np.array([[0.0, 1.0], [1e-9, 1e-12], [-3.0, 40.0]])
    want = []
    for b, a in vectors:
        m = b + a * x
        want.append(max((m[y == 1] >= t).mean() - (m[y == 0] >= t).mean() for t in np.unique(m)))
    for held, bits in ((4_000_000, 18), (100, 18), (100, 6), (100, 40)):
        monkeypatch.setattr(metrics, "HELD_CELLS", held)
        monkeypatch.setattr(metrics, "BIN_BITS", bits)
        got = {q["round"]: q["ks"] for q in metrics.evaluate_rounds(df, ["x1"], np.arange(1, 4), vectors).collect()}
        assert [got[k + 1] for k in range(3)] == pytest.approx(want, abs=1e-12)
