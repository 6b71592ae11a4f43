import numpy as np
import pytest

from devfed.operators import baselines, blocks, localtrain, rounds, splitter, weighting
from devfed.operators.rounds import FedConfig
from devfed.plans import plan_checks

FEATURES = ["x1", "x2"]


def _rows(spark, n=600, clients=6, seed=1):
    r = np.random.default_rng(seed)
    x = r.normal(size=(n, 2))
    y = (x[:, 0] - 0.5 * x[:, 1] + r.normal(scale=0.5, size=n) > 0).astype(float)
    client = np.minimum((np.arange(n) * clients) // n, clients - 1)
    rows = [(int(i), int(c), int(c) % 2, int(i) % 2, float(a), float(b), float(l)) for i, (c, (a, b), l) in enumerate(zip(client, x, y, strict=True))]
    return spark.createDataFrame(rows, "k long, client_id int, subserver_id int, cluster_id int, x1 double, x2 double, label double")


@pytest.fixture(scope="module")
def rows(spark):
    return _rows(spark).persist()


@pytest.fixture(scope="module")
def held(rows):
    return blocks.to_blocks(rows, FEATURES, order=["k"], block_rows=37).persist()


def test_averaging_one_whole_step_is_a_pooled_step(rows, held):
    cfg = FedConfig(rounds=3, epochs=1, lr=0.5).fedavg()
    assert np.allclose(rounds.train(held, 3, cfg).vectors, baselines.pooled(rows, FEATURES, 3, 0.5), atol=1e-9)
    assert np.allclose(baselines.fedsgd(rows, FEATURES, 3, 0.5), baselines.pooled(rows, FEATURES, 3, 0.5), atol=1e-9)


def test_one_subserver_equals_two_tiers(rows, held):
    one = blocks.to_blocks(rows.withColumn("subserver_id", rows["client_id"] * 0), FEATURES, order=["k"])
    cfg = FedConfig(rounds=2, epochs=2, lr=0.5)
    assert np.allclose(rounds.train(one, 3, cfg, three_tier=True).vectors, rounds.train(held, 3, cfg).vectors, atol=1e-12)
    avg = cfg.fedavg()
    assert np.allclose(rounds.train(held, 3, avg, three_tier=True).vectors, rounds.train(held, 3, avg).vectors, atol=1e-12)


def test_frame_merge_equals_driver_merge(held):
    for three in (False, True):
        a = rounds.train(held, 3, FedConfig(rounds=2, epochs=2, lr=0.5, engine="driver"), three_tier=three)
        b = rounds.train(held, 3, FedConfig(rounds=2, epochs=2, lr=0.5, engine="frame"), three_tier=three)
        assert np.allclose(a.vectors, b.vectors, atol=1e-10)


def test_blocks_keep_all_rows_and_kernels_agree(rows, held):
    assert held.agg({"n": "sum"}).first()[0] == rows.count()
    own = rows.where("client_id = 0").orderBy("k").toPandas()
    x, y = np.column_stack([np.ones(len(own)), own[FEATURES]]), own["label"].to_numpy()
    whole = localtrain.sgd(x, y, [0, 0, 0], 3, 0.5)
    assert np.allclose(whole, localtrain.sgd_stream([(x[:40], y[:40]), (x[40:], y[40:])], [0, 0, 0], 3, 0.5))
    from pyspark.sql import functions as F

    packed = rows.where("client_id = 0").agg(F.collect_list(F.struct(F.array(F.lit(1.0), "x1", "x2").alias("x"), F.col("label").alias("y"))).alias("r"))
    hof = packed.select(localtrain.hof_train(F.col("r"), [0, 0, 0], 3, 0.5).alias("w")).first()["w"]
    assert np.allclose(whole, hof)


def test_mini_batches_are_repeatable_and_use_every_row():
    r = np.random.default_rng(3)
    x, y = r.normal(size=(101, 2)), (r.random(101) > 0.5).astype(float)
    a = localtrain.sgd(x, y, [0, 0], 2, 0.1, batch=10, seed=4)
    assert np.array_equal(a, localtrain.sgd(x, y, [0, 0], 2, 0.1, batch=10, seed=4))
    assert not np.array_equal(a, localtrain.sgd(x, y, [0, 0], 2, 0.1, batch=10, seed=5))
    for loss in localtrain.SLOPES:
        assert np.isfinite(localtrain.sgd(x, y, [0, 0], 2, 0.1, loss=loss)).all()


def test_a_round_moves_no_rows(held):
    local = rounds._local(held, {-1: np.zeros(3)}, FedConfig(), None)
    held.count()
    plan_checks.assert_no_exchange(local)
    plan_checks.assert_no_row_egress(local)
    plan_checks.assert_no_row_udf(local)


def test_quorum_resume_and_ledger(spark, held, tmp_path):
    result = rounds.train(held, 3, FedConfig(rounds=3, epochs=1, quorum=0.5))
    assert len(result.models) == 3
    assert result.ledger.agg({"messages": "sum"}).first()[0] == 3 * 2 * 3
    path = str(tmp_path / "history")
    whole = rounds.train(held, 3, FedConfig(rounds=4, epochs=1))
    rounds.train(held, 3, FedConfig(rounds=2, epochs=1, history_path=path))
    rest = rounds.train(held, 3, FedConfig(rounds=4, epochs=1, history_path=path))
    assert rest.first_round == 3 and np.allclose(rest.weights, whole.weights)
    assert result.history(spark).count() == 3


def test_early_stop_and_wrong_settings(held):
    assert len(rounds.train(held, 3, FedConfig(rounds=5, tol=1e9)).vectors) == 1
    for wrong in ({"client_rule": "none"}, {"local_mode": "x"}, {"quorum": 0}, {"rounds": 0}, {"loss": "x"}, {"sub_share": "x"}, {"engine": "x"}):
        with pytest.raises(ValueError):
            FedConfig(**wrong)


def test_local_only_and_client_rounds(held):
    alone = baselines.local_only(held, 3, FedConfig(rounds=2, epochs=2, lr=0.5)).collect()
    assert len(alone) == 6
    assert rounds.train(held, 3, FedConfig(rounds=1, epochs=1, client_rounds=3)).weights.shape == (3,)
    assert set(baselines.ablations(FedConfig())) >= {"neither", "split_only", "both_inverse"}


def test_experiments_are_registered_in_full(spark, monkeypatch):
    from devfed import queries
    from devfed.plans import workloads

    runs = []

    def run(spark, sf_dir, configs, scheme="attribute", k=100, q=None, scale="global", **_):
        runs.append((scheme, q, configs))
        rows = [(m, c.rounds, *[0.5] * 6) for m, c in configs.items()]
        return {}, spark.createDataFrame(rows, "method string, round long, accuracy double, precision double, recall double, f1 double, ks double, logloss double")

    monkeypatch.setattr(workloads, "late_shipment_run", run)
    for name in ("experiment_two_tier", "experiment_three_tier"):
        assert queries.QUERIES[name](spark, "").count() > 0
    grid = queries.QUERIES["ablation_grid"](spark, "")
    assert {c.rounds for _, _, configs in runs[:2] for c in configs.values()} == {400}
    assert {c.rounds for _, _, configs in runs[2:] for c in configs.values()} == {20}
    assert {(s, q) for s, q, _ in runs[2:]} == {(s, q) for s in workloads.SCHEMES for q in (None, 5)}
    assert grid.count() == grid.select("scheme", "tiers", "method").distinct().count() == sum(len(configs) for _, _, configs in runs[2:])
    three = next(configs for _, q, configs in runs[2:] if q == 5)
    assert {(c.client_rule, c.subserver_rule, c.server_rule) for c in three.values()} >= {tuple(r if k == t else "samples" for k in range(3)) for r in ("proportional", "inverse", "complement", "uniform") for t in range(3)}
    # with and without splitting, where a rule at that tier alone can act
    assert {c.split for c in three.values() if (c.client_rule, c.server_rule) == ("samples", "inverse")} == {True, False}


def test_configurations_side_by_side_equal_runs_one_by_one(spark, held, monkeypatch):
    configs = {"a": FedConfig(rounds=3, epochs=2), "b": FedConfig(rounds=2, epochs=1).fedavg(), "c": FedConfig(rounds=2, epochs=1, quorum=0.5, sub_rounds=2), "d": FedConfig(rounds=2, epochs=2, loss="hinge"), "e": FedConfig(rounds=2, epochs=2, batch_size=20, shuffle=False), "f": FedConfig(rounds=2, epochs=1, local_mode="gradient")}
    for three in (False, True):
        together = rounds.simulate(held, 3, configs, three)
        for name, cfg in configs.items():
            alone = rounds.train(held, 3, cfg, three)
            assert np.allclose(together[name].vectors, alone.vectors) and sorted(together[name].ledger.collect()) == sorted(alone.ledger.collect())
    monkeypatch.setattr(rounds, "SIMULATED_BYTES", 0)
    assert np.allclose(rounds.simulate(held, 3, configs)["a"].vectors, rounds.train(held, 3, configs["a"]).vectors)


def test_stacked_clusters_descend_as_each_does(monkeypatch):
    r = np.random.default_rng(5)
    clusters = []
    for n in (1, 3, 3, 50, 55, 400, 7):
        x, y = r.normal(size=(n, 4)), (r.random(n) > 0.5).astype(float)
        clusters.append([(x[: n // 2], y[: n // 2]), (x[n // 2 :], y[n // 2 :])] if n > 5 else [(x, y)])
    w = r.normal(size=(len(clusters), 4))
    for size in (1 << 20, 1000):
        monkeypatch.setattr(localtrain, "STACK_BYTES", size)
        held = localtrain.stacks(clusters)
        assert sorted(np.concatenate([h[0] for h in held]).tolist()) == list(range(len(clusters)))
        for loss in localtrain.SLOPES:
            got = localtrain.sgd_stacked(held, w, 5, 0.3, loss)
            assert np.allclose(got, [localtrain.sgd_stream(c, w[k], 5, 0.3, loss=loss) for k, c in enumerate(clusters)])


def test_early_stop_leaves_its_history(spark, held, tmp_path):
    path = str(tmp_path / "h")
    rounds.train(held, 3, FedConfig(rounds=9, epochs=1, tol=1e9, history_path=path))
    assert spark.read.parquet(path).count() == 1
    assert rounds.train(held, 3, FedConfig(rounds=2, epochs=1, history_path=path)).first_round == 2


def test_members_are_trained_once_a_round_and_their_owners_need_not_be_known(held, monkeypatch):
    seen, own = [], weighting.merge

    def merge(members, *a, **k):
        merged = own(members, *a, **k)
        seen.append(merged._jdf.queryExecution().optimizedPlan().toString())
        return merged

    monkeypatch.setattr(weighting, "merge", merge)
    for rule in ("proportional", "inverse"):
        rounds.train(held, 3, FedConfig(rounds=1, epochs=1, engine="frame", server_rule=rule))
    assert seen and all("MapInArrow" not in p and "Window" not in p for p in seen)
    cfg = FedConfig(rounds=3, epochs=1, quorum=0.5, engine="frame")
    want = rounds.train(held, 3, cfg)
    monkeypatch.setattr(rounds, "DRIVER_CLIENTS", 2)
    assert np.allclose(rounds.train(held, 3, cfg).vectors, want.vectors)


def test_batches_in_stored_order():
    r = np.random.default_rng(3)
    x, y, w = r.normal(size=(10, 2)), (r.random(10) > 0.5).astype(float), np.zeros(2)
    for rows in (slice(0, 4), slice(4, 8), slice(8, 10)):
        w = w - 0.1 * localtrain.gradient(x[rows], y[rows], w)
    assert np.allclose(localtrain.sgd(x, y, np.zeros(2), 1, 0.1, 4, shuffle=False), w)
    assert np.allclose(localtrain.sgd_stream([(x, y)], np.zeros(2), 1, 0.1, 4, shuffle=False), w)


def test_strata_are_a_part_of_each_cluster(spark):
    df = spark.range(400).selectExpr("id AS k", "CAST(id % 2 AS INT) AS client_id", "CAST(id % 3 AS INT) AS cluster_id", "rand(3) AS x1", "CAST(id % 5 < 2 AS DOUBLE) AS label")
    n = lambda f: rounds.prepare(df, ["x1"], ["k"], FedConfig(strata_fraction=f)).groupBy("client_id", "cluster_id").agg({"n": "sum"}).toPandas().sort_values(["client_id", "cluster_id"])["sum(n)"].tolist()
    assert n(1.0) == df.groupBy("client_id", "cluster_id").count().orderBy("client_id", "cluster_id").toPandas()["count"].tolist()
    assert n(0.1) == [-(-c // 10) for c in n(1.0)]
    with pytest.raises(ValueError):
        FedConfig(strata_fraction=0)


def test_splitting_packs_the_blocks_of_split_rows(spark):
    # rows were dealt out and ordered a second time to be packed
    r = np.random.default_rng(11)
    rows = [(c, c % 2, int(k), *map(float, r.normal(size=2) + 6 * (k % 3)), float(r.integers(2))) for c in range(5) for k in r.permutation(700)]
    df = spark.createDataFrame(rows, "client_id int, subserver_id int, k long, a double, b double, label double")
    options = {"min_rows": 100, "most": 4}
    own = splitter.split_blocks(df, ["a", "b"], ["k"], block_rows=150, **options)
    told = blocks.to_blocks(splitter.split_clients(df, ["a", "b"], ["k"], **options), ["a", "b"], order=["k"], block_rows=150)
    assert sorted(map(tuple, own.collect())) == sorted(map(tuple, told.select(*own.columns).collect()))
    assert own.columns == blocks.NAMES and max(x["cluster_id"] for x in own.collect()) > 0
    # sub-servers may be left out, and all blocks of a client lie in one task in order
    parts = splitter.split_blocks(df.drop("subserver_id"), ["a", "b"], ["k"], block_rows=150, **options).rdd.glom().collect()
    seen = [(x["client_id"], x["cluster_id"], x["block"]) for p in parts for x in p]
    assert all([y[:3] for y in p] == sorted(y[:3] for y in p) for p in [[(x["client_id"], x["cluster_id"], x["block"]) for x in p] for p in parts])
    assert len({c for c, *_ in seen}) == 5 and sum(len({c for c, *_ in map(tuple, p)}) for p in parts) == 5
    plan = rounds.prepare(df, ["a", "b"], ["k"], FedConfig(), **options)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange") == 1


def test_samples_of_split_rows_are_packed_at_once(spark):
    # the sample was drawn from rows that were split once to be counted and once more to be taken
    r = np.random.default_rng(12)
    rows = [(c, int(k), float(k) / 4, *map(float, r.normal(size=2) + 6 * (k % 3)), float(r.integers(2))) for c in range(4) for k in r.permutation(500 + c)]
    df = spark.createDataFrame(rows, "client_id int, k long, d double, a double, b double, label double")
    options, key = {"min_rows": 100, "most": 4}, ["k", "d"]
    for fraction, seed in ((0.25, 0), (0.001, 3)):
        own = rounds.prepare(df, ["a", "b"], key, FedConfig(strata_fraction=fraction, seed=seed), **options)
        assert own._jdf.queryExecution().executedPlan().toString().count("Exchange") == 1
        told = splitter.stratified_sample(splitter.split_clients(df, ["a", "b"], key, **options), fraction, key=key, seed=seed)
        told = blocks.to_blocks(told, ["a", "b"], order=key)
        assert sorted(map(tuple, own.collect())) == sorted(map(tuple, told.select(*own.columns).collect()))
