"""Sums of all pairs' distances by cubes, and what of them the splitter needs."""

import time

import duckdb
import numpy as np
import pandas as pd
import pytest

from devfed.operators import pairwise, splitter


def _rows(n, seed=0):
    r = np.random.default_rng(seed)
    return splitter.standardized(np.column_stack([r.integers(1, 51, n), r.uniform(900, 1e5, n).round(2), r.integers(0, 2500, n), r.integers(0, 2400, n)]).astype(float))


def _all_pairs(z, monkeypatch):
    with monkeypatch.context() as m:
        m.setattr(pairwise, "LEAST", 10**9)
        return splitter.mean_pairwise(z)


@pytest.mark.parametrize("width", [1, 2, 3, 4])
def test_cubes_give_the_sum_of_all_pairs(monkeypatch, width):
    z = _rows(16_000)[:, :width]
    found = pairwise.total(*splitter.distinct(z))
    assert splitter.mean_pairwise(z) == pytest.approx(_all_pairs(z, monkeypatch), rel=1e-7)
    # one column of fifty values has fifty different rows
    assert (found is None) == (width == 1)


def test_cubes_count_repeated_rows(monkeypatch):
    z = _rows(14_000, 1)
    many = z[np.repeat(np.arange(len(z)), np.random.default_rng(2).integers(1, 9, len(z)))]
    assert splitter.mean_pairwise(many) == pytest.approx(_all_pairs(many, monkeypatch), rel=1e-7)


def test_uneven_rows_are_right(monkeypatch):
    # a few far rows leave nearly all others in one cube; a cluster of normal rows; rows along a line
    r = np.random.default_rng(3)
    tight = np.vstack([r.normal(size=(13_000, 4)), 1e5 * r.normal(size=(5, 4))])
    for z in (tight, r.normal(size=(13_000, 4)), np.exp(r.normal(size=(13_000, 4))), r.normal(size=(13_000, 1)) + 0.05 * r.normal(size=(13_000, 4))):
        assert splitter.mean_pairwise(z) == pytest.approx(_all_pairs(z, monkeypatch), rel=2e-7)


def test_many_different_rows_in_time():
    # 120 000 different rows: all pairs took over half a minute
    z = _rows(120_000, 4)
    splitter.mean_pairwise(z[:20_000])
    began = time.process_time()
    splitter.mean_pairwise(z)
    assert time.process_time() - began < 25


def test_clusters_that_cannot_be_widest_are_not_measured(monkeypatch):
    z = np.random.default_rng(5).normal(size=(4000, 4))
    label = np.arange(4000) // 1000
    z[label == 2] *= 3
    taken, measure = [], splitter.mean_pairwise
    widest = max(measure(z[label == j]) for j in range(4))
    monkeypatch.setattr(splitter, "mean_pairwise", lambda rows, limit=None: taken.append(len(rows)) or measure(rows, limit))
    found = splitter.figures(z, label, np.eye(4))
    assert found["spread_ratio"] == widest / measure(z) and taken == [4000, 1000]
    splitter.figures(z, label, np.eye(4), limit=100)
    assert len(taken) == 2 + 5


def test_clusters_of_equal_rows():
    z = np.repeat(np.eye(4), 5, axis=0)
    assert splitter.figures(z, np.arange(20) // 5, np.eye(4))["spread_ratio"] == 0.0


def test_owners_of_many_rows_as_sql():
    z = _rows(13_000, 6)
    con = duckdb.connect()
    con.register("rows", pd.DataFrame(z, columns=["a", "b", "c", "d"]).reset_index())
    mean = con.execute("SELECT avg(sqrt((p.a-q.a)*(p.a-q.a)+(p.b-q.b)*(p.b-q.b)+(p.c-q.c)*(p.c-q.c)+(p.d-q.d)*(p.d-q.d))) FROM rows p JOIN rows q ON p.index < q.index").fetchone()[0]
    assert pairwise.total(*splitter.distinct(z)) is not None
    assert splitter.mean_pairwise(z) == pytest.approx(mean, rel=1e-7)


def test_bounds_hold_and_settle_what_measuring_says():
    r, told = np.random.default_rng(8), set()
    for k in range(120):
        n, width, parts = int(r.integers(2, 400)), int(r.integers(1, 13)), int(r.integers(1, 5))
        z = splitter.standardized(np.round(r.normal(size=(n, width)) * np.exp(r.normal(size=width)), int(r.integers(0, 4))) + 5 * r.integers(0, 2, size=(n, 1)))
        label = r.integers(0, parts, n) if k % 2 else splitter.assign(z, z[:parts])
        label, mean = np.unique(label, return_inverse=True)[1], splitter.mean_pairwise(z)
        assert splitter._least_mean(z) <= mean <= splitter._most_mean(z)
        centres = np.stack([z[label == j].mean(axis=0) for j in range(label.max() + 1)])
        found = splitter.figures(z, label, centres)
        for accept in splitter.ACCEPT:
            for factors in ((1.2, 0.5), (0.7, 1.0), (0.3, 0.05)):
                sure = splitter.settled(z, label, centres, accept, *factors)
                assert sure is None or sure == splitter.accepted(found, accept, *factors)
                told.add((accept, sure))
    assert told == {(a, s) for a in splitter.ACCEPT for s in (True, False, None)} - {("always", False), ("always", None)}


def test_splits_need_no_measure_where_bounds_settle_them(monkeypatch):
    # owners of the whole method were measured, pair by pair or by cubes, once for each threshold
    z = _rows(20_000, 9)
    label, told = splitter.split_rows(z, (0.5, 0.7), 1000, most=8)
    taken = []
    measure = splitter.mean_pairwise
    monkeypatch.setattr(splitter, "mean_pairwise", lambda rows, limit=None: taken.append(len(rows)) or measure(rows, limit))
    again, report = splitter.split_rows(z, (0.5, 0.7), 1000, most=8, ratios=())
    assert not taken and (label == again).all()
    assert all(report[c] == told[c] for c in ("n_rows", "n_clusters", "accepted", "theta")) and report["spread_ratio"] is None
    # a factor that no bound settles is measured
    factor = told["spread_ratio"] * (1 + 1e-6)
    assert splitter.split_rows(z, (0.5, 0.7), 1000, most=8, spread_factor=factor, ratios=())[1]["accepted"] and taken
    assert not splitter.split_rows(z, (0.5, 0.7), 1000, most=8, spread_factor=told["spread_ratio"] * (1 - 1e-6), ratios=())[1]["accepted"]


def test_equal_clusters_of_two_thresholds_are_judged_once(monkeypatch):
    taken, figures = [], splitter.figures
    monkeypatch.setattr(splitter, "figures", lambda *a, **k: taken.append(1) or figures(*a, **k))
    assert splitter.split_rows(_rows(2000, 10), (0.3, 0.31), 1000, most=3)[1]["theta"] == 0.3 and len(taken) == 1


def test_gaps_alone_need_no_cluster_measured(monkeypatch):
    taken, measure = [], splitter.mean_pairwise
    monkeypatch.setattr(splitter, "mean_pairwise", lambda rows, limit=None: taken.append(len(rows)) or measure(rows, limit))
    report = splitter.split_rows(_rows(2000, 11), (1e-9,), 1, cap=3, accept="gap", ratios=("gap",))[1]
    assert taken == [2000] and report["gap_ratio"] > 0 and report["spread_ratio"] is None
