import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from devfed.operators import weighting


@settings(max_examples=60, deadline=None)
@given(st.integers(1, 8), st.integers(1, 5), st.integers(0, 10**6), st.sampled_from(weighting.RULES))
def test_weights_are_a_partition_of_one_and_merge_stays_in_the_hull(n, d, seed, rule):
    r = np.random.default_rng(seed)
    v, rows = r.normal(size=(n, d)), r.integers(1, 100, n).astype(float)
    w = weighting.weights_np(v, rows, rule)
    assert (w >= -1e-12).all() and abs(w.sum() - 1) < 1e-9
    merged = weighting.merge_np(v, rows, rule)
    assert (merged >= v.min(0) - 1e-9).all() and (merged <= v.max(0) + 1e-9).all()


def test_two_members_swap_shares_under_the_printed_rule():
    v, rows = np.array([[0.0, 1.0], [2.0, 5.0]]), np.array([30.0, 10.0])
    assert np.allclose(weighting.weights_np(v, rows, "proportional"), [0.25, 0.75])
    for rule in ("inverse", "complement", "samples"):
        assert np.allclose(weighting.weights_np(v, rows, rule), [0.75, 0.25])


def test_equal_members_and_single_members_fall_back_to_shares():
    same = np.ones((3, 2))
    for rule in weighting.RULES:
        assert np.allclose(weighting.merge_np(same, np.array([1.0, 2, 3]), rule), [1, 1])
        assert np.allclose(weighting.weights_np(np.array([[3.0]]), np.array([7.0]), rule), [1])
    assert np.allclose(weighting.weights_np(same, np.array([1.0, 2, 1]), "proportional"), [0.25, 0.5, 0.25])
    with pytest.raises(ValueError):
        weighting.weights_np(same, np.ones(3), "other")


def test_frame_equals_numpy_below_several_parents(spark):
    r = np.random.default_rng(5)
    rows = [(int(i % 3), int(i), int(r.integers(1, 50)), [float(x) for x in r.normal(size=4)]) for i in range(12)]
    df = spark.createDataFrame(rows, "p int, m int, n_rows long, w array<double>")
    for rule in weighting.RULES:
        found = {x["p"]: x["w"] for x in weighting.merge(df, ["p"], rule=rule).collect()}
        for p in range(3):
            own = [x for x in rows if x[0] == p]
            assert np.allclose(found[p], weighting.merge_np(np.array([x[3] for x in own]), np.array([x[2] for x in own], float), rule))
    total = float(sum(x[2] for x in rows))
    found = {x["p"]: x["w"] for x in weighting.merge(df, ["p"], share="global").collect()}
    own = [x for x in rows if x[0] == 0]
    assert np.allclose(found[0], weighting.merge_np(np.array([x[3] for x in own]), np.array([x[2] for x in own], float), total=total))
