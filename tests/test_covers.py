"""Golden vectors, exact covers and invariants of the greedy cover."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from slotlens.functions import covers

# Ten published (median, MAD) pairs.
GOLDEN = np.array([(0.79, 0.04), (0.78, 0.01), (0.77, 0.02), (0.84, 0.04), (0.99, 0.05), (1.30, 0.08), (1.69, 0.09), (1.76, 0.07), (1.69, 0.09), (1.60, 0.11)])


def groups(s0, **how):
    label = covers.greedy(covers.threshold_graph(covers.distances(GOLDEN), s0), **how)
    return sorted(sorted((np.flatnonzero(label == g) + 1).tolist()) for g in range(label.max() + 1))


def test_golden_similarities():
    with np.errstate(divide="ignore"):
        s = 1 / covers.distances(GOLDEN)
    assert s[0, 1] == pytest.approx(31.623, abs=1e-3)
    assert s[1, 2] == pytest.approx(70.711, abs=1e-3)
    assert s[0, 2] == pytest.approx(35.355, abs=1e-3)
    assert s[0, 3] == pytest.approx(20.0)
    assert np.isinf(s[6, 8])


@pytest.mark.parametrize(
    ("s0", "expected"),
    [
        (2, [[1, 2, 3], [4, 5, 6], [7, 8, 9, 10]]),
        (3, [[1, 2, 3, 4, 5], [6, 10], [7, 8, 9]]),
        (5, [[1, 2, 3, 4], [5], [6], [7, 8, 9, 10]]),
        (10, [[1, 2, 3, 4], [5], [6], [7, 8, 9], [10]]),
    ],
)
def test_golden_covers(s0, expected):
    assert groups(s0) == expected


@pytest.mark.parametrize(("s0", "n"), [(2, 2), (3, 3)])
def test_exact_cover_of_the_golden_vectors(s0, n):
    label = covers.exact(covers.threshold_graph(covers.distances(GOLDEN), s0))
    assert label.max() + 1 == n


@settings(max_examples=40, deadline=None)
@given(st.lists(st.tuples(st.floats(0, 3), st.floats(0, 1)), min_size=1, max_size=9), st.floats(0.5, 20))
def test_greedy_and_exact_are_valid_and_ordered(points, s0):
    a = covers.threshold_graph(covers.distances(np.array(points)), s0)
    g, e = covers.greedy(a), covers.exact(a)
    for label in (g, e):
        assert (label >= 0).all()
        for i in range(len(points)):
            for j in range(i):
                assert label[i] != label[j] or a[i, j]
    assert e.max() <= g.max() < len(points)


def test_extremes():
    v = np.array([[0.0, 0], [1, 0], [2, 0]])
    assert covers.greedy(covers.threshold_graph(covers.distances(v), 1e9)).max() == 2
    assert covers.greedy(covers.threshold_graph(covers.distances(v), 1e-9)).max() == 0
    assert covers.greedy(covers.threshold_graph(covers.distances(v[:1]), 1.0)).tolist() == [0]


def test_curve_of_many_items_reaches_every_number_of_groups():
    v = np.random.default_rng(8).gamma(2, 1, (60, 2))
    d = covers.distances(v)
    every = np.unique(d[np.triu_indices(60, 1)])
    grid = 1 / np.concatenate([[every[-1] * 1.01], ((every[1:] + every[:-1]) / 2)[::-1], [every[0] / 2]])
    want = {int(label.max()) + 1 for _, label in covers.cover_curve(v, grid)}
    got = [int(label.max()) + 1 for _, label in covers.cover_curve(v)]
    assert len(every) > 400 and set(got) == want and max(got) == 60


def test_threshold_curve_of_more_than_forty_slots_is_whole(spark):
    import pandas as pd

    from slotlens.operators import threshold

    v = np.random.default_rng(9).gamma(2, 1, (44, 2))
    values = spark.createDataFrame(pd.DataFrame({"series_id": "s", "slot": range(44), "y": v[:, 0]}))
    vectors = spark.createDataFrame(pd.DataFrame({"series_id": "s", "slot": range(44), "theta": v[:, 0], "mad": v[:, 1]}))
    assert threshold.sweep(values, vectors).toPandas()["n_groups"].max() == 44
