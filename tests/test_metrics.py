"""Measures against definitions by brute force."""

from __future__ import annotations

import itertools

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from gridcluster.operators import metrics


def pair_counting_ari(a, b):
    n = len(a)
    both = same_a = same_b = 0
    for i, j in itertools.combinations(range(n), 2):
        x, y = a[i] == a[j], b[i] == b[j]
        both += x and y
        same_a += x
        same_b += y
    total = n * (n - 1) / 2
    expected = same_a * same_b / total
    top = (same_a + same_b) / 2
    return 1.0 if top == expected else (both - expected) / (top - expected)


def table(a, b):
    out = np.zeros((max(a) + 1, max(b) + 1))
    np.add.at(out, (a, b), 1)
    return out


@settings(max_examples=60, deadline=None)
@given(st.lists(st.tuples(st.integers(0, 3), st.integers(0, 4)), min_size=2, max_size=40))
def test_ari_is_pair_counting(rows):
    a, b = zip(*rows)
    assert metrics.ari(table(a, b)) == pytest.approx(pair_counting_ari(a, b), abs=1e-12)


@settings(max_examples=60, deadline=None)
@given(st.lists(st.tuples(st.integers(0, 4), st.integers(0, 3)), min_size=1, max_size=60))
def test_acc_is_best_permutation(rows):
    a, b = zip(*rows)
    u = table(a, b)
    assert metrics.acc(u) == pytest.approx(metrics.acc_by_permutations(u))


def test_identical_and_trivial_labels():
    u = np.diag([3.0, 4.0, 5.0])
    assert metrics.ari(u) == metrics.nmi(u) == metrics.acc(u) == 1.0
    assert metrics.ari(u[:, [2, 0, 1]]) == 1.0 and metrics.acc(u[:, [2, 0, 1]]) == 1.0
    constant = np.array([[2.0], [2.0]])
    assert metrics.nmi(constant) == 0.0
    assert metrics.nmi(np.array([[4.0]])) == 1.0


def test_nmi_by_hand():
    u = np.array([[1.0, 1.0], [0.0, 2.0]])
    h_a, h_b = np.log(2), -(0.25 * np.log(0.25) + 0.75 * np.log(0.75))
    mutual = 0.25 * np.log(0.25 / (0.5 * 0.25)) + 0.25 * np.log(0.25 / (0.5 * 0.75)) + 0.5 * np.log(0.5 / (0.5 * 0.75))
    assert metrics.nmi(u) == pytest.approx(mutual / np.sqrt(h_a * h_b))


def test_pct_delta_is_absolute(spark):
    from gridcluster.operators import diagnostics

    rows = [("d", "pooled", 0, "ari", 0.008), ("d", "grid", 0, "ari", 0.024)]
    ledger = spark.createDataFrame(rows, "dataset string, method string, trial int, metric string, value double")
    out = diagnostics.pct_delta(diagnostics.summarise_trials(ledger)).first()
    assert out["pct"] == pytest.approx(200.0) and out["signed_pct"] == pytest.approx(200.0)


def test_trivial_labels_have_the_same_value_in_tables(spark):
    """One class, one cluster, one row, no row: the column versions follow the driver's conventions."""
    for rows in ([], [(0, 0)], [(0, 0), (0, 0)], [(0, 0), (1, 0)], [(0, 0), (0, 1)], [(0, 1), (1, 2)], [(None, 0), (0, 1), (None, 0)]):
        df = spark.createDataFrame(rows, "truth int, pred int")
        u = metrics.table_of(metrics.contingency(df)) if rows else np.zeros((0, 0))
        assert metrics.ari_rows(df).first()["ari"] == pytest.approx(metrics.ari(u))
        assert metrics.nmi_rows(df).first()["nmi"] == pytest.approx(metrics.nmi(u))


def test_difference_to_a_mean_of_zero(spark):
    from gridcluster.operators import diagnostics

    summary = spark.createDataFrame([("d", "pooled", "ari", 0.0), ("d", "grid", "ari", 0.0), ("d", "solo", "ari", 0.2)], "dataset string, method string, metric string, mean double")
    got = {r["method"]: r["pct"] for r in diagnostics.pct_delta(summary).collect()}
    assert got == {"grid": 0.0, "solo": None}
    assert {r["method"]: r["avg_pct"] for r in diagnostics.avg_pct_delta(diagnostics.pct_delta(summary)).collect()} == {"grid": 0.0, "solo": None}
