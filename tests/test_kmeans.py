"""Seeding and Lloyd passes against numpy, and their invariants."""

from __future__ import annotations

import numpy as np
import pytest

from gridcluster.operators import kmeans


def frame(spark, x, parts=3):
    return spark.createDataFrame([(i, list(map(float, v))) for i, v in enumerate(x)], "row_id long, z array<double>").repartition(parts)


def test_hand_case(spark):
    """Six points on a line, two clusters."""
    df = frame(spark, [[0], [1], [2], [10], [11], [12]])
    found = kmeans.lloyd(df, {0: [np.array([[0.0], [1.0]])]}, 10)[0][0]
    assert np.allclose(found.centers, [[1.0], [11.0]])
    assert found.inertia == pytest.approx(4 / 6)
    assert kmeans.inertia(df, found.centers) == pytest.approx(4 / 6)


def test_passes_equal_numpy_and_inertia_falls(spark):
    rng = np.random.default_rng(0)
    x = rng.standard_normal((300, 3))
    start = x[:4].copy()
    found = kmeans.lloyd(frame(spark, x), {0: [start]}, 6)[0][0]
    c = start.copy()
    for _ in range(6):
        near = ((x[:, None] - c) ** 2).sum(axis=2).argmin(axis=1)
        c = np.array([x[near == k].mean(axis=0) if (near == k).any() else c[k] for k in range(4)])
    assert np.allclose(found.centers, c, atol=1e-9)
    assert all(a >= b - 1e-12 for a, b in zip(found.history, found.history[1:]))


def test_empty_cluster_keeps_its_center(spark):
    df = frame(spark, [[0.0], [1.0]])
    found = kmeans.lloyd(df, {0: [np.array([[0.5], [99.0]])]}, 5)[0][0]
    assert found.centers[1, 0] == 99.0


def test_seeding_is_deterministic_and_distinct(spark):
    x = np.repeat(np.arange(5.0), 40)[:, None]
    a = kmeans.seed_dsq(frame(spark, x, 2), 5, seed=3)[0][0]
    b = kmeans.seed_dsq(frame(spark, x, 7), 5, seed=3)[0][0]
    assert np.array_equal(a, b)
    assert sorted(a[:, 0]) == [0, 1, 2, 3, 4]


def test_fewer_distinct_points_than_clusters(spark):
    assert len(kmeans.seed_dsq(frame(spark, [[1.0]] * 6), 3)[0][0]) == 1


def test_first_draws_follow_squared_distance(spark):
    """Of rows at distance 1 and 3 from the first, the farther one is drawn in nine of ten cases."""
    rows = [(0, [0.0]), (1, [1.0]), (2, [3.0])]
    df = spark.createDataFrame(rows, "row_id long, z array<double>").coalesce(1)
    lists = kmeans.seed_dsq(df, 2, seed=1, restarts=3000)[0]
    second = np.array([c[1, 0] for c in lists if c[0, 0] == 0.0])
    assert len(second) > 800
    assert np.mean(second == 3.0) == pytest.approx(0.9, abs=0.04)


def test_groups_and_restarts_in_one_pass(spark):
    rows = [(i, i % 2, [float(i % 2 * 100 + i % 3)]) for i in range(60)]
    df = spark.createDataFrame(rows, "row_id long, row_grp int, z array<double>")
    seeds = kmeans.seed_dsq(df, 3, seed=2, restarts=2, group="row_grp")
    found = kmeans.lloyd(df, seeds, 5, group="row_grp")
    for g in (0, 1):
        for r in found[g]:
            assert np.allclose(sorted(r.centers[:, 0]), [g * 100 + v for v in (0, 1, 2)])


def test_parallel_seeding_covers_clusters(spark):
    rng = np.random.default_rng(1)
    x = np.vstack([rng.standard_normal((100, 2)) * 0.1 + 10 * k for k in range(4)])
    assert kmeans.fit(frame(spark, x), 4, 20, seeding="parallel").inertia < 0.05


def test_labels_in_code_and_in_batches_agree(spark):
    rng = np.random.default_rng(2)
    x, centers = rng.standard_normal((50, 20)), rng.standard_normal((15, 20))  # 300 products: batches
    got = {r["row_id"]: r["pred"] for r in kmeans.assign(frame(spark, x), centers).collect()}
    narrow = {r["row_id"]: r["pred"] for r in kmeans.assign(frame(spark, x), centers[:10]).collect()}
    d = ((x[:, None] - centers) ** 2).sum(axis=2)
    assert [got[i] for i in range(50)] == d.argmin(axis=1).tolist()
    assert [narrow[i] for i in range(50)] == d[:, :10].argmin(axis=1).tolist()
