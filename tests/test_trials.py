"""The engine of the trials: the same numbers as comparing every row with every other, in less work."""

from __future__ import annotations

import numpy as np
import pytest

from gridcluster.operators import kmeans
from gridcluster.plans import trials


def plain_lloyd(points, weights, centers, passes):
    distances = lambda c: sum((points[:, i, None] - c[None, :, i]) ** 2 for i in range(points.shape[1]))
    for _ in range(passes):
        near = distances(centers).argmin(axis=1)
        mass = np.bincount(near, weights=weights, minlength=len(centers))
        new = np.stack([np.bincount(near, weights=weights * x, minlength=len(centers)) for x in points.T], axis=1)
        new = np.where(mass[:, None] > 0, new / np.maximum(mass, 1e-300)[:, None], centers)
        if np.array_equal(new, centers):
            break
        centers = new
    return centers, distances(centers).argmin(axis=1)


@pytest.mark.parametrize("shift", [0.0, 1e6])
def test_bounded_passes_compare_few_rows_and_end_in_the_same_bits(monkeypatch, shift):
    rng = np.random.default_rng(1)
    looked, whole = [], kmeans.nearest_two
    monkeypatch.setattr(kmeans, "nearest_two", lambda columns, centers: looked.append(columns.shape[1]) or whole(columns, centers))
    for k, passes in ((1, 5), (2, 300), (7, 300), (7, 3)):
        z = np.vstack([rng.standard_normal((20_000, 5)) + 0.5 * rng.integers(0, 3, (20_000, 1)), np.zeros((50, 5)), np.ones((50, 5))]) + shift
        weights = rng.integers(0, 3, len(z)).astype(float)
        del looked[:]
        centers, _, near = kmeans.lloyd_labels(z, weights, z[:: len(z) // k][:k], passes)
        want, labels = plain_lloyd(z, weights, z[:: len(z) // k][:k], passes)
        assert np.array_equal(centers, want) and np.array_equal(near, labels)
        if passes == 300:
            assert sum(looked) < 0.5 * len(looked) * len(z)


def test_blocks_of_anchors_give_the_aligner_of_all(monkeypatch):
    rng = np.random.default_rng(2)
    x = rng.standard_normal((900, 4)) * [1, 2, 3, 4]
    points, groups = trials.Points(np.arange(900), x, np.zeros(900, dtype=int)), np.arange(900) % 10
    whole = trials.common_space(points, groups, ((0, 1), (2, 3)), trials.Setting(3), 7)
    held = []
    monkeypatch.setattr(trials, "ANCHOR_BLOCK", 64)
    monkeypatch.setattr(np, "hstack", lambda parts, f=np.hstack: held.append(len(parts[0])) or f(parts))
    assert np.allclose(whole, trials.common_space(points, groups, ((0, 1), (2, 3)), trials.Setting(3), 7), atol=1e-9)
    assert max(held[10:]) <= 64


def test_features_of_one_small_file_are_worked_out_on_all_cores(spark, small):
    from gridcluster.plans import workloads

    for loader, _, _ in [workloads.DATASETS[n] for n in ("small_three", "text_quality", "language")]:
        assert loader(spark, small).rdd.getNumPartitions() >= spark.sparkContext.defaultParallelism


def test_letter_shares_of_odd_texts(spark):
    from pyspark.sql import functions as F

    from gridcluster.functions import features

    texts = ["", "AEIou", "İaİ", "naïve ÀÉ", "e\x00e", "Kelvin", "ooooo" * 100]
    df = spark.createDataFrame([(t,) for t in texts], "t string")
    low = F.lower("t")
    want = [(F.length("t") - F.length(F.translate(low, c, ""))) / F.greatest(F.length("t"), F.lit(1)) for c in features.LETTERS]
    got = df.select(F.array(*features.letter_shares(F.col("t"))).alias("a"), F.array(*want).alias("b")).collect()
    assert len(got) == len(texts) and all(r["a"] == r["b"] for r in got)
    assert "translate" not in df.select(*features.letter_shares(F.col("t")))._jdf.queryExecution().toString()


def clouds(sizes, width, seed=3):
    rng = np.random.default_rng(seed)
    return np.vstack([rng.standard_normal((n, width)) + 4 * i for i, n in enumerate(sizes)])


@pytest.mark.parametrize("shift, scale", [(0.0, 1.0), (1e7, 1.0), (0.0, 1e-25), (0.0, 1e25)])
def test_sifted_neighbours_are_those_of_all_differences(shift, scale):
    from gridcluster.operators.graph import _nearest_between
    from gridcluster.operators.local import LeafTree

    z = np.vstack([clouds((700, 900), 3), np.ones((40, 3)), np.round(clouds((300,), 3))]) * scale + shift
    ids = np.random.default_rng(4).permutation(len(z)).astype(np.int64)
    tree = LeafTree(ids, z, 6)
    edges = lambda t: sorted(zip(*(t[c].to_pylist() for c in ("src", "dst", "dist"))))
    got = edges(tree.nearest(range(len(tree))))
    assert got == edges(_nearest_between(ids, z, ids, z, 6, False))


def test_embedding_is_as_near_as_the_gap_asks():
    """A narrow cloud, whose eigenvalues lie close together: the vectors are those of the whole matrix."""
    from gridcluster.operators import local, spectral
    from gridcluster.operators.graph import _nearest_between

    for z, k in ((clouds((2500,), 2), 3), (np.random.default_rng(5).random((2500, 1)) * 50, 3), (clouds((1200, 900), 2) * [1, 9], 4)):
        ids = np.arange(len(z))
        e = _nearest_between(ids, z, ids, z, 10, False)
        src, dst = e["src"].to_numpy(), e["dst"].to_numpy()
        edges = ids, np.concatenate([src, dst]), np.concatenate([dst, src]), np.full(2 * len(src), 0.5), k
        values, want = spectral.dense_embedding(*edges)
        found, got = local.sparse_embedding(*edges, spectral.TOLERANCE, spectral.DEGREE)
        assert found == pytest.approx(values, rel=1e-3, abs=1e-9)
        assert np.linalg.svd(want.T @ got)[1] == pytest.approx(1, abs=0.01)


def test_patches_and_leaves_are_as_many_as_the_table_is_worth():
    """A graph of 6,000 nodes has 150 patches, not 1,000, whose matrix took longer than all products; the vectors are as near as asked."""
    from gridcluster.operators import local, spectral

    z = clouds((3500, 2500), 5)
    ids, tree = np.arange(6000), local.LeafTree(np.arange(6000), z, 10)
    assert len(tree) == 32  # leaves of up to 256 rows
    e = tree.nearest(range(len(tree)))
    src, dst = e["src"].to_numpy(), e["dst"].to_numpy()
    at_s, at_d = np.concatenate([src, dst]), np.concatenate([dst, src])
    patch = local.patches(6000, at_s, at_d, np.random.default_rng(0))
    assert patch.max() + 1 == 150
    values, x = local.sparse_embedding(ids, at_s, at_d, np.full(len(at_s), 0.5), 3, spectral.TOLERANCE, spectral.DEGREE)
    root = np.sqrt(np.bincount(at_s, minlength=6000) * 0.5)
    image = np.stack([np.bincount(at_s, weights=0.5 * (c / root)[at_d], minlength=6000) / root for c in x.T], axis=1)
    assert np.linalg.norm(image - x * (1 - values), axis=0).max() <= spectral.TOLERANCE


def test_few_rows_are_sorted_for_a_leaf(monkeypatch):
    """Of the rows that the sift leaves, only those within the q-th distance are put in order."""
    from gridcluster.operators.local import LeafTree

    z = np.random.default_rng(6).standard_normal((6000, 9))
    tree, sorted_, whole = LeafTree(np.arange(6000), z, 10), [], np.lexsort
    monkeypatch.setattr(np, "lexsort", lambda keys: sorted_.append(len(keys[0])) or whole(keys))
    assert tree.nearest(range(len(tree))).num_rows == 60_000
    assert sum(sorted_) < 61_000


@pytest.mark.parametrize("kinds", [2, 500])
def test_products_are_those_of_the_matrix(kinds):
    """Edges of few and of many weights, nodes of few and of very many edges, in both precisions."""
    from gridcluster.operators.local import NODES, Products

    rng, n = np.random.default_rng(7), NODES + 700
    a, b = np.concatenate([rng.integers(0, n, 20_000), np.zeros(n - 1, dtype=int)]), np.concatenate([rng.integers(0, n, 20_000), np.arange(1, n)])
    pairs = np.unique(np.minimum(a, b)[a != b] * n + np.maximum(a, b)[a != b])
    a, b = np.divmod(pairs, n)
    w = rng.choice(rng.random(kinds) + 0.5, len(pairs))
    s, d, w = np.concatenate([a, b]), np.concatenate([b, a]), np.concatenate([w, w])
    by = np.argsort(s, kind="stable")
    s, d, w = s[by], d[by], w[by]
    root = np.sqrt(np.bincount(s, weights=w, minlength=n))
    dense = np.zeros((n, n))
    dense[s, d] = w / (root[s] * root[d])
    times = Products(n, s, d, w, 1 / root)
    for width in (1, 5, 11):
        x = rng.standard_normal((n, width))
        assert np.allclose(times(x), dense @ x, atol=1e-12)
        single = times(x.astype(np.float32))
        assert single.dtype == np.float32 and np.allclose(single, dense @ x, atol=1e-5)


def test_long_filters_work_in_single_precision(monkeypatch):
    """A chain's eigenvalues ask for filters of high degree: their products are single, and the vectors those of the matrix."""
    from gridcluster.operators import local, spectral

    n = 2500
    a = np.arange(n - 1)
    edges = np.arange(n), np.concatenate([a, a + 1]), np.concatenate([a + 1, a]), np.ones(2 * (n - 1)), 3
    kinds, whole = [], local.Products.__call__
    monkeypatch.setattr(local.Products, "__call__", lambda self, x: kinds.append(x.dtype.itemsize) or whole(self, x))
    values, want = spectral.dense_embedding(*edges)
    found, got = local.sparse_embedding(*edges, spectral.TOLERANCE, spectral.DEGREE)
    assert kinds.count(4) > 2 * kinds.count(8)
    assert found == pytest.approx(values, rel=1e-2, abs=1e-7)
    assert np.linalg.svd(want.T @ got)[1] == pytest.approx(1, abs=0.01)


def test_pooled_embedding_is_a_task_and_trials_run_once(spark, small, monkeypatch):
    """Nothing is embedded on the driver, and a report that reads the ledger again reads what is written."""
    from gridcluster.plans import workloads

    here, whole = [], trials.embedded
    monkeypatch.setattr(trials, "embedded", lambda *a: here.append(1) or whole(*a))  # tasks have a list of their own
    ledger = workloads.run_exp2(spark, small, "small_three", "spectral", 2)
    assert "MapInArrow" not in ledger._jdf.queryExecution().toString()
    rows = ledger.collect()
    assert not here
    assert sorted({(r["method"], r["trial"]) for r in rows}) == [(m, t) for m in ("fed", "grid", "pooled", "solo") for t in (0, 1)]
    assert len(rows) == 24 and all(r["value"] is not None for r in rows)


def test_character_shares_of_runs(spark):
    from pyspark.sql import functions as F

    from gridcluster.functions import features

    texts = ["", "AAAbbb  12\n\t9", "ÀÉ 𝐀𝐁 12½", "a1b2 C3", "  ", "..--"]
    want = [[sum(map(f, t)) / max(1, len(t)) for f in (str.isalpha, lambda c: c in "0123456789", lambda c: c in " \t\n\r")] for t in texts]
    df = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "i int, t string")
    got = [r["a"] for r in df.select("i", F.array(*features.character_shares(F.col("t"))).alias("a")).orderBy("i").collect()]
    assert [g[:3] for g in got] == [pytest.approx(w) for w in want]
    assert r"\p{L}+" in df.select(*features.character_shares(F.col("t")))._jdf.queryExecution().toString()


@pytest.mark.parametrize("shift", [0.0, 1e6])
def test_sums_are_moved_by_few_points_and_end_in_the_same_bits(monkeypatch, shift):
    """Few passes sum all points; equal points, ties and centers that lose their points are as with all sums."""
    rng = np.random.default_rng(8)
    z, summed, whole = rng.standard_normal((20_000, 5)) + shift, [], np.bincount
    monkeypatch.setattr(np, "bincount", lambda x, *a, **o: summed.append(len(x)) or whole(x, *a, **o))
    centers, _, near = kmeans.lloyd_labels(z, np.ones(len(z)), z[:3], 300)
    monkeypatch.undo()
    want, labels = plain_lloyd(z, np.ones(len(z)), z[:3], 300)
    assert np.array_equal(centers, want) and np.array_equal(near, labels)
    assert sum(summed) < 0.5 * len(summed) * len(z)
    for t in range(40):
        z = rng.integers(0, 4, (300, 2)) + shift if t % 2 else np.round(rng.standard_normal((300, 3)), 1) + shift
        weights, k = rng.integers(0, 3, 300) if t % 3 else rng.random(300), int(rng.integers(1, 9))
        start, passes = z[rng.choice(300, k)] + (1e9 if t % 7 == 0 else 0) * np.eye(k, z.shape[1]), int(rng.integers(0, 40))
        centers, _, near = kmeans.lloyd_labels(z, weights, start, passes)
        want, labels = plain_lloyd(z, weights, start, passes)
        assert np.array_equal(centers, want) and np.array_equal(near, labels)


def test_embedding_of_a_neighbour_graph_holds_few_bytes_a_node(monkeypatch):
    """A trial of over a million rows has to fit beside another one: edges in four bytes, vectors written over."""
    import tracemalloc

    from gridcluster.operators import local, spectral

    monkeypatch.setattr(local, "PATCHES", 100)  # their matrix has a size of its own
    z, n = clouds((45_000, 35_000), 3), 80_000
    links = local.neighbour_links(np.arange(n), z, 10)
    e = np.divmod(np.concatenate(links), n)
    tracemalloc.start()
    values, x = local.neighbour_embedding(n, links, 3, spectral.TOLERANCE, spectral.DEGREE)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert not links and x.shape == (n, 3)
    assert peak < 900 * n  # 1,800 with eight bytes and copies
    at_s, at_d = np.concatenate(e), np.concatenate(e[::-1])
    root = np.sqrt(np.bincount(at_s, minlength=n) * 0.5)
    image = np.stack([np.bincount(at_s, weights=0.5 * (c / root)[at_d], minlength=n) / root for c in x.T], axis=1)
    assert np.linalg.norm(image - x * (1 - values), axis=0).max() <= spectral.TOLERANCE
    assert np.allclose(x.T @ x, np.eye(3), atol=1e-9)


def test_blocks_of_rows_are_made_orthonormal_as_a_whole(monkeypatch):
    from gridcluster.operators import local

    monkeypatch.setattr(local, "SOME_ROWS", 64)
    x = np.random.default_rng(8).standard_normal((1000, 6)) @ np.diag([1, 1e3, 1e6, 1e-3, 1, 1]) + 5
    base = local.orthonormal(x.copy())
    assert np.allclose(base.T @ base, np.eye(6), atol=1e-12) and np.linalg.matrix_rank(np.hstack([x / np.linalg.norm(x, axis=0), base]), tol=1e-8) == 6


def test_tables_of_over_200_000_rows_are_trials_in_tasks():
    """The 900,000 customers and 1,200,000 parts of 60 copies do not go trial by trial through written tables."""
    from gridcluster.operators import spectral

    assert trials.MOST_ROWS["spectral"] >= 1_200_000 and spectral.NEIGHBOUR_NODES >= trials.MOST_ROWS["spectral"]


def test_runs_delete_their_tables(spark, small, monkeypatch, tmp_path):
    """Trial by trial and in the first experiment: what a run has written goes when its scores are known."""
    from gridcluster import session
    from gridcluster.plans import workloads

    known = dict(session._WRITTEN)
    workloads.run_exp1(spark, small, "rings", methods=("solo", "grid"), restarts=1)
    monkeypatch.setattr(trials, "MOST_ROWS", {"kmeans": 0, "spectral": 0})
    rows = workloads.run_exp2(spark, small, "small_three", "spectral", 1, passes=5).collect()
    assert len(rows) == 12
    assert session._WRITTEN.keys() == known.keys()
