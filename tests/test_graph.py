"""Neighbour graphs, Laplacians and embeddings against numpy."""

from __future__ import annotations

import numpy as np
import pytest

from gridcluster.operators import graph, metrics
from gridcluster.operators import spectral as sp


def frame(spark, x):
    return spark.createDataFrame([(i, list(map(float, v))) for i, v in enumerate(x)], "row_id long, z array<double>")


def dense(edges, n, col="w"):
    out = np.zeros((n, n))
    for r in edges.collect():
        out[r["src"], r["dst"]] = r[col]
    return out


def test_knn_is_brute_force(spark, monkeypatch):
    monkeypatch.setattr(graph, "BLOCK_ROWS", 17)
    x = np.random.default_rng(0).standard_normal((60, 3))
    got = dense(graph.knn_graph(frame(spark, x), 4), 60)
    d = ((x[:, None] - x) ** 2).sum(axis=2)
    np.fill_diagonal(d, np.inf)
    want = np.zeros((60, 60))
    want[np.arange(60)[:, None], np.argsort(d, axis=1, kind="stable")[:, :4]] = 1
    assert np.array_equal(got, want)


def test_square_graph_by_hand(spark):
    """Four corners: each has degree two, and the plain Laplacian's rows add up to nothing."""
    e = graph.symmetrise(graph.knn_graph(frame(spark, [[0, 0], [1, 0], [1, 1], [0, 1]]), 2))
    lap = dense(graph.laplacian(e), 4, "val")
    assert np.allclose(np.diag(lap), 2) and np.allclose(lap.sum(axis=1), 0)
    values = np.linalg.eigvalsh(dense(graph.laplacian(e, "sym"), 4, "val"))
    assert np.allclose(values, [0, 1, 1, 2])


def test_symmetries(spark):
    e = spark.createDataFrame([(0, 1, 1.0), (1, 0, 1.0), (0, 2, 1.0)], "src long, dst long, w double")
    assert dense(graph.symmetrise(e, "mean"), 3)[2, 0] == 0.5
    assert dense(graph.symmetrise(e, "union"), 3)[2, 0] == 1.0
    assert dense(graph.symmetrise(e, "mutual"), 3)[2, 0] == 0.0 and dense(graph.symmetrise(e, "mutual"), 3)[0, 1] == 1.0


def test_distributed_embedding_spans_the_dense_one(spark):
    rng = np.random.default_rng(1)
    x = np.vstack([rng.standard_normal((30, 2)) * 0.3 + c for c in ((0, 0), (4, 0), (0, 4))])
    e = graph.symmetrise(graph.knn_graph(frame(spark, x), 8)).cache()
    a, va = sp.embed(spark, e, 3)
    b, vb = sp.subspace_embedding(spark, e, 3, degree=6)
    assert np.allclose(va, vb, atol=1e-4)
    za = np.array([r["z"] for r in a.orderBy("row_id").collect()])
    zb = np.array([r["z"] for r in b.orderBy("row_id").collect()])
    assert np.abs(za @ za.T - zb @ zb.T).max() < 1e-2


def test_count_of_zero_eigenvalues_is_count_of_components(spark):
    x = [[0.0], [0.1], [0.2], [9.0], [9.1], [9.2]]
    _, values = sp.embed(spark, graph.symmetrise(graph.knn_graph(frame(spark, x), 2)), 3)
    assert np.allclose(values[:2], 0, atol=1e-9) and values[2] > 0.1


def test_radius_edges(spark):
    x = np.random.default_rng(2).uniform(-1, 1, (80, 2))
    got = {(r["src"], r["dst"]) for r in graph.radius_edges(frame(spark, x), 0.3).collect()}
    d = np.sqrt(((x[:, None] - x) ** 2).sum(axis=2))
    assert got == {(i, j) for i in range(80) for j in range(i + 1, 80) if d[i, j] <= 0.3}


@pytest.mark.parametrize("n,width", [(300, 4), (20_000, 8), (100_000, 8)])
def test_lsh_graph_keeps_its_recall_as_rows_grow(spark, n, width):
    x = np.random.default_rng(3).standard_normal((n, width))
    rows = spark.range(n).mapInPandas(_normal_rows(x), "row_id long, z array<double>")
    near = graph.knn_graph(rows, 5, method="lsh", rows=n)
    probe = np.random.default_rng(4).choice(n, 200, replace=False)
    got = {}
    for r in near.where(near.src.isin(probe.tolist())).collect():
        got.setdefault(r["src"], set()).add(r["dst"])
    hit = 0
    for i in probe:
        d = ((x - x[i]) ** 2).sum(axis=1)
        d[i] = np.inf
        hit += len(set(np.argsort(d, kind="stable")[:5].tolist()) & got.get(int(i), set()))
    assert hit / (5 * len(probe)) >= 0.9


def _normal_rows(x):
    import pandas as pd

    return lambda frames: (pd.DataFrame({"row_id": f["id"], "z": [x[i].tolist() for i in f["id"]]}) for f in frames)


def test_lsh_graph_of_a_dense_spot_and_of_few_rows(spark, monkeypatch):
    """A third of all rows in one place: their bucket is compared in chunks, and all have their neighbours."""
    monkeypatch.setattr(graph, "BLOCK_ROWS", 50)
    x = np.vstack([np.zeros((200, 3)), np.random.default_rng(5).standard_normal((400, 3))])
    found = graph.knn_graph(frame(spark, x), 4, method="lsh").collect()
    by = {}
    for r in found:
        by.setdefault(r["src"], []).append((r["dist"], r["dst"]))
    assert all(len(v) == 4 for v in by.values()) and len(by) == 600
    assert sorted(by[7]) == [(0.0, 0), (0.0, 1), (0.0, 2), (0.0, 3)]
    assert graph.knn_graph(frame(spark, x[:2]), 4, method="lsh").count() == 2
    assert graph.knn_graph(frame(spark, x).limit(0), 4, method="lsh").count() == 0
    assert graph.knn_graph(frame(spark, x).limit(0), 4).count() == 0


def test_embedding_that_does_not_settle_says_so(spark):
    e = graph.symmetrise(graph.knn_graph(frame(spark, np.random.default_rng(6).uniform(size=(300, 2))), 6))
    with pytest.warns(UserWarning, match="residuals"):
        sp.subspace_embedding(spark, e, 4, rounds=1, degree=2, tol=1e-12)


def test_landmarks_separate_rings(spark):
    t = np.linspace(0, 2 * np.pi, 150, endpoint=False)
    x = np.vstack([np.column_stack([r * np.cos(t), r * np.sin(t)]) for r in (2, 8)])
    points, clusters = sp.spectral_landmarks(frame(spark, x), 2, landmarks=80, q=4)
    label = clusters[((x[:, None] - points) ** 2).sum(axis=2).argmin(axis=1)]
    u = np.zeros((2, 2))
    np.add.at(u, (np.repeat([0, 1], 150), label), 1)
    assert metrics.ari(u) == pytest.approx(1.0)


@pytest.mark.parametrize("include_self", [False, True])
@pytest.mark.parametrize("crowded", [False, True])
def test_tree_search_is_brute_force(spark, monkeypatch, include_self, crowded):
    """A table of bounded size is searched leaf by leaf: same neighbours, also among rows in one place."""
    monkeypatch.setattr(graph, "BLOCK_ROWS", 50)
    made = []
    monkeypatch.setattr(graph, "LeafTree", lambda *a, tree=graph.LeafTree: made.append(1) or tree(*a, leaf=16))
    rng = np.random.default_rng(3)
    x = rng.integers(0, 3, (400, 3)).astype(float) if crowded else rng.standard_normal((400, 3))
    rows = lambda e: sorted((r["src"], r["dst"], r["dist"]) for r in e.collect())
    tree = rows(graph.knn_graph(frame(spark, x), 5, include_self=include_self))
    few = rows(graph.knn_graph(frame(spark, x), 5, include_self=include_self, of=frame(spark, x).where("row_id % 7 = 0")))
    assert len(made) == 1
    monkeypatch.setattr(graph, "TREE_VALUES", 0)
    assert tree == rows(graph.knn_graph(frame(spark, x), 5, include_self=include_self))
    assert few == [r for r in tree if r[0] % 7 == 0]


def test_embedding_in_a_task_is_that_of_the_matrix(spark, monkeypatch):
    """Connected graphs and graphs of several components."""
    rng = np.random.default_rng(6)
    for gap, known in ((1.5, 1), (30.0, 3)):
        x = np.vstack([rng.standard_normal((150, 2)) + gap * i for i in range(3)])
        edges = graph.symmetrise(graph.knn_graph(frame(spark, x), 8)).cache()
        want, least = sp.embed(spark, edges, 4)
        monkeypatch.setattr(sp, "DENSE_NODES", 100)
        monkeypatch.setattr(sp, "subspace_embedding", None)
        got, values = sp.embed(spark, edges, 4)
        monkeypatch.undo()
        a, b = (np.array([r["z"] for r in z.orderBy("row_id").collect()]) for z in (want, got))
        assert values == pytest.approx(least, abs=1e-6) and (least[:known] < 1e-9).all()
        assert np.linalg.svd(a.T @ b)[1] == pytest.approx(1, abs=1e-3)


def test_only_drawn_rows_look_for_neighbours(spark, monkeypatch):
    """Few anchors of many rows: same anchors as with the graph of all rows."""
    from gridcluster.operators import anchors

    x = np.random.default_rng(9).standard_normal((300, 3))
    public = frame(spark, x).withColumnRenamed("z", "feats")
    rows = lambda: sorted((r["anchor_id"], *r["feats"]) for r in anchors.anchor_mix(public, 20, seed=2).collect())
    given, whole = [], graph.knn_graph
    monkeypatch.setattr(graph, "knn_graph", lambda *a, of=None, **o: given.append(of.count()) or whole(*a, of=of, **o))
    few = rows()
    monkeypatch.setattr(graph, "knn_graph", lambda *a, of=None, **o: whole(*a, **o))
    assert given == [20] and few == rows()


def test_trials_of_larger_tables_are_tasks(spark, monkeypatch):
    """15,000 rows under spectral clustering: no trial goes through the distributed operators."""
    from gridcluster.plans import workloads

    monkeypatch.setattr(workloads, "equal_groups", None)
    ledger = workloads.run_exp2(spark, "/root/testdata/sf0.1", "small_three", "spectral", 1, methods=("solo", "grid")).collect()
    assert {r["method"] for r in ledger} == {"solo", "grid"} and all(r["value"] > 0.3 for r in ledger)


def test_halves_are_summed_to_the_mean_and_embedded_without_an_exchange(spark, monkeypatch):
    """The edges of a written neighbour graph go to the task that solves it as they are: no sum over all executors."""
    from gridcluster.operators import spectral
    from gridcluster.session import materialise

    rng = np.random.default_rng(9)
    z = np.vstack([rng.standard_normal((300, 2)), rng.standard_normal((200, 2)) + 3])
    df = spark.createDataFrame([(int(7 * i), x.tolist()) for i, x in enumerate(z)], "row_id long, z array<double>")
    near = materialise(spark, graph.knn_graph(df, 5), "near")
    halves = graph.symmetrise(near, "halves")
    assert "Exchange" not in halves._jdf.queryExecution().executedPlan().toString()
    want = {(r["src"], r["dst"]): r["w"] for r in graph.symmetrise(near).where("src < dst").collect()}
    got: dict = {}
    for r in halves.collect():
        assert r["src"] < r["dst"]
        got[r["src"], r["dst"]] = got.get((r["src"], r["dst"]), 0) + r["w"]
    assert got == want

    dense = spectral.spectral(df, 3, 5)
    monkeypatch.setattr(spectral, "DENSE_NODES", 100)
    found = spectral.spectral(df, 3, 5)
    assert found.eigenvalues == pytest.approx(dense.eigenvalues, abs=1e-6)
    side = lambda f: np.array([r["z"] for r in f.embedding.orderBy("row_id").collect()])
    a, b = side(dense), side(found)
    assert len(a) == len(b) == 500 and np.linalg.svd(a.T @ b)[1] == pytest.approx(1, abs=0.01)
