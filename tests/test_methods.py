"""Whole methods: accuracy gates, invariants, negative controls, the ledger."""

from __future__ import annotations

import numpy as np
import pytest

from gridcluster.operators import grid, kmeans, metrics, protocol
from gridcluster.operators.grid import GridSpec, even_columns, split_grid
from gridcluster.plans import baselines, workloads
from gridcluster.plans.estimator import GridClusterer
from gridcluster.plans.pipeline import grid_cluster
from gridcluster.session import materialise


@pytest.fixture(scope="module")
def language(spark, middle):
    return materialise(spark, workloads.text_language(spark, middle, least=200), "language")


def ari(labels, points):
    return metrics.scores(labels.select("row_id", "pred").join(points.select("row_id", "truth"), "row_id"))["ari"]


def test_language_gate(spark, language):
    p = materialise(spark, split_grid(language, 2), "split")
    spec = GridSpec(even_columns(10, 2))
    found = grid_cluster(p, spec, 4, restarts=5, passes=50)
    g = ari(found.labels, p)
    assert g >= 0.95
    assert ari(baselines.pooled(p, 4, restarts=5, passes=50), p) >= 0.98
    assert ari(baselines.solo(p, spec, 0, 0, 4, restarts=5, passes=50), p) < g
    assert found.ledger.rounds == 1
    assert set(found.labels.columns) == {"row_id", "row_grp", "pred"}
    n, widths = p.count(), {k: m.width for k, m in found.maps.items()}
    assert found.ledger.volume("down") == sum((r["count"] + 4) * 9 * 2 for r in p.groupBy("row_grp").count().collect())
    assert sum(widths.values()) == 16 and n == found.labels.count()


def test_affine_wins_where_rows_are_sorted_by_class(spark, language):
    p = materialise(spark, grid.sorted_groups(language, "truth", 4), "sorted")
    spec = GridSpec(even_columns(10, 2))
    by = {k: ari(grid_cluster(p, spec, 4, aligner=k, restarts=5, passes=50, fuse=True).labels, p) for k in ("affine", "linear")}
    assert by["affine"] > 0.95 and by["linear"] < 0.7


def test_spectral_branch_and_landmarks(spark, language):
    p = materialise(spark, split_grid(language, 10), "split")
    spec = GridSpec(even_columns(10, 2))
    assert ari(grid_cluster(p, spec, 4, "spectral", restarts=3, passes=50, fuse=True).labels, p) >= 0.95
    assert ari(grid_cluster(p, spec, 4, "spectral", landmarks=100, fuse=True).labels, p) >= 0.9


def test_federated_baselines_lie_between(spark, language):
    p = materialise(spark, split_grid(language, 10), "split")
    spec = GridSpec(even_columns(10, 2))
    labels, ledger = baselines.fed_kmeans(p, spec, 4, rounds=5)
    assert 0.5 < ari(labels, p) <= 1.0 and ledger.rounds == 5
    labels, ledger = baselines.fed_spectral(p, spec, 4)
    assert labels.count() == p.count() and ledger.rounds == 1


@pytest.mark.parametrize("split", ["iid", "skew"])
def test_planted_blobs_as_in_the_first_experiment(spark, small, split):
    out = {r["method"]: r["value"] for r in workloads.run_exp1(spark, small, "blobs", split, keys=workloads.ORDERS, methods=("solo", "pooled", "grid")).where("metric = 'ari'").collect()}
    assert out["pooled"] == pytest.approx(1.0, abs=0.01) and out["grid"] == pytest.approx(1.0, abs=0.01)
    if split == "skew":
        assert max(v for m, v in out.items() if m.startswith("solo")) < 0.8


def test_planted_rings_need_the_spectral_branch(spark, small):
    points = materialise(spark, workloads.planted_rings(spark, small, "skew"), "rings")
    spec = GridSpec(workloads.SHAPE_COLUMNS)
    options = {"map_options": {"scale": False}, "target": "US", "restarts": 3, "fuse": True}
    assert ari(grid_cluster(points, spec, 3, "spectral", **options).labels, points) > 0.95
    assert ari(grid_cluster(points, spec, 3, "kmeans", passes=30, **options).labels, points) < 0.5


def test_no_structure_no_agreement(spark, middle):
    points = materialise(spark, split_grid(workloads.embedding_shift(spark, middle, 13, 0.0, 2), 10), "noise")
    assert abs(ari(grid_cluster(points, GridSpec(even_columns(13, 2)), 2, passes=50, fuse=True).labels, points)) < 0.05


def test_degenerate_lattice_is_pca_and_kmeans(spark, language):
    p = materialise(spark, split_grid(language, 1), "one")
    spec = GridSpec(even_columns(10, 1))
    found = grid_cluster(p, spec, 4, restarts=5, passes=50, fuse=True)
    assert ari(found.labels, p) > 0.9 and len(found.maps) == 1


def test_labels_do_not_depend_on_partitions(spark, language):
    spec = GridSpec(even_columns(10, 2))
    a, b = split_grid(language, 2).repartition(2), split_grid(language, 2).repartition(7)
    x = grid_cluster(a, spec, 4, passes=30, fuse=True).labels
    y = grid_cluster(b, spec, 4, passes=30, fuse=True).labels
    assert metrics.agreement(x, y)["ari"] == pytest.approx(1.0)


def test_party_and_hub_labels_agree_and_only_codes_cross(spark, language):
    p = split_grid(language, 2)
    found = grid_cluster(p, GridSpec(even_columns(10, 2)), 4, passes=20)
    hub = kmeans.assign(found.z, found.centers).select("row_id", "pred")
    assert metrics.agreement(found.labels, hub)["acc"] == 1.0
    with pytest.raises(AssertionError):
        protocol.hub_may_hold(p)
    bad = protocol.Ledger()
    bad.send(1, "party(0,0)", "hub", "rows", 5, 5)
    with pytest.raises(AssertionError):
        bad.audit()


@pytest.mark.parametrize("kind", ["lpp", "autoencoder"])
def test_other_party_maps(spark, language, kind):
    p = materialise(spark, split_grid(language, 2), "split")
    assert ari(grid_cluster(p, GridSpec(even_columns(10, 2)), 4, map_kind=kind, restarts=5, passes=50).labels, p) > 0.9


def test_other_anchors(spark, language):
    from gridcluster.operators import anchors

    p = materialise(spark, split_grid(language, 2), "split")
    # these anchors have narrow directions, which a target of unit variances would blow up
    for a in (anchors.anchor_lowrank(spark, p, 500, 9, noise=0.3), anchors.anchor_mix(p, 500), anchors.anchor_from(p)):
        assert ari(grid_cluster(p, GridSpec(even_columns(10, 2)), 4, anchor=a, anchor_count=500, target="US", restarts=5, passes=50, fuse=True).labels, p) > 0.9


def test_estimator(spark, language):
    p = materialise(spark, split_grid(language, 2), "split")
    model = GridClusterer(GridSpec(even_columns(10, 2)), 4, passes=50).fit(p)
    assert metrics.scores(model.transform(p))["ari"] > 0.95


def test_equal_groups(spark):
    df = spark.range(1003).withColumnRenamed("id", "row_id")
    sizes = [r["count"] for r in grid.equal_groups(df, 10).groupBy("row_grp").count().collect()]
    assert len(sizes) == 10 and max(sizes) - min(sizes) <= 1


def test_even_columns():
    assert sorted(i for g in even_columns(7, 3, seed=4) for i in g) == list(range(7))
    with pytest.raises(ValueError):
        even_columns(2, 3)
    assert np.isfinite(grid.default_anchor_rows(100, 8))


def test_repeated_ids_are_refused_where_rows_meet_by_id(spark):
    """Two rows of one id aren't added up to a third point: an error without `fuse`, labels of their own with it."""
    rng = np.random.default_rng(0)
    rows = [(min(i, 199), int(i % 2), rng.standard_normal(4).tolist()) for i in range(201)]
    p = spark.createDataFrame(rows, "row_id long, row_grp int, feats array<double>")
    spec = GridSpec(((0, 1), (2, 3)))
    assert grid_cluster(p, spec, 2, passes=5, fuse=True).labels.count() == 201
    with pytest.raises(ValueError, match="unique"):
        grid_cluster(p, spec, 2, passes=5)
    from gridcluster.operators import align, partymap

    codes = partymap.encode(p, spec, partymap.fit_pca_maps(p, spec))
    with pytest.raises(Exception, match="ids must be unique"):
        align.concat_codes(codes.withColumn("row_grp", codes.row_grp * 0)).collect()


def test_empty_table_has_no_centers_and_no_labels(spark):
    from gridcluster.plans import baselines

    p = spark.createDataFrame([], "row_id long, row_grp int, feats array<double>")
    assert baselines.pooled(p, 3).count() == 0
    with pytest.raises(ValueError, match="no points"):
        grid_cluster(p, GridSpec(((0,), (1,))), 2)


def test_seeds_and_labels_of_a_trial_are_those_of_the_operators(spark, small):
    """The trial engine draws the seeds that the distributed search draws, and ends in the same clusters."""
    from gridcluster.operators import kmeans
    from gridcluster.plans import trials, workloads

    points = materialise(spark, workloads.planted_like(spark, small, "customer", "c_custkey", 4, 3, 2.2), "points")
    p = trials.Points.of(points)
    z = points.withColumnRenamed("feats", "z")
    assert np.allclose(trials.seeds(p.ids, p.feats, 3, 5, 0), kmeans.seed_dsq(z, 3, 5)[0][0])
    labels, centers = trials.kmeans_labels(p.ids, p.feats, 3, trials.Setting(3), 5)
    assert np.allclose(centers, kmeans.fit(z, 3, seed=5).centers)
    got = {r["row_id"]: r["pred"] for r in kmeans.assign(z, centers).collect()}
    assert [got[i] for i in p.ids] == labels.tolist()


@pytest.mark.parametrize("algo", ["kmeans", "spectral"])
def test_trials_follow_the_protocol(spark, small, algo):
    from gridcluster.operators import diagnostics
    from gridcluster.plans import workloads

    ledger = workloads.run_exp2(spark, small, "small_three", algo, trials=6).cache()
    assert ledger.count() == 6 * 4 * 3
    mean = {(r["method"], r["metric"]): r["mean"] for r in diagnostics.summarise_trials(ledger).collect()}
    assert abs(mean["grid", "ari"] - mean["pooled", "ari"]) < abs(mean["solo", "ari"] - mean["pooled", "ari"])
    again = workloads.run_exp2(spark, small, "small_three", algo, trials=6)
    assert sorted(map(tuple, again.collect())) == sorted(map(tuple, ledger.collect()))


def test_whole_and_sampled_projections_agree(spark, small):
    """On a party that the sample holds whole, the distributed sums give the driver's maps."""
    from gridcluster.operators import partymap
    from gridcluster.plans import workloads

    p = materialise(spark, workloads.planted_blobs(spark, small), "blobs")
    spec = GridSpec(((0, 2, 3), (1, 4, 5)))
    a, b = partymap.fit_lpp_maps(p, spec), partymap.fit_lpp_maps(p, spec, sample=10_000)
    assert all(np.allclose(a[k].proj, b[k].proj, atol=1e-6) for k in a)


def test_mixed_anchors_lie_between_neighbours(spark):
    from gridcluster.operators import anchors

    rng = np.random.default_rng(1)
    x = rng.standard_normal((60, 2))
    public = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "row_id long, feats array<double>")
    got = anchors.anchor_mix(public, 150, neighbours=3).collect()
    assert len(got) == 150 and len({r["anchor_id"] for r in got}) == 150
    d = ((x[:, None] - x) ** 2).sum(axis=2)
    np.fill_diagonal(d, np.inf)
    near = np.argsort(d, axis=1)[:, :3]
    for r in got:
        k, a = r["anchor_id"] // 3, np.array(r["feats"])
        on = [abs(np.linalg.norm(a - x[k]) + np.linalg.norm(a - x[o]) - np.linalg.norm(x[k] - x[o])) for o in near[k]]
        assert min(on) < 1e-9
