"""Party maps and aligners against numpy, and the exactness theorem."""

from __future__ import annotations

import warnings

import numpy as np
import pytest
from pyspark.sql import functions as F

from gridcluster.operators import align, exactness, numeric, partymap, privacy
from gridcluster.operators.grid import GridSpec, even_columns


def frame(spark, x, grp, key="row_id"):
    return spark.createDataFrame([(i, int(g), list(map(float, v))) for i, (g, v) in enumerate(zip(grp, x))], f"{key} long, row_grp int, feats array<double>").repartition(3)


def codes_frame(spark, blocks):
    rows = [(a, i, 0, list(map(float, v))) for i, x in blocks.items() for a, v in enumerate(x)]
    return spark.createDataFrame(rows, "anchor_id long, row_grp int, col_grp int, code array<double>")


def test_moments_survive_large_offsets(spark):
    rng = np.random.default_rng(0)
    x = rng.standard_normal((500, 3)) + [1e8, -1e6, 0]
    grp = rng.integers(0, 2, 500)
    found = numeric.moments(frame(spark, x, grp), ((0, 1), (2,)))
    for g in (0, 1):
        n, mean, cross = found[g, 0]
        assert n == (grp == g).sum()
        assert np.allclose(cross / n, np.cov(x[grp == g][:, :2].T, bias=True), atol=1e-6)


def test_pca_map_and_codes(spark):
    rng = np.random.default_rng(1)
    x = rng.standard_normal((200, 4)) @ rng.standard_normal((4, 4))
    spec = GridSpec(even_columns(4, 2))
    df = frame(spark, x, np.zeros(200, int))
    m = partymap.fit_pca_maps(df, spec)[0, 0]
    own = x[:, :2]
    z = (own - own.mean(axis=0)) / own.std(axis=0)
    values, vectors = np.linalg.eigh(np.cov(z.T, bias=True))
    assert abs(abs(vectors[:, -1] @ m.proj[:, 0]) - 1) < 1e-10
    code = {(r["row_id"], r["col_grp"]): r["code"] for r in partymap.encode(df, spec, partymap.fit_pca_maps(df, spec)).collect()}
    assert np.allclose([code[i, 0][0] for i in range(200)], z @ m.proj[:, 0])


def test_constant_and_single_features(spark):
    x = np.column_stack([np.ones(20), np.arange(20.0), np.arange(20.0) % 3])
    spec = GridSpec(((0, 1), (2,)))
    maps = partymap.fit_pca_maps(frame(spark, x, np.zeros(20, int)), spec)
    assert maps[0, 0].scale[0] == 1.0 and maps[0, 1].width == 1
    with pytest.raises(ValueError):
        partymap.code_width(3, 3)
    with pytest.raises(NotImplementedError):
        GridSpec(((0, 1), (1, 2)))


def test_null_or_nan_points_are_refused(spark):
    df = spark.createDataFrame([(0, 0, [1.0, float("nan")])], "row_id long, row_grp int, feats array<double>")
    with pytest.raises(Exception, match="null, NaN or infinite"):
        numeric.moments(df, ((0, 1),))


@pytest.mark.parametrize("kind", ["linear", "affine"])
@pytest.mark.parametrize("target", ["U", "US"])
@pytest.mark.parametrize("solver", ["gram", "tsqr"])
def test_aligner_equals_direct_pseudo_inverse(spark, kind, target, solver):
    rng = np.random.default_rng(2)
    blocks = {i: rng.standard_normal((60, 3)) @ rng.standard_normal((3, 3)) + rng.standard_normal(3) for i in range(3)}
    found = align.fit_aligner(codes_frame(spark, blocks), kind, width=3, target=target, solver=solver)
    full = {i: np.hstack([b, np.ones((60, 1))]) if kind == "affine" else b for i, b in blocks.items()}
    u, s, _ = np.linalg.svd(np.hstack([full[i] for i in range(3)]), full_matrices=False)
    goal = u[:, :3] * (s[:3] if target == "US" else 1)
    for i in range(3):
        mine, direct = full[i] @ found.full(i), full[i] @ np.linalg.pinv(full[i]) @ goal
        sign = np.sign((mine * direct).sum(axis=0))
        assert np.allclose(mine * sign, direct, atol=1e-7)


def test_affine_brings_equal_ranges_together_and_linear_does_not(spark):
    """Maps F_0 Q_i of one range with different means: the affine residual vanishes."""
    rng = np.random.default_rng(3)
    anchors, base = rng.uniform(-1, 1, (80, 6)), rng.standard_normal((6, 4))
    means = {i: rng.standard_normal(6) for i in range(3)}
    proj = {i: base @ rng.standard_normal((4, 4)) for i in range(3)}
    blocks = {i: (anchors - means[i]) @ proj[i] for i in range(3)}
    codes = codes_frame(spark, blocks)
    affine = align.fit_aligner(codes, "affine", solver="tsqr")
    linear = align.fit_aligner(codes, "linear", solver="tsqr")
    assert max(align.anchor_difference(codes, affine, 0, i) for i in (1, 2)) < 1e-8
    assert align.anchor_difference(codes, linear, 0, 1) > 0.1
    report = exactness.exactness_report(proj, blocks)
    assert report.affine_exact
    exact = exactness.exact_affine(proj, means)
    common = [blocks[i] @ exact[i][0] + exact[i][1] for i in range(3)]
    assert np.abs(common[0] - common[1]).max() < 1e-10 and np.abs(common[0] - common[2]).max() < 1e-10


def test_unequal_ranges_are_reported():
    rng = np.random.default_rng(4)
    proj = {i: rng.standard_normal((6, 4)) for i in range(2)}
    report = exactness.exactness_report(proj, {0: rng.standard_normal((20, 4))})
    assert not report.equal_ranges and report.full_rank


def test_protocol_and_fused_coordinates_agree(spark):
    rng = np.random.default_rng(5)
    x, grp = rng.standard_normal((120, 6)), rng.integers(0, 3, 120)
    df, spec = frame(spark, x, grp), GridSpec(even_columns(6, 2))
    maps = partymap.fit_pca_maps(df, spec)
    shared = spark.createDataFrame([(i, list(map(float, v))) for i, v in enumerate(rng.uniform(-2, 2, (50, 6)))], "anchor_id long, feats array<double>")
    found = align.fit_aligner(partymap.encode_anchors(shared, spec, maps))
    widths = {k: m.width for k, m in maps.items()}
    a = {r["row_id"]: r["z"] for r in align.apply_aligner(partymap.encode(df, spec, maps), found, widths).collect()}
    b = {r["row_id"]: r["z"] for r in align.fused_transform(df, spec, maps, found).collect()}
    assert all(np.allclose(a[i], b[i], atol=1e-10) for i in range(120))


def test_leak_probe_is_the_dropped_variance(spark):
    rng = np.random.default_rng(6)
    x = rng.standard_normal((300, 3)) * [3, 2, 1]
    df, spec = frame(spark, x, np.zeros(300, int)), GridSpec(((0, 1, 2),))
    maps = partymap.fit_pca_maps(df, spec, scale=False)
    values = np.linalg.eigvalsh(np.cov(x.T, bias=True))
    assert privacy.leak_probe(df, spec, maps)[0, 0] == pytest.approx(values[0] / values.sum(), rel=1e-6)
    with warnings.catch_warnings(record=True) as seen:
        warnings.simplefilter("always")
        assert privacy.leak_probe(df, spec, partymap.fit_pca_maps(df, spec, width=3, allow_full=True))[0, 0] < 1e-12
    assert seen


def test_bounds_and_anchors_are_the_parties_own_work(spark):
    from gridcluster.operators import anchors

    a = anchors.anchor_uniform(spark, [(0.0, 1.0), (-2.0, 2.0)], 50, seed=9)
    b = anchors.anchor_uniform(spark, [(0.0, 1.0), (-2.0, 2.0)], 50, seed=9).repartition(3)
    assert sorted(map(tuple, (r["feats"] for r in a.collect()))) == sorted(map(tuple, (r["feats"] for r in b.collect())))
    lo, hi = a.agg(F.min(F.col("feats")[1]), F.max(F.col("feats")[1])).first()
    assert -2 <= lo < hi <= 2
