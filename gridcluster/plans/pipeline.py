"""Grid clustering from raw blocks to labels at the parties, with its ledger and diagnostics."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import anchors as anchor_tables
from ..operators import kmeans, partymap, protocol
from ..operators import spectral as spectral_ops
from ..operators.align import Aligner, anchor_rows, apply_aligner, fit_aligner, fused_transform
from ..operators.grid import GridSpec, default_anchor_rows
from ..operators.numeric import column_bounds
from ..session import materialise


@dataclass
class GridResult:
    """labels: row_id, row_grp, pred. z: the cluster space. landmarks, if any, stand for centers."""

    labels: DataFrame
    centers: np.ndarray
    z: DataFrame
    maps: dict
    aligner: Aligner | None
    ledger: protocol.Ledger
    diagnostics: dict = field(default_factory=dict)
    landmark_clusters: np.ndarray | None = None


def fit_maps(points: DataFrame, spec: GridSpec, kind: str = "pca", **options) -> dict:
    fits = {"pca": partymap.fit_pca_maps, "lpp": partymap.fit_lpp_maps, "autoencoder": partymap.fit_autoencoder_maps}
    return fits[kind](points, spec, **options)


def make_anchors(points: DataFrame, spec: GridSpec, rows: int, seed: int, kind: str | DataFrame = "uniform", bounds: list[tuple[float, float]] | None = None) -> DataFrame:
    """A shared table: `uniform` in the features' ranges (given, or taken from the data), or a table of one's own."""
    if isinstance(kind, DataFrame):
        return kind
    if kind != "uniform":
        raise ValueError(kind)
    return anchor_tables.anchor_uniform(points.sparkSession, bounds or column_bounds(points, spec.width), rows, seed)


def grid_cluster(points: DataFrame, spec: GridSpec, k: int, algo: str = "kmeans", anchor: str | DataFrame = "uniform", anchor_count: int | None = None, bounds: list[tuple[float, float]] | None = None, map_kind: str = "pca", map_options: dict | None = None, aligner: str = "affine", width: int | str | float = "min_code", target: str = "U", solver: str = "gram", passes: int = 300, restarts: int = 1, tol: float | None = None, q: int = 10, seed: int = 0, fuse: bool = False, landmarks: int | None = None) -> GridResult:
    """Clusters points (row_id, row_grp, feats) that parties hold in blocks.

    Parties reduce their rows and the shared anchors by private maps and send both once; the hub learns
    aligners from the anchors' codes, clusters the common representation, and sends back centers and
    each row group's part of the cluster space; parties label rows by the nearest center. Row ids must be
    unique wherever rows are put together by them: without `fuse`, and for neighbour graphs; that is checked.

    aligner: `affine`, `linear`, or `none` (codes as they are: shown to fail). fuse: map and align in
    one narrow step, for one trusted cluster. landmarks: spectral clustering of so many representatives,
    for tables beyond exact neighbour graphs.
    """
    spark = points.sparkSession
    n_by = {r["row_grp"]: r["n"] for r in points.groupBy("row_grp").agg(F.count(F.lit(1)).alias("n")).collect()}
    if not n_by:
        raise ValueError("no points")
    if not fuse or (algo == "spectral" and not landmarks):
        twice = points.groupBy("row_id").agg(F.count(F.lit(1)).alias("n")).where("n > 1").first()
        if twice:
            raise ValueError(f"row_id {twice['row_id']} is there {twice['n']} times: ids must be unique")
    maps = fit_maps(points, spec, map_kind, **(map_options or {}))
    widths = {key: m.width for key, m in maps.items()}
    total = sum(widths.values())
    n = sum(n_by.values())
    rows = anchor_count or default_anchor_rows(n, total)
    shared = make_anchors(points, spec, rows, seed, anchor, bounds)
    if aligner == "none":
        found = None
        z = partymap_concat(points, spec, maps)
    else:
        codes = protocol.hub_may_hold(partymap.encode_anchors(shared, spec, maps))
        found = fit_aligner(codes, aligner, width, target, solver)
        if fuse:
            z = fused_transform(points, spec, maps, found)
        else:
            z = apply_aligner(protocol.hub_may_hold(partymap.encode(points, spec, maps)), found, widths)
    z = materialise(spark, protocol.hub_may_hold(z), "common")
    result = hub_cluster(z, k, algo, passes, restarts, tol, q, seed, landmarks)
    space = result[1].shape[1] if len(result[1]) else 0
    ledger = protocol.grid_ledger(n_by, widths, rows, k, space, {j: len(c) for j, c in enumerate(spec.col_groups)} if anchor == "uniform" and bounds is None else None)
    ledger.audit()
    space_rows, centers, lookup = result
    return GridResult(party_labels(space_rows, centers, lookup), centers, space_rows, maps, found, ledger, {"anchor_rows": rows, "width": space}, lookup)


def partymap_concat(points: DataFrame, spec: GridSpec, maps: dict) -> DataFrame:
    from ..operators.align import concat_codes

    return concat_codes(partymap.encode(points, spec, maps)).select("row_id", "row_grp", F.col("code").alias("z"))


def hub_cluster(z: DataFrame, k: int, algo: str, passes: int, restarts: int, tol: float | None, q: int, seed: int, landmarks: int | None) -> tuple[DataFrame, np.ndarray, np.ndarray | None]:
    """Cluster space (row_id, row_grp, z), centers, and the cluster of each center where these are landmarks."""
    if algo == "kmeans":
        return z, kmeans.fit(z, k, passes, seed, restarts, tol).centers, None
    if algo != "spectral":
        raise ValueError(algo)
    if landmarks:
        points, clusters = spectral_ops.spectral_landmarks(z, k, landmarks, q, seed=seed, restarts=max(restarts, 1))
        return z, points, clusters
    found = spectral_ops.spectral(z, k, q, passes, seed, restarts)
    return found.embedding.join(z.select("row_id", "row_grp"), "row_id").select("row_id", "row_grp", "z"), found.centers, None


def party_labels(z: DataFrame, centers: np.ndarray, lookup: np.ndarray | None = None) -> DataFrame:
    """What each party works out for its rows from the download."""
    out = kmeans.assign(z, centers).select("row_id", "row_grp", "pred")
    if lookup is not None:
        named = F.array(*(F.lit(int(c)) for c in lookup))
        out = out.withColumn("pred", F.element_at(named, F.col("pred") + 1))
    return out
