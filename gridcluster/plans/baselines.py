"""What grid clustering is compared with: pooled, solo, and two horizontal-only federated methods."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import kmeans
from ..operators import spectral as spectral_ops
from ..operators.grid import GridSpec, block
from ..operators.numeric import list_column, matrix, merge_moments, moments
from ..operators.protocol import Ledger
from ..session import materialise


def scaled(points: DataFrame, scale: str = "raw") -> DataFrame:
    """row_id, row_grp, z: features as they are, or standardised over all rows."""
    if scale == "raw":
        return points.select("row_id", "row_grp", F.col("feats").alias("z"))
    if scale != "standard":
        raise ValueError(scale)
    width = len(points.select("feats").first()["feats"])
    parts = moments(points, (tuple(range(width)),))
    n, mean, cross = merge_moments(list(parts.values()))
    sd = np.sqrt(np.diag(cross) / max(n, 1))
    sd = np.where(sd > 1e-12, sd, 1.0)

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in it:
            if b.num_rows:
                yield pa.RecordBatch.from_arrays([b.column("row_id"), b.column("row_grp"), list_column((matrix(b.column("feats")) - mean) / sd)], names=["row_id", "row_grp", "z"])

    return points.select("row_id", "row_grp", "feats").mapInArrow(run, f"row_id {dict(points.dtypes)['row_id']}, row_grp int, z array<double>")


def cluster(z: DataFrame, k: int, algo: str, passes: int = 300, restarts: int = 1, seed: int = 0, q: int = 10) -> DataFrame:
    """row_id, row_grp, pred by k-means or spectral clustering of z."""
    z = materialise(z.sparkSession, z, "points")
    if algo == "kmeans":
        return kmeans.assign(z, kmeans.fit(z, k, passes, seed, restarts).centers).select("row_id", "row_grp", "pred")
    found = spectral_ops.spectral(z, k, q, passes, seed, restarts)
    return kmeans.assign(found.embedding, found.centers).select("row_id", "pred").join(z.select("row_id", "row_grp"), "row_id").select("row_id", "row_grp", "pred")


def pooled(points: DataFrame, k: int, algo: str = "kmeans", scale: str = "raw", **options) -> DataFrame:
    """The ideal: all raw rows and features in one place."""
    return cluster(scaled(points, scale), k, algo, **options)


def solo(points: DataFrame, spec: GridSpec, i: int, j: int, k: int, algo: str = "kmeans", scale: str = "raw", **options) -> DataFrame:
    """One party's own block; its labels cover its rows only."""
    return cluster(scaled(block(points, spec, i, j), scale), k, algo, **options)


def fed_kmeans(points: DataFrame, spec: GridSpec, k: int, rounds: int = 10, local_passes: int = 20, seed: int = 0, scale: str = "raw", restarts: int = 1) -> tuple[DataFrame, Ledger]:
    """Federated k-means of the first column's parties.

    Each party seeds and refines on its rows; the hub clusters the received centers by their counts
    and sends its own; from then on a round is one local pass from the hub's centers and one merge.
    All parties' passes are one job. Restarts: the run of least inertia over the parties' reports.
    """
    z = scaled(block(points, spec, None, 0), scale)
    z = materialise(z.sparkSession, z, "column-one")
    local = kmeans.lloyd(z, kmeans.seed_dsq(z, k, seed, restarts, group="row_grp"), local_passes, group="row_grp")
    stats = kmeans.lloyd_step(z, {g: [r.centers for r in rs] for g, rs in local.items()}, group="row_grp")
    ledger = Ledger()
    width = len(spec.col_groups[0])
    best = None
    for t in range(restarts):
        sent = [(local[g][t].centers, stats[g][t][1]) for g in local]
        points_, weights = np.vstack([c for c, _ in sent]), np.concatenate([w for _, w in sent])
        keep = weights > 0
        tries = [kmeans.weighted_lloyd(points_[keep], weights[keep], kmeans.weighted_seeds(points_[keep], weights[keep], k, seed + 31 * t + a)) for a in range(5)]
        hub = min(tries, key=lambda x: x[1])[0]
        value = float("inf")
        for r in range(1, rounds):
            part = kmeans.lloyd_step(z, {g: [hub] for g in local}, group="row_grp")
            mass = sum(p[0][1] for p in part.values())
            total = sum(p[0][0] for p in part.values())
            value = sum(p[0][2] for p in part.values())
            hub = np.where(mass[:, None] > 0, total / np.maximum(mass, 1e-300)[:, None], hub)
        if best is None or value < best[0]:
            best = (value, hub)
    for r in range(1, rounds + 1):
        for g in sorted(local):
            ledger.send(r, f"party({g},0)", "hub", "centers", k, width + 1)
            ledger.send(r, "hub", f"party({g},0)", "centers", k, width)
    return kmeans.assign(z, best[1]).select("row_id", "row_grp", "pred"), ledger


def fed_spectral(points: DataFrame, spec: GridSpec, k: int, reps: int = 20, q: int = 10, passes: int = 20, seed: int = 0, scale: str = "raw") -> tuple[DataFrame, Ledger]:
    """Federated spectral clustering of the first column's parties, in one round.

    Each party sends weighted representatives; the hub clusters these by their neighbour graph and
    sends labels back; rows take the label of their party's nearest representative.
    """
    z = scaled(block(points, spec, None, 0), scale)
    z = materialise(z.sparkSession, z, "column-one")
    local = kmeans.lloyd(z, kmeans.seed_dsq(z, reps, seed, 1, group="row_grp"), passes, group="row_grp")
    stats = kmeans.lloyd_step(z, {g: [rs[0].centers] for g, rs in local.items()}, group="row_grp")
    groups = sorted(local)
    every = np.vstack([local[g][0].centers for g in groups])
    weights = np.concatenate([stats[g][0][1] for g in groups])
    used = weights > 0
    clusters = np.full(len(every), -1)
    clusters[used] = spectral_ops.cluster_landmarks(every[used], weights[used], k, q, seed)
    of, at = {}, 0
    for g in groups:
        size = len(local[g][0].centers)
        of[g] = (local[g][0].centers, clusters[at : at + size])
        at += size

    def label(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in it:
            if not b.num_rows:
                continue
            x, grp = matrix(b.column("z")), b.column("row_grp").to_numpy()
            out = np.zeros(len(x), dtype=np.int32)
            for g in np.unique(grp):
                c, names = of[int(g)]
                d = kmeans._distances(x[grp == g], c)
                d[:, names < 0] = np.inf
                out[grp == g] = names[d.argmin(axis=1)]
            yield pa.RecordBatch.from_arrays([b.column("row_id"), b.column("row_grp"), pa.array(out)], names=["row_id", "row_grp", "pred"])

    ledger = Ledger()
    for g in groups:
        ledger.send(1, f"party({g},0)", "hub", "centers", reps, every.shape[1] + 1)
        ledger.send(1, "hub", f"party({g},0)", "centers", reps, 1)
    return z.mapInArrow(label, f"row_id {dict(z.dtypes)['row_id']}, row_grp int, pred int"), ledger
