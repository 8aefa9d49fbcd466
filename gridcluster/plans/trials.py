"""Many trials of the second experiment on a small table: a trial is a task, the table is broadcast.

The numbers are those of the distributed operators: maps, aligners, seeds, passes, graphs and embeddings
come from the same functions, over the whole table in one process.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator, Sequence
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame, SparkSession

from ..functions.portable import hashed_uniform
from ..operators import kmeans, metrics, partymap
from ..operators import spectral as spectral_ops
from ..operators.align import block_order, solve_aligner
from ..operators.graph import _nearest_between
from ..operators.grid import even_columns
from ..operators.local import neighbour_embedding, neighbour_links
from ..operators.numeric import matrix
from ..session import materialise

#: Rows of a table whose trials run in tasks: some 100 bytes each for k-means, some 600 for spectral clustering.
MOST_ROWS = {"kmeans": 2_000_000, "spectral": 1_500_000}
#: Rows of a table whose eigenproblem a trial solves from the matrix.
DENSE_ROWS = 500
#: Anchors whose codes are held at once.
ANCHOR_BLOCK = 1 << 14


@dataclass(frozen=True)
class Points:
    ids: np.ndarray
    feats: np.ndarray
    truth: np.ndarray

    @classmethod
    def of(cls, points: DataFrame) -> Points:
        t = points.select("row_id", "feats", "truth").orderBy("row_id").toArrow()  # the caller has checked the size
        return cls(t["row_id"].to_numpy(), matrix(t["feats"]), t["truth"].to_numpy())


@dataclass(frozen=True)
class Setting:
    k: int
    algo: str = "kmeans"
    row_groups: int = 10
    column_groups: int = 2
    methods: Sequence[str] = ("solo", "fed", "grid", "pooled")
    restarts: int = 1
    passes: int = 300
    rounds: int = 10
    aligner: str = "affine"
    target: str = "U"
    q: int = 10
    anchors: int | None = None


def trial_seed(dataset: str, trial: int) -> int:
    return int(hashlib.md5(f"{dataset}~{trial}".encode()).hexdigest()[:8], 16)


def table_of(truth: np.ndarray, pred: np.ndarray) -> np.ndarray:
    _, a = np.unique(truth, return_inverse=True)
    _, b = np.unique(pred, return_inverse=True)
    out = np.zeros((a.max(initial=-1) + 1, b.max(initial=-1) + 1))
    np.add.at(out, (a, b), 1)
    return out


def kmeans_labels(ids: np.ndarray, z: np.ndarray, k: int, s: Setting, seed: int, passes: int | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Labels and centers: seeds by squared distance and the restart of least inertia, as `kmeans.fit`."""
    best = None
    for r in range(s.restarts):
        centers, value, near = kmeans.lloyd_labels(z, np.ones(len(z)), seeds(ids, z, k, seed, r), passes or s.passes)
        if best is None or value < best[0]:
            best = (value, centers, near)
    return best[2], best[1]


def seeds(ids: np.ndarray, z: np.ndarray, k: int, seed: int, restart: int) -> np.ndarray:
    """The rows that `kmeans.seed_dsq` draws."""
    out: list[np.ndarray] = []
    near, zero = np.full(len(z), np.inf), 1e-12 * np.maximum(1.0, (z**2).sum(axis=1))
    for draw in range(min(k, len(z))):
        d2 = np.ones(len(z))
        if draw:
            near = np.minimum(near, kmeans._distances(z, out[-1][None])[:, 0])
            d2 = np.where(near > zero, near, 0)
        with np.errstate(divide="ignore"):
            race = np.where(d2 > 0, -np.log(hashed_uniform(ids, seed, draw, restart)) / d2, np.inf)
        least = np.nonzero(race == race.min())[0]
        i = int(least[ids[least].argmin()])
        if not np.isfinite(race[i]):
            break  # all rows lie at the places drawn
        out.append(z[i])
    return np.array(out)


def embedded(ids: np.ndarray, z: np.ndarray, k: int, q: int) -> np.ndarray:
    """Rows of the k eigenvectors over the neighbour graph, made symmetric by the mean."""
    if len(ids) > DENSE_ROWS:
        return neighbour_embedding(len(ids), neighbour_links(ids, z, q), k, spectral_ops.TOLERANCE, spectral_ops.DEGREE)[1]
    e = _nearest_between(ids, z, ids, z, q, include_self=False)
    src, dst = e["src"].to_numpy(), e["dst"].to_numpy()
    return spectral_ops.dense_embedding(np.unique(ids), np.concatenate([src, dst]), np.concatenate([dst, src]), np.full(2 * len(src), 0.5), k)[1]


def clustered(ids: np.ndarray, z: np.ndarray, s: Setting, seed: int) -> np.ndarray:
    z = embedded(ids, z, s.k, s.q) if s.algo == "spectral" else z
    return kmeans_labels(ids, z, s.k, s, seed)[0]


def common_space(points: Points, groups: np.ndarray, columns: tuple[tuple[int, ...], ...], s: Setting, seed: int) -> np.ndarray:
    """Party maps, uniform anchors, aligners, aligned codes; with aligner `none` the codes as they are."""
    maps, codes = {}, []
    for i in range(s.row_groups):
        rows = points.feats[groups == i]
        blocks = [np.take(rows, cols, axis=1) for cols in columns]
        for j, x in enumerate(blocks):
            mean = x.mean(axis=0)
            maps[i, j] = partymap.pca_map(len(x), mean, (x - mean).T @ (x - mean))
        codes.append(np.hstack([maps[i, j].apply(x) for j, x in enumerate(blocks)]))
    if s.aligner == "none":
        out = np.zeros((len(points.ids), codes[0].shape[1]))
        for i, c in enumerate(codes):
            out[groups == i] = c
        return out
    lo, hi = points.feats.min(axis=0), points.feats.max(axis=0)
    one = s.aligner == "affine"
    dots, rng, count = 0.0, np.random.default_rng(seed), s.anchors or len(points.ids)
    for a in range(0, count, ANCHOR_BLOCK):  # all anchors, but their codes at all parties only block by block
        anchors = lo + rng.random((min(ANCHOR_BLOCK, count - a), len(lo))) * (hi - lo)
        wide = np.hstack([maps[i, j].apply(anchors[:, list(c)]) for i in range(s.row_groups) for j, c in enumerate(columns)] + ([np.ones((len(anchors), 1))] if one else []))
        dots = dots + wide.T @ wide
    order, spans = block_order([(i, j, maps[i, j].width) for i in range(s.row_groups) for j in range(len(columns))], one)
    found = solve_aligner(dots[np.ix_(order, order)], spans, s.aligner, "min_code", s.target)
    out = np.zeros((len(points.ids), found.width))
    for i, c in enumerate(codes):
        out[groups == i] = c @ found.weights[i] + found.shift[i]
    return out


def federated_kmeans(points: Points, groups: np.ndarray, columns: tuple[int, ...], s: Setting, seed: int, local_passes: int = 20) -> np.ndarray:
    """As `baselines.fed_kmeans`: local clusterings, their merge by counts, then rounds of one local pass and one merge."""
    z = points.feats[:, list(columns)]
    columns_ = np.ascontiguousarray(z.T)
    best = None
    for t in range(s.restarts):
        sent, weights = [], []
        for i in range(s.row_groups):
            mine = groups == i
            centers, _, own = kmeans.lloyd_labels(z[mine], np.ones(int(mine.sum())), seeds(points.ids[mine], z[mine], s.k, seed, t), local_passes)
            sent.append(centers)
            weights.append(np.bincount(own, minlength=len(centers)))
        sent_, weights_ = np.vstack(sent), np.concatenate(weights).astype(np.float64)
        keep = weights_ > 0
        tries = [kmeans.weighted_lloyd(sent_[keep], weights_[keep], kmeans.weighted_seeds(sent_[keep], weights_[keep], s.k, seed + 31 * t + a)) for a in range(5)]
        hub, value = min(tries, key=lambda x: x[1])[0], float("inf")
        for _ in range(1, s.rounds):
            near, d, _ = kmeans.nearest_two(columns_, hub)
            mass = np.bincount(near, minlength=len(hub))
            total = np.stack([np.bincount(near, weights=x, minlength=len(hub)) for x in columns_], axis=1)
            value = float(d.sum())
            hub = np.where(mass[:, None] > 0, total / np.maximum(mass, 1)[:, None], hub)
        if best is None or value < best[0]:
            best = (value, hub)
    return kmeans.nearest_two(columns_, best[1])[0]


def federated_spectral(points: Points, groups: np.ndarray, columns: tuple[int, ...], s: Setting, seed: int, reps: int = 20, passes: int = 20) -> np.ndarray:
    """As `baselines.fed_spectral`: weighted representatives of each party, clustered at the hub; rows follow their party's nearest."""
    z = points.feats[:, list(columns)]
    every, weights, near = [], [], np.zeros(len(z), dtype=np.int64)
    at = 0
    for i in range(s.row_groups):
        mine = groups == i
        centers, _, own = kmeans.lloyd_labels(z[mine], np.ones(int(mine.sum())), seeds(points.ids[mine], z[mine], reps, seed, 0), passes)
        near[mine] = own + at
        every.append(centers)
        weights.append(np.bincount(own, minlength=len(centers)).astype(np.float64))
        at += len(centers)
    every_, weights_ = np.vstack(every), np.concatenate(weights)
    used = weights_ > 0
    clusters = np.full(len(every_), -1)
    clusters[used] = spectral_ops.cluster_landmarks(every_[used], weights_[used], s.k, s.q, seed)
    return clusters[near]


def one_trial(points: Points, s: Setting, seed: int, pooled: np.ndarray | None = None) -> list[tuple[str, str, float]]:
    """(method, measure, value) under a random cut into equal row groups and equal column groups."""
    columns = even_columns(points.feats.shape[1], s.column_groups, seed)
    order = np.argsort(hashed_uniform(points.ids, seed, 77), kind="stable")
    groups = np.empty(len(order), dtype=np.int64)
    groups[order] = np.arange(len(order)) % s.row_groups
    out = []
    for m in s.methods:
        truth = points.truth
        if m == "solo":
            mine = groups == 0
            truth = truth[mine]
            pred = clustered(points.ids[mine], points.feats[mine][:, list(columns[0])], s, seed)
        elif m == "fed":
            pred = (federated_kmeans if s.algo == "kmeans" else federated_spectral)(points, groups, columns[0], s, seed)
        elif m == "grid":
            pred = clustered(points.ids, common_space(points, groups, columns, s, seed), s, seed)
        elif m == "pooled":
            pred = kmeans_labels(points.ids, points.feats if pooled is None else pooled, s.k, s, seed)[0]
        else:
            raise ValueError(m)
        u = table_of(truth, pred)
        out += [(m, "ari", metrics.ari(u)), (m, "nmi", metrics.nmi(u)), (m, "acc", metrics.acc(u))]
    return out


_LEDGER = "dataset string, method string, trial int, metric string, value double"


def run_trials(spark: SparkSession, points: Points, s: Setting, dataset: str, trials: int) -> DataFrame:
    """A ledger row a trial, method and measure: dataset, method, trial, metric, value. Written, so that a report which
    reads it several times doesn't run the trials as often.

    The pooled embedding is the same in all trials: one more task beside theirs, numbered -1, whose rows are clustered after it.
    """
    apart = s.algo == "spectral" and "pooled" in s.methods
    shared = spark.sparkContext.broadcast(points)  # at most MOST_ROWS rows
    first = _trials(spark, dataset, replace(s, methods=[m for m in s.methods if m != "pooled"]) if apart else s, shared, -1 if apart else 0, trials)
    first = materialise(spark, first, "trials")
    if not apart:
        return first.drop("embedding")
    found = np.frombuffer(first.where("trial < 0").first()["embedding"]).reshape(len(points.ids), -1)
    pooled = _trials(spark, dataset, replace(s, methods=["pooled"]), shared, 0, trials, spark.sparkContext.broadcast(found))
    return first.where("trial >= 0").unionByName(materialise(spark, pooled, "trials")).drop("embedding")


def _trials(spark: SparkSession, dataset: str, s: Setting, shared: Broadcast, begin: int, end: int, pooled: Broadcast | None = None) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = shared.value
        for b in batches:
            for t in b.column("id").to_pylist():
                if t < 0:
                    rows = [(dataset, "pooled", t, "embedding", None, embedded(table.ids, table.feats, s.k, s.q).tobytes())]
                else:
                    rows = [(dataset, m, t, name, float(v), None) for m, name, v in one_trial(table, s, trial_seed(dataset, t), pooled and pooled.value)]
                if rows:
                    kinds = pa.string(), pa.string(), pa.int32(), pa.string(), pa.float64(), pa.binary()
                    yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows), kinds)], names=["dataset", "method", "trial", "metric", "value", "embedding"])

    tasks = max(1, min(end - begin, 16 * spark.sparkContext.defaultParallelism))
    return spark.range(begin, end, 1, tasks).mapInArrow(run, f"{_LEDGER}, embedding binary")
