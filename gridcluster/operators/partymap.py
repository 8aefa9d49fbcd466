"""Private row-wise reducers of the parties, and the codes they give."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .grid import GridSpec
from .numeric import fix_signs, gram, list_column, matrix, moments


@dataclass
class AffineMap:
    """code = ((x - mean) / scale) @ proj"""

    mean: np.ndarray
    scale: np.ndarray
    proj: np.ndarray

    def apply(self, x: np.ndarray) -> np.ndarray:
        return ((x - self.mean) / self.scale) @ self.proj

    @property
    def width(self) -> int:
        return self.proj.shape[1]

    @property
    def matrix(self) -> np.ndarray:
        return self.proj / self.scale[:, None]


@dataclass
class NeuralMap:
    """Encoder half of a small autoencoder: tanh layer, then a linear code."""

    mean: np.ndarray
    scale: np.ndarray
    layers: list[np.ndarray]

    def apply(self, x: np.ndarray) -> np.ndarray:
        h = np.tanh((x - self.mean) / self.scale @ self.layers[0] + self.layers[1])
        return h @ self.layers[2] + self.layers[3]

    @property
    def width(self) -> int:
        return self.layers[2].shape[1]


def code_width(features: int, width: str | int = "minus1", allow_full: bool = False) -> int:
    """One less than the features, at least one; a given number must be smaller than the features unless a full width is allowed (then the second privacy layer is off)."""
    w = max(1, features - 1) if width == "minus1" else int(width)
    if w > features or w < 1 or (w == features and features > 1 and not allow_full):
        raise ValueError(f"code width {w} for {features} features")
    return w


def rotation(width: int, seed: int) -> np.ndarray:
    q, r = np.linalg.qr(np.random.default_rng(seed).standard_normal((width, width)))
    return q * np.sign(np.diag(r))


def fit_pca_maps(points: DataFrame, spec: GridSpec, width: str | int = "minus1", scale: bool = True, center: bool = True, rotate_seed: int | None = None, allow_full: bool = False) -> dict[tuple[int, int], AffineMap]:
    """A map for every party, all from one pass: standardise (or center only), then leading components.

    A constant feature keeps scale 1. center=False takes components about zero. rotate_seed mixes each
    party's code by its own secret rotation.
    """
    found = sorted(moments(points, spec.col_groups).items())
    return {(i, j): pca_map(n, mean, cross, width, scale, center, None if rotate_seed is None else rotate_seed + 1009 * i + j, allow_full) for (i, j), (n, mean, cross) in found}


def pca_map(n: int, mean: np.ndarray, cross: np.ndarray, width: str | int = "minus1", scale: bool = True, center: bool = True, rotate_seed: int | None = None, allow_full: bool = False) -> AffineMap:
    """One party's map from its rows' number, mean and centered cross products."""
    m = len(mean)
    w = code_width(m, width, allow_full)
    cov = cross / max(n, 1)
    if not center:
        cov, mean = cov + np.outer(mean, mean), np.zeros(m)
    sd = np.sqrt(np.maximum(np.diag(cov), 0)) if scale else np.ones(m)
    sd = np.where(sd > 1e-12 * max(1.0, float(np.abs(mean).max(initial=0))), sd, 1.0)
    _, vectors = np.linalg.eigh(cov / np.outer(sd, sd))
    proj = fix_signs(vectors[:, ::-1][:, :w])
    return AffineMap(mean, sd, proj if rotate_seed is None else proj @ rotation(w, rotate_seed))


def sample_rows(points: DataFrame, per_group: int, seed: int, key: str = "row_id") -> dict[int, np.ndarray]:
    """At most per_group rows of each row group, those of smallest hash: a bounded sample."""
    from pyspark.sql.window import Window

    slices = F.pmod("h", F.lit(64))
    tagged = points.select("row_grp", "feats", F.xxhash64(F.lit(seed), key).alias("h")).withColumn("s", slices)
    first = tagged.withColumn("r", F.row_number().over(Window.partitionBy("row_grp", "s").orderBy("h"))).where(F.col("r") <= -(-per_group // 16))
    top = first.withColumn("q", F.row_number().over(Window.partitionBy("row_grp").orderBy("h"))).where(F.col("q") <= per_group)
    out: dict[int, list] = {}
    for r in top.orderBy("row_grp", "q").collect():
        out.setdefault(r["row_grp"], []).append(r["feats"])
    return {g: np.array(x) for g, x in out.items()}


def _scaled_blocks(points: DataFrame, spec: GridSpec, stats: dict) -> dict[tuple[int, int], tuple[np.ndarray, np.ndarray]]:
    """Mean and deviation of each party's features; 1 for a constant one."""
    out = {}
    for key, (n, mean, cross) in sorted(stats.items()):
        sd = np.sqrt(np.diag(cross) / max(n, 1))
        out[key] = (mean, np.where(sd > 1e-12, sd, 1.0))
    return out


def fit_lpp_maps(points: DataFrame, spec: GridSpec, width: str | int = "minus1", neighbours: int = 10, sample: int | None = None, seed: int = 0, method: str = "exact", key: str = "row_id") -> dict[tuple[int, int], AffineMap]:
    """Locality-preserving projection: smallest generalised eigenvectors of the Laplacian of a party's
    neighbour graph against its degrees.

    All rows of a party take part: its graph is an edge table, and two sums of outer products over it reach the
    driver. method: of the neighbour search (`lsh` for parties of many rows). sample: at most so many rows of each
    row group instead, solved on the driver.
    """
    scales = _scaled_blocks(points, spec, moments(points, spec.col_groups))
    if sample is not None:
        rows = sample_rows(points, sample, seed, key)
    maps = {}
    for (i, j), (mean, sd) in scales.items():
        cols = list(spec.col_groups[j])
        if sample is not None:
            x = (rows[i][:, cols] - mean) / sd
            d = ((x[:, None] - x[None]) ** 2).sum(axis=2)
            np.fill_diagonal(d, np.inf)
            near = np.argsort(d, axis=1, kind="stable")[:, : min(neighbours, len(x) - 1)]
            w = np.zeros(d.shape)
            w[np.arange(len(x))[:, None], near] = 1
            w = np.maximum(w, w.T)
            deg = w.sum(axis=1)
            a, b = x.T @ (deg[:, None] * x) - x.T @ w @ x, x.T @ (deg[:, None] * x)
        else:
            a, b = _graph_products(points, i, cols, mean, sd, neighbours, seed, method, key)
        e, u = np.linalg.eigh(b + 1e-9 * np.trace(b) / len(b) * np.eye(len(b)))
        half = u / np.sqrt(e)
        _, v = np.linalg.eigh(half.T @ a @ half)
        proj = half @ v[:, : code_width(len(mean), width)]
        maps[i, j] = AffineMap(mean, sd, fix_signs(proj / np.linalg.norm(proj, axis=0)))
    return maps


def _graph_products(points: DataFrame, i: int, cols: list[int], mean: np.ndarray, sd: np.ndarray, neighbours: int, seed: int, method: str, key: str) -> tuple[np.ndarray, np.ndarray]:
    """X'LX and X'DX of a party's neighbour graph: sums over edges of the outer products of differences and of ends."""
    from ..session import forget, materialise
    from . import graph

    spark = points.sparkSession
    z = F.array(*((F.col("feats")[c] - F.lit(float(m))) / F.lit(float(v)) for c, m, v in zip(cols, mean, sd)))
    rows = materialise(spark, points.where(F.col("row_grp") == i).select(F.col(key).alias("id"), z.alias("z")), "party")
    near = graph.knn_graph(rows, neighbours, "z", "id", method=method, seed=seed)
    edges = near.select(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b")).distinct()
    ends = edges.join(rows.select(F.col("id").alias("a"), F.col("z").alias("x")), "a").join(rows.select(F.col("id").alias("b"), F.col("z").alias("y")), "b")
    pairs = materialise(spark, ends.select("x", "y"), "edges")
    lap = gram(pairs.select(F.zip_with("x", "y", lambda p, q: p - q).alias("v")), "v")
    own = gram(pairs.select(F.col("x").alias("v")).unionAll(pairs.select(F.col("y").alias("v"))), "v")
    forget(spark, rows, pairs)
    width = len(cols)
    return (lap, own) if len(own) else (np.eye(width), np.eye(width))


def fit_autoencoder_maps(points: DataFrame, spec: GridSpec, width: str | int = "minus1", hidden: int = 16, steps: int = 30, rounds: int = 10, rate: float = 0.05, seed: int = 0) -> dict[tuple[int, int], NeuralMap]:
    """A small autoencoder a party, trained over all its rows.

    A round is one scan for all parties: each task takes some gradient steps with momentum on each batch
    of a party's rows, and the tasks' weights are averaged by their rows; the next round goes on from there.
    """
    scales = _scaled_blocks(points, spec, moments(points, spec.col_groups))
    nets = {}
    for (i, j), (mean, _) in scales.items():
        m, w = len(mean), code_width(len(mean), width)
        rng = np.random.default_rng(seed + 1009 * i + j)
        nets[i, j] = [rng.standard_normal((m, hidden)) / np.sqrt(m), np.zeros(hidden), rng.standard_normal((hidden, w)) / np.sqrt(hidden), np.zeros(w), rng.standard_normal((w, m)) / np.sqrt(w), np.zeros(m)]
    groups = spec.col_groups
    for _ in range(rounds):
        now = {key: [p.copy() for p in net] for key, net in nets.items()}

        def run(batches: Iterator[pa.RecordBatch], now=now) -> Iterator[pa.RecordBatch]:
            held: dict[tuple[int, int], list] = {}
            for b in batches:
                if not b.num_rows:
                    continue
                x, grp = matrix(b.column("feats")), b.column("row_grp").to_numpy()
                for i in np.unique(grp):
                    for j, cols in enumerate(groups):
                        mean, sd = scales[int(i), j]
                        at = held.setdefault((int(i), j), [0, [p.copy() for p in now[int(i), j]]])
                        part = (x[grp == i][:, list(cols)] - mean) / sd
                        at[0] += len(part)
                        _train(at[1], part, steps, rate)
            names = ["row_grp", "col_grp", "n", "dots"]
            rows = [(i, j, n, (n * np.concatenate([p.ravel() for p in net])).tolist()) for (i, j), (n, net) in held.items()]
            types = [pa.int32(), pa.int32(), pa.int64(), pa.list_(pa.float64())]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(list(zip(*rows)) or [[]] * 4, types)], names=names)

        def add(t: pa.Table) -> pa.Table:
            return pa.table({"row_grp": t["row_grp"].slice(0, 1), "col_grp": t["col_grp"].slice(0, 1), "n": pa.array([sum(t["n"].to_pylist())]), "dots": list_column(matrix(t["dots"]).sum(axis=0, keepdims=True))})

        schema = "row_grp int, col_grp int, n long, dots array<double>"
        for r in points.select("row_grp", "feats").mapInArrow(run, schema).groupBy("row_grp", "col_grp").applyInArrow(add, schema).collect():  # a row a party
            flat, at, net = np.array(r["dots"]) / r["n"], 0, nets[r["row_grp"], r["col_grp"]]
            for p in net:
                p[...] = flat[at : at + p.size].reshape(p.shape)
                at += p.size
    return {key: NeuralMap(*scales[key], net[:4]) for key, net in nets.items()}


def _train(p: list[np.ndarray], x: np.ndarray, steps: int, rate: float) -> None:
    speed = [np.zeros_like(q) for q in p]
    for _ in range(steps):
        h = np.tanh(x @ p[0] + p[1])
        z = h @ p[2] + p[3]
        err = (z @ p[4] + p[5] - x) / len(x)
        dz = err @ p[4].T
        dh = dz @ p[2].T * (1 - h * h)
        grads = [x.T @ dh, dh.sum(axis=0), h.T @ dz, dz.sum(axis=0), z.T @ err, err.sum(axis=0)]
        for k, g in enumerate(grads):
            speed[k] = 0.9 * speed[k] - rate * g
            p[k] += speed[k]


def encode(points: DataFrame, spec: GridSpec, maps: dict, key: str = "row_id") -> DataFrame:
    """Codes of all parties: key, row_grp, col_grp, code. Each row meets its own row group's maps only."""
    groups = spec.col_groups

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            x, grp = matrix(b.column("feats")), b.column("row_grp").to_numpy()
            for i in np.unique(grp):
                mine = grp == i
                ids = b.column(key).filter(pa.array(mine))
                for j, cols in enumerate(groups):
                    code = maps[int(i), j].apply(x[mine][:, list(cols)])
                    yield pa.RecordBatch.from_arrays([ids, pa.array(np.full(len(code), i, dtype=np.int32)), pa.array(np.full(len(code), j, dtype=np.int32)), list_column(code)], names=[key, "row_grp", "col_grp", "code"])

    kind = dict(points.dtypes)[key]
    return points.select(key, "row_grp", "feats").mapInArrow(run, f"{key} {kind}, row_grp int, col_grp int, code array<double>")


def encode_anchors(anchors: DataFrame, spec: GridSpec, maps: dict) -> DataFrame:
    """Every party's code of every anchor: anchor_id, row_grp, col_grp, code."""
    row_groups = sorted({i for i, _ in maps})
    every = anchors.withColumn("row_grp", F.explode(F.array(*map(F.lit, row_groups)))).withColumn("row_grp", F.col("row_grp").cast("int"))
    return encode(every, spec, maps, key="anchor_id")
