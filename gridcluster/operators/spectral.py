"""Spectral embedding and clustering of a neighbour graph."""

from __future__ import annotations

import warnings
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import forget, materialise
from . import graph, kmeans
from .local import links_between, neighbour_embedding, sparse_embedding
from .numeric import fix_signs, list_column

#: Nodes up to which the eigenproblem is solved whole on the driver (a matrix of 8 n^2 bytes).
DENSE_NODES = 3000
#: Nodes up to which one task solves it with sparse products (some 500 bytes a node).
TASK_NODES = 500_000
#: The same for the neighbour graph of rows whose edges come as halves (some 600 bytes a node).
NEIGHBOUR_NODES = 2_000_000


@dataclass
class SpectralResult:
    """embedding: row_id, z; centers in that space."""

    embedding: DataFrame
    centers: np.ndarray
    eigenvalues: np.ndarray


def dense_embedding(ids: np.ndarray, src: np.ndarray, dst: np.ndarray, w: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Eigenvectors of the k least eigenvalues of the normalised Laplacian, as columns."""
    n = len(ids)
    at_s, at_d = np.searchsorted(ids, src), np.searchsorted(ids, dst)
    weights = np.zeros((n, n))
    np.add.at(weights, (at_s, at_d), w)
    root = 1 / np.sqrt(np.maximum(weights.sum(axis=1), 1e-300))
    values, vectors = np.linalg.eigh(np.eye(n) - root[:, None] * weights * root[None])
    return values[:k], fix_signs(vectors[:, :k])


#: Products with the edges between two written blocks, and what a round may leave as residual of an eigenvector.
DEGREE, TOLERANCE = 12, 1e-4


def subspace_embedding(spark: SparkSession, edges: DataFrame, k: int, rounds: int = 25, tol: float = TOLERANCE, padding: int | None = None, seed: int = 0, degree: int = DEGREE) -> tuple[DataFrame, np.ndarray]:
    """The same eigenvectors by subspace iteration with a Chebyshev filter of the normalised weights.

    A product is one join with the edges, which lie dealt by their end once and for all, and one sum by
    their begin; the block and the one before it, which the filter's recursion needs, travel in one row, so
    `degree` products are one job without a table in between. After them the block is made orthonormal and
    turned to its Ritz vectors; only small matrices of products reach the driver. Ends when the residual
    of each of the k vectors is at most tol; warns if `rounds` don't get there.
    """
    from ..functions.portable import gaussian

    p = k + (max(4, k) if padding is None else padding)
    norm = materialise(spark, graph.normalised_weights(edges), "normalised")
    ids = norm.select(F.col("src").alias("id")).distinct()
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    both = norm.select("src", "dst", "w", F.lit(False).alias("own")).unionAll(ids.select(F.col("id").alias("src"), F.col("id").alias("dst"), F.lit(0.0).alias("w"), F.lit(True).alias("own")))
    ends = both.repartition(parts, "dst").persist(StorageLevel.MEMORY_AND_DISK)
    cols, olds = [f"v{i}" for i in range(p)], [f"o{i}" for i in range(p)]

    def products(a: DataFrame, left: list[str], right: list[str]) -> np.ndarray:
        r = a.agg(*(F.sum(F.col(x) * F.col(y)).alias(f"{i}_{j}") for i, x in enumerate(left) for j, y in enumerate(right))).first()
        return np.array(r, dtype=np.float64).reshape(len(left), len(right))

    def turned(a: DataFrame, t: np.ndarray) -> DataFrame:
        return a.select("id", *(sum((F.col(x) * F.lit(float(t[i, j])) for i, x in enumerate(cols)), F.lit(0.0)).alias(cols[j]) for j in range(t.shape[1])))

    def step(a: DataFrame, edge: float, own: float, old: float, keep: bool = True) -> DataFrame:
        """edge * (weights times v) + own * v + old * o, and v as the next o."""
        met = ends.join(a, F.col("dst") == F.col("id"))
        new = [F.when(F.col("own"), F.col(v) * own + (F.col(o) * old if old else 0.0)).otherwise(F.col("w") * F.col(v) * edge).alias(v) for v, o in zip(cols, olds)]
        before = [F.when(F.col("own"), F.col(v)).otherwise(0.0).alias(o) for v, o in zip(cols, olds)]
        return met.select(F.col("src").alias("id"), *new, *(before if keep else [])).groupBy("id").agg(*(F.sum(c).alias(c) for c in cols + (olds if keep else [])))

    try:
        block = materialise(spark, ids.select("id", *(gaussian(seed, F.col("id"), i).alias(f"v{i}") for i in range(p))), "block")
        view, turn, low, ritz, rest = block, np.eye(p), 0.5, np.zeros(p), np.inf
        for _ in range(rounds):
            half, mid = (low + 1) / 2, (low - 1) / 2  # the filter damps what lies between -1 and low
            y = step(turned(view, turn), 1 / half, -mid / half, 0.0)
            for _ in range(degree - 1):
                y = step(y, 2 / half, -2 * mid / half, -1.0)
            y = materialise(spark, y.select("id", *cols), "block")
            forget(spark, block)
            values, vectors = np.linalg.eigh(products(y, cols, cols))
            orthonormal = turned(y, vectors / np.sqrt(np.maximum(values, 1e-300 + values[-1] * 1e-15)))
            images = step(orthonormal, 1.0, 0.0, 0.0)  # an image and, as `o`, what it is of
            block = materialise(spark, images, "block")
            forget(spark, y)
            t, square = products(block, olds, cols), products(block, cols, cols)
            ritz, turn = np.linalg.eigh((t + t.T) / 2)
            ritz, turn = ritz[::-1], turn[:, ::-1]
            left = np.sqrt(np.maximum(np.einsum("ij,ik,kj->j", turn, square, turn) - ritz**2, 0))
            view = block.select("id", *(F.col(o).alias(v) for o, v in zip(olds, cols)))
            rest, low = float(left[:k].max()), float(np.clip(ritz[-1], -0.5, 1 - 1e-6))
            if rest <= tol:
                break
        else:
            warnings.warn(f"the embedding was left with residuals of {rest:.1e} after {rounds} rounds", stacklevel=2)
        out = materialise(spark, turned(view, turn), "embedding")
        forget(spark, block)
        return out.select(F.col("id").alias("row_id"), F.array(*cols[:k]).alias("z")), 1 - ritz[:k]
    finally:
        ends.unpersist()


def local_embedding(ids: np.ndarray, src: np.ndarray, dst: np.ndarray, w: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Eigenvalues and vectors in one process: from the matrix up to DENSE_NODES, else by sparse products."""
    return dense_embedding(ids, src, dst, w, k) if len(ids) <= DENSE_NODES else sparse_embedding(ids, src, dst, w, k, TOLERANCE, DEGREE)


def task_embedding(spark: SparkSession, edges: DataFrame, k: int) -> tuple[DataFrame, np.ndarray]:
    """row_id, z of a graph that fits a task, solved in one."""

    def solve(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        e = pa.Table.from_batches(list(batches))
        src, dst, w = (e[c].to_numpy() for c in ("src", "dst", "w"))
        ids = np.unique(src)
        values, z = local_embedding(ids, src, dst, w, k)
        for a in range(0, len(ids), 10_000):
            part = slice(a, a + 10_000)
            yield pa.RecordBatch.from_arrays([pa.array(ids[part]), list_column(z[part]), list_column(np.tile(values, (len(ids[part]), 1)))], names=["row_id", "z", "eigenvalues"])

    found = materialise(spark, edges.select("src", "dst", "w").repartition(1).mapInArrow(solve, "row_id long, z array<double>, eigenvalues array<double>"), "embedding")
    return found.select("row_id", "z"), np.array(found.first()["eigenvalues"])


def neighbour_task_embedding(spark: SparkSession, halves: DataFrame, k: int) -> tuple[DataFrame, np.ndarray]:
    """row_id, z of the graph whose edges are written as `graph.symmetrise(edges, "halves")`, all of weight a half: read and
    solved in one task, no exchange."""

    def solve(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ends = [(b.column("src").to_numpy(), b.column("dst").to_numpy()) for b in batches if b.num_rows]
        ids = np.zeros(0, dtype=np.int64)
        for a in range(0, len(ends), 64):
            ids = np.unique(np.concatenate([ids, *(x for e in ends[a : a + 64] for x in e)]))
        links = []
        while ends:
            links.append(links_between(ids, *ends.pop()))
        values, z = neighbour_embedding(len(ids), links, k, TOLERANCE, DEGREE)
        for a in range(0, len(ids), 10_000):
            part = slice(a, a + 10_000)
            yield pa.RecordBatch.from_arrays([pa.array(ids[part]), list_column(z[part]), list_column(np.tile(values, (len(ids[part]), 1)))], names=["row_id", "z", "eigenvalues"])

    found = materialise(spark, halves.select("src", "dst").coalesce(1).mapInArrow(solve, "row_id long, z array<double>, eigenvalues array<double>"), "embedding")
    return found.select("row_id", "z"), np.array(found.first()["eigenvalues"])


def embed(spark: SparkSession, edges: DataFrame, k: int, nodes: int | None = None, row_normalise: bool = False, halves: bool = False) -> tuple[DataFrame, np.ndarray]:
    """row_id, z for every node with an edge; a small graph's eigenproblem is solved whole on the driver, a larger
    one's in a task (TASK_NODES), and beyond that over all executors, by iteration to a residual of TOLERANCE. row_normalise: each row of the embedding at length 1.
    halves: the edges of a written neighbour graph of at most NEIGHBOUR_NODES rows, as `graph.symmetrise` leaves them."""
    n = 0 if halves else nodes if nodes is not None else edges.select("src").distinct().count()
    if halves:
        out, values = neighbour_task_embedding(spark, edges, k)
    elif n <= DENSE_NODES:
        e = edges.select("src", "dst", "w").toArrow()  # at most DENSE_NODES x neighbours rows
        src, dst, w = (e[c].to_numpy() for c in ("src", "dst", "w"))
        ids = np.unique(src)
        values, vectors = dense_embedding(ids, src, dst, w, k)
        rows = [(int(i), v.tolist()) for i, v in zip(ids, vectors)]
        out = spark.createDataFrame(rows, "row_id long, z array<double>")
    elif n <= TASK_NODES:
        out, values = task_embedding(spark, edges, k)
    else:
        out, values = subspace_embedding(spark, edges, k)
    if row_normalise:
        length = F.sqrt(F.aggregate("z", F.lit(0.0), lambda s, x: s + x * x))
        out = out.withColumn("z", F.transform("z", lambda x: F.when(length > 0, x / length).otherwise(0.0)))
    return out, values


def spectral(df: DataFrame, k: int, q: int = 10, passes: int = 300, seed: int = 0, restarts: int = 1, symmetry: str = "mean", row_normalise: bool = False, name: str = "z", key: str = "row_id", method: str = "exact") -> SpectralResult:
    """Neighbour graph, normalised Laplacian, its k least eigenvectors, k-means on their rows."""
    spark = df.sparkSession
    n = df.count()
    halves = symmetry == "mean" and q > 0 and DENSE_NODES < n <= NEIGHBOUR_NODES
    edges = materialise(spark, graph.symmetrise(graph.knn_graph(df, q, name, key, method=method, rows=n), "halves" if halves else symmetry), "edges")
    embedding, values = embed(spark, edges, k, row_normalise=row_normalise, halves=halves)
    forget(spark, edges)
    found = kmeans.fit(embedding, k, passes, seed, restarts)
    return SpectralResult(embedding, found.centers, values)


def spectral_landmarks(df: DataFrame, k: int, landmarks: int = 500, q: int = 10, passes: int = 20, seed: int = 0, restarts: int = 5, name: str = "z", key: str = "row_id") -> tuple[np.ndarray, np.ndarray]:
    """For very many rows: weighted representatives, spectral clustering of those, rows follow their nearest.

    Returns the landmarks and the cluster of each; `kmeans.assign` to landmarks and a lookup labels rows.
    """
    reps = kmeans.fit(df, landmarks, passes, seed, name=name, key=key, seeding="parallel", tol=1e-6)
    stats = kmeans.lloyd_step(df, {0: [reps.centers]}, name, key)[0][0]
    used = stats[1] > 0
    points, weights = reps.centers[used], stats[1][used]
    return points, cluster_landmarks(points, weights, k, q, seed, restarts)


def cluster_landmarks(points: np.ndarray, weights: np.ndarray, k: int, q: int, seed: int, restarts: int = 5) -> np.ndarray:
    """Spectral clustering of a small weighted table on the driver."""
    n = len(points)
    d = ((points[:, None] - points[None]) ** 2).sum(axis=2)
    np.fill_diagonal(d, np.inf)
    near = np.argsort(d, axis=1, kind="stable")[:, : min(q, n - 1)]
    src = np.repeat(np.arange(n), near.shape[1])
    dst = near.reshape(-1)
    s, t = np.concatenate([src, dst]), np.concatenate([dst, src])
    _, e = dense_embedding(np.arange(n), s, t, np.full(len(s), 0.5), k)
    best = min((kmeans.weighted_lloyd(e, weights, kmeans.weighted_seeds(e, weights, k, seed + r)) for r in range(restarts)), key=lambda x: x[1])
    return kmeans._distances(e, best[0]).argmin(axis=1)


def power_iteration(edges: DataFrame, k: int, iterations: int = 20) -> DataFrame:
    """Power iteration clustering from Spark's library, for comparison: id, cluster."""
    from pyspark.ml.clustering import PowerIterationClustering

    one_way = edges.where("src < dst").select("src", "dst", F.col("w").alias("weight"))
    return PowerIterationClustering(k=k, maxIter=iterations, initMode="degree", weightCol="weight").assignClusters(one_way)
