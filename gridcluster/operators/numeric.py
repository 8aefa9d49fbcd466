"""Arrow batches as matrices, and sums over them that merge in any order."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def matrix(column: pa.Array) -> np.ndarray:
    """A list column of equal lengths as rows x width."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    if not np.isfinite(flat).all():
        raise ValueError("null, NaN or infinite value in a point: clean the features first")
    n = len(column)
    if n and len(flat) % n:
        raise ValueError("points differ in width")
    return flat.reshape(n, len(flat) // n if n else 0)


def list_column(x: np.ndarray) -> pa.Array:
    n, m = x.shape
    return pa.ListArray.from_arrays(pa.array(np.arange(n + 1, dtype=np.int32) * np.int32(m)), pa.array(np.ascontiguousarray(x, dtype=np.float64).reshape(-1)))


def fix_signs(vectors: np.ndarray) -> np.ndarray:
    """Columns turned so that the entry of largest size is positive."""
    if not vectors.size:
        return vectors
    top = np.abs(vectors).argmax(axis=0)
    return vectors * np.where(vectors[top, np.arange(vectors.shape[1])] < 0, -1.0, 1.0)


def merge_moments(parts: list[tuple[int, np.ndarray, np.ndarray]]) -> tuple[int, np.ndarray, np.ndarray]:
    """Counts, means and centered cross products of disjoint row sets, put together pairwise."""
    n, mean, cross = parts[0]
    mean, cross = mean.copy(), cross.copy()
    for k, other, c in parts[1:]:
        if not k:
            continue
        d = other - mean
        cross = cross + c + np.outer(d, d) * (n * k / (n + k))
        mean = mean + d * (k / (n + k))
        n += k
    return n, mean, cross


def moments(points: DataFrame, columns: tuple[tuple[int, ...], ...], feats: str = "feats") -> dict[tuple[int, int], tuple[int, np.ndarray, np.ndarray]]:
    """For each block (row_grp, column group): rows, mean vector, centered cross products. One pass.

    Each partition sends one small record a block; a second small aggregation merges them, and as
    many records as there are parties reach the driver. Centering happens batch by batch, so large offsets lose no digits.
    """

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple[int, int], list] = {}
        for b in batches:
            if not b.num_rows:
                continue
            x, grp = matrix(b.column(feats)), b.column("row_grp").to_numpy()
            for i in np.unique(grp):
                rows = x[grp == i]
                for j, cols in enumerate(columns):
                    part = rows[:, list(cols)]
                    mean = part.mean(axis=0)
                    c = part - mean
                    new = (len(part), mean, c.T @ c)
                    key = (int(i), j)
                    held[key] = [merge_moments([*held[key], new])] if key in held else [new]
        yield _records([(i, j, *held[i, j][0]) for i, j in held])

    def merge(t: pa.Table) -> pa.Table:
        parts = [(n, np.array(m), np.array(c).reshape(len(m), len(m))) for n, m, c in zip(t["n"].to_pylist(), t["mean"].to_pylist(), t["cross"].to_pylist())]
        return pa.Table.from_batches([_records([(t["row_grp"][0].as_py(), t["col_grp"][0].as_py(), *merge_moments(parts))])])

    schema = "row_grp int, col_grp int, n long, mean array<double>, cross array<double>"
    found = points.select("row_grp", feats).mapInArrow(partial, schema).groupBy("row_grp", "col_grp").applyInArrow(merge, schema).collect()
    return {(r["row_grp"], r["col_grp"]): (r["n"], np.array(r["mean"]), np.array(r["cross"]).reshape(len(r["mean"]), -1)) for r in found}


_MOMENTS = pa.schema([("row_grp", pa.int32()), ("col_grp", pa.int32()), ("n", pa.int64()), ("mean", pa.list_(pa.float64())), ("cross", pa.list_(pa.float64()))])


def _records(rows: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays(
        [pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.int32()), pa.array([r[2] for r in rows], pa.int64()), pa.array([r[3].tolist() for r in rows], pa.list_(pa.float64())), pa.array([np.asarray(r[4]).reshape(-1).tolist() for r in rows], pa.list_(pa.float64()))],
        schema=_MOMENTS,
    )


def gram(rows: DataFrame, column: str, with_one: bool = False) -> np.ndarray:
    """Sum of outer products of a list column, with a trailing constant 1 if asked; adds up in a tree of tasks."""

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = None
        for b in batches:
            if b.num_rows:
                x = matrix(b.column(column))
                x = np.hstack([x, np.ones((len(x), 1))]) if with_one else x
                total = x.T @ x if total is None else total + x.T @ x
        if total is not None:
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(total), dtype=np.int32)), list_column(total)], names=["pos", "dots"])

    def add(t: pa.Table) -> pa.Table:
        return pa.table({"pos": t["pos"].slice(0, 1), "dots": list_column(matrix(t["dots"]).sum(axis=0, keepdims=True))})

    schema = "pos int, dots array<double>"
    found = rows.select(column).mapInArrow(partial, schema).groupBy("pos").applyInArrow(add, schema).collect()
    return np.array([r["dots"] for r in sorted(found, key=lambda r: r["pos"])])


def tsqr(rows: DataFrame, column: str) -> np.ndarray:
    """The triangular factor of a tall list column, by a tree of small QR steps: half the digits that the Gram matrix loses stay."""

    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        r = None
        for b in batches:
            if b.num_rows:
                x = matrix(b.column(column))
                r = np.linalg.qr(x if r is None else np.vstack([r, x]), mode="r")
        if r is not None:
            yield pa.RecordBatch.from_arrays([list_column(r)], names=[column])

    out = rows.select(column)
    parts = out.rdd.getNumPartitions()
    schema = f"{column} array<double>"
    out = out.mapInArrow(local, schema)
    while parts > 1:
        parts = -(-parts // 16)
        out = out.coalesce(parts).mapInArrow(local, schema)
    return np.array([r[0] for r in out.collect()])


def column_bounds(points: DataFrame, width: int, feats: str = "feats") -> list[tuple[float, float]]:
    """Least and greatest value of each feature, in one pass."""
    r = points.agg(*(f(F.col(feats)[i]).alias(f"{n}{i}") for i in range(width) for n, f in (("lo", F.min), ("hi", F.max)))).first()
    return [(r[f"lo{i}"], r[f"hi{i}"]) for i in range(width)]
