"""SQL surface: functions and table functions, registered under plain names."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import udtf

from ..operators import metrics


#: Functions in SQL, which the optimizer puts into the calling plan: no Python worker.
_SQL = {
    "nearest_center": (
        "z ARRAY<DOUBLE>, centers ARRAY<ARRAY<DOUBLE>>", "INT",
        "CAST(array_position(transform(centers, c -> {d}), array_min(transform(centers, c -> {d}))) - 1 AS INT)".format(d="aggregate(zip_with(z, c, (a, b) -> (a - b) * (a - b)), 0D, (s, x) -> s + x)"),
    ),
    "encode_code": (
        "feats ARRAY<DOUBLE>, mean ARRAY<DOUBLE>, scale ARRAY<DOUBLE>, proj ARRAY<ARRAY<DOUBLE>>", "ARRAY<DOUBLE>",
        "transform(sequence(0, size(proj[0]) - 1), j -> aggregate(sequence(0, size(feats) - 1), 0D, (s, i) -> s + (feats[i] - mean[i]) / scale[i] * proj[i][j]))",
    ),
}


def _table(truth: pd.Series, pred: pd.Series) -> np.ndarray:
    return pd.crosstab(truth, pred).to_numpy().astype(float)


@F.pandas_udf(T.DoubleType())
def ari_agg(truth: pd.Series, pred: pd.Series) -> float:
    """Adjusted Rand index of a group that fits a task; for whole tables use the contingency."""
    return metrics.ari(_table(truth, pred))


@F.pandas_udf(T.DoubleType())
def nmi_agg(truth: pd.Series, pred: pd.Series) -> float:
    return metrics.nmi(_table(truth, pred))


@udtf(returnType="anchor_id: bigint, feats: array<double>")
class AnchorRows:
    """Rows of uniform anchors: anchor_rows(rows, lows, highs, seed)."""

    def eval(self, rows: int, lows: list, highs: list, seed: int):
        import hashlib

        for i in range(rows):
            u = [int(hashlib.md5(f"{seed}~{i}~{j}".encode()).hexdigest()[:8], 16) / 4294967296.0 for j in range(len(lows))]
            yield i, [lo + (hi - lo) * x for lo, hi, x in zip(lows, highs, u)]


@udtf(returnType="src: bigint, dst: bigint, dist: double")
class KnnRows:
    """Neighbours of one point among given ones: knn_rows(id, point, ids, points, q)."""

    def eval(self, src: int, point: list, ids: list, points: list, q: int):
        d = sorted((sum((a - b) ** 2 for a, b in zip(point, p)), i) for i, p in zip(ids, points) if i != src)
        for dist, i in d[:q]:
            yield src, i, dist


def register_all(spark: SparkSession) -> None:
    """nearest_center(z, centers): number of the nearest center, ties to the lowest; encode_code(feats, mean, scale,
    proj): a party's code of a point; ari_agg, nmi_agg (truth, pred); anchor_rows and knn_rows as table functions."""
    for name, (arguments, kind, body) in _SQL.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({arguments}) RETURNS {kind} RETURN {body}")
    for name, f in (("ari_agg", ari_agg), ("nmi_agg", nmi_agg)):
        spark.udf.register(name, f)
    spark.udtf.register("anchor_rows", AnchorRows)
    spark.udtf.register("knn_rows", KnnRows)
