"""Anchor tables: artificial or public rows that all parties share."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.portable import gaussian, uniform
from ..session import materialise
from . import graph
from .numeric import moments


def anchor_uniform(spark: SparkSession, bounds: list[tuple[float, float]], rows: int, seed: int = 0) -> DataFrame:
    """Uniform in each feature's range; every party can make the same rows from the seed."""
    feats = F.array(*(F.lit(float(lo)) + uniform(seed, F.col("id"), j) * F.lit(float(hi) - float(lo)) for j, (lo, hi) in enumerate(bounds)))
    return spark.range(rows).select(F.col("id").alias("anchor_id"), feats.alias("feats"))


def anchor_lowrank(spark: SparkSession, public: DataFrame, rows: int, rank: int, noise: float = 0.05, seed: int = 0) -> DataFrame:
    """Random rows in the leading subspace of a public (or perturbed) table, with a little noise outside."""
    width = len(public.select("feats").first()["feats"])
    n, mean, cross = moments(public.withColumn("row_grp", F.lit(0)), (tuple(range(width)),))[0, 0]
    values, vectors = np.linalg.eigh(cross / max(n, 1))
    values, vectors = np.maximum(values[::-1], 0), vectors[:, ::-1]
    factor = vectors[:, :rank] * np.sqrt(values[:rank])
    spread = np.sqrt(np.diag(cross) / max(n, 1)) * noise
    z = [gaussian(seed, F.col("id"), f"z{k}") for k in range(rank)]
    feats = [sum((z[k] * F.lit(float(factor[j, k])) for k in range(rank)), F.lit(float(mean[j]))) + gaussian(seed, F.col("id"), f"e{j}") * F.lit(float(spread[j])) for j in range(width)]
    return spark.range(rows).select(F.col("id").alias("anchor_id"), F.array(*feats).alias("feats"))


def anchor_mix(public: DataFrame, rows: int, seed: int = 0, key: str = "row_id", neighbours: int = 5, method: str = "exact") -> DataFrame:
    """Oversampling of a public table: each anchor lies at random between a row and one of its nearest neighbours.

    Rows are taken in the order of a hash, each as often as the number of anchors asks for. method: of
    the neighbour search (`lsh` for a public table of many rows). A table of one row gives copies of it.
    """
    n = public.count()
    copies = max(1, -(-rows // max(n, 1)))
    points = public.select(F.col(key).cast("long").alias("k"), "feats")
    drawn = points.withColumn("c", F.explode(F.sequence(F.lit(0), F.lit(copies - 1)))).withColumn("h", F.xxhash64(F.lit(seed), "k", "c"))
    drawn = materialise(points.sparkSession, drawn.orderBy("c", "h", "k").limit(rows), "drawn")
    # of a large table only the rows that are drawn look for neighbours
    few = drawn.select("k", "feats").distinct() if method == "exact" and rows * 4 < n else None
    near = graph.knn_graph(points, neighbours, "feats", "k", method=method, rows=n, seed=seed, of=few)
    ranked = near.groupBy("src").agg(F.sort_array(F.collect_list(F.struct("dist", "dst"))).alias("near"))
    drawn = drawn.join(ranked, F.col("k") == F.col("src"), "left")
    partner = F.element_at("near", (F.pmod(F.xxhash64(F.lit(seed + 1), "k", "c"), F.size("near")) + 1).cast("int"))["dst"]
    drawn = drawn.withColumn("partner", F.when(F.size("near") > 0, partner))
    met = drawn.join(points.select(F.col("k").alias("partner"), F.col("feats").alias("other")), "partner", "left")
    share = uniform(seed, F.concat_ws("~", F.col("k").cast("string"), F.col("c").cast("string")), "mix")
    mixed = F.zip_with("feats", F.coalesce("other", "feats"), lambda a, b: a + (b - a) * share)
    return met.select((F.col("k") * copies + F.col("c")).alias("anchor_id"), mixed.alias("feats"))


def anchor_from(public: DataFrame, key: str = "row_id") -> DataFrame:
    """A table that may be shared as it is."""
    return public.select(F.col(key).alias("anchor_id"), "feats")
