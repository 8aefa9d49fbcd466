"""Connected components of links, by alternating large-star and small-star steps on tables."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import forget, materialise

MOST_ROUNDS = 60
#: Links up to which the components are worked out on the driver (16 bytes each) instead of in some twenty small jobs.
FEW_LINKS = 50_000


def least_nodes(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The nodes of links (a, b), and the least node that each is tied to."""
    nodes, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    left, right = at[: len(a)], at[len(a) :]
    root = np.arange(len(nodes))
    while True:
        low = np.minimum(root[left], root[right])
        new = root.copy()
        for side in (root[left], root[right]):  # the roots are hooked, so whole trees move
            np.minimum.at(new, side, low)
        while not np.array_equal(new, new[new]):
            new = new[new]
        if np.array_equal(new, root):
            return nodes, nodes[root]
        root = new


def _hook(spark: SparkSession, sides: DataFrame, keep_larger: bool) -> DataFrame:
    """Ties the neighbours of each node u to the least of them and u; sides has rows (u, v). Returns a written table."""
    least = materialise(spark, sides.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m")), "least")
    tied = sides.join(least, "u")
    out = tied.where(F.col("v") > F.col("u")).select(F.col("v").alias("a"), F.col("m").alias("b")) if keep_larger else tied.select(F.col("v").alias("a"), F.col("m").alias("b")).unionAll(least.select(F.col("u").alias("a"), F.col("m").alias("b")))
    made = materialise(spark, out.where("a != b").distinct(), "star")
    forget(spark, least)
    return made


def components(spark: SparkSession, links: DataFrame) -> DataFrame:
    """node, component (its least node) for every node of links (a, b); many links stay on the executors.

    A small table of links (FEW_LINKS) is solved on the driver. Else each round is a few aggregations and joins on tables written to the shared folder, so a lost
    executor costs one round at most; earlier rounds' tables are deleted. A node with very many links
    is split by the join, since both of its sides are written tables or plain exchanges.
    """
    edges = materialise(spark, links.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).where("a != b").distinct(), "links")

    def state(e: DataFrame) -> tuple:
        r = e.agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("a", "b")), F.bit_xor(F.xxhash64("b", "a"))).first()
        return tuple(r)

    before = state(edges)
    if before[0] <= FEW_LINKS:
        t = edges.toArrow()  # at most FEW_LINKS rows
        nodes, least = least_nodes(t["a"].to_numpy(), t["b"].to_numpy())
        return materialise(spark, spark.createDataFrame(pa.table({"node": pa.array(nodes, pa.int64()), "component": pa.array(least, pa.int64())}), "node long, component long"), "components")
    for _ in range(MOST_ROUNDS):
        if not before[0]:
            break
        both = edges.select(F.col("a").alias("u"), F.col("b").alias("v")).unionAll(edges.select(F.col("b").alias("u"), F.col("a").alias("v")))
        large = _hook(spark, both, keep_larger=True)
        # a star's links point from the larger to the smaller node in both steps
        small = _hook(spark, large.select(F.col("a").alias("u"), F.col("b").alias("v")), keep_larger=False)
        forget(spark, edges, large)
        edges = small
        after = state(edges)
        if after == before:
            break
        before = after
    else:
        raise RuntimeError("components did not settle")
    return edges.select(F.col("a").alias("node"), F.col("b").alias("component")).unionAll(edges.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct())
