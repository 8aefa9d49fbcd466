"""The lattice of parties: row groups and column groups of one matrix."""

from __future__ import annotations

import math
from collections.abc import Sequence
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.portable import uniform


@dataclass(frozen=True)
class GridSpec:
    """col_groups: for each column party the positions of its features in `feats`."""

    col_groups: tuple[tuple[int, ...], ...]
    row_key: str = "row_id"
    row_groups: int = field(default=1)

    def __post_init__(self):
        flat = sorted(i for g in self.col_groups for i in g)
        if flat != list(range(len(flat))) or not all(self.col_groups):
            # overlapping or partial blocks are declared possible by the reference, and not treated there either
            raise NotImplementedError("column groups must cut the features into disjoint, non-empty parts")

    @property
    def width(self) -> int:
        return sum(map(len, self.col_groups))


def even_columns(width: int, parts: int, seed: int | None = None) -> tuple[tuple[int, ...], ...]:
    """Features in equal groups (sizes differ by one at most); with a seed in random order."""
    if not 1 <= parts <= width:
        raise ValueError("each column party needs a feature")
    order = list(range(width))
    if seed is not None:
        import numpy as np

        order = np.random.default_rng(seed).permutation(width).tolist()
    cut = [round(i * width / parts) for i in range(parts + 1)]
    return tuple(tuple(sorted(order[a:z])) for a, z in zip(cut, cut[1:]))


def split_grid(points: DataFrame, groups: int, row_group: Column | None = None, seed: int = 0, key: str = "row_id") -> DataFrame:
    """Adds row_grp: a given expression, or a hash of the key and seed (sizes equal up to chance; no shuffle)."""
    expr = row_group if row_group is not None else F.pmod(F.xxhash64(F.lit(seed), F.col(key)), F.lit(groups))
    return points.withColumn("row_grp", expr.cast("int"))


#: Rows of a slice that are ranked in one task, about.
SLICE_ROWS = 200_000


def equal_groups(points: DataFrame, groups: int, seed: int = 0, key: str = "row_id") -> DataFrame:
    """Random groups whose sizes differ by one at most: a rank within hash slices, carried over slices.

    The order is that of a hash; slices of it are ranked side by side, as many as keep a slice's rows
    bounded, so no task sees all rows.
    """
    slices = max(256, points.count() // SLICE_ROWS)
    h = F.xxhash64(F.lit(seed), F.col(key))
    tagged = points.withColumn("__h", h).withColumn("__s", F.pmod("__h", F.lit(slices)))
    before = Window.orderBy("s").rowsBetween(Window.unboundedPreceding, -1)
    sizes = tagged.groupBy(F.col("__s").alias("s")).agg(F.count(F.lit(1)).alias("n")).withColumn("before", F.coalesce(F.sum("n").over(before), F.lit(0))).select("s", "before")
    rank = F.row_number().over(Window.partitionBy("__s").orderBy("__h", key)) - 1
    placed = tagged.withColumn("__r", rank).join(F.broadcast(sizes), F.col("__s") == F.col("s"))
    return placed.withColumn("row_grp", F.pmod(F.col("__r") + F.col("before"), F.lit(groups)).cast("int")).select(*points.columns, "row_grp")


def skewed_groups(points: DataFrame, label: str = "truth", seed: int = 0, key: str = "row_id") -> DataFrame:
    """Two row groups: group 0 has class 0 alone and half of class 1, group 1 the other half and class 2 alone."""
    half = uniform(seed, F.col(key), "half") < 0.5
    return points.withColumn("row_grp", F.when(F.col(label) == 0, 0).when((F.col(label) == 1) & half, 0).otherwise(1).cast("int"))


def sorted_groups(points: DataFrame, label: str, groups: int) -> DataFrame:
    """Row groups by class: the hardest non-identical split."""
    return points.withColumn("row_grp", F.pmod(F.col(label), F.lit(groups)).cast("int"))


def block(points: DataFrame, spec: GridSpec, i: int | None, j: int, feats: str = "feats") -> DataFrame:
    """What party (i, j) holds; i None: the rows of all row groups."""
    rows = points if i is None else points.where(F.col("row_grp") == i)
    picked = F.array(*(F.col(feats)[p] for p in spec.col_groups[j]))
    return rows.withColumn(feats, picked)


def complete_rows(rows: DataFrame, blocks: Sequence[DataFrame], key: str = "row_id") -> DataFrame:
    """Rows that every column party knows."""
    for b in blocks:
        rows = rows.join(b.select(key), key, "left_semi")
    return rows


def missing_rows(rows: DataFrame, blocks: Sequence[DataFrame], key: str = "row_id") -> DataFrame:
    """Rows that some column party lacks, with the party's number: a broken lattice."""
    parts = [rows.join(b.select(key), key, "left_anti").select(key, F.lit(j).alias("col_grp")) for j, b in enumerate(blocks)]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def stack(parts: Sequence[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def shared_ids(a: DataFrame, b: DataFrame, key: str = "row_id") -> DataFrame:
    return a.select(key).intersect(b.select(key))


def extra_ids(a: DataFrame, b: DataFrame, key: str = "row_id") -> DataFrame:
    return a.select(key).exceptAll(b.select(key))


def default_anchor_rows(n: int, code_width: int) -> int:
    """The reference takes as many anchors as rows; aligning needs the rank of the codes only."""
    return min(n, max(8 * code_width, 2000)) if n else 0


def groups_for(n: int, rows: int) -> int:
    return max(1, math.ceil(n / max(1, rows)))
