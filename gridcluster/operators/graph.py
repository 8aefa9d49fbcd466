"""Neighbour graphs as edge lists, degrees and Laplacians."""

from __future__ import annotations

import math
import warnings
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..session import materialise
from .local import LeafTree
from .numeric import matrix

#: Rows of a block in the exact search: a task holds two blocks and one matrix of their distances.
BLOCK_ROWS = 2000
#: Coordinates (8 bytes each) of a table whose search tree is shared with all tasks.
TREE_VALUES = 6_000_000


def top_neighbours(pairs: DataFrame, q: int) -> DataFrame:
    """The q rows of least (dist, dst) for each src."""
    w = Window.partitionBy("src").orderBy("dist", "dst")  # cut to q a task before the exchange
    return pairs.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= q)


def knn_graph(df: DataFrame, q: int = 10, name: str = "z", key: str = "row_id", include_self: bool = False, method: str = "exact", rows: int | None = None, seed: int = 0, recall: float = 0.95, of: DataFrame | None = None) -> DataFrame:
    """Directed edges src, dst, w=1 to the q nearest rows (ties by id), with squared distance. Ids must be unique.
    of: only the edges of these of the rows, exactly.

    exact: a table of bounded size (TREE_VALUES) is shared as a tree, of which each task searches some leaves; rows of a
    larger one are dealt to hash blocks; each unordered pair of blocks is one task's distances, which
    keeps q candidates a row in both directions. Its cost is the square of the rows: meant for up to a
    million; beyond, the landmark graph in `spectral`, or lsh: candidates from random projections, table
    after table until a sample of rows finds the share `recall` of its true neighbours.
    """
    points = df.select(F.col(key).cast("long").alias("id"), F.col(name).alias("z"))
    n = rows if rows is not None else points.count()
    if method == "lsh":
        return _lsh_graph(points, q, include_self, seed, n, recall)
    if method != "exact":
        raise ValueError(method)
    if of is not None:
        return _probed_graph(points, of.select(F.col(key).cast("long").alias("id"), F.col(name).alias("z")), q, include_self, n)
    if n > BLOCK_ROWS and n * len(points.first()["z"]) <= TREE_VALUES:
        return _tree_graph(points, q, include_self)
    blocks = max(1, math.ceil(n / BLOCK_ROWS))
    own = F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int")
    other = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    dealt = points.select(own.alias("own"), other.alias("other"), "id", "z").select(F.least("own", "other").alias("a"), F.greatest("own", "other").alias("b"), "own", "id", "z")

    def search(t: pa.Table) -> pa.Table:
        ids, z, own = t["id"].to_numpy(), matrix(t["z"]), t["own"].to_numpy()
        a, b = t["a"][0].as_py(), t["b"][0].as_py()
        left, right = np.nonzero(own == a)[0], np.nonzero(own == b)[0]
        out = [_nearest_between(ids[left], z[left], ids[right], z[right], q, include_self)]
        if a != b:
            out.append(_nearest_between(ids[right], z[right], ids[left], z[left], q, include_self))
        return pa.concat_tables(out)

    found = dealt.groupBy("a", "b").applyInArrow(search, "src long, dst long, dist double")
    return top_neighbours(found, q).select("src", "dst", F.lit(1.0).alias("w"), "dist")


def _tree_graph(points: DataFrame, q: int, include_self: bool) -> DataFrame:
    spark = points.sparkSession
    t = points.toArrow()  # at most TREE_VALUES coordinates
    tree = LeafTree(t["id"].to_numpy(), matrix(t["z"]), q)
    shared = spark.sparkContext.broadcast(tree)

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            leaves = b.column("id").to_pylist()
            for a in range(0, len(leaves), 64):
                yield from shared.value.nearest(leaves[a : a + 64], include_self).combine_chunks().to_batches()

    found = spark.range(0, len(tree), 1, max(1, min(len(tree), 4 * spark.sparkContext.defaultParallelism))).mapInArrow(search, "src long, dst long, dist double")
    return found.select("src", "dst", F.lit(1.0).alias("w"), "dist")


def _probed_graph(points: DataFrame, probes: DataFrame, q: int, include_self: bool, n: int) -> DataFrame:
    """Blocks of probes meet all blocks of rows."""
    blocks, several = max(1, math.ceil(n / BLOCK_ROWS)), max(1, math.ceil(probes.count() / BLOCK_ROWS))
    every = lambda k: F.explode(F.sequence(F.lit(0), F.lit(k - 1)))
    own = lambda k: F.pmod(F.xxhash64("id"), F.lit(k)).cast("int")
    met = points.select(own(blocks).alias("a"), every(several).alias("b"), F.lit(False).alias("probe"), "id", "z").unionAll(probes.select(every(blocks).alias("a"), own(several).alias("b"), F.lit(True).alias("probe"), "id", "z"))

    def search(t: pa.Table) -> pa.Table:
        ids, z, probe = t["id"].to_numpy(), matrix(t["z"]), t["probe"].to_numpy()
        return _nearest_between(ids[probe], z[probe], ids[~probe], z[~probe], q, include_self)

    found = met.groupBy("a", "b").applyInArrow(search, "src long, dst long, dist double")
    return top_neighbours(found, q).select("src", "dst", F.lit(1.0).alias("w"), "dist")


_EDGES = pa.schema([("src", pa.int64()), ("dst", pa.int64()), ("dist", pa.float64())])


def _nearest_between(ids: np.ndarray, z: np.ndarray, to_ids: np.ndarray, to: np.ndarray, q: int, include_self: bool) -> pa.Table:
    """The q nearest of `to` for each of z, ties to the lower id; a matrix of some million distances at a time."""
    order = np.argsort(to_ids, kind="stable")
    to_ids, to = to_ids[order], to[order]
    take = min(q, len(to_ids))
    out = []
    step = max(1, (1 << 22) // max(1, len(to_ids)))
    for at in range(0, len(ids) if take else 0, step):
        part = z[at : at + step]
        d = np.zeros((len(part), len(to)))
        for i in range(z.shape[1]):  # differences, not products: equal points are at distance 0
            d += (part[:, i : i + 1] - to[:, i]) ** 2
        if not include_self:
            d[ids[at : at + step, None] == to_ids[None]] = np.inf
        near = np.argsort(d, axis=1, kind="stable")[:, :take] if take * 4 >= len(to_ids) else _smallest(d, take)
        dist = np.take_along_axis(d, near, axis=1)
        ok = np.isfinite(dist).reshape(-1)
        out.append(pa.table({"src": np.repeat(ids[at : at + step], take)[ok], "dst": to_ids[near].reshape(-1)[ok], "dist": dist.reshape(-1)[ok]}, schema=_EDGES))
    return pa.concat_tables(out) if out else _EDGES.empty_table()


def _smallest(d: np.ndarray, take: int) -> np.ndarray:
    """Columns of the `take` least of each row, by value, then column; where values tie at the border the lowest columns."""
    limit = np.partition(d, take - 1, axis=1)[:, take - 1 : take]
    row, col = np.nonzero(d <= limit)
    order = np.lexsort((col, d[row, col], row))
    row, col = row[order], col[order]
    first = np.searchsorted(row, np.arange(len(d)))
    return col[first[:, None] + np.arange(take)]


#: Rows of a bucket, about, and rows that are compared with all to measure what share of neighbours is found.
BUCKET_ROWS, PROBES = 500, 200
#: Tables of hashes that are added at a time, and at most.
TABLES, MOST_TABLES = 8, 96


def _lsh_graph(points: DataFrame, q: int, include_self: bool, seed: int, n: int, recall: float) -> DataFrame:
    """Rows that lie on the same side of random planes, in any of several tables, are compared.

    A table has as many planes as make buckets of bounded size, so they grow with the logarithm of
    the rows; a plane lies anywhere between the inner rows of a bounded sample. A bucket that is larger all
    the same (a dense spot) is compared in all pairs of its chunks: no pair of a bucket is left out.
    Tables are added until a sample of rows, compared with all rows, finds enough of its neighbours.
    """
    spark = points.sparkSession
    points = materialise(spark, points, "points")
    sample = points.orderBy(F.xxhash64(F.lit(seed), "id"), "id").limit(1000).toArrow()
    if not sample.num_rows:
        return spark.createDataFrame([], "src long, dst long, w double, dist double")
    z = matrix(sample["z"])
    probes = sample.slice(0, PROBES)
    bits = max(1, math.ceil(math.log2(max(n, 2) / BUCKET_ROWS)))
    rng = np.random.default_rng(seed)
    truth = _true_neighbours(points, probes, q, include_self)
    found = None
    for _ in range(MOST_TABLES // TABLES):
        planes = rng.standard_normal((TABLES, bits, z.shape[1]))
        at = np.take_along_axis(np.sort(planes @ z.T, axis=2), (len(z) * rng.uniform(0.3, 0.7, (TABLES, bits, 1))).astype(int), axis=2)[:, :, 0]
        more = _bucket_edges(points, planes, at, q, include_self)
        found = materialise(spark, top_neighbours((more if found is None else found.unionAll(more)).distinct(), q).select("src", "dst", "dist"), "neighbours")
        got = found.where(F.col("src").isin(probes["id"].to_pylist())).select("src", "dst").collect()  # q rows a probe
        if len(truth & {(r["src"], r["dst"]) for r in got}) >= recall * len(truth):
            break
    else:
        warnings.warn(f"the neighbour graph was left at less than {recall} of the true neighbours after {MOST_TABLES} tables", stacklevel=2)
    return found.select("src", "dst", F.lit(1.0).alias("w"), "dist")


def _true_neighbours(points: DataFrame, probes: pa.Table, q: int, include_self: bool) -> set[tuple[int, int]]:
    """(src, dst) of the true neighbours of a bounded number of rows, by one pass over all."""
    ids, z = probes["id"].to_numpy(), matrix(probes["z"])

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                yield from _nearest_between(ids, z, b.column("id").to_numpy(), matrix(b.column("z")), q, include_self).to_batches()

    near = top_neighbours(points.mapInArrow(scan, "src long, dst long, dist double"), q)
    return {(r["src"], r["dst"]) for r in near.select("src", "dst").collect()}


def _bucket_edges(points: DataFrame, planes: np.ndarray, at: np.ndarray, q: int, include_self: bool) -> DataFrame:
    tables, bits, _ = planes.shape
    powers = 1 << np.arange(bits, dtype=np.int64)

    def code(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                z = matrix(b.column("z"))
                for t in range(tables):
                    c = ((z @ planes[t].T > at[t]) * powers).sum(axis=1)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(z), t, dtype=np.int32)), pa.array(c), b.column("id")], names=["t", "code", "id"])

    coded = points.mapInArrow(code, "t int, code long, id long")
    sizes = coded.groupBy("t", "code").agg(F.ceil(F.count(F.lit(1)) / BLOCK_ROWS).cast("int").alias("chunks"), F.count(F.lit(1)).alias("n")).where("n > 1").drop("n")
    own = F.pmod(F.xxhash64("id"), F.col("chunks")).cast("int")
    other = F.explode(F.sequence(F.lit(0), F.col("chunks") - 1))
    dealt = coded.join(sizes, ["t", "code"]).select("t", "code", "id", own.alias("own"), other.alias("other"))
    dealt = dealt.select("t", "code", "id", "own", F.least("own", "other").alias("a"), F.greatest("own", "other").alias("b")).join(points, "id")

    def search(x: pa.Table) -> pa.Table:
        ids, z, own = x["id"].to_numpy(), matrix(x["z"]), x["own"].to_numpy()
        a, b = x["a"][0].as_py(), x["b"][0].as_py()
        left, right = np.nonzero(own == a)[0], np.nonzero(own == b)[0]
        out = [_nearest_between(ids[left], z[left], ids[right], z[right], q, include_self)]
        if a != b:
            out.append(_nearest_between(ids[right], z[right], ids[left], z[left], q, include_self))
        return pa.concat_tables(out)

    return dealt.groupBy("t", "code", "a", "b").applyInArrow(search, "src long, dst long, dist double")


def radius_edges(df: DataFrame, eps: float, name: str = "z", key: str = "row_id") -> DataFrame:
    """Pairs src < dst within eps: rows meet in the cells of a grid over the first two coordinates."""
    from ..functions.vectors import sqdist

    cell = lambda i: F.floor(F.col("z")[i] / F.lit(eps)).cast("long")
    p = df.select(F.col(key).alias("id"), F.col(name).alias("z")).withColumn("cx", cell(0)).withColumn("cy", F.when(F.size("z") > 1, F.floor(F.element_at("z", F.least(F.size("z"), F.lit(2))) / F.lit(eps)).cast("long")).otherwise(0))
    around = F.array(*map(F.lit, (-1, 0, 1)))
    spread = p.withColumn("dx", F.explode(around)).withColumn("dy", F.explode(around)).select(F.col("id").alias("dst"), F.col("z").alias("y"), (F.col("cx") + F.col("dx")).alias("cx"), (F.col("cy") + F.col("dy")).alias("cy"))
    near = p.select(F.col("id").alias("src"), F.col("z").alias("x"), "cx", "cy").join(spread, ["cx", "cy"]).where("src < dst")
    return near.withColumn("dist", sqdist(F.col("x"), F.col("y"))).where(F.col("dist") <= eps * eps).select("src", "dst", "dist")


def symmetrise(edges: DataFrame, mode: str = "mean") -> DataFrame:
    """Symmetric weights from directed ones: mean of both directions, union, or mutual only; or `halves`: what the mean
    sums, a row a < b and half the weight for each directed edge, without an exchange."""
    if mode == "halves":
        return edges.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"), (F.col("w") / 2).alias("w"))
    ways = F.array(F.struct("src", "dst"), F.struct(F.col("dst").alias("src"), F.col("src").alias("dst")))
    both = edges.select(F.explode(ways).alias("e"), "w").select("e.src", "e.dst", "w")  # the edges are worked out once
    summed = both.groupBy("src", "dst").agg(F.sum("w").alias("s"), F.count(F.lit(1)).alias("n"), F.max("w").alias("m"))
    if mode == "mean":
        return summed.select("src", "dst", (F.col("s") / 2).alias("w"))
    if mode == "union":
        return summed.select("src", "dst", F.col("m").alias("w"))
    if mode == "mutual":
        return summed.where((F.col("n") > 1) | (F.col("src") == F.col("dst"))).select("src", "dst", F.col("m").alias("w"))
    raise ValueError(mode)


def degree(edges: DataFrame) -> DataFrame:
    return edges.groupBy(F.col("src").alias("id")).agg(F.sum("w").alias("deg"))


def normalised_weights(edges: DataFrame) -> DataFrame:
    """w over the root of both degrees."""
    d = degree(edges)
    return edges.join(d.select(F.col("id").alias("src"), F.col("deg").alias("da")), "src").join(d.select(F.col("id").alias("dst"), F.col("deg").alias("db")), "dst").select("src", "dst", (F.col("w") / F.sqrt(F.col("da") * F.col("db"))).alias("w"))


def laplacian(edges: DataFrame, kind: str = "plain") -> DataFrame:
    """Entries src, dst, val of D - W, or of I - W over the roots of the degrees (`sym`)."""
    d = degree(edges)
    if kind == "plain":
        off, diagonal = edges.select("src", "dst", (-F.col("w")).alias("val")), d.select(F.col("id").alias("src"), F.col("id").alias("dst"), F.col("deg").alias("val"))
    elif kind == "sym":
        off, diagonal = normalised_weights(edges).select("src", "dst", (-F.col("w")).alias("val")), d.select(F.col("id").alias("src"), F.col("id").alias("dst"), F.lit(1.0).alias("val"))
    else:
        raise ValueError(kind)
    return off.unionAll(diagonal).groupBy("src", "dst").agg(F.sum("val").alias("val"))
