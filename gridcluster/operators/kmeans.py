"""k-means: squared-distance seeding, Lloyd passes, several restarts and row groups in one scan."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.portable import hashed_uniform
from ..session import materialise
from .numeric import matrix


@dataclass
class KMeansResult:
    """centers: k x width of the best restart; history: inertia (mean squared distance) by pass, each restart."""

    centers: np.ndarray
    inertia: float
    history: list[list[float]] = field(default_factory=list)
    passes: int = 0


#: Moves of centers, in parts of the greatest coordinate, that count as none.
ROUNDING = 1e-12
#: Distances that are worked out at once.
CELLS = 1 << 20


#: Rows of a block whose distances to one center are worked out at once, and centers up to which that pays.
BLOCK, FEW_CENTERS = 1 << 14, 32


def _distances(z: np.ndarray, centers: np.ndarray) -> np.ndarray:
    """Squared distances by differences, coordinate after coordinate: the same numbers, to the last digit, as the
    generated code of `functions.vectors`, and no loss of digits for features far from zero."""
    out = np.zeros((len(z), len(centers)))
    if len(centers) <= FEW_CENTERS:
        for a in range(0, len(z), BLOCK):
            columns = np.ascontiguousarray(z[a : a + BLOCK].T)
            for c, center in enumerate(centers):
                out[a : a + BLOCK, c] = _to_center(columns, center)
        return out
    step = max(1, CELLS // max(1, len(centers)))
    for a in range(0, len(z), step):
        part = out[a : a + step]
        for i in range(z.shape[1]):
            d = z[a : a + step, i, None] - centers[None, :, i]
            part += d * d
    return out


def _to_center(columns: np.ndarray, center: np.ndarray) -> np.ndarray:
    out = np.zeros(columns.shape[1])
    for x, c in zip(columns, center):
        d = x - c
        d *= d
        out += d
    return out


def nearest_two(columns: np.ndarray, centers: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of points that lie column by column: the nearest center (ties to the lowest), its squared distance and the
    next one's; the numbers of `_distances` without its table."""
    n = columns.shape[1]
    near, best, second = np.zeros(n, dtype=np.int64), np.full(n, np.inf), np.full(n, np.inf)
    for a in range(0, n, BLOCK):
        part, label, least, next_ = columns[:, a : a + BLOCK], near[a : a + BLOCK], best[a : a + BLOCK], second[a : a + BLOCK]
        for c, center in enumerate(centers):
            d = _to_center(part, center)
            closer = d < least
            np.minimum(next_, np.maximum(least, d), out=next_)
            np.minimum(least, d, out=least)
            label[closer] = c
    return near, best, second


def _batches(it: Iterator[pa.RecordBatch], key: str, name: str, group: str | None, weight: str | None):
    for b in it:
        if b.num_rows:
            yield (
                b.column(key).cast(pa.int64()).to_numpy(zero_copy_only=False),
                matrix(b.column(name)),
                b.column(group).to_numpy() if group else np.zeros(b.num_rows, dtype=np.int64),
                b.column(weight).to_numpy() if weight else np.ones(b.num_rows),
            )


def seed_dsq(df: DataFrame, k: int, seed: int = 0, restarts: int = 1, name: str = "z", key: str = "row_id", group: str | None = None, weight: str | None = None) -> dict[int, list[np.ndarray]]:
    """For each group, `restarts` lists of up to k centers drawn by squared distance.

    The first is uniform among rows. A draw in proportion to w is the row with the least -ln(u)/w,
    u hashed from row, draw, restart and seed: one candidate a partition, no running sums, the same
    choice in any partitioning. Where all distances are 0 fewer centers come back.
    """
    chosen: dict[int, list[list[np.ndarray]]] = {}
    columns = [key, name, *([group] if group else []), *([weight] if weight else [])]
    rows = df.select(*columns)
    kind = "grp long, restart int, race double, row long, z array<double>"
    for draw in range(k):
        now = {g: [np.array(c) for c in cs] for g, cs in chosen.items()}

        def candidates(it: Iterator[pa.RecordBatch], now=now, draw=draw) -> Iterator[pa.RecordBatch]:
            best: dict[tuple[int, int], tuple[float, int, list[float]]] = {}
            for ids, z, grp, w in _batches(it, key, name, group, weight):
                for g in np.unique(grp):
                    mine = np.nonzero(grp == g)[0]
                    for r in range(restarts):
                        d2 = w[mine].astype(np.float64)
                        if draw:
                            if int(g) not in now:
                                continue
                            near = _distances(z[mine], now[int(g)][r]).min(axis=1)
                            d2 = d2 * np.where(near > 1e-12 * np.maximum(1.0, (z[mine] ** 2).sum(axis=1)), near, 0)
                        u = hashed_uniform(ids[mine], seed, draw, r)
                        with np.errstate(divide="ignore"):
                            race = np.where(d2 > 0, -np.log(u) / d2, np.inf)
                        i = int(np.lexsort((ids[mine], race))[0])
                        if np.isfinite(race[i]):
                            new = (float(race[i]), int(ids[mine[i]]), z[mine[i]].tolist())
                            key_ = (int(g), r)
                            best[key_] = min(best.get(key_, new), new)
            yield pa.RecordBatch.from_pylist([{"grp": g, "restart": r, "race": v[0], "row": v[1], "z": v[2]} for (g, r), v in best.items()], schema=pa.schema([("grp", pa.int64()), ("restart", pa.int32()), ("race", pa.float64()), ("row", pa.int64()), ("z", pa.list_(pa.float64()))]))

        won = rows.mapInArrow(candidates, kind).groupBy("grp", "restart").agg(F.min_by("z", F.struct("race", "row")).alias("z")).collect()
        for r in won:
            lists = chosen.setdefault(r["grp"], [[] for _ in range(restarts)])
            lists[r["restart"]].append(np.array(r["z"]))
    return {g: [np.array(c) for c in cs] for g, cs in chosen.items()}


def seed_parallel(df: DataFrame, k: int, seed: int = 0, rounds: int = 4, oversample: float = 2.0, name: str = "z", key: str = "row_id") -> np.ndarray:
    """Oversampled seeding: a few passes that each keep rows with probability in proportion to their squared
    distance, then a weighted draw of k among them on the driver. Passes don't grow with k."""
    rows = df.select(key, name)
    centers = seed_dsq(rows, 1, seed, name=name, key=key)[0][0]
    schema = "row long, z array<double>"
    for t in range(rounds):
        now = centers

        def cost(it: Iterator[pa.RecordBatch], now=now) -> Iterator[pa.RecordBatch]:
            total = sum(float(_distances(z, now).min(axis=1).sum()) for _, z, _, _ in _batches(it, key, name, None, None))
            yield pa.RecordBatch.from_arrays([pa.array([total])], names=["cost"])

        phi = rows.mapInArrow(cost, "cost double").agg(F.sum("cost")).first()[0] or 0.0
        if phi <= 0:
            break

        def pick(it: Iterator[pa.RecordBatch], now=now, phi=phi, t=t) -> Iterator[pa.RecordBatch]:
            for ids, z, _, _ in _batches(it, key, name, None, None):
                take = hashed_uniform(ids, seed, 100 + t) < oversample * k * _distances(z, now).min(axis=1) / phi
                if take.any():
                    yield pa.RecordBatch.from_arrays([pa.array(ids[take]), pa.array(z[take].tolist(), pa.list_(pa.float64()))], names=["row", "z"])

        new = rows.mapInArrow(pick, schema).orderBy("row").collect()  # about oversample x k rows
        if new:
            centers = np.vstack([centers, np.array([r["z"] for r in new])])
    weights = lloyd_step(rows, {0: [centers]}, name=name, key=key)[0][0][1]
    return weighted_seeds(centers, np.maximum(weights, 1e-9), k, seed)


def weighted_seeds(points: np.ndarray, weights: np.ndarray, k: int, seed: int) -> np.ndarray:
    rng = np.random.default_rng(seed)
    out = [points[rng.choice(len(points), p=weights / weights.sum())]]
    while len(out) < min(k, len(points)):
        d = weights * _distances(points, np.array(out)).min(axis=1)
        if d.sum() <= 0:
            break
        out.append(points[rng.choice(len(points), p=d / d.sum())])
    return np.array(out)


def weighted_lloyd(points: np.ndarray, weights: np.ndarray, centers: np.ndarray, passes: int = 100) -> tuple[np.ndarray, float]:
    """k-means of a small weighted table on the driver."""
    return lloyd_labels(points, weights, centers, passes)[:2]


#: Part of the greatest distance by which bounds must lie apart: far above their rounding.
SLACK = 1e-10


def lloyd_labels(points: np.ndarray, weights: np.ndarray, centers: np.ndarray, passes: int = 100, whole_sums: bool = False) -> tuple[np.ndarray, float, np.ndarray]:
    """Centers, mean squared distance and the nearest center of each point, of a weighted table in one process.

    A pass looks only at points whose nearest center may have changed: each keeps an upper bound of the distance to
    its own center and a lower one to all others, which widen by what the centers move. Of the sums, it moves only the
    points that changed their center; the last sums, and those of a pass in which two centers are as near to
    a point as the rounding of moved sums, are made of all points. So the labels and
    centers are those of comparing every point with every center and of summing all points in each pass.
    """
    start, centers, k = centers, centers.copy(), len(centers)
    columns = np.ascontiguousarray(points.T)
    weighted = columns if (weights == 1).all() else [weights * x for x in columns]

    def summed(rows: np.ndarray | slice, labels: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Mass, number and sums of some points by label."""
        total = [np.bincount(labels, weights=x[rows], minlength=k) for x in weighted]
        w = weights[rows]
        return np.bincount(labels, weights=w, minlength=k), np.bincount(labels[w != 0], minlength=k), np.stack(total, axis=1)

    def middles(mass: np.ndarray, total: np.ndarray) -> np.ndarray:
        return np.where(mass[:, None] > 0, total / np.maximum(mass, 1e-300)[:, None], centers)

    near, upper, lower = nearest_two(columns, centers)
    np.sqrt(upper, out=upper), np.sqrt(lower, out=lower)
    reach = float(lower.max(initial=0, where=np.isfinite(lower)) + upper.max(initial=0))
    # more than sums in another order may differ by, in distances
    rounding = 4 * (len(points) + passes) * np.finfo(np.float64).eps * float(np.abs(points).max(initial=0)) * max(1, points.shape[1]) ** 0.5
    moved, held = None, None
    for p in range(passes):
        whole = whole_sums or held is None or p == passes - 1 or 4 * len(moved[0]) > len(near)
        if moved is not None and not len(moved[0]):
            break  # the same labels have the same sums
        if whole:
            held = summed(slice(None), near)
        else:
            rows, old = moved
            held = tuple(h + x - y for h, x, y in zip(held, summed(rows, near[rows]), summed(rows, old)))
            if (held[1] == 0).any():  # a center without points stays where it was, to the last digit
                return lloyd_labels(points, weights, start, passes, whole_sums=True)
        new = middles(held[0], held[2])
        if whole and np.array_equal(new, centers):
            break
        before, move = centers, np.sqrt(((new - centers) ** 2).sum(axis=1))
        upper += move[near]
        lower -= move.max()
        reach += float(move.max())
        rows = np.nonzero(upper + (SLACK * reach + rounding) >= lower)[0]
        some = len(rows) < len(near) // 2
        looked, to = np.take(columns, rows, axis=1) if some else columns, rows if some else slice(None)
        found, d, e = nearest_two(looked, new)
        d, e = np.sqrt(d), np.sqrt(e)
        if not whole and (e - d <= SLACK * reach + rounding).any():
            held = summed(slice(None), near)
            centers = before
            new = middles(held[0], held[2])
            found, d, e = nearest_two(looked, new)
            d, e = np.sqrt(d), np.sqrt(e)
        centers = new
        changed = np.nonzero(found != near[to])[0]
        moved = (rows[changed] if some else changed), near[to][changed]
        near[to], upper[to], lower[to] = found, d, e
    if moved is not None and not len(moved[0]) and not whole:
        mass, _, total = summed(slice(None), near)
        centers = middles(mass, total)
    near, best, _ = nearest_two(columns, centers)
    return centers, float((weights * best).sum() / weights.sum()), near


def seed_fixed(df: DataFrame, k: int, mode: str = "lowest", name: str = "z", key: str = "row_id") -> np.ndarray:
    """Reproducible seeds: the rows of the k lowest keys, or farthest-first from the lowest."""
    if mode == "lowest":
        return np.array([r[name] for r in df.orderBy(key).limit(k).collect()])
    from ..functions.vectors import sqdist

    out = [df.orderBy(key).first()[name]]
    for _ in range(k - 1):
        far = F.array_min(F.array(*(sqdist(F.col(name), F.array(*map(F.lit, c))) for c in out)))
        out.append(df.withColumn("__d", far).orderBy(F.col("__d").desc(), key).first()[name])
    return np.array(out)


def lloyd_step(df: DataFrame, centers: dict[int, list[np.ndarray]], name: str = "z", key: str = "row_id", group: str | None = None, weight: str | None = None) -> dict[int, list[tuple[np.ndarray, np.ndarray, float]]]:
    """One assignment pass for all groups and restarts: sums, counts and squared distance by cluster.

    A partition sends one row a group, restart and cluster; those are added by one small aggregation.
    """
    width = len(next(c for cs in centers.values() for c in cs)[0])

    def partial(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[tuple[int, int], np.ndarray] = {}
        for _, z, grp, w in _batches(it, key, name, group, weight):
            for g in np.unique(grp):
                mine = grp == g
                x, v = z[mine], w[mine].astype(np.float64)
                for r, c in enumerate(centers.get(int(g), [])):
                    d = _distances(x, c)
                    near = d.argmin(axis=1)
                    part = np.zeros((len(c), width + 2))
                    one = np.zeros((len(x), len(c)))
                    one[np.arange(len(x)), near] = v
                    part[:, :width] = one.T @ x
                    part[:, width] = one.sum(axis=0)
                    part[:, width + 1] = np.bincount(near, weights=v * d[np.arange(len(x)), near], minlength=len(c))
                    at = (int(g), r)
                    total[at] = total[at] + part if at in total else part
        out = [(g, r, k, *row) for (g, r), p in total.items() for k, row in enumerate(p.tolist())]
        names = ["grp", "restart", "cluster", *(f"s{i}" for i in range(width)), "n", "d"]
        cols = list(zip(*out)) if out else [[] for _ in names]
        types = [pa.int64(), pa.int32(), pa.int32(), *([pa.float64()] * (width + 2))]
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types)], names=names)

    sums = [f"s{i}" for i in range(width)] + ["n", "d"]
    columns = [key, name, *([group] if group else []), *([weight] if weight else [])]
    parts = df.select(*columns).mapInArrow(partial, "grp long, restart int, cluster int, " + ", ".join(f"{s} double" for s in sums))
    found = parts.groupBy("grp", "restart", "cluster").agg(*(F.sum(s).alias(s) for s in sums)).collect()
    out = {g: [[np.zeros((len(c), width)), np.zeros(len(c)), 0.0] for c in cs] for g, cs in centers.items()}
    for r in found:
        slot = out[r["grp"]][r["restart"]]
        slot[0][r["cluster"]] = [r[f"s{i}"] for i in range(width)]
        slot[1][r["cluster"]] = r["n"]
        slot[2] += r["d"]
    return {g: [tuple(s) for s in ss] for g, ss in out.items()}


def lloyd(df: DataFrame, centers: dict[int, list[np.ndarray]], passes: int = 300, tol: float | None = None, name: str = "z", key: str = "row_id", group: str | None = None, weight: str | None = None) -> dict[int, list[KMeansResult]]:
    """`passes` updates of all groups' and restarts' centers; an empty cluster keeps its center.

    Ends early when nothing moves any more but by rounding (sums come in any order), or when no center
    moves by more than tol. Ties go to the lowest cluster.
    """
    size = max((float(np.abs(c).max(initial=0)) for cs in centers.values() for c in cs), default=0.0)
    still = ROUNDING * max(size, 1e-300)
    results = {g: [KMeansResult(c, float("nan")) for c in cs] for g, cs in centers.items()}
    now = {g: [c.copy() for c in cs] for g, cs in centers.items()}
    for done in range(passes + 1):
        stats = lloyd_step(df, now, name, key, group, weight)
        moved = 0.0
        for g, ss in stats.items():
            for r, (s, n, d) in enumerate(ss):
                results[g][r].history.append(d / max(n.sum(), 1e-300))
                results[g][r].centers, results[g][r].inertia, results[g][r].passes = now[g][r], d / max(n.sum(), 1e-300), done
                if done < passes:
                    new = np.where(n[:, None] > 0, s / np.maximum(n, 1e-300)[:, None], now[g][r])
                    moved = max(moved, float(np.abs(new - now[g][r]).max(initial=0)))
                    now[g][r] = new
        if moved <= max(still, tol or 0.0):
            break
    return results


def fit(df: DataFrame, k: int, passes: int = 300, seed: int = 0, restarts: int = 1, tol: float | None = None, name: str = "z", key: str = "row_id", seeding: str = "dsq", sample: float | None = None, weight: str | None = None) -> KMeansResult:
    """Seeding and Lloyd passes; the restart of least inertia. Points are kept narrow in memory and on disk.

    seeding: `dsq`, k passes over the rows; or `parallel`, five passes whatever k, the choice for many
    clusters. sample: passes on a hash sample first, then on all rows from there. No rows: no centers.
    """
    if k < 1:
        raise ValueError("k")
    narrow = df.select(key, name, *([weight] if weight else [])).persist(StorageLevel.MEMORY_AND_DISK)
    try:
        if seeding == "parallel":
            start = {0: [seed_parallel(narrow, k, seed + r, name=name, key=key) for r in range(restarts)]}
        else:
            start = seed_dsq(narrow, k, seed, restarts, name, key, weight=weight)
        if not start:
            return KMeansResult(np.zeros((0, 0)), float("nan"))
        if sample:
            part = narrow.where(F.pmod(F.xxhash64(F.lit(seed), key), F.lit(1_000_000)) < int(sample * 1_000_000))
            start = {0: [r.centers for r in lloyd(part, start, passes, tol, name, key, weight=weight)[0]]}
        return min(lloyd(narrow, start, passes, tol, name, key, weight=weight)[0], key=lambda r: r.inertia)
    finally:
        narrow.unpersist()


def assign(df: DataFrame, centers: np.ndarray, name: str = "z", label: str = "pred", distance: str | None = None) -> DataFrame:
    """Adds the nearest center's number (ties to the lowest; null without any center). Narrow and stateless: for streams too.

    Up to a few hundred products the distances are plain expressions in generated code; beyond, the same
    sums a batch at a time.
    """
    from ..functions.vectors import nearest

    k, m = centers.shape if centers.ndim == 2 else (0, 0)
    if k * m <= 256:
        number, least = nearest([F.col(name)[i] for i in range(m)], centers.tolist())
        out = df.withColumn(label, number)
        return out.withColumn(distance, least) if distance else out

    @F.pandas_udf("cluster int, dist double")
    def near(z):
        import pandas as pd

        d = _distances(np.stack(z.to_numpy()), centers) if len(z) else np.zeros((0, k))
        return pd.DataFrame({"cluster": d.argmin(axis=1).astype("int32") if len(z) else [], "dist": d.min(axis=1) if len(z) else []})

    out = df.withColumn("__near", near(name)).withColumn(label, F.col("__near.cluster"))
    return (out.withColumn(distance, F.col("__near.dist")) if distance else out).drop("__near")


def inertia(df: DataFrame, centers: np.ndarray, name: str = "z") -> float:
    return assign(df, centers, name, "__c", "__d").agg(F.avg("__d")).first()[0]


def pairwise_assign(df: DataFrame, centers: np.ndarray, name: str = "z", key: str = "row_id", label: str = "pred") -> DataFrame:
    """The same labels by a join of all rows with the table of centers (k rows, broadcast) and a least distance a row:
    key, label, dist. For comparison; `assign` needs neither the join nor the aggregation. Ids must be unique."""
    from ..functions.vectors import sqdist

    table = df.sparkSession.createDataFrame([(k, c.tolist()) for k, c in enumerate(centers)], f"{label} int, center array<double>")
    pairs = df.select(key, F.col(name).alias("z")).crossJoin(F.broadcast(table)).select(key, label, sqdist(F.col("z"), F.col("center")).alias("dist"))
    return pairs.groupBy(key).agg(F.min(F.struct("dist", label)).alias("best")).select(key, f"best.{label}", "best.dist")


def cumulative_draw(df: DataFrame, shares: list[float], weight: str = "w", key: str = "row_id") -> list:
    """For each share u of the total weight the row, in the order of keys, at which the running sum first exceeds u.

    The draw by running sums, which the exponential race of `seed_dsq` does without. Rows are sorted by
    ranges; each range's sum reaches the driver, and only the range that a share falls into is summed up row by row.
    """
    spark = df.sparkSession
    ranged = df.select(F.col(key).alias("k"), F.col(weight).cast("double").alias("w")).where("w > 0").repartitionByRange("k").withColumn("part", F.spark_partition_id())
    ranged = materialise(spark, ranged, "ranges")
    sums = {r["part"]: r["w"] for r in ranged.groupBy("part").agg(F.sum("w").alias("w")).collect()}
    total, out = sum(sums.values()), []
    for u in shares:
        left, at = u * total, None
        for part in sorted(sums):
            at = part
            if left < sums[part]:
                break
            left -= sums[part]
        running = F.sum("w").over(Window.partitionBy("part").orderBy("k").rowsBetween(Window.unboundedPreceding, 0))
        found = ranged.where(F.col("part") == F.lit(at)).withColumn("sum", running).where(F.col("sum") > left).agg(F.min("k").alias("k")).first()
        out.append(found["k"])
    return out
