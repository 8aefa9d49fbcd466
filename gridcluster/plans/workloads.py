"""Experiment workloads on the given tables, and the runners that fill the trial ledger."""

from __future__ import annotations

import math
from collections.abc import Callable, Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import features
from ..functions.portable import gaussian, uniform
from ..operators import diagnostics, metrics
from ..operators.grid import GridSpec, equal_groups, even_columns, skewed_groups, split_grid
from ..session import forget, materialise, passing
from ..sources.tables import load
from . import baselines
from . import trials as trials_
from .pipeline import grid_cluster

#: Layout of the planted shapes: centers of the blobs, radii of the rings, spread of the minor features.
BLOB_CENTERS = ((-6.0, -3.0), (0.0, 6.0), (6.0, -3.0))
RING_RADII, RING_JITTER = (2.0, 6.0, 10.0), 0.1
MINOR_OWN, MINOR_COMMON = 0.3, 0.1  # variance 0.1, covariance 0.01
#: Columns of each party: one major feature and two minor ones.
SHAPE_COLUMNS = ((0, 2, 3), (1, 4, 5))
#: Tables whose keys carry planted points; customers are 1,500 at the middle size, as many as in the first experiment.
ORDERS, CUSTOMERS = ("orders", "o_orderkey"), ("customer", "c_custkey")


def _spread(rows: DataFrame, key: str) -> DataFrame:
    """Rows over all cores: a small file comes as one task, whose features take longer than its trials."""
    return rows.repartition(2 * rows.sparkSession.sparkContext.defaultParallelism, key)


def _minors(key, seed: int) -> list:
    common = gaussian(seed, key, "common") * MINOR_COMMON
    return [gaussian(seed, key, f"minor{i}") * MINOR_OWN + common for i in range(4)]


def _planted(spark: SparkSession, sf_dir: str, seed: int, majors, keys: tuple[str, str]) -> DataFrame:
    table, key = keys
    rows = _spread(load(spark, sf_dir, table, [key]), key).select(F.col(key).cast("long").alias("row_id"), F.pmod(key, F.lit(3)).cast("int").alias("truth"))
    x, y = majors(F.col("truth"), F.col("row_id"))
    return rows.select("row_id", "truth", F.array(x, y, *_minors(F.col("row_id"), seed)).alias("feats"))


def _pick(values: Sequence[float], truth):
    return F.element_at(F.array(*(F.lit(float(v)) for v in values)), truth + 1)


def planted_blobs(spark: SparkSession, sf_dir: str, split: str = "iid", seed: int = 1, keys: tuple[str, str] = ORDERS) -> DataFrame:
    """Three normal clusters in two major features, four minor ones of correlated noise; a row a key of a given table."""
    points = _planted(spark, sf_dir, seed, lambda t, k: tuple(_pick([c[i] for c in BLOB_CENTERS], t) + gaussian(seed, k, f"major{i}") for i in (0, 1)), keys)
    return _grouped(points, split, seed)


def planted_rings(spark: SparkSession, sf_dir: str, split: str = "iid", seed: int = 1, radii: Sequence[float] = RING_RADII, jitter: float = RING_JITTER, keys: tuple[str, str] = ORDERS) -> DataFrame:
    """Three rings around the origin, else as the blobs."""

    def majors(t, k):
        r, a = _pick(radii, t), uniform(seed, k, "angle") * (2 * math.pi)
        return r * F.cos(a) + gaussian(seed, k, "jx") * jitter, r * F.sin(a) + gaussian(seed, k, "jy") * jitter

    return _grouped(_planted(spark, sf_dir, seed, majors, keys), split, seed)


def _grouped(points: DataFrame, split: str, seed: int) -> DataFrame:
    if split == "iid":
        return split_grid(points, 2, seed=seed)
    if split == "skew":
        return skewed_groups(points, seed=seed)
    raise ValueError(split)


def planted_like(spark: SparkSession, sf_dir: str, table: str, key: str, width: int, k: int, gap: float, seed: int = 1) -> DataFrame:
    """k unit-variance normal groups whose means lie gap apart along directions of their own."""
    rows = _spread(load(spark, sf_dir, table, [key]), key).select(F.col(key).cast("long").alias("row_id"), F.pmod(F.col(key), F.lit(k)).cast("int").alias("truth"))
    mean = lambda i: F.element_at(F.array(*(F.lit(gap * math.cos(2.4 * c + 1.7 * i)) for c in range(k))), F.col("truth") + 1)
    return rows.select("row_id", "truth", F.array(*(mean(i) + gaussian(seed, F.col("row_id"), i) for i in range(width))).alias("feats"))


def embedding_shift(spark: SparkSession, sf_dir: str, dims: int = 16, shift: float = 0.7, classes: int = 10) -> DataFrame:
    """Leading embedding dimensions, with a shift on the label's own; shift 0: a control without structure."""
    label = F.pmod("label", F.lit(classes)).cast("int")
    feats = [F.col("embedding")[i].cast("double") + F.when(label == i, F.lit(shift)).otherwise(0.0) for i in range(dims)]
    return load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("row_id"), label.alias("truth"), F.array(*feats).alias("feats"))


#: Languages by number; any other label, or none, has a number of its own behind them.
LANGUAGES = ("de", "en", "es", "fr")


def text_language(spark: SparkSession, sf_dir: str, least: int = 0) -> DataFrame:
    """Letter shares of all texts; truth: the language. least: only texts of so many characters (of the text itself)."""
    docs = load(spark, sf_dir, "documents", ["doc_id", "text", "lang"])
    if least:
        docs = docs.where(F.length("text") >= least)
    docs = _spread(docs, "doc_id")
    number = F.coalesce(F.array_position(F.array(*map(F.lit, LANGUAGES)), F.col("lang")), F.lit(0))
    truth = F.when(number > 0, number - 1).otherwise(len(LANGUAGES)).cast("int")
    text = F.coalesce(F.col("text"), F.lit(""))
    return docs.select(F.col("doc_id").alias("row_id"), truth.alias("truth"), F.array(*features.letter_shares(text)).alias("feats"))


def text_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Character shares of labelled texts; truth: quality."""
    docs = load(spark, sf_dir, "documents", ["doc_id", "text"]).join(load(spark, sf_dir, "labels", ["doc_id", "quality"]), "doc_id")
    docs = _spread(docs, "doc_id")
    return docs.select(F.col("doc_id").alias("row_id"), F.col("quality").cast("int").alias("truth"), F.array(*features.character_shares(F.col("text"))).alias("feats"))


def customer_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two holders of the same customers: profile (balance, nation) and behaviour (orders); row groups by region."""
    orders = load(spark, sf_dir, "orders", ["o_custkey", "o_totalprice", "o_orderstatus"]).groupBy("o_custkey").agg(
        F.count(F.lit(1)).cast("double").alias("n"), F.avg("o_totalprice").alias("mean"), F.coalesce(F.stddev_pop("o_totalprice"), F.lit(0.0)).alias("sd"), F.avg(F.when(F.col("o_orderstatus") == "F", 1.0).otherwise(0.0)).alias("share")
    )
    nations = load(spark, sf_dir, "nation", ["n_nationkey", "n_regionkey"])
    rows = load(spark, sf_dir, "customer").join(F.broadcast(nations), F.col("c_nationkey") == F.col("n_nationkey")).join(orders, F.col("c_custkey") == F.col("o_custkey"), "left")
    own = [F.col("c_acctbal"), F.col("c_nationkey").cast("double")]
    behaviour = [F.coalesce(F.col(c), F.lit(0.0)) for c in ("n", "mean", "sd", "share")]
    segment = F.when(F.col("c_mktsegment").isin("AUTOMOBILE", "BUILDING"), 0).otherwise(1)
    return rows.select(F.col("c_custkey").alias("row_id"), segment.cast("int").alias("truth"), F.col("n_regionkey").cast("int").alias("row_grp"), F.array(*own, *behaviour).alias("feats"))


def lineitem_numeric(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Four measures and the ship month of each line; the key hashes the columns that tell lines apart."""
    parts = [F.col(c).cast("string") for c in ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")]
    key = F.conv(F.substring(F.md5(F.concat_ws("~", *parts)), 1, 15), 16, 10).cast("long")
    lines = load(spark, sf_dir, "lineitem", ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_shipdate"])
    return lines.select(key.alias("row_id"), F.array("l_quantity", "l_extendedprice", "l_discount", "l_tax", F.month("l_shipdate").cast("double")).alias("feats"))


#: Twins of the six tables of the second experiment: loader, features, clusters, scaling of the pooled run.
DATASETS = {
    "small_three": (lambda s, d: planted_like(s, d, "customer", "c_custkey", 4, 3, 2.2), 4, 3),
    "two_overlapping": (lambda s, d: planted_like(s, d, "part", "p_partkey", 7, 2, 0.75), 7, 2),
    "ten_classes": (lambda s, d: embedding_shift(s, d), 16, 10),
    "no_structure": (lambda s, d: embedding_shift(s, d, 13, 0.0, 2), 13, 2),
    "behaviour": (lambda s, d: customer_orders(s, d).drop("row_grp"), 6, 2),
    "text_quality": (text_quality, 5, 2),
    "language": (text_language, 10, 4),
}


def _ledger(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame(rows, "dataset string, method string, trial int, metric string, value double")


def _scored(pred: DataFrame, truth: DataFrame) -> dict[str, float]:
    return metrics.scores(pred.join(truth, "row_id"))


def run_exp1(spark: SparkSession, sf_dir: str, shape: str = "blobs", split: str = "iid", scale: bool = False, methods: Sequence[str] = ("solo", "pooled", "grid"), seed: int = 1, restarts: int = 5, q: int = 10, keys: tuple[str, str] = CUSTOMERS, target: str | None = None, anchor_count: int | None = None) -> DataFrame:
    """First experiment: one trial of four parties; a ledger row a method and measure.

    The recipe as printed standardises before the component analysis and aligns to orthonormal targets, with as
    many anchors as rows: scale=True, target="U". By default rows are only centered, and rings aligned to scaled targets.
    """
    points = materialise(spark, (planted_blobs if shape == "blobs" else planted_rings)(spark, sf_dir, split, seed, keys=keys), shape)
    algo = "kmeans" if shape == "blobs" else "spectral"
    spec, truth = GridSpec(SHAPE_COLUMNS), points.select("row_id", "truth")
    options = {"restarts": restarts, "seed": seed, "q": q}
    out = []

    def note(method: str, run: Callable[[], DataFrame]) -> None:
        with passing(spark):
            out.extend((f"{shape}-{split}", method, 0, m, v) for m, v in _scored(run().select("row_id", "pred"), truth).items())

    if "solo" in methods:
        for i, j in [(0, 0), (0, 1)] + ([(1, 0), (1, 1)] if split == "skew" else []):
            note(f"solo({i + 1},{j + 1})", lambda: baselines.solo(points, spec, i, j, 3, algo, **options))
    if "pooled" in methods:
        note("pooled", lambda: baselines.pooled(points, 3, algo, **options))
    if "grid" in methods:
        note("grid", lambda: grid_cluster(points, spec, 3, algo, anchor_count=anchor_count or points.count(), map_options={"scale": scale}, target=target or ("US" if algo == "spectral" else "U"), restarts=restarts, seed=seed, q=q).labels)
    forget(spark, points)
    return _ledger(spark, out)


def run_exp2(spark: SparkSession, sf_dir: str, dataset: str, algo: str = "kmeans", trials: int = 100, row_groups: int = 10, column_groups: int = 2, methods: Sequence[str] = ("solo", "fed", "grid", "pooled"), restarts: int = 1, passes: int = 300, rounds: int = 10, aligner: str = "affine", q: int = 10) -> DataFrame:
    """Second experiment: random rows and columns each trial, in equal groups, with as many anchors as rows; a ledger
    row a trial, method and measure.

    A table of bounded size is broadcast, and each trial is a task; a larger one is taken trial by
    trial through the distributed operators.
    """
    loader, width, k = DATASETS[dataset]
    points = materialise(spark, loader(spark, sf_dir), dataset)
    n = points.count()
    setting = trials_.Setting(k, algo, row_groups, column_groups, tuple(methods), restarts, passes, rounds, aligner, "U", q)
    if n <= trials_.MOST_ROWS[algo]:
        table = trials_.Points.of(points)
        forget(spark, points)
        return trials_.run_trials(spark, table, setting, dataset, trials)
    truth = points.select("row_id", "truth")
    out = []
    for t in range(trials):
        seed = trials_.trial_seed(dataset, t)
        spec = GridSpec(even_columns(width, column_groups, seed))
        split = materialise(spark, equal_groups(points, row_groups, seed=seed), "split")
        options = {"restarts": restarts, "seed": seed, "passes": passes, "q": q}
        runs = {
            "solo": lambda: baselines.solo(split, spec, 0, 0, k, algo, **options),
            "fed": lambda: (baselines.fed_kmeans(split, spec, k, rounds, seed=seed, restarts=restarts) if algo == "kmeans" else baselines.fed_spectral(split, spec, k, seed=seed, q=q))[0],
            "grid": lambda: grid_cluster(split, spec, k, algo, anchor_count=n, aligner=aligner, passes=passes, restarts=restarts, seed=seed, q=q).labels,
            "pooled": lambda: baselines.pooled(split, k, algo, **options),
        }
        for m in methods:
            with passing(spark):
                out.extend((dataset, m, t, name, v) for name, v in _scored(runs[m]().select("row_id", "pred"), truth).items())
        forget(spark, split)
    forget(spark, points)
    return _ledger(spark, out)


#: The six tables of the second experiment; `language` is one more.
PRINTED = ("small_three", "two_overlapping", "ten_classes", "no_structure", "behaviour", "text_quality")


def average_deviations(spark: SparkSession, sf_dir: str, trials: int = 100, spectral_trials: int = 100, datasets: Sequence[str] = PRINTED) -> DataFrame:
    """Average difference to pooled, in percent, over all tables and measures: algo, method, avg_pct, tables."""
    parts = []
    for algo, n in (("kmeans", trials), ("spectral", spectral_trials)):
        ledger = run_exp2(spark, sf_dir, datasets[0], algo, n)
        for d in datasets[1:]:
            ledger = ledger.unionByName(run_exp2(spark, sf_dir, d, algo, n))
        parts.append(deviation_report(ledger).withColumn("algo", F.lit(algo)))
    return parts[0].unionByName(parts[1]).select("algo", "method", "avg_pct")


def deviation_report(ledger: DataFrame) -> DataFrame:
    """Average relative difference to pooled, by method."""
    return diagnostics.avg_pct_delta(diagnostics.pct_delta(diagnostics.summarise_trials(ledger)))
