"""Reports on results: outliers, quantiles, rankings, shifts of centers, trial summaries."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def outliers(df: DataFrame, top: int, distance: str = "dist", key: str = "row_id") -> DataFrame:
    return df.orderBy(F.col(distance).desc(), key).limit(top)


def distance_quantiles(df: DataFrame, distance: str = "dist", by: str = "pred", at: tuple[float, ...] = (0.5, 0.9, 0.99), exact: bool = False) -> DataFrame:
    """Quantiles by cluster: a sketch of bounded size, or exact (interpolated) ones, which hold a cluster's distinct values in one task."""
    if exact:
        return df.groupBy(by).agg(F.percentile(distance, list(at)).alias("quantiles"))
    return df.groupBy(by).agg(F.percentile_approx(distance, list(at), 10_000).alias("quantiles"))


def label_counts(df: DataFrame, label: str = "pred", key: str = "row_id", approx: bool = False) -> DataFrame:
    count = F.approx_count_distinct if approx else F.count_distinct
    return df.groupBy(label).agg(F.count(F.lit(1)).alias("n"), count(key).alias("n_distinct"))


def center_shift(history: DataFrame) -> DataFrame:
    """How far each center moved from pass to pass; history: pass, cluster, center."""
    from ..functions.vectors import sqdist

    w = Window.partitionBy("cluster").orderBy("pass")
    return history.withColumn("before", F.lag("center").over(w)).where("before IS NOT NULL").select("pass", "cluster", F.sqrt(sqdist(F.col("center"), F.col("before"))).alias("shift"))


def summarise_trials(ledger: DataFrame) -> DataFrame:
    """Mean and standard deviation over trials: dataset, method, metric, mean, sd, trials."""
    return ledger.groupBy("dataset", "method", "metric").agg(F.avg("value").alias("mean"), F.coalesce(F.stddev("value"), F.lit(0.0)).alias("sd"), F.count(F.lit(1)).alias("trials"))


def pct_delta(summary: DataFrame, against: str = "pooled") -> DataFrame:
    """Relative difference of each mean to that of `against`, in percent: absolute (improvements count too) and signed.

    Where that mean is 0, equal means differ by 0 percent and others by null, which averages leave out.
    """
    base = summary.where(F.col("method") == against).select("dataset", "metric", F.col("mean").alias("base"))
    diff = F.when(F.col("mean") == F.col("base"), 0.0).otherwise(F.try_divide(F.col("mean") - F.col("base"), F.abs("base")) * 100)
    return summary.where(F.col("method") != against).join(base, ["dataset", "metric"]).select("dataset", "method", "metric", F.abs(diff).alias("pct"), diff.alias("signed_pct"))


def avg_pct_delta(deltas: DataFrame) -> DataFrame:
    return deltas.groupBy("method").agg(F.avg("pct").alias("avg_pct"))


def rank_methods(summary: DataFrame) -> DataFrame:
    w = Window.partitionBy("dataset", "metric").orderBy(F.col("mean").desc(), "method")
    return summary.withColumn("rank", F.rank().over(w))


def wide_table(summary: DataFrame) -> DataFrame:
    """A row a dataset and method, a column a metric."""
    return summary.groupBy("dataset", "method").pivot("metric", ["ari", "nmi", "acc"]).agg(F.first("mean"))


def long_table(wide: DataFrame) -> DataFrame:
    return wide.unpivot(["dataset", "method"], ["ari", "nmi", "acc"], "metric", "mean")
