"""Labels, window counts, late rows and running centers of a stream of points or events."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout
from pyspark.sql.window import Window

from ..functions.vectors import matvec
from ..operators import kmeans
from ..session import discard, shared_dir


def score(points: DataFrame, centers: np.ndarray, matrix: np.ndarray | None = None, shift: np.ndarray | None = None, feats: str = "feats") -> DataFrame:
    """Adds pred to a stream or table: an affine map (map and aligner of one row group), then the nearest center.

    Stateless: only projections.
    """
    z = F.col(feats)
    if matrix is not None:
        z = matvec(z, matrix.tolist())
        if shift is not None:
            z = F.zip_with(z, F.array(*(F.lit(float(s)) for s in shift)), lambda a, b: a + b)
    return kmeans.assign(points.withColumn("__z", z), centers, "__z").drop("__z")


def _watermarked(stream: DataFrame, time: str, delay: str) -> DataFrame:
    """A watermark needs a timestamp: one without a zone is taken as of the session's zone."""
    if dict(stream.dtypes)[time] == "timestamp_ntz":
        stream = stream.withColumn(time, F.col(time).cast("timestamp"))
    return stream.withWatermark(time, delay)


def label_counts(scored: DataFrame, kind: str = "tumbling", size: str = "1 hour", slide: str = "15 minutes", gap: str = "30 minutes", watermark: str | None = "10 minutes", time: str = "ts", label: str = "pred", key: str = "user_id") -> DataFrame:
    """Rows by label and window; sessions are per key. The watermark bounds the state of a stream."""
    df = _watermarked(scored, time, watermark) if watermark and scored.isStreaming else scored
    if kind == "tumbling":
        w, by = F.window(time, size), [label]
    elif kind == "sliding":
        w, by = F.window(time, size, slide), [label]
    elif kind == "session":
        w, by = F.session_window(time, gap), [key]
    else:
        raise ValueError(kind)
    return df.groupBy(w.alias("w"), *by).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *by, "n")


def dedup(stream: DataFrame, key: str = "event_id", time: str = "ts", watermark: str = "10 minutes") -> DataFrame:
    """First row a key within the watermark on a stream; on a table plain distinct keys."""
    if not stream.isStreaming:
        return stream.dropDuplicates([key])
    return _watermarked(stream, time, watermark).dropDuplicatesWithinWatermark([key])


def late_splitter(on_time: Callable[[DataFrame, int], None], late: Callable[[DataFrame, int], None], delay_seconds: int = 600, time: str = "ts", state: str | None = None) -> Callable[[DataFrame, int], None]:
    """A foreachBatch function that writes rows older than the greatest time seen, less the delay, aside.

    The greatest time up to each batch is kept in `state`, a folder that outlives the driver (by
    default one of the shared folder, for this function's life only), under the batch's number. So a batch
    that is run again after a restart is split as it was the first time.
    """
    folder: list[str] = [state] if state else []
    at = F.col(time).cast("timestamp")  # what comes back as a literal is a timestamp, too

    def known(spark: SparkSession, number: int):
        path = f"{folder[0]}/batch={number}"
        jvm = spark.sparkContext._jvm
        where = jvm.org.apache.hadoop.fs.Path(path)
        if not where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(where):
            return None
        return spark.read.schema("top timestamp").parquet(path).first()["top"]

    def run(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        if not folder:
            folder.append(f"{shared_dir(spark)}/late-{uuid.uuid4().hex}")
        batch = batch.persist()
        limit = known(spark, number - 1)
        if limit is None:
            on_time(batch, number)
        else:
            cut = F.lit(limit) - F.make_interval(secs=F.lit(delay_seconds))
            on_time(batch.where((at >= cut) | at.isNull()), number)
            late(batch.where(at < cut), number)
        top = batch.agg(F.max(at).alias("top")).first()["top"]
        top = limit if top is None else top if limit is None else max(limit, top)
        spark.createDataFrame([(top,)], "top timestamp").coalesce(1).write.mode("overwrite").parquet(f"{folder[0]}/batch={number}")
        discard(spark, f"{folder[0]}/batch={number - 2}")
        batch.unpersist()

    return run


def running_centers(scored: DataFrame, width: int, label: str = "pred", feats: str = "feats") -> DataFrame:
    """Per cluster the count and mean of all points so far: state of one vector a cluster."""

    def update(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, total = (state.get[0], np.array(state.get[1])) if state.exists else (0, np.zeros(width))
        for f in frames:
            n += len(f)
            total = total + np.stack(f[feats].to_numpy()).sum(axis=0)
        state.update((n, total.tolist()))
        yield pd.DataFrame({label: [key[0]], "n": [n], "center": [(total / max(n, 1)).tolist()]})

    return scored.groupBy(label).applyInPandasWithState(update, f"{label} int, n long, center array<double>", "n long, total array<double>", "update", GroupStateTimeout.NoTimeout)


def latest_model(events: DataFrame, versions: DataFrame, time: str = "ts", version: str = "version", slices: str = "1 day") -> DataFrame:
    """As-of join: each event with the last model version that is not younger than it.

    Versions and events are put in one order within time slices; each slice first gets the last
    version before it, so slices are worked on side by side.
    """
    cut = lambda c: F.window(c, slices)["start"]
    v = versions.select(F.col(time).alias("__t"), F.col(version).alias("__v"))
    e = events.withColumn("__t", F.col(time)).withColumn("__v", F.lit(None).cast(dict(versions.dtypes)[version])).withColumn("__event", F.lit(True))
    both = e.unionByName(v.withColumn("__event", F.lit(False)), allowMissingColumns=True).withColumn("__slice", cut("__t"))
    # the version that holds at the begin of each slice: a table of one row a slice
    last = both.groupBy("__slice").agg(F.max(F.when(F.col("__v").isNotNull(), F.struct("__t", "__v"))).alias("last"))
    before = last.withColumn("carry", F.last("last", ignorenulls=True).over(Window.orderBy("__slice").rowsBetween(Window.unboundedPreceding, -1))).select(F.col("__slice").alias("__s"), F.col("carry.__v").alias("__carry"))
    order = Window.partitionBy("__slice").orderBy("__t", F.col("__event")).rowsBetween(Window.unboundedPreceding, 0)
    found = both.join(before, F.col("__slice") == F.col("__s")).withColumn(version, F.coalesce(F.last("__v", ignorenulls=True).over(order), F.col("__carry")))
    return found.where("__event").select(*events.columns, version)


def within(a: DataFrame, b: DataFrame, seconds: int, time_a: str = "ts", time_b: str = "ts", key: str = "user_id") -> DataFrame:
    """Pairs of one key whose times differ by no more than so many seconds: joined on time buckets and their neighbours."""
    bucket = lambda c: F.floor(F.unix_seconds(c.cast("timestamp")) / seconds)
    left = a.withColumn("__b", bucket(F.col(time_a)))
    right = b.select(F.col(key).alias("__k"), F.struct(*b.columns).alias("other"), F.unix_micros(F.col(time_b).cast("timestamp")).alias("__u"), F.explode(F.array(*(bucket(F.col(time_b)) + d for d in (-1, 0, 1)))).alias("__c"))
    near = left.join(right, (F.col(key) == F.col("__k")) & (F.col("__b") == F.col("__c")))
    return near.where(F.abs(F.unix_micros(F.col(time_a).cast("timestamp")) - F.col("__u")) <= seconds * 1_000_000).select(*a.columns, "other")
