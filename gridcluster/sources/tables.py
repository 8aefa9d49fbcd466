"""Tables, text files, file streams; block and bucketed tables; models as JSON."""

from __future__ import annotations

import json
from collections.abc import Sequence

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from ..functions.portable import uniform


def load(spark: SparkSession, sf_dir: str, name: str, columns: Sequence[str] | None = None) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def load_text(spark: SparkSession, path: str, fmt: str, schema: StructType | str, **options: str) -> DataFrame:
    """CSV or JSON with a schema: nothing is inferred."""
    if fmt not in ("csv", "json"):
        raise ValueError(fmt)
    return spark.read.format(fmt).schema(schema).options(**options).load(path)


def stream(spark: SparkSession, path: str, schema: StructType | str, files_per_batch: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(path)


def write_blocks(df: DataFrame, path: str) -> None:
    """One folder a row group and column group, so that a party reads its block alone."""
    df.write.mode("overwrite").partitionBy("row_grp", "col_grp").parquet(path)


def write_bucketed(df: DataFrame, table: str, buckets: int, key: str = "row_id") -> None:
    """Blocks of one key distribution join without a shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(table)


def hash_sample(df: DataFrame, fraction: float, seed: int, key: str = "row_id") -> DataFrame:
    """The same rows in every run, partitioning and engine: by the portable uniform number of the key."""
    return df.where(uniform(seed, F.col(key), "sample") < fraction)


def save_model(spark: SparkSession, model: dict, path: str) -> None:
    """A model of centers, maps and aligners as one JSON line in a folder that Spark writes."""

    def plain(x):
        return x.tolist() if isinstance(x, np.ndarray) else int(x) if isinstance(x, np.integer) else float(x) if isinstance(x, np.floating) else x

    spark.createDataFrame([(json.dumps(model, default=plain),)], "value string").coalesce(1).write.mode("overwrite").text(path)


def load_model(spark: SparkSession, path: str) -> dict:
    return json.loads(spark.read.text(path, wholetext=True).first()[0])
