"""Points as arrays, wide columns or long rows, and the check of a stage's columns."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def require(df: DataFrame, **types: str) -> DataFrame:
    """Raises unless df has these columns with these types."""
    have = dict(df.dtypes)
    wrong = {c: (t, have.get(c)) for c, t in types.items() if have.get(c) != t}
    if wrong:
        raise ValueError(f"columns differ (wanted, found): {wrong}")
    return df


def to_array(df: DataFrame, columns: Sequence[str], name: str = "feats") -> DataFrame:
    others = [c for c in df.columns if c not in set(columns)]
    return df.select(*others, F.array(*(F.col(c).cast("double") for c in columns)).alias(name))


def to_wide(df: DataFrame, width: int, name: str = "feats", prefix: str = "f") -> DataFrame:
    return df.select(*(c for c in df.columns if c != name), *(F.col(name)[i].alias(f"{prefix}{i + 1}") for i in range(width)))


def to_long(df: DataFrame, name: str = "feats", key: str = "row_id") -> DataFrame:
    return df.select(key, F.posexplode(name).alias("pos", "val"))


def from_long(df: DataFrame, name: str = "feats", key: str = "row_id") -> DataFrame:
    ordered = F.sort_array(F.collect_list(F.struct("pos", "val")))
    return df.groupBy(key).agg(ordered.alias("pairs")).select(key, F.col("pairs.val").alias(name))
