"""Numeric features from the given kinds of columns: text, HTML, JSON events, dates, categories."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

LETTERS = "aeinrstuoh"


def letter_shares(text: Column, letters: str = LETTERS) -> list[Column]:
    """Share of each letter among a text's characters, case aside; 0 for empty text."""
    low, n = F.lower(text), F.greatest(F.length(text), F.lit(1))
    return [(F.length(text) - F.length(F.replace(low, F.lit(ch), F.lit("")))) / n for ch in letters]


def character_shares(text: Column) -> list[Column]:
    """Shares of letters, digits, white space, the rest, and ASCII capitals."""
    n = F.greatest(F.length(text), F.lit(1))
    count = lambda pattern: F.length(text) - F.length(F.regexp_replace(text, pattern, ""))
    # a run of characters is one match
    letters, digits, blanks, upper = count(r"\p{L}+"), count("[0-9]+"), count(r"[ \t\n\r]+"), count("[A-Z]+")
    return [letters / n, digits / n, blanks / n, (F.length(text) - letters - digits - blanks) / n, upper / n]


def html_text(html: Column) -> Column:
    """Visible text, roughly: without scripts, styles, comments and tags."""
    bare = F.regexp_replace(html, r"(?is)<(script|style)\b.*?</\1>|<!--.*?-->", " ")
    return F.trim(F.regexp_replace(F.regexp_replace(bare, r"(?s)<[^>]*>", " "), r"\s+", " "))


def events_profile(events: DataFrame) -> DataFrame:
    """event_id and value, hour, weekday and the JSON property k."""
    k = F.from_json("props", "k INT")["k"]
    return events.select(F.col("event_id").alias("row_id"), F.array(F.col("value"), F.hour("ts").cast("double"), F.dayofweek("ts").cast("double"), F.coalesce(k, F.lit(0)).cast("double")).alias("feats"), "event_type", "ts", "user_id")


def date_parts(df: DataFrame, column: str, origin: str = "1992-01-01") -> DataFrame:
    return df.withColumns({f"{column}_year": F.year(column), f"{column}_month": F.month(column), f"{column}_days": F.datediff(column, F.lit(origin))})


def clean(df: DataFrame, columns: Sequence[str], policy: str = "drop") -> DataFrame:
    """Nulls, NaN and infinities: rows dropped, or values replaced by zero or by the column's mean."""
    bad = lambda c: F.col(c).isNull() | F.isnan(c) | (F.abs(c) == float("inf"))
    if policy == "drop":
        for c in columns:
            df = df.where(~bad(c))
        return df
    if policy == "zero":
        return df.withColumns({c: F.when(bad(c), F.lit(0.0)).otherwise(F.col(c)) for c in columns})
    if policy == "mean":
        means = df.agg(*(F.avg(F.when(~bad(c), F.col(c))).alias(c) for c in columns)).first()
        return df.withColumns({c: F.when(bad(c), F.lit(means[c])).otherwise(F.col(c)) for c in columns})
    raise ValueError(policy)


def standardise(df: DataFrame, columns: Sequence[str], by: str | None = None) -> DataFrame:
    """Columns less their mean over their deviation (population), in all or within groups; a constant becomes 0."""
    stats = (df.groupBy(by) if by else df.groupBy()).agg(*(f(c).alias(f"__{n}_{c}") for c in columns for n, f in (("m", F.avg), ("s", F.stddev_pop))))
    joined = df.join(F.broadcast(stats), by) if by else df.crossJoin(F.broadcast(stats))  # a row a group
    scaled = {c: F.when(F.col(f"__s_{c}") > 0, (F.col(c) - F.col(f"__m_{c}")) / F.col(f"__s_{c}")).otherwise(F.lit(0.0)) for c in columns}
    return joined.withColumns(scaled).select(*df.columns)


def index_category(df: DataFrame, column: str) -> DataFrame:
    """Adds the rank of the category by name, from 1."""
    ranks = df.select(column).distinct().withColumn(f"{column}_index", F.dense_rank().over(Window.orderBy(column)))
    return df.join(ranks, column, "left")


def one_hot(df: DataFrame, column: str, values: Sequence[str]) -> DataFrame:
    return df.withColumn(f"{column}_hot", F.array(*(F.when(F.col(column) == v, 1.0).otherwise(0.0) for v in values)))
