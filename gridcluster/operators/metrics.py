"""Agreement of labels with truth: contingency, adjusted Rand, normalised mutual information, accuracy."""

from __future__ import annotations

import itertools
import math

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def contingency(df: DataFrame, truth: str = "truth", pred: str = "pred") -> DataFrame:
    return df.groupBy(F.col(truth).alias("truth"), F.col(pred).alias("pred")).agg(F.count(F.lit(1)).alias("cnt"))


def margins(df: DataFrame, truth: str = "truth", pred: str = "pred") -> DataFrame:
    """The contingency with its margins and total; null stands for all."""
    return df.cube(F.col(truth).alias("truth"), F.col(pred).alias("pred")).agg(F.count(F.lit(1)).alias("cnt"))


def table_of(counts: DataFrame) -> np.ndarray:
    """The classes x clusters table on the driver; its size doesn't depend on the rows."""
    rows = counts.collect()
    truth, pred = sorted({r["truth"] for r in rows}, key=repr), sorted({r["pred"] for r in rows}, key=repr)
    out = np.zeros((len(truth), len(pred)), dtype=np.float64)
    for r in rows:
        out[truth.index(r["truth"]), pred.index(r["pred"])] = r["cnt"]
    return out


def ari(u: np.ndarray) -> float:
    """Adjusted Rand index; 1 when both sides are trivial in the same way."""
    pairs = lambda x: (x * (x - 1) / 2).sum()
    index, a, b, n = pairs(u), pairs(u.sum(axis=1)), pairs(u.sum(axis=0)), u.sum()
    if n < 2:
        return 1.0
    expected = a * b / (n * (n - 1) / 2)
    top = (a + b) / 2
    return 1.0 if top == expected else float((index - expected) / (top - expected))


def nmi(u: np.ndarray) -> float:
    """Mutual information over the geometric mean of the entropies; 0 if one side is constant, 1 if both are."""
    n = u.sum()
    a, b = u.sum(axis=1), u.sum(axis=0)
    entropy = lambda p: float(-(p[p > 0] / n * np.log(p[p > 0] / n)).sum())
    ha, hb = entropy(a), entropy(b)
    if ha <= 0 or hb <= 0:
        return 1.0 if ha <= 0 and hb <= 0 else 0.0
    mine = u > 0
    mutual = (u[mine] / n * np.log(u[mine] * n / np.outer(a, b)[mine])).sum()
    return float(mutual / math.sqrt(ha * hb))


def assignment(cost: np.ndarray) -> np.ndarray:
    """Column of each row in a least-cost one-to-one assignment of a square table, by shortest augmenting paths."""
    n = len(cost)
    row_price, col_price = np.zeros(n + 1), np.zeros(n + 1)
    owner = np.zeros(n + 1, dtype=np.int64)  # row (from 1) of each column; 0: free
    for row in range(1, n + 1):
        owner[0], at = row, 0
        least, came = np.full(n + 1, np.inf), np.zeros(n + 1, dtype=np.int64)
        done = np.zeros(n + 1, dtype=bool)
        while True:
            done[at] = True
            open_cols = np.nonzero(~done[1:])[0] + 1
            slack = cost[owner[at] - 1, open_cols - 1] - row_price[owner[at]] - col_price[open_cols]
            better = slack < least[open_cols]
            least[open_cols[better]], came[open_cols[better]] = slack[better], at
            nxt = open_cols[int(least[open_cols].argmin())]
            delta = least[nxt]
            row_price[owner[done]] += delta
            col_price[done] -= delta
            least[~done] -= delta
            at = nxt
            if not owner[at]:
                break
        while at:
            owner[at] = owner[came[at]]
            at = came[at]
    out = np.zeros(n, dtype=np.int64)
    out[owner[1:] - 1] = np.arange(n)
    return out


def acc(u: np.ndarray) -> float:
    """Share of rows that agree under the best one-to-one naming of clusters; unequal numbers are padded with zeros."""
    n = max(u.shape)
    square = np.zeros((n, n))
    square[: u.shape[0], : u.shape[1]] = u
    return float(square[np.arange(n), assignment(-square)].sum() / u.sum()) if u.sum() else 1.0


def acc_by_permutations(u: np.ndarray) -> float:
    n = max(u.shape)
    square = np.zeros((n, n))
    square[: u.shape[0], : u.shape[1]] = u
    return max(square[np.arange(n), list(p)].sum() for p in itertools.permutations(range(n))) / u.sum()


def scores(df: DataFrame, truth: str = "truth", pred: str = "pred") -> dict[str, float]:
    u = table_of(contingency(df, truth, pred))
    return {"ari": ari(u), "nmi": nmi(u), "acc": acc(u)}


def agreement(a: DataFrame, b: DataFrame, key: str = "row_id", label: str = "pred") -> dict[str, float]:
    """The same measures between two labellings of the same rows."""
    return scores(a.select(key, F.col(label).alias("truth")).join(b.select(key, F.col(label).alias("pred")), key))


def ari_rows(df: DataFrame, truth: str = "truth", pred: str = "pred") -> DataFrame:
    """The adjusted Rand index as a one-row table, by aggregation alone; 1 where `ari` gives 1 for trivial sides."""
    u = contingency(df, truth, pred)
    pairs = lambda c: F.coalesce(F.sum(F.col(c).cast("double") * (F.col(c) - 1) / 2), F.lit(0.0))
    one = u.agg(pairs("cnt").alias("i"), F.coalesce(F.sum("cnt"), F.lit(0)).cast("double").alias("n"))
    a = u.groupBy("truth").agg(F.sum("cnt").alias("c")).agg(pairs("c").alias("a"))
    b = u.groupBy("pred").agg(F.sum("cnt").alias("c")).agg(pairs("c").alias("b"))
    expected = F.try_divide(F.col("a") * F.col("b"), F.col("n") * (F.col("n") - 1) / 2)
    value = F.try_divide(F.col("i") - expected, (F.col("a") + F.col("b")) / 2 - expected)
    return one.crossJoin(a).crossJoin(b).select(F.coalesce(value, F.lit(1.0)).alias("ari"))  # three one-row tables


def nmi_rows(df: DataFrame, truth: str = "truth", pred: str = "pred") -> DataFrame:
    """Normalised mutual information as a one-row table; 0 if one side is constant, 1 if both are."""
    u = contingency(df, truth, pred)
    total = u.agg(F.sum("cnt").cast("double").alias("n"))
    a = u.groupBy("truth").agg(F.sum("cnt").cast("double").alias("a"))
    b = u.groupBy("pred").agg(F.sum("cnt").cast("double").alias("b"))
    entropy = lambda d, c: d.crossJoin(total).agg(F.coalesce(-F.sum(F.col(c) / F.col("n") * F.ln(F.col(c) / F.col("n"))), F.lit(0.0)).alias(f"h{c}"))
    mutual = u.join(a, u["truth"].eqNullSafe(a["truth"])).join(b, u["pred"].eqNullSafe(b["pred"])).crossJoin(total).agg(F.coalesce(F.sum(F.col("cnt") / F.col("n") * F.ln(F.col("cnt") * F.col("n") / (F.col("a") * F.col("b")))), F.lit(0.0)).alias("mi"))
    trivial = F.when((F.col("ha") <= 0) & (F.col("hb") <= 0), 1.0).when((F.col("ha") <= 0) | (F.col("hb") <= 0), 0.0)
    return mutual.crossJoin(entropy(a, "a")).crossJoin(entropy(b, "b")).select(trivial.otherwise(F.try_divide("mi", F.sqrt(F.col("ha") * F.col("hb")))).alias("nmi"))


def dataset_card(df: DataFrame, features: int, truth: str = "truth") -> DataFrame:
    """Rows, features, classes, least and greatest class."""
    sizes = df.groupBy(truth).agg(F.count(F.lit(1)).alias("c"))
    return sizes.agg(F.sum("c").alias("n"), F.lit(features).alias("m"), F.count(F.lit(1)).alias("k"), F.min("c").alias("min_class"), F.max("c").alias("max_class"))
