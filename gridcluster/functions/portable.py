"""Random numbers that depend on seed, id and position only, the same bits in Spark and in SQL elsewhere."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

_U = 4294967296.0


def uniform(seed: int, key: Column, position: int | str) -> Column:
    """In [0, 1), from the first 32 bits of the md5 of seed~key~position."""
    text = F.concat_ws("~", F.lit(str(seed)), key.cast("string"), F.lit(str(position)))
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("double") / F.lit(_U)


def uniform_sql(seed: int, key: str, position: int | str) -> str:
    """The same value in DuckDB SQL."""
    return f"(concat('0x', substr(md5(concat_ws('~', '{seed}', CAST({key} AS VARCHAR), '{position}')), 1, 8))::BIGINT / {_U})"


def gaussian(seed: int, key: Column, position: int | str) -> Column:
    """Standard normal from two uniforms."""
    u, v = uniform(seed, key, f"{position}a"), uniform(seed, key, f"{position}b")
    return F.sqrt(F.lit(-2.0) * F.ln(u + F.lit(0.5 / _U))) * F.cos(F.lit(2 * math.pi) * v)


def gaussian_sql(seed: int, key: str, position: int | str) -> str:
    u, v = uniform_sql(seed, key, f"{position}a"), uniform_sql(seed, key, f"{position}b")
    return f"(sqrt(-2.0 * ln({u} + {0.5 / _U!r})) * cos({2 * math.pi!r} * {v}))"


def hashed_uniform(keys: np.ndarray, *salt: int) -> np.ndarray:
    """In (0, 1) for 64-bit keys, in batches on the executors."""
    x = keys.astype(np.int64).view(np.uint64).copy()
    for s in salt:
        x = x + np.uint64((s * 0x9E3779B97F4A7C15 + 0x632BE59BD9B4E019) & (2**64 - 1))
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        x = x ^ (x >> np.uint64(31))
    return ((x >> np.uint64(11)).astype(np.float64) + 0.5) / float(1 << 53)
