"""Sharding: a keyed Feistel permutation of global row numbers gives each row its shard and slot."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from ..session import materialise

#: Modulus of the round function: products of two residues stay within 63 bits.
_PRIME = (1 << 31) - 1
ROUNDS = 6
SEED = 20_231
#: Copies of one row that are numbered together.
BLOCK_ROWS = 4096


def round_keys(seed: int) -> list[tuple[int, int]]:
    """Two residues a round, drawn by a linear congruence from the seed."""
    out, x = [], (seed * 2 + 1) % _PRIME
    for _ in range(ROUNDS):
        pair = []
        for _ in range(2):
            x = (x * 48271 + 11) % _PRIME
            pair.append(x + 1)
        out.append((pair[0] % _PRIME, pair[1] % _PRIME))
    return out


def half_bits(n: int) -> int:
    return max(1, -(-max(n - 1, 1).bit_length() // 2))


def _scramble(right: np.ndarray, keys: tuple[int, int], mask: int) -> np.ndarray:
    t = (right + keys[0]) % _PRIME
    return ((t * t) % _PRIME * keys[1] + keys[0]) % _PRIME & mask


def permute(rows: np.ndarray, n: int, seed: int, inverse: bool = False) -> np.ndarray:
    """The image of each row number under the keyed permutation of 0..n-1.

    The network permutes the next power of four; numbers that land at n or above walk on along their
    cycle until they are back below n, so the result is a permutation of exactly 0..n-1.
    """
    if n > 1 << 60:
        raise ValueError("more than 2**60 rows")
    bits = half_bits(n)
    mask, keys = (1 << bits) - 1, round_keys(seed)

    def once(x: np.ndarray) -> np.ndarray:
        left, right = x >> bits, x & mask
        if inverse:
            for k in reversed(keys):
                left, right = right ^ _scramble(left, k, mask), left
        else:
            for k in keys:
                left, right = right, left ^ _scramble(right, k, mask)
        return (left << bits) | right

    out = once(np.asarray(rows, dtype=np.int64))
    while (over := out >= n).any():
        out[over] = once(out[over])
    return out


def place(row: int, n: int, shards: int, seed: int) -> tuple[int, int]:
    """Shard and slot of a global row number, computed without the table."""
    p = int(permute(np.array([row]), n, seed)[0])
    return p % shards, p // shards


def row_at(shard: int, slot: int, n: int, shards: int, seed: int) -> int:
    """The global row number that lies in a shard's slot."""
    return int(permute(np.array([slot * shards + shard]), n, seed, inverse=True)[0])


def number_rows(rows: DataFrame, id_col: str, *ties: str) -> tuple[DataFrame, int]:
    """Adds `row_number` 0..n-1 in ascending order of id (null first), then of ties; returns it and n.

    Equal rows are counted first, so what is sorted by ranges holds each (id, ties) once and an id with
    very many texts is cut between tasks like many ids. Each range is numbered in its own task and moved
    by the count of the ranges before it. A row that repeats very often is numbered block by block.
    """
    order = [F.col(c).asc_nulls_first() for c in (id_col, *ties)]
    counted = rows.groupBy(id_col, *ties).agg(F.count(F.lit(1)).alias("__n"))
    placed = counted.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("__ord", F.monotonically_increasing_id()).withColumn("__part", F.shiftright("__ord", 33).cast("int"))
    placed = materialise(rows.sparkSession, placed, "ranges")
    sizes = placed.groupBy("__part").agg(F.sum("__n").alias("n"), F.max("__n").alias("most")).collect()  # a row a range
    total, most, before = 0, 0, [0] * (max((r["__part"] for r in sizes), default=0) + 1)
    for r in sorted(sizes, key=lambda r: r["__part"]):
        before[r["__part"]] = total
        total, most = total + r["n"], max(most, r["most"])
    start = F.from_json(F.lit(str(before)), T.ArrayType(T.LongType()))
    above = Window.partitionBy("__part").orderBy("__ord").rowsBetween(Window.unboundedPreceding, -1)
    first = placed.withColumn("__first", F.coalesce(F.sum("__n").over(above), F.lit(0)) + F.element_at(start, F.col("__part") + 1)).withColumn("__end", F.col("__first") + F.col("__n"))
    blocks = first.withColumn("__from", F.explode(F.sequence(F.col("__first"), F.col("__end") - 1, F.lit(BLOCK_ROWS).cast("long"))))
    if most > BLOCK_ROWS:
        blocks = blocks.repartition("__from")
    upto = F.least(F.col("__from") + BLOCK_ROWS, F.col("__end")) - 1
    return blocks.select(id_col, *ties, F.explode(F.sequence("__from", upto)).alias("row_number")), total


def feistel_shards(docs: DataFrame, shards: int = 8, seed: int = SEED, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """A reproducible shuffle of the documents over shards.

    Law `rows`: shard = image mod shards, slot = image div shards, so shard sizes differ by one row at
    most and slots run gapless from 0. Any row's place follows from its row number, the row count and
    the seed alone (`place`), and back (`row_at`).
    Null text: no bytes (size 1), crc 0. Null ids come first. Equal rows get places of their own. Other
    columns are not looked at; an empty table gives no row.
    Returns doc_id, size, text_crc32, law, shard, slot, grown_shard (null under this law), row_number.
    """
    spark_text = F.coalesce(F.col(text_col), F.lit(""))
    light = docs.select(F.col(id_col).alias("doc_id"), (F.octet_length(spark_text).cast("long") + 1).alias("size"), F.crc32(spark_text).alias("text_crc32"))
    numbered, n = number_rows(light, "doc_id", "size", "text_crc32")
    if not n:
        image = F.lit(0).cast("long")
    else:
        @F.pandas_udf(T.LongType())
        def permuted(rows: pd.Series) -> pd.Series:
            return pd.Series(permute(rows.to_numpy(), n, seed))

        image = permuted("row_number")
    placed = numbered.withColumn("__image", image)
    return placed.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), F.pmod("__image", F.lit(shards)).cast("int").alias("shard"), F.expr(f"__image div {int(shards)}").alias("slot"), F.lit(None).cast("int").alias("grown_shard"), "row_number")
