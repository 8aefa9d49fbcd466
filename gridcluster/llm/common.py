"""Pieces shared by the operators: bounded Arrow slices, word splitting, hashing."""

from __future__ import annotations

import ctypes
import sys
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes of text that are worked on at once; a longer single text is worked on alone.
SLICE_BYTES = 2 << 20


def documents(spark: SparkSession, sf_dir: str, *columns: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet").select(*(columns or ("doc_id", "text")))


def slices(batches: Iterator[pa.RecordBatch], column: str = "text", limit: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Cuts batches so that each slice holds about `limit` bytes of text at most, or one row.

    A worker lives through many tasks: what the last slice used goes back to the system at the end.
    """
    try:
        yield from _cut(batches, column, limit)
    finally:
        give_back()


def give_back() -> None:
    """Free memory of this worker to the system."""
    pa.default_memory_pool().release_unused()
    if _TRIM:
        _TRIM(0)


_TRIM = getattr(ctypes.CDLL(None), "malloc_trim", None) if sys.platform.startswith("linux") else None


def _cut(batches: Iterator[pa.RecordBatch], column: str, limit: int) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        if not batch.num_rows:
            continue
        size = np.cumsum(pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False).astype(np.int64))
        at = 0
        while at < batch.num_rows:
            base = size[at - 1] if at else 0
            to = max(at + 1, int(np.searchsorted(size, base + limit, side="right")))
            yield batch.slice(at, to - at)
            at = to


def texts(batch: pa.RecordBatch, column: str = "text") -> pa.Array:
    return pc.fill_null(batch.column(column), "")


def flat_split(lists: pa.Array, drop_empty: bool = False) -> tuple[pa.Array, np.ndarray]:
    """The values of a list array, and where each row begins and ends among them."""
    flat, offsets = lists.flatten(), lists.offsets.to_numpy().astype(np.int64)
    offsets = offsets - offsets[0]
    if drop_empty:
        full = pc.greater(pc.binary_length(flat), 0).to_numpy(zero_copy_only=False)
        if not full.all():
            flat, offsets = flat.filter(pa.array(full)), np.concatenate([[0], np.cumsum(full)])[offsets]
    return flat, offsets


def split_words(text: pa.Array, lower: bool) -> tuple[pa.Array, np.ndarray]:
    """Words [^\\x20\\x09-\\x0D]+ of each text; lower: A-Z become a-z, other letters stay."""
    return flat_split(pc.ascii_split_whitespace(pc.ascii_lower(text) if lower else text), drop_empty=True)


def row_of(offsets: np.ndarray) -> np.ndarray:
    """For each flat value the number of its row."""
    return np.repeat(np.arange(len(offsets) - 1), np.diff(offsets))


def sums(values: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Sums of the values of each row; an empty row has 0."""
    total = np.concatenate([np.zeros(1, dtype=values.dtype if values.dtype.kind == "f" else np.int64), np.cumsum(values)])
    return total[offsets[1:]] - total[offsets[:-1]]


def coded(flat: pa.Array) -> tuple[np.ndarray, pa.Array]:
    """A number for each value, and the distinct values."""
    d = flat.dictionary_encode()
    return d.indices.to_numpy(zero_copy_only=False).astype(np.int64), d.dictionary


def string_hash(values: pa.Array) -> np.ndarray:
    """A 64-bit hash of each string, the same in all tasks."""
    return pd.util.hash_array(values.to_numpy(zero_copy_only=False).astype(object), categorize=False)


def mix64(x: np.ndarray) -> np.ndarray:
    """Bijective finisher over unsigned 64-bit integers."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def document_key(id_col: str, text_col: str) -> list[Column]:
    """What names a document when ids may be null or repeat with other texts."""
    return [F.coalesce(F.col(id_col), F.lit(-(1 << 63))).alias("__id"), F.xxhash64(F.coalesce(F.col(text_col), F.lit(""))).alias("__text_hash")]


def packed(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """__doc (all columns of docs in one, so that no name can clash), __id, __text_hash."""
    return docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("__doc"), *document_key(id_col, text_col))


def free_name(name: str, taken: list[str]) -> str:
    """name, with as many underscores behind it as no taken name (case aside) needs."""
    low = {t.lower() for t in taken}
    while name.lower() in low:
        name += "_"
    return name


def crc_bucket(id_col: str, buckets: int) -> Column:
    """crc32 of the id as text, modulo buckets; a null id counts as empty text."""
    return F.pmod(F.crc32(F.coalesce(F.col(id_col).cast("string"), F.lit(""))), F.lit(buckets)).cast("int")
