"""Benchmark decontamination: spaced-seed hashes find hits, and the overlap around each hit is verified."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import coded, mix64, slices, split_words, texts

#: Masks over token positions; 0 is ignored. No overlap of 12 agreeing tokens that are four fifths of its stretch
#: escapes all three: without five agreeing tokens in a row, and without a run of two beside one of three
#: over one differing token, n differing tokens leave fewer than 4 n agreeing ones from n = 3 on (and fewer than 12 below).
MASKS = ("11111", "110111", "111011")
#: Items of fewer tokens say nothing; those shorter than a mask are looked up by all their tokens.
MIN_ITEM = 3
#: (position, posting) pairs of hits that are worked on at once.
PAIRS = 500_000
#: An overlap counts when at least so many tokens on one diagonal agree, and so large a share of the aligned stretch.
MIN_MATCHES, MIN_SHARE = 12, 0.8
#: Bytes of benchmark text that go to the executors at once; a larger benchmark is taken in blocks of this size.
BLOCK_BYTES = 16 << 20


def tokens(text: pa.Array) -> tuple[pa.Array, np.ndarray]:
    """Lower-case words (split at ASCII white space), which keeps offsets simple and case aside."""
    return split_words(pc.utf8_lower(text), lower=False)


def mask_offsets(mask: str) -> np.ndarray:
    return np.array([i for i, c in enumerate(mask) if c == "1"], dtype=np.int64)


def seed_hashes(codes: np.ndarray, mask: str, number: int) -> np.ndarray:
    """One hash for each start position of a mask over hashed tokens."""
    at, span = mask_offsets(mask), len(mask)
    n = len(codes) - span + 1
    if n <= 0:
        return np.zeros(0, dtype=np.uint64)
    h = np.full(n, number + 1, dtype=np.uint64)
    for o in at:
        h = (h ^ codes[o : o + n]) * np.uint64(0x9E3779B97F4A7C15)
        h ^= h >> np.uint64(29)
    return h


class BenchmarkIndex:
    """Token numbers, texts and seed hashes of a block of items."""

    def __init__(self, items: list[tuple[int, str]], masks: tuple[str, ...] = MASKS, min_matches: int = MIN_MATCHES, min_share: float = MIN_SHARE):
        self.min_matches, self.min_share = min_matches, min_share
        text = pa.array([t or "" for _, t in items], pa.string())
        flat, self.offsets = tokens(text)
        codes, self.vocabulary = coded(flat)
        self.codes = codes
        self.item_ids = np.array([i for i, _ in items], dtype=np.int64)
        self.word_hash = mix64(np.arange(1, len(self.vocabulary) + 1, dtype=np.uint64))
        size = np.diff(self.offsets)
        item = np.repeat(np.arange(len(items)), size)
        self.masks = (*masks, *("1" * n for n in range(MIN_ITEM, min(map(len, masks)))))
        self.seeds: list[tuple[np.ndarray, np.ndarray]] = []
        hashed = self.word_hash[codes] if len(codes) else np.zeros(0, dtype=np.uint64)
        for m, mask in enumerate(self.masks):
            h = seed_hashes(hashed, mask, m)
            span = len(mask)
            inside = item[: len(h)] == item[span - 1 : span - 1 + len(h)]
            if m >= len(masks):
                inside &= size[item[: len(h)]] == span
            h, at = h[inside], np.nonzero(inside)[0]
            order = np.argsort(h, kind="stable")
            self.seeds.append((h[order], at[order]))
        self.item_of = item

    def hits(self, text: pa.Array) -> list[tuple[int, int, int, int, int]]:
        """Verified overlaps: row, item number, first token, tokens, agreeing tokens."""
        flat, offsets = tokens(text)
        if not len(flat) or not len(self.vocabulary):
            return []
        local, distinct = coded(flat)
        known = pc.fill_null(pc.index_in(distinct, value_set=self.vocabulary), -1).to_numpy(zero_copy_only=False).astype(np.int64)
        codes = known[local]
        row = np.repeat(np.arange(len(offsets) - 1), np.diff(offsets))
        hashed = np.where(codes >= 0, self.word_hash[codes], np.uint64(0))
        # only positions whose masked tokens are all of the benchmark can hit
        in_bench = codes >= 0
        found: set[tuple[int, int, int, int, int]] = set()
        for m, mask in enumerate(self.masks):
            keys, at = self.seeds[m]
            n = len(codes) - len(mask) + 1
            if n <= 0 or not len(keys):
                continue
            ok = row[:n] == row[len(mask) - 1 : len(mask) - 1 + n]
            for o in mask_offsets(mask):
                ok &= in_bench[o : o + n]
            where = np.nonzero(ok)[0]
            h = np.full(len(where), m + 1, dtype=np.uint64)
            for o in mask_offsets(mask):
                h = (h ^ hashed[where + o]) * np.uint64(0x9E3779B97F4A7C15)
                h ^= h >> np.uint64(29)
            lo, hi = np.searchsorted(keys, h, "left"), np.searchsorted(keys, h, "right")
            some = np.nonzero(hi > lo)[0]
            where, lo, count = where[some], lo[some], (hi - lo)[some]
            for a, z, skip, take in _blocks(count, PAIRS):
                size = count[a:z].copy()
                size[0] -= skip
                if take is not None:
                    size[-1] = take
                begin = lo[a:z].copy()
                begin[0] += skip
                q = at[np.repeat(begin - (np.cumsum(size) - size), size) + np.arange(int(size.sum()))]
                p = np.repeat(where[a:z], size)
                diagonals = pd.DataFrame({"row": row[p], "item": self.item_of[q], "shift": p - q}).drop_duplicates()
                found.update(self._verified(codes, offsets, *(diagonals[c].to_numpy() for c in ("row", "item", "shift"))))
        return sorted(found)

    def _verified(self, codes: np.ndarray, offsets: np.ndarray, row: np.ndarray, item: np.ndarray, shift: np.ndarray) -> list[tuple[int, int, int, int, int]]:
        """The overlaps of those diagonals that agree often enough; first all agreements are counted, then stretches sought."""
        a, z = self.offsets[item], self.offsets[item + 1]
        lo, hi = np.maximum(a, offsets[row] - shift), np.minimum(z, offsets[row + 1] - shift)
        need = np.minimum(self.min_matches, z - a)
        out = []
        for x, y, _, _ in _blocks(hi - lo, 8 * PAIRS, whole=True):
            size = (hi - lo)[x:y]
            begin = np.cumsum(size) - size
            q = np.repeat(lo[x:y] - begin, size) + np.arange(int(size.sum()))
            same = self.codes[q] == codes[q + np.repeat(shift[x:y], size)]
            total = np.concatenate([[0], np.cumsum(same)])
            for i in np.nonzero(total[begin + size] - total[begin] >= need[x:y])[0]:
                k = x + int(i)
                first, last, good = best_stretch(same[begin[i] : begin[i] + size[i]], self.min_share)
                if good >= need[k]:
                    out.append((int(row[k]), int(item[k]), int(lo[k] + first + shift[k] - offsets[row[k]]), last - first, good))
        return out


def _blocks(count: np.ndarray, limit: int, whole: bool = False) -> Iterator[tuple[int, int, int, int | None]]:
    """Cuts rows with so many values each into blocks of `limit` values at most: first row, end row, values of the
    first row that went before, values of the last row to take (None: all). whole: rows are not cut."""
    ends = np.cumsum(count)
    total, at = int(ends[-1]) if len(ends) else 0, 0
    if whole:
        row = 0
        while row < len(count):
            base = int(ends[row - 1]) if row else 0
            to = max(row + 1, int(np.searchsorted(ends, base + limit, side="right")))
            yield row, to, 0, None
            row = to
        return
    while at < total:
        to = min(total, at + limit)
        first, last = int(np.searchsorted(ends, at, side="right")), int(np.searchsorted(ends, to, side="left"))
        skip = at - (int(ends[first - 1]) if first else 0)
        cut = None if to == ends[last] else to - max(at, int(ends[last - 1]) if last else 0)
        yield first, last + 1, skip, cut
        at = to


def best_stretch(same: np.ndarray, share: float) -> tuple[int, int, int]:
    """The longest stretch of a diagonal in which at least `share` of the tokens agree, its ends agreeing: begin, end, agreements."""
    percent = round(100 * share)
    total = np.concatenate([[0], np.cumsum(100 * same.astype(np.int64) - percent)])
    # from each begin the last end with no smaller sum: suffix maxima fall, so one search finds it
    best = np.maximum.accumulate(total[::-1])[::-1]
    ends = np.searchsorted(-best, -total, side="right") - 1
    begin = int(np.argmax(ends - np.arange(len(total))))
    inside = np.nonzero(same[begin : ends[begin]])[0]
    if not len(inside):
        return 0, 0, 0
    return begin + int(inside[0]), begin + int(inside[-1]) + 1, len(inside)


def benchmark_blocks(benchmark: DataFrame, item_col: str, text_col: str, block_bytes: int = BLOCK_BYTES) -> Iterator[list[tuple[int, str]]]:
    """The benchmark in blocks of bounded size, fetched one after another."""
    rows = benchmark.select(F.col(item_col).cast("long").alias("item_id"), F.col(text_col).alias("text")).where(F.col("item_id").isNotNull() & (F.length("text") > 0))
    size = rows.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    blocks = max(1, -(-size // block_bytes) * 2 if size > block_bytes else 1)
    for i in range(blocks):
        part = rows if blocks == 1 else rows.where(F.pmod(F.xxhash64("item_id"), F.lit(blocks)) == i)
        yield [(r["item_id"], r["text"]) for r in part.orderBy("item_id", "text").collect()]


_WORKER: dict[str, BenchmarkIndex] = {}


def index_of(name: str, items: list[tuple[int, str]], *options) -> BenchmarkIndex:
    """The index of a block, made once a worker; a worker holds one block's at a time."""
    if name not in _WORKER:
        _WORKER.clear()
        _WORKER[name] = BenchmarkIndex(items, *options)
    return _WORKER[name]


def contaminated_spans(spark: SparkSession, docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", masks: tuple[str, ...] = MASKS, min_matches: int = MIN_MATCHES, min_share: float = MIN_SHARE, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """Overlaps of documents with benchmark items: doc_id, item_id, first_token, n_tokens, n_same.

    A hit of a mask fixes a diagonal; along it the longest stretch with at least `min_share` agreeing
    tokens is taken. It counts with `min_matches` agreeing tokens, or all of a shorter item (of MIN_ITEM
    tokens or more). With the given masks and limits no such overlap is missed.
    Null or empty texts and items have no overlap; null item ids are left out; repeated rows give
    their overlaps once each; empty tables give no row; other columns are not looked at. The benchmark's seeds go to the executors in blocks of proven size,
    one pass over the documents for each block; documents are never shuffled.
    """
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    schema = "doc_id long, item_id long, first_token long, n_tokens long, n_same long"
    out = None
    for items in benchmark_blocks(benchmark, item_col, item_text_col, block_bytes):
        shared, name = spark.sparkContext.broadcast(items), uuid.uuid4().hex

        def run(batches: Iterator[pa.RecordBatch], shared=shared, name=name) -> Iterator[pa.RecordBatch]:
            index = index_of(name, shared.value, masks, min_matches, min_share)
            for piece in slices(batches, "text"):
                found = np.array(index.hits(texts(piece)), dtype=np.int64).reshape(-1, 5)
                if len(found):
                    yield pa.RecordBatch.from_arrays([piece.column("doc_id").take(pa.array(found[:, 0])), pa.array(index.item_ids[found[:, 1]]), *(pa.array(found[:, i]) for i in (2, 3, 4))], names=["doc_id", "item_id", "first_token", "n_tokens", "n_same"])

        one = rows.mapInArrow(run, schema)
        out = one if out is None else out.unionAll(one)
    return out


def drop_contaminated(spark: SparkSession, docs: DataFrame, benchmark: DataFrame, text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", masks: tuple[str, ...] = MASKS, min_matches: int = MIN_MATCHES, min_share: float = MIN_SHARE, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """The documents without an overlap, with all their columns, whatever these are named; a narrow pass for each block of the benchmark.

    Null and empty texts stay; repeated rows go or stay alike; an empty benchmark drops nothing.
    """
    out = docs
    for items in benchmark_blocks(benchmark, item_col, item_text_col, block_bytes):
        shared, name = spark.sparkContext.broadcast(items), uuid.uuid4().hex

        def run(batches: Iterator[pa.RecordBatch], shared=shared, name=name) -> Iterator[pa.RecordBatch]:
            index = index_of(name, shared.value, masks, min_matches, min_share)
            for piece in slices(batches, text_col):
                clean = np.ones(piece.num_rows, dtype=bool)
                clean[[h[0] for h in index.hits(texts(piece, text_col))]] = False
                yield piece.filter(pa.array(clean))

        out = out.mapInArrow(run, docs.schema)
    return out
