"""Substring dedup by hashing units: whole lines or paragraphs, and passages inside lines.

A unit's words are put in a normal form and hashed; digests are grouped over all documents; the earliest
ranked occurrence stays, all later ones are cut out, and what remains is given as spans of the original.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..session import materialise
from .common import coded, document_key, free_name, packed, slices, split_words, texts

#: A passage has so many words at least; so does a whole line that is hashed beside passages.
MIN_WORDS, LINE_WORDS = 8, 4
_MULTIPLIER = 0xD6E8FEB86659FD93
_KEYS = ("0123456789123456", "fedcba9876543210")
KINDS = ("passages", "lines", "paragraphs")


class Units:
    """The pieces of each text of a slice, and the digests of the units that begin at them.

    A piece begins at a text's first word, behind a line break, behind a word that ends in `.`, `!`
    or `?`, and at a word with an ASCII or Latin-1 capital. A unit is a run of pieces:
    lines, paragraphs: all pieces of a line, or of what stands between blank lines, with `min_words` words or more.
    passages: a piece and as many following ones as make `min_words` words (near the end of a text there
    may be none), and beside them whole lines of LINE_WORDS words or more. So a passage is found in the middle
    of a line, and a repeated line whatever follows it.
    Normal form: lower case, words parted by one blank; a digest is two 64-bit hashes of it.
    """

    def __init__(self, text: pa.Array, min_words: int, kind: str = "passages"):
        n = len(text)
        base = np.frombuffer(text.buffers()[1], dtype=np.int32)[text.offset : text.offset + n + 1].astype(np.int64)
        self.data = np.frombuffer(text.buffers()[2] or b"", dtype=np.uint8)[base[0] : base[-1]]
        self.bounds = base - base[0]
        data = self.data
        white = np.zeros(256, dtype=bool)
        white[[0x20, *range(0x09, 0x0E)]] = True
        blank = white[data]
        edge = np.zeros(len(data) + 1, dtype=bool)
        edge[self.bounds] = True
        solid = ~blank
        starts = np.nonzero(solid & (np.concatenate([[True], blank[:-1]]) | edge[:-1]))[0] if len(data) else np.zeros(0, dtype=np.int64)
        ends = np.nonzero(solid & (np.concatenate([blank[1:], [True]]) | edge[1:]))[0] + 1 if len(data) else np.zeros(0, dtype=np.int64)
        self.starts = starts
        flat, offsets = split_words(pc.utf8_lower(text), lower=False)
        assert len(flat) == len(starts)
        opens = np.zeros(len(starts), dtype=bool)
        opens[offsets[:-1][np.diff(offsets) > 0]] = True
        first, block = opens.copy(), opens.copy()
        if len(starts):
            newlines = np.concatenate([[0], np.cumsum(data == 0x0A)])
            between = newlines[starts[1:]] - newlines[ends[:-1]]
            block[1:] |= between > (kind == "paragraphs")
            stop = np.isin(data[ends - 1], np.frombuffer(b".!?", dtype=np.uint8))
            first[1:] |= stop[:-1] | (between > 0)
            lead, follow = data[starts], data[np.minimum(starts + 1, len(data) - 1)]
            first |= (lead >= 0x41) & (lead <= 0x5A) | (lead == 0xC3) & (follow >= 0x80) & (follow <= 0x9E)
        self.piece_start = np.nonzero(first)[0]  # by word
        row = np.repeat(np.arange(n), np.diff(offsets))
        self.piece_row = row[self.piece_start]
        pieces = len(self.piece_start)
        piece_end = np.append(self.piece_start[1:], len(starts))
        begin = np.nonzero(block[self.piece_start])[0]
        last = np.append(begin[1:], pieces) - 1 if pieces else begin
        least = LINE_WORDS if kind == "passages" else min_words
        whole = piece_end[last] - self.piece_start[begin] >= least
        begin, last = begin[whole], last[whole]
        inside = np.zeros(len(begin), dtype=np.int64)
        if kind == "passages":
            # the piece in which a passage's least number of words is reached
            need = self.piece_start + min_words
            fits = np.nonzero(need <= offsets[1:][self.piece_row])[0] if pieces else np.zeros(0, dtype=np.int64)
            to = np.searchsorted(self.piece_start, need[fits], side="left") - 1
            same = np.full(pieces, -1, dtype=np.int64)
            same[fits] = to
            other = same[begin] != last
            begin, last = np.concatenate([fits, begin[other]]), np.concatenate([to, last[other]])
            inside = np.concatenate([np.zeros(len(fits), dtype=np.int64), np.ones(int(other.sum()), dtype=np.int64)])
            order = np.lexsort((inside, begin))
            begin, last, inside = begin[order], last[order], inside[order]
        self.begin, self.last, self.sort = begin, last, inside
        a, b = self.piece_start[begin], piece_end[last]
        codes, distinct = coded(flat)
        length = (b - a).astype(np.uint64)
        self.digests = []
        powers = np.full(len(starts) + 1, _MULTIPLIER, dtype=np.uint64)
        powers[:1] = 1
        powers = np.cumprod(powers, dtype=np.uint64)
        inverse = np.full(len(starts) + 1, pow(_MULTIPLIER, -1, 1 << 64), dtype=np.uint64)
        inverse[:1] = 1
        inverse = np.cumprod(inverse, dtype=np.uint64)
        for key in _KEYS:
            hashed = pd.util.hash_array(distinct.to_numpy(zero_copy_only=False), hash_key=key, categorize=False)[codes] if len(codes) else np.zeros(0, dtype=np.uint64)
            total = np.concatenate([np.zeros(1, dtype=np.uint64), np.cumsum(hashed * powers[:-1], dtype=np.uint64)])
            self.digests.append(((total[b] - total[a]) * inverse[a] + length).view(np.int64))

    def numbers(self) -> np.ndarray:
        """A number for each unit within its text: twice its first piece's, one more for a line beside passages."""
        first = np.searchsorted(self.piece_row, np.arange(len(self.bounds) - 1))
        return (self.begin - first[self.piece_row[self.begin]]) * 2 + self.sort

    def repeats_inside(self) -> np.ndarray:
        """Units whose digest an earlier unit of the same text has."""
        frame = pd.DataFrame({"r": self.piece_row[self.begin], "a": self.digests[0], "b": self.digests[1]})
        return frame.duplicated(keep="first").to_numpy()


def unit_rows(docs: DataFrame, id_col: str, text_col: str, min_words: int, kind: str) -> DataFrame:
    """One row for each distinct unit of a document: __id, __text_hash, d1, d2, unit."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece in slices(batches, "text"):
            u = Units(texts(piece), min_words, kind)
            fresh = ~u.repeats_inside()
            row = pa.array(u.piece_row[u.begin[fresh]])
            yield pa.RecordBatch.from_arrays([piece.column("__id").take(row), piece.column("__text_hash").take(row), pa.array(u.digests[0][fresh]), pa.array(u.digests[1][fresh]), pa.array(u.numbers()[fresh].astype(np.int64))], names=["__id", "__text_hash", "d1", "d2", "unit"])

    return docs.select(*document_key(id_col, text_col), F.col(text_col).alias("text")).mapInArrow(run, "__id long, __text_hash long, d1 long, d2 long, unit long")


def repeated_units(spark: SparkSession, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_words: int = MIN_WORDS, kind: str = "passages") -> DataFrame:
    """For each document with units that an earlier document has: __id, __text_hash, __units.

    Earlier is by id, then by a hash of the text. Counting is a combined aggregation: a digest that is
    everywhere is one row a map task. The join back has one row a digest on one side; both sides come
    from written tables, and the engine's skew join splits a digest that is everywhere.
    """
    units = materialise(spark, unit_rows(docs, id_col, text_col, min_words, kind), "units")
    who = F.struct("__id", "__text_hash")
    shared = units.groupBy("d1", "d2").agg(F.min(who).alias("first"), F.max(who).alias("last")).where("first < last").select("d1", "d2", "first")
    shared = materialise(spark, shared, "shared-units")
    later = units.join(shared, ["d1", "d2"]).where(who > F.col("first"))
    return later.groupBy("__id", "__text_hash").agg(F.collect_list("unit").alias("__units"))


REPORT = "__kept array<struct<start:long,end:long>>, __n_units long, __n_removed long"


def remove_repeats(spark: SparkSession, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_words: int = MIN_WORDS, kind: str = "passages", report: bool = True) -> DataFrame:
    """The rows of docs with repeated units cut out of the text; with `report` also `__kept` spans, `__n_units` and `__n_removed` pieces.

    Rank is the document id (null first), then a hash of its text, then the place in the text; the first
    occurrence of a unit stays and all later ones go, in the same text too. What remains is unchanged: the
    new text is the original's spans `__kept` (code points, end exclusive) in a row. Texts without repeats
    keep text and null-ness; null and empty texts have no unit. Rows that agree in id and text are one
    document and are cut alike. Input columns stay, whatever their names: where one has the name of a
    report column, the report's gets underscores behind it. An empty table stays empty.
    """
    if kind not in KINDS:
        raise ValueError(kind)
    marked = repeated_units(spark, docs, id_col, text_col, min_words, kind)
    joined = packed(docs, id_col, text_col).join(marked, ["__id", "__text_hash"], "left").select("__doc", "__units")
    extra = T.StructType.fromDDL(REPORT).fields if report else []
    for f in extra:
        f.name = free_name(f.name, docs.columns)
    schema = T.StructType([*docs.schema.fields, *extra])
    columns, place = docs.columns, docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fields = batch.column("__doc").flatten()
            flat_batch = pa.RecordBatch.from_arrays([*fields, batch.column("__units"), fields[place]], names=[*(f"c{i}" for i in range(len(fields))), "units", "text"])
            for piece in slices(iter([flat_batch]), "text"):
                yield cut(piece)

    def cut(piece: pa.RecordBatch) -> pa.RecordBatch:
        text = texts(piece)
        u = Units(text, min_words, kind)
        n = piece.num_rows
        drop = np.zeros(len(u.piece_start) + 1, dtype=np.int64)
        first_piece = np.searchsorted(u.piece_row, np.arange(n + 1))
        unit_of = np.full(2 * len(u.piece_start), -1, dtype=np.int64)
        unit_of[2 * u.begin + u.sort] = np.arange(len(u.begin))
        bad = u.repeats_inside()
        lists = piece.column("units")
        flat = lists.flatten().to_numpy(zero_copy_only=False).astype(np.int64)
        sizes = pc.fill_null(pc.list_value_length(lists), 0).to_numpy(zero_copy_only=False)
        bad[unit_of[2 * first_piece[np.repeat(np.arange(n), sizes)] + flat]] = True
        np.add.at(drop, u.begin[bad], 1)
        np.add.at(drop, u.last[bad] + 1, -1)
        gone = np.cumsum(drop[:-1]) > 0
        new, spans = [], []
        original = piece.column("text")
        removed = np.bincount(u.piece_row[gone], minlength=n)
        for r in range(n):
            t = original[r].as_py()
            if not removed[r]:
                new.append(t)
                spans.append([(0, len(t))] if t else [])
                continue
            a, z = first_piece[r], first_piece[r + 1]
            begin, end = int(u.bounds[r]), int(u.bounds[r + 1])
            edges = np.append(u.starts[u.piece_start[a:z]], end)
            raw = u.data[begin:end]
            chars = np.concatenate([[0], np.cumsum((raw & 0xC0) != 0x80)])
            kept, at = [], 0
            for i in np.nonzero(gone[a:z])[0]:  # a piece reaches to the next one's first word
                lo, hi = int(chars[edges[i] - begin]), int(chars[edges[i + 1] - begin])
                if lo > at:
                    kept.append((at, lo))
                at = hi
            if at < len(t):
                kept.append((at, len(t)))
            new.append("".join(t[x:y] for x, y in kept))
            spans.append(kept)
        arrays = [pa.array(new, pa.string()) if i == place else piece.column(f"c{i}") for i in range(len(columns))]
        if report:
            kept_type = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))
            arrays += [pa.array([[{"start": x, "end": y} for x, y in s] for s in spans], kept_type), pa.array(np.bincount(u.piece_row, minlength=n).astype(np.int64)), pa.array(removed.astype(np.int64))]
        return pa.RecordBatch.from_arrays(arrays, names=[f.name for f in schema.fields])

    return joined.mapInArrow(run, schema)
