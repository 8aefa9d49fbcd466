"""Language ID by cross-parsing: the language whose reference text needs the fewest normalised phrases wins.

A text is parsed greedily into longest substrings of a language's reference; n letters in c phrases
against a reference of r letters estimate a cross entropy of c * log2(r) / n bits a letter. A letter that the
reference lacks cannot be pointed at: besides its phrase it costs the bits of any character, so that a short
reference is not the cheapest for a script that it doesn't have.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import crc_bucket, slices, texts

#: Bounds of the labelled sample: rows a language, characters of them in its reference, and characters of all references.
SAMPLE_ROWS, REFERENCE_CHARS, ALL_CHARS = 60, 40_000, 4_000_000
#: Rows of the list of sampled texts (a label and two numbers) that may be broadcast.
BROADCAST_ROWS = 200_000
#: Phrases end at every so many characters, so that long texts are parsed side by side.
SEGMENT = 1024
#: Bits that spell any character out.
LETTER_BITS = math.log2(0x110000)
UNKNOWN = "und"


def normalised(text: pa.Array) -> pa.Array:
    """Running text in lower case with one blank for whatever lies between letters, and at both ends; empty without a letter."""
    low = pc.replace_substring_regex(pc.utf8_lower(text), r"[^\p{L}]+", " ")
    bare = pc.utf8_trim(low, " ")
    return pc.if_else(pc.equal(pc.binary_length(bare), 0), "", pc.binary_join_element_wise(" ", bare, " ", ""))


class SuffixAutomaton:
    """All substrings of a text as paths from state 0; built online, character by character."""

    def __init__(self, text: str):
        self.next: list[dict[str, int]] = [{}]
        link, length, last = [-1], [0], 0
        for ch in text:
            cur = len(self.next)
            self.next.append({})
            length.append(length[last] + 1)
            link.append(0)
            p = last
            while p >= 0 and ch not in self.next[p]:
                self.next[p][ch] = cur
                p = link[p]
            if p >= 0:
                q = self.next[p][ch]
                if length[q] != length[p] + 1:
                    clone = len(self.next)
                    self.next.append(dict(self.next[q]))
                    length.append(length[p] + 1)
                    link.append(link[q])
                    while p >= 0 and self.next[p].get(ch) == q:
                        self.next[p][ch] = clone
                        p = link[p]
                    link[q] = q = clone
                link[cur] = q
            last = cur

    def phrases(self, text: str) -> int:
        """Greedy parse into longest substrings of the reference; a character it lacks is a phrase by itself."""
        count, state = 0, 0
        for ch in text:
            to = self.next[state].get(ch)
            if to is None or state == 0:
                count += 1
                to = self.next[0].get(ch, 0)
            state = to
        return count


class EdgeTable:
    """The transitions of all automata as one hash table by state and letter: as large as the edges, whatever the alphabet."""

    def __init__(self, state: np.ndarray, letter: np.ndarray, to: np.ndarray, letters: int):
        self.letters = letters
        self.bits = max(4, int(2 * len(state) + 1).bit_length())
        self.keys, self.to = np.full(1 << self.bits, -1, dtype=np.int64), np.zeros(1 << self.bits, dtype=np.int32)
        key = state.astype(np.int64) * letters + letter
        rest, slot = np.arange(len(key)), self._slot(key)
        while len(rest):  # of those that want one free place the first gets it, the others go on to the next
            wish = rest[self.keys[slot[rest]] < 0]
            won = wish[np.unique(slot[wish], return_index=True)[1]]
            self.keys[slot[won]], self.to[slot[won]] = key[won], to[won]
            rest = np.setdiff1d(rest, won, assume_unique=True)
            slot[rest] = (slot[rest] + 1) & (len(self.keys) - 1)

    def _slot(self, key: np.ndarray) -> np.ndarray:
        return (key.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(64 - self.bits)).astype(np.int64)

    def step(self, state: np.ndarray, letter: np.ndarray) -> np.ndarray:
        """The state that each letter leads to, -1 without such an edge."""
        key = state * self.letters + letter
        slot = self._slot(key)
        there = self.keys[slot]
        out = np.where(there == key, self.to[slot], np.int32(-1))
        rest = np.nonzero((there != key) & (there >= 0))
        while len(rest[0]):
            slot[rest] = (slot[rest] + 1) & (len(self.keys) - 1)
            there = self.keys[slot[rest]]
            hit = there == key[rest]
            if hit.any():
                found = tuple(r[hit] for r in rest)
                out[found] = self.to[slot[found]]
            more = ~hit & (there >= 0)
            rest = tuple(r[more] for r in rest)
        return out


class LanguageModel:
    """Automata of all languages' references in one table; the alphabet is every character of any reference."""

    def __init__(self, references: dict[str, str]):
        self.langs = sorted(references)
        points = sorted({ord(c) for t in references.values() for c in t})
        self.points = np.array(points, dtype=np.uint32)  # letter numbers from 1; 0: any other character
        number = {chr(p): i + 1 for i, p in enumerate(points)}
        root, base, state, letter, to = [], 0, [], [], []
        for lang in self.langs:
            a = SuffixAutomaton(references[lang])
            for s, edges in enumerate(a.next):
                for ch, target in edges.items():
                    state.append(s + base)
                    letter.append(number[ch])
                    to.append(target + base)
            root.append(base)
            base += len(a.next)
        self.root = np.array(root, dtype=np.int64)
        self.bits = np.array([math.log2(len(references[lang]) + 2) for lang in self.langs])
        self.edges = EdgeTable(np.array(state, dtype=np.int64), np.array(letter, dtype=np.int64), np.array(to, dtype=np.int32), len(points) + 1)
        everything = np.arange(len(points) + 1)
        self.from_root = self.edges.step(np.repeat(self.root[None], len(everything), axis=0), np.repeat(everything[:, None], len(self.langs), axis=1)) if self.langs else None
        self.lacks = self.from_root < 0 if self.langs else None

    def phrases(self, texts_: list[str]) -> np.ndarray:
        """Phrases of each text in each language: an array texts x languages."""
        return self.parsed(texts_)[0]

    def parsed(self, texts_: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Phrases of each text in each language, and how many of them are characters that its reference lacks; all
        segments are parsed in lock step."""
        n, k = len(texts_), len(self.langs)
        out, lacking = np.zeros((n, k), dtype=np.int64), np.zeros((n, k), dtype=np.int64)
        flat = np.frombuffer("".join(texts_).encode("utf-32-le"), dtype=np.uint32)
        if not len(flat) or not k:
            return out, lacking
        at = np.minimum(np.searchsorted(self.points, flat), len(self.points) - 1)
        codes = np.where(self.points[at] == flat, at + 1, 0)
        lengths = np.fromiter(map(len, texts_), dtype=np.int64, count=n)
        pieces = -(-lengths // SEGMENT)
        row = np.repeat(np.arange(n), pieces)
        place = np.arange(len(row)) - np.repeat(np.cumsum(pieces) - pieces, pieces)
        begin = np.repeat(np.cumsum(lengths) - lengths, pieces) + place * SEGMENT
        size = np.minimum(lengths[row] - place * SEGMENT, SEGMENT)
        order = np.argsort(-size, kind="stable")
        row, begin, size = row[order], begin[order], size[order]
        count = np.zeros((len(row), k), dtype=np.int32)
        state = np.repeat(self.root[None], len(row), axis=0)
        for t in range(int(size[0])):
            live = int(np.searchsorted(-size, -t, side="left"))
            ch = codes[begin[:live] + t]
            to = self.edges.step(state[:live], ch[:, None])
            fresh = (to < 0) | (state[:live] == self.root[None])
            count[:live] += fresh
            again = self.from_root[ch]  # a character that the reference lacks is a phrase by itself
            state[:live] = np.where(fresh, np.where(again < 0, self.root[None], again), to)
        for j in range(k):
            out[:, j] = np.bincount(row, weights=count[:, j], minlength=n)
        odd = np.nonzero(self.lacks.any(axis=1)[codes])[0]
        own = np.searchsorted(np.cumsum(lengths), odd, side="right")
        for j in range(k):
            lacking[:, j] = np.bincount(own, weights=self.lacks[codes[odd], j], minlength=n)
        return out, lacking

    def predict(self, text: pa.Array) -> tuple[list[str], np.ndarray]:
        """Language and score of each text; `und` and 0 without a letter or without any learned language."""
        clean = normalised(text)
        n, k = len(text), len(self.langs)
        known = (pc.binary_length(clean).to_numpy(zero_copy_only=False) > 0) & (k > 0)
        if not k:
            return [UNKNOWN] * n, np.zeros(n)
        phrases, lacking = self.parsed(clean.to_pylist())
        cost = phrases * self.bits + lacking * LETTER_BITS
        best = cost.argmin(axis=1)
        low = cost[np.arange(n), best]
        rest = (1 / np.maximum(cost, 1e-9)).sum(axis=1)
        score = np.where(known, np.minimum(1.0, 1 / np.maximum(low, 1e-9) / rest), 0.0)
        return [self.langs[b] if ok else UNKNOWN for b, ok in zip(best.tolist(), known.tolist())], score


def reference_text(samples: list[str], chars: int = REFERENCE_CHARS) -> str:
    """Running text of the samples, an equal share of `chars` from each at first, then what is left of those that have more."""
    clean = [t for t in normalised(pa.array(samples, pa.string())).to_pylist() if t]
    out, used, share = [], 0, max(1, chars // max(1, len(clean)))
    for from_, to in ((0, share), (share, chars)):
        for t in clean:
            part = t[from_:to][: chars - used]
            out.append(part)
            used += len(part)
    return "".join(out)


def fit_language_model(labelled: DataFrame, text_col: str = "text", lang_col: str = "lang", sample_rows: int = SAMPLE_ROWS, chars: int = REFERENCE_CHARS, all_chars: int = ALL_CHARS, seed: int = 3) -> LanguageModel:
    """Learns from a bounded sample of labelled rows: per language the rows of smallest text hash.

    Rows with null or empty text or null language are left out. At most `chars` characters of a row
    travel, at most `sample_rows` rows a language, and all references together hold `all_chars`
    characters at most; the number of languages and of letters is free.
    """
    rows = labelled.where(F.col(lang_col).isNotNull() & (F.length(text_col) > 0)).select(F.col(lang_col).cast("string").alias("lang"), F.col(text_col).alias("text"), F.xxhash64(F.lit(seed), F.col(text_col)).alias("h"))
    # the hashes decide first, without texts; a few candidates of each slice, so that no language has to meet in one task
    spread = rows.select("lang", "h").distinct().withColumn("part", F.pmod("h", F.lit(64)))
    near = spread.withColumn("place", F.row_number().over(Window.partitionBy("lang", "part").orderBy("h"))).where(F.col("place") <= sample_rows)
    top = Window.partitionBy("lang").orderBy("h")
    picked = near.withColumn("rank", F.row_number().over(top)).where(F.col("rank") <= sample_rows).select("lang", "h", "rank")
    counted = picked.groupBy("lang").agg(F.max("rank").alias("n"))
    languages = counted.count()
    chars = max(1, min(chars, all_chars // max(1, languages)))
    few = F.broadcast(picked) if languages * sample_rows <= BROADCAST_ROWS else picked
    chosen = rows.join(few, ["lang", "h"]).groupBy("lang", "h", "rank").agg(F.min(F.substring("text", 1, chars)).alias("text"))
    samples: dict[str, list[str]] = {}
    for r in chosen.orderBy("lang", "rank").collect():  # rows a language are bounded, and so are their texts
        samples.setdefault(r["lang"], []).append(r["text"])
    return LanguageModel({lang: t for lang, s in samples.items() if (t := reference_text(s, chars))})


def predict_languages(spark: SparkSession, docs: DataFrame, model: LanguageModel, id_col: str = "doc_id", text_col: str = "text", buckets: int = 4, held: int = 2) -> DataFrame:
    """Language of every whole text: doc_id, held_out, lang_pred, score.

    Null or empty text, and text without a letter: `und`, score 0. Ties go to the first name. Repeated
    rows are predicted alike; other columns are not looked at; an empty table gives no row.
    """
    shared = spark.sparkContext.broadcast(model)  # bounded by ALL_CHARS

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece in slices(batches, "text", 4 << 20):
            langs, score = shared.value.predict(texts(piece))
            yield pa.RecordBatch.from_arrays([piece.column("doc_id"), piece.column("held_out"), pa.array(langs, pa.string()), pa.array(score)], names=["doc_id", "held_out", "lang_pred", "score"])

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"), (crc_bucket(id_col, buckets) == held).alias("held_out"))
    return rows.mapInArrow(run, "doc_id long, held_out boolean, lang_pred string, score double")
