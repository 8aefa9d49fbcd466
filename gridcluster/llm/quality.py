"""Quality rules: a short-circuit cascade whose order follows rejection per cost on a sample."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import coded, flat_split, row_of, slices, split_words, sums, texts

# The characters that count as symbols.
SYMBOLS = "#*$%&|<>"
MIN_WORDS, MOST_REPEAT_PERCENT = 50, 50
#: Documents on which costs and rejection shares are estimated.
SAMPLE_DOCS = 400


class Batch:
    """Documents of a slice with what several rules share, each worked out when first asked for."""

    def __init__(self, text: pa.Array):
        self.text = text
        self._parts: dict[str, object] = {}

    def take(self, keep: np.ndarray) -> Batch:
        """The documents that are kept, with the figures that are known already."""
        if keep.all():
            return self
        out = Batch(self.text.filter(pa.array(keep)))
        out._parts = {k: v[keep] for k, v in self._parts.items() if isinstance(v, np.ndarray) and len(v) == len(keep)}
        return out

    def part(self, name: str, make: Callable[[], object]):
        if name not in self._parts:
            self._parts[name] = make()
        return self._parts[name]

    @property
    def words(self) -> tuple[pa.Array, np.ndarray]:
        return self.part("words", lambda: split_words(self.text, lower=False))

    @property
    def n_words(self) -> np.ndarray:
        return self.part("n_words", lambda: np.diff(self.words[1]))

    @property
    def lines(self) -> tuple[pa.Array, np.ndarray]:
        return self.part("lines", lambda: flat_split(pc.split_pattern(self.text, "\n")))

    @property
    def n_full_lines(self) -> np.ndarray:
        def make():
            flat, offsets = self.lines
            return sums(_with_word(flat).astype(np.int64), offsets)

        return self.part("full_lines", make)

    def count_bytes(self, wanted: str) -> np.ndarray:
        """Occurrences of ASCII characters in each text."""
        if not len(self.text):
            return np.zeros(0, dtype=np.int64)
        table = np.zeros(256, dtype=np.int8)
        table[np.frombuffer(wanted.encode(), dtype=np.uint8)] = 1
        offsets = np.frombuffer(self.text.buffers()[1], dtype=np.int32)[self.text.offset : self.text.offset + len(self.text) + 1].astype(np.int64)
        data = np.frombuffer(self.text.buffers()[2] or b"", dtype=np.uint8)[offsets[0] : offsets[-1]]
        return sums(table[data], offsets - offsets[0])

    def chars(self) -> np.ndarray:
        return self.part("chars", lambda: pc.utf8_length(self.text).to_numpy(zero_copy_only=False).astype(np.int64))

    def word_chars(self) -> np.ndarray:
        flat, offsets = self.words
        return self.part("word_chars", lambda: sums(pc.utf8_length(flat).to_numpy(zero_copy_only=False).astype(np.int64), offsets))

    def dup_lines(self) -> np.ndarray:
        """Lines with a word that equal an earlier line of their text."""

        def make():
            flat, offsets = self.lines
            full = _with_word(flat)
            codes, _ = coded(flat)
            again = pd.Series(row_of(offsets) << 32 | codes).duplicated(keep="first").to_numpy() & full
            return sums(again.astype(np.int64), offsets)

        return self.part("dup_lines", make)

    def repeat_words(self) -> np.ndarray:
        """Words that lie in a three-word window which their text has twice or more."""

        def make():
            flat, offsets = self.words
            if len(flat) < 3:
                return np.zeros(len(offsets) - 1, dtype=np.int64)
            codes, row = coded(flat)[0], row_of(offsets)
            inside = row[2:] == row[:-2]
            pairs = pd.factorize(codes[:-2] << 32 | codes[1:-1])[0].astype(np.int64)
            triples = pd.factorize(pairs << 32 | codes[2:])[0].astype(np.int64)
            seen = pd.Series(row[2:] << 32 | triples).duplicated(keep=False).to_numpy() & inside
            covered = np.zeros(len(flat), dtype=np.int64)
            for shift in range(3):
                covered[shift : len(flat) - 2 + shift] |= seen
            return sums(covered, offsets)

        return self.part("repeat_words", make)

    def symbols(self) -> np.ndarray:
        return self.part("symbols", lambda: self.count_bytes(SYMBOLS))


def _with_word(lines: pa.Array) -> np.ndarray:
    return pc.greater(pc.binary_length(pc.ascii_trim_whitespace(lines)), 0).to_numpy(zero_copy_only=False)


@dataclass(frozen=True)
class Rule:
    """rejects: documents of a batch that the rule turns down."""

    name: str
    rejects: Callable[[Batch], np.ndarray]


def _share_of_letters_upper(b: Batch) -> np.ndarray:
    upper, lower = b.count_bytes("ABCDEFGHIJKLMNOPQRSTUVWXYZ"), b.count_bytes("abcdefghijklmnopqrstuvwxyz")
    return 100 * upper > 60 * (upper + lower)


#: Thresholds in whole numbers, so that SQL gives the same verdicts.
RULES = (
    Rule("many_symbols", lambda b: 100 * b.symbols() > 20 * b.n_words),
    Rule("word_length", lambda b: (b.word_chars() < 2 * b.n_words) | (b.word_chars() > 25 * b.n_words)),
    Rule("exclamations", lambda b: 100 * b.count_bytes("!?") > 40 * b.n_words),
    Rule("upper_case", _share_of_letters_upper),
    Rule("repeated_lines", lambda b: 100 * b.dup_lines() > 50 * b.n_full_lines),
    Rule("digits", lambda b: 100 * b.count_bytes("0123456789") > 40 * b.chars()),
    Rule("braces", lambda b: 100 * b.count_bytes("{}[]\\_=") > 10 * b.chars()),
)


#: What every document must pass, as rules.
BASE = (
    Rule("few_words", lambda b: b.n_words < MIN_WORDS),
    Rule("repeated_words", lambda b: 100 * b.repeat_words() > MOST_REPEAT_PERCENT * b.n_words),
)


def measured(batches: Iterator[pa.RecordBatch], rules: tuple[Rule, ...], column: str) -> Iterator[pa.RecordBatch]:
    seconds, turned = np.zeros(len(rules)), np.zeros(len(rules), dtype=np.int64)
    docs = 0
    for piece in slices(batches, column):
        docs += piece.num_rows
        for i, r in enumerate(rules):
            fresh = Batch(texts(piece, column))
            began = time.perf_counter()
            turned[i] += int(r.rejects(fresh).sum())
            seconds[i] += time.perf_counter() - began
    yield pa.RecordBatch.from_arrays([pa.array([r.name for r in rules]), pa.array([docs] * len(rules), pa.int64()), pa.array(turned), pa.array(seconds)], names=["rule", "docs", "rejected", "seconds"])


def plan_cascade(docs: DataFrame, rules: tuple[Rule, ...] = RULES, text_col: str = "text", sample_docs: int = SAMPLE_DOCS, seed: int = 7) -> list[tuple[str, float, float]]:
    """Rule name, rejection share and seconds a document on a sample, best rejection per cost first.

    The sample is drawn by a hash of the text, measured where it lies; a row a rule and task comes
    back. It decides the order only: the verdict of a cascade doesn't depend on its order.
    """
    n = docs.count()
    one_in = max(1, n // max(1, sample_docs))
    sample = docs.select(text_col).where(F.pmod(F.xxhash64(F.lit(seed), F.coalesce(text_col, F.lit(""))), F.lit(one_in)) == 0)
    parts = sample.mapInArrow(lambda it: measured(it, rules, text_col), "rule string, docs long, rejected long, seconds double")
    found = parts.groupBy("rule").agg(F.sum("docs").alias("docs"), F.sum("rejected").alias("rejected"), F.sum("seconds").alias("seconds")).collect()
    by = {r["rule"]: (r["rejected"] / max(1, r["docs"]), r["seconds"] / max(1, r["docs"])) for r in found}
    order = [(r.name, *by.get(r.name, (0.0, 0.0))) for r in rules]
    return sorted(order, key=lambda x: -x[1] / max(x[2], 1e-9))


def cascade(batch: Batch, alive: np.ndarray, rules: list[Rule], blame: np.ndarray | None = None) -> np.ndarray:
    """Runs each rule on the documents that are still alive, and stops when none is."""
    alive = alive.copy()
    rest, where = batch.take(alive), np.nonzero(alive)[0]
    for i, rule in enumerate(rules):
        if not len(where):
            break
        out = rule.rejects(rest)
        if out.any():
            alive[where[out]] = False
            if blame is not None:
                blame[where[out]] = i
            rest, where = rest.take(~out), where[~out]
    return alive


def quality_verdicts(docs: DataFrame, rules: tuple[Rule, ...] = RULES, id_col: str = "doc_id", text_col: str = "text", order: list[str] | None = None, sample_docs: int = SAMPLE_DOCS) -> DataFrame:
    """Base figures of every document, and whether it is kept.

    base_failed: under 50 words, or over half of the words in repeated three-word windows. A document
    that passes goes through the cascade; kept is false from the first rule that rejects it.
    Null or empty text: no words, so base_failed. Rows stay as they are, repeated ones too.
    rejected_by: the rule that turned it down, in the order the sample gave (`base` for the base).
    """
    names = order or [n for n, _, _ in plan_cascade(docs, rules, text_col, sample_docs)]
    ranked = [next(r for r in rules if r.name == n) for n in names]
    labels = pa.array([*names, "base"])

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece in slices(batches, "text"):
            b = Batch(texts(piece))
            n_words, repeated = b.n_words.astype(np.int64), b.repeat_words()
            failed = (n_words < MIN_WORDS) | (100 * repeated > MOST_REPEAT_PERCENT * n_words)
            blame = np.where(failed, len(names), -1)
            kept = cascade(b, ~failed, ranked, blame)
            yield pa.RecordBatch.from_arrays(
                [piece.column("doc_id"), *map(pa.array, (n_words, b.word_chars(), b.symbols(), b.dup_lines(), repeated, failed, kept)), labels.take(pa.array(blame, mask=blame < 0))],
                names=["doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "rejected_by"],
            )

    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(judge, "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, kept boolean, rejected_by string")


def keep_good(docs: DataFrame, rules: tuple[Rule, ...] = RULES, text_col: str = "text", sample_docs: int = SAMPLE_DOCS) -> DataFrame:
    """The rows that the base and all rules keep, with all their columns, whatever these are named, in one narrow pass.

    The base's two conditions are rules of the cascade like the others, so the dear one (repeated words)
    is worked out for the documents that are still in. Null and empty texts have too few words and go; repeated
    rows stay or go alike; an empty table stays empty.
    """
    rules = (*BASE, *rules)
    names = [n for n, _, _ in plan_cascade(docs, rules, text_col, sample_docs)]
    ranked = [next(r for r in rules if r.name == n) for n in names]

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece in slices(batches, text_col):
            b = Batch(texts(piece, text_col))
            yield piece.filter(pa.array(cascade(b, np.ones(piece.num_rows, dtype=bool), ranked)))

    return docs.mapInArrow(judge, docs.schema)
