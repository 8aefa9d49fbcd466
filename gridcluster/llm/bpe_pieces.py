"""Byte-level BPE through the tokenizers library, with each distinct piece of text encoded once."""

from __future__ import annotations

import os
from itertools import chain

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc

from .common import coded, flat_split, row_of

#: Distinct pieces that a worker keeps, at some 40 bytes each; beyond that it starts again.
CACHE = 2_000_000
#: Pieces are handed to the library in runs of about so many characters.
RUN = 1 << 16
_SECOND_KEY = "fedcba9876543210"


def _gappy(text: pa.Array) -> np.ndarray:
    """Texts that may have white space beside white space or at an end, or a special string.

    Works on bytes. ASCII white space is seen exactly; every other white-space character of Unicode
    makes its text count, wherever it stands.
    """
    n = len(text)
    offsets = np.frombuffer(text.buffers()[1], dtype=np.int32)[text.offset : text.offset + n + 1].astype(np.int64)
    data = np.frombuffer(text.buffers()[2] or b"", dtype=np.uint8)[offsets[0] : offsets[-1]]
    offsets = offsets - offsets[0]
    if not len(data):
        return np.zeros(n, dtype=bool)
    kind = np.zeros(256, dtype=bool)
    kind[[0x20, *range(0x09, 0x0E), *range(0x1C, 0x20)]] = True
    white = kind[data]
    bad = np.zeros(len(data), dtype=bool)
    bad[1:] |= white[1:] & white[:-1]
    filled = offsets[1:] > offsets[:-1]
    bad[offsets[:-1][filled]] |= white[offsets[:-1][filled]]
    bad[offsets[1:][filled] - 1] |= white[offsets[1:][filled] - 1]
    lead = np.zeros(256, dtype=bool)
    lead[[0xC2, 0xE1, 0xE2, 0xE3, 0x3C]] = True
    at = np.nonzero(lead[data[:-1]])[0]
    if len(at):
        a, b = data[at], data[at + 1]
        c = data[np.minimum(at + 2, len(data) - 1)]
        odd = (a == 0xC2) & ((b == 0x85) | (b == 0xA0)) | (a == 0xE1) & (b == 0x9A) & (c == 0x80) | (a == 0xE3) & (b == 0x80) & (c == 0x80)
        odd |= (a == 0xE2) & ((b == 0x80) & ((c <= 0x8A) | (c == 0xA8) | (c == 0xA9) | (c == 0xAF)) | (b == 0x81) & (c == 0x9F))
        odd |= (a == 0x3C) & (b == 0x7C)
        bad[at[odd]] = True
    total = np.concatenate([[0], np.cumsum(bad)])
    return total[offsets[1:]] > total[offsets[:-1]]


class PieceEncoder:
    """Encodes texts exactly as the library does on whole texts.

    The splitter never joins letters over a single space: between two characters that are not white
    space, a space begins a new piece. So such texts are cut before each space and each distinct piece
    is encoded once a worker. Texts with runs of white space or special strings are encoded whole.
    """

    def __init__(self, tokenizer: bytes):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_buffer(tokenizer)
        self.tokenizer.encode_special_tokens = True
        vocab = self.tokenizer.get_vocab()
        self.width = np.zeros(max(vocab.values()) + 1, dtype=np.int64)  # a token's characters stand for a byte each
        for name, i in vocab.items():
            self.width[i] = len(name)
        self._forget()

    def _forget(self) -> None:
        self.hash, self.check = np.zeros(0, dtype=np.uint64), np.zeros(0, dtype=np.uint64)
        self.begin, self.size = np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64)
        self.values = np.zeros(0, dtype=np.uint32)

    def _whole(self, texts: list[str]) -> list[list[int]]:
        return [e.ids for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def _pieces(self, names: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Sizes and ids of pieces: those that begin with a space are encoded in joined runs."""
        joined = [i for i, n in enumerate(names) if n[:1] == " " and len(n) > 1]
        apart = [i for i, n in enumerate(names) if not (n[:1] == " " and len(n) > 1)]
        sizes = np.zeros(len(names), dtype=np.int64)
        runs, run, length = [], [], 0
        for i in joined:
            run.append(names[i])
            length += len(names[i])
            if length >= RUN:
                runs.append("".join(run))
                run, length = [], 0
        runs.append("".join(run))
        got = np.fromiter(chain.from_iterable(self._whole(runs)), dtype=np.uint32)
        ends = np.cumsum([len(names[i].encode()) for i in joined], dtype=np.int64)
        upto = np.searchsorted(np.cumsum(self.width[got]), ends, side="right")
        sizes[joined] = np.diff(upto, prepend=0)
        single = self._whole([names[i] for i in apart])
        sizes[apart] = [len(x) for x in single]
        begin = np.cumsum(sizes) - sizes
        values = np.zeros(int(sizes.sum()), dtype=np.uint32)
        own = np.array(joined, dtype=np.int64)
        values[np.repeat(begin[own] - (upto - sizes[own]), sizes[own]) + np.arange(len(got))] = got
        for i, ids in zip(apart, single):
            values[begin[i] : begin[i] + len(ids)] = ids
        return sizes, values

    def _lookup(self, distinct: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Where the ids of each distinct piece lie in self.values, and how many they are."""
        objects = distinct.to_numpy(zero_copy_only=False)
        h = pd.util.hash_array(objects, categorize=False)
        check = pd.util.hash_array(objects, categorize=False, hash_key=_SECOND_KEY)
        if len(self.hash) + len(h) > CACHE:
            self._forget()

        def find():
            at = np.minimum(np.searchsorted(self.hash, h), max(0, len(self.hash) - 1))
            return at, (self.hash[at] == h) & (self.check[at] == check) if len(self.hash) else np.zeros(len(h), dtype=bool)

        at, known = find()
        if not known.all():
            new = np.nonzero(~known)[0]
            sizes, values = self._pieces(objects[new].tolist())
            begin = np.cumsum(sizes) - sizes + len(self.values)
            everything = np.concatenate([self.hash, h[new]])
            order = np.argsort(everything, kind="stable")
            self.hash = everything[order]
            self.check = np.concatenate([self.check, check[new]])[order]
            self.begin = np.concatenate([self.begin, begin])[order]
            self.size = np.concatenate([self.size, sizes])[order]
            self.values = np.concatenate([self.values, values])
            at, known = find()
            if not known.all():  # two pieces of one hash: the cache can't hold both
                self._forget()
                sizes, self.values = self._pieces(objects.tolist())
                return np.cumsum(sizes) - sizes, sizes
        return self.begin[at], self.size[at]

    def encode(self, text: pa.Array, end_id: int) -> tuple[np.ndarray, np.ndarray]:
        """Ids with the end id per text: lengths, and all ids in a row."""
        whole = _gappy(text)
        lengths = np.zeros(len(text), dtype=np.int64)
        cut = text.filter(pa.array(~whole)) if whole.any() else text
        flat, offsets = flat_split(pc.split_pattern(cut, " "))
        first = np.zeros(len(flat), dtype=bool)
        first[offsets[:-1]] = True
        # a text's first piece has no space before it
        codes, distinct = coded(flat)
        inner = np.unique(codes[~first])
        outer = np.unique(codes[first])
        pieces = pa.concat_arrays([pc.binary_join_element_wise(" ", distinct.take(pa.array(inner)), ""), distinct.take(pa.array(outer))])
        begins, sizes = self._lookup(pieces)
        number = np.zeros((2, len(distinct)), dtype=np.int64)
        number[0, inner] = np.arange(len(inner))
        number[1, outer] = len(inner) + np.arange(len(outer))
        which = number[first.astype(np.int8), codes]
        per = sizes[which]
        total = np.concatenate([[0], np.cumsum(per)])
        lengths[~whole] = total[offsets[1:]] - total[offsets[:-1]]
        direct = self._whole(text.filter(pa.array(whole)).to_pylist()) if whole.any() else []
        lengths[whole] = [len(x) for x in direct]
        lengths += 1
        out = np.full(int(lengths.sum()), end_id, dtype=np.uint32)
        start = np.cumsum(lengths) - lengths
        # a piece's ids go where its row begins, behind the row's pieces before it
        cut_start = start[np.nonzero(~whole)[0]]
        target = (cut_start - total[offsets[:-1]])[row_of(offsets)] + total[:-1]
        run = np.arange(int(total[-1]))
        out[run + np.repeat(target - total[:-1], per)] = self.values[run + np.repeat(begins[which] - total[:-1], per)]
        for i, ids in zip(np.nonzero(whole)[0], direct):
            out[start[i] : start[i] + len(ids)] = ids
        return lengths, out


_WORKER: dict[int, PieceEncoder] = {}


def encoder_of(tokenizer: bytes) -> PieceEncoder:
    """One encoder a worker and vocabulary, so that pieces of earlier tasks are known."""
    key = hash(tokenizer)
    if key not in _WORKER:
        _WORKER.clear()
        _WORKER[key] = PieceEncoder(tokenizer)
    return _WORKER[key]
