"""SentencePiece encoding and decoding: exact merge-type (BPE) segmentation by backtracking."""

from __future__ import annotations

import hashlib
import heapq
import re
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import coded, flat_split, row_of, slices, texts

SPACE = "▁"
#: Distinct words and token pairs that a worker keeps.
WORDS, PAIRS = 300_000, 200_000
_WORD = re.compile(f"{SPACE}+[^{SPACE}]*|[^{SPACE}]+")


class MergeEncoder:
    """Ids of a text as the merge procedure of the vocabulary gives them.

    Candidates at a position are the vocabulary entries that are prefixes of the rest, longest first,
    from an Aho-Corasick automaton over the vocabulary. A candidate is taken if its end isn't known to fail
    and if the last token and it stay two tokens when their joined text is merged anew; otherwise the
    next shorter one is tried; when none is left the position is marked as failed in a bitfield and the
    last token is taken back.

    No entry has a word mark behind another character (checked), so a merge never crosses the begin of
    a word, and each distinct word is segmented once.
    """

    def __init__(self, model: bytes):
        import ahocorasick
        import sentencepiece

        self.processor = sp = sentencepiece.SentencePieceProcessor(model_proto=model)
        self.bos, self.eos, self.unk = sp.bos_id(), sp.eos_id(), sp.unk_id()
        self.score: dict[str, float] = {}
        self.ids: dict[str, int] = {}
        self.byte_ids = [self.unk] * 256
        for i in range(sp.get_piece_size()):
            piece = sp.id_to_piece(i)
            if sp.is_byte(i):
                self.byte_ids[int(piece[3:5], 16)] = i
            elif not (sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i)):
                self.score[piece], self.ids[piece] = sp.get_score(i), i
        if any(re.search(f"[^{SPACE}]{SPACE}", p) for p in self.ids):
            raise ValueError("an entry crosses the begin of a word")
        if sp.normalize("a  Å\t") != f"{SPACE}a{SPACE}{SPACE}Å\t":
            raise ValueError("the model normalizes texts; only the identity with a leading mark is expressed here")
        self.automaton = ahocorasick.Automaton()
        self.reachable: set[str] = set()
        for p in self.ids:
            if self.remerge(p) == [p]:  # others never come out of merging
                self.reachable.add(p)
                self.automaton.add_word(p, len(p))
        self.automaton.make_automaton()
        self.pairs: dict[str, bool] = {}
        self.words: dict[str, bytes] = {}  # ids as 32-bit integers
        self.shorter = {p: next((p[:k] for k in range(len(p) - 1, 0, -1) if p[:k] in self.reachable), "") for p in self.reachable}

    def remerge(self, text: str) -> list[str]:
        """The merge procedure itself: best score first, then leftmost."""
        parts: list[str | None] = list(text)
        n = len(parts)
        left, right = list(range(-1, n - 1)), [*range(1, n), -1]
        queue: list[tuple[float, int, int, str]] = []

        def offer(a: int, b: int) -> None:
            if a >= 0 and b >= 0 and (s := self.score.get(joined := parts[a] + parts[b])) is not None:
                heapq.heappush(queue, (-s, a, b, joined))

        for i in range(n - 1):
            offer(i, i + 1)
        while queue:
            _, a, b, joined = heapq.heappop(queue)
            if parts[a] is None or parts[b] is None or right[a] != b or parts[a] + parts[b] != joined:
                continue
            parts[a], parts[b] = joined, None
            right[a] = right[b]
            if right[b] >= 0:
                left[right[b]] = a
            offer(left[a], a)
            offer(a, right[a])
        return [p for p in parts if p is not None]

    def compatible(self, a: str, b: str) -> bool:
        key = f"{a} {b}"  # no entry holds a blank
        ok = self.pairs.get(key)
        if ok is None:
            if len(self.pairs) >= PAIRS:
                self.pairs.clear()
            ok = self.pairs[key] = self.remerge(a + b) == [a, b]
        return ok

    def segment(self, word: str) -> list[str]:
        """Backtracking over one word."""
        n, taken, at = len(word), [], 0
        failed = bytearray((n >> 3) + 1)  # a bit for each position that no segmentation goes on from
        longest = self._longest(word)
        token = longest[0]
        while at < n:
            while True:
                end = at + len(token)
                if not failed[end >> 3] >> (end & 7) & 1 and (not taken or self.compatible(taken[-1], token)):
                    taken.append(token)
                    at = end
                    token = longest[at] if at < n else ""
                    break
                token = self.shorter.get(token, "")
                if not token:
                    failed[at >> 3] |= 1 << (at & 7)
                    if not taken:
                        return self.remerge(word)  # cannot happen with a closed vocabulary
                    token = taken.pop()
                    at -= len(token)
        return taken

    def _longest(self, word: str) -> list[str]:
        """For each position the longest entry that begins there; a character of no entry stands alone."""
        size = [1] * len(word)
        for end, length in self.automaton.iter(word):  # all matches, each by its end
            begin = end - length + 1
            if length > size[begin]:
                size[begin] = length
        return [word[i : i + k] for i, k in enumerate(size)]

    def word_ids(self, word: str) -> bytes:
        if word.startswith(SPACE * 2):  # marks in a row have equal scores: merged outright
            parts = self.remerge(word)
        else:
            parts = self.segment(word)
        out: list[int] = []
        for p in parts:
            i = self.ids.get(p)
            out.extend((i,) if i is not None else (self.byte_ids[b] for b in p.encode()))
        return array("I", out).tobytes()

    def encode(self, text: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Lengths per text and all ids in a row, each text between begin and end id."""
        has_gap = pc.match_substring_regex(text, f"  |^ | $|{SPACE}").to_numpy(zero_copy_only=False) | (pc.binary_length(text).to_numpy(zero_copy_only=False) == 0)
        if has_gap.any():
            lists = pc.split_pattern(text, " ").to_pylist()
            for i in np.nonzero(has_gap)[0]:
                t = text[int(i)].as_py()
                lists[i] = [w[1:] if w[0] == SPACE else w for w in _WORD.findall(SPACE + t.replace(" ", SPACE))] if t else []
            split = pa.array(lists, pa.list_(pa.string()))
        else:
            split = pc.split_pattern(text, " ")
        flat, offsets = flat_split(split)
        codes, distinct = coded(flat)
        names = distinct.to_pylist()
        cache = self.words
        if len(cache) + len(names) > WORDS:
            kept = {w: cache[w] for w in names if w in cache}
            cache = self.words = kept
        found = []
        for w in names:
            ids = cache.get(w)
            if ids is None:
                ids = cache[w] = self.word_ids(SPACE + w)
            found.append(ids)
        sizes = np.fromiter(map(len, found), dtype=np.int64, count=len(found)) // 4
        values = np.frombuffer(b"".join(found), dtype=np.uint32)
        begins, per = np.cumsum(sizes) - sizes, sizes[codes]
        total = np.concatenate([[0], np.cumsum(per)])
        lengths = total[offsets[1:]] - total[offsets[:-1]] + 2
        out = np.empty(int(lengths.sum()), dtype=np.uint32)
        start = np.cumsum(lengths) - lengths
        out[start], out[start + lengths - 1] = self.bos, self.eos
        target = (start + 1 - total[offsets[:-1]])[row_of(offsets)] + total[:-1]
        run = np.arange(int(total[-1]))
        out[run + np.repeat(target - total[:-1], per)] = values[run + np.repeat(begins[codes] - total[:-1], per)]
        return lengths, out


_WORKER: dict[int, MergeEncoder] = {}


def encoder_of(model: bytes) -> MergeEncoder:
    """One encoder a worker and model."""
    key = hash(model)
    if key not in _WORKER:
        _WORKER.clear()
        _WORKER[key] = MergeEncoder(model)
    return _WORKER[key]


def sentence_piece_digests(spark: SparkSession, docs: DataFrame, model: bytes, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False) -> DataFrame:
    """Encodes every whole text with begin and end ids and decodes it again.

    Null or empty text: the begin and the end id, which decode to empty text. Rows stay as they are,
    repeated ones too; other columns are not looked at; an empty table gives no row.
    Returns doc_id, n_tokens, ids_sha256, decoded_sha256, round_trip (the text came back) and, if asked for, ids and decoded.
    """
    shared = spark.sparkContext.broadcast(model)  # a vocabulary file: under a MB or a few, whatever the data
    extra = ", ids array<int>, decoded string" if with_ids else ""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = encoder_of(shared.value)
        for piece in slices(batches, "text"):
            text = texts(piece)
            lengths, ids = encoder.encode(text)
            ends = np.cumsum(lengths)
            rows = [ids[z - n : z] for z, n in zip(ends.tolist(), lengths.tolist())]
            decoded = [encoder.processor.decode(r.tolist()) for r in rows]
            sha = [hashlib.sha256(r.astype("<u4").tobytes()).hexdigest() for r in rows]
            back = [hashlib.sha256(d.encode()).hexdigest() for d in decoded]
            same = [a == b for a, b in zip(decoded, text.to_pylist())]
            out = [piece.column("doc_id"), pa.array(lengths), pa.array(sha), pa.array(back), pa.array(same)]
            if with_ids:
                out += [pa.ListArray.from_arrays(pa.array(np.concatenate([[0], ends]).astype(np.int32)), pa.array(ids.astype(np.int32))), pa.array(decoded)]
            yield pa.RecordBatch.from_arrays(out, names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256", "round_trip", "ids", "decoded"][: len(out)])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, f"doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string, round_trip boolean{extra}")
