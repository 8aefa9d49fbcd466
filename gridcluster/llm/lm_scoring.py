"""LM scoring: logistic mixing of hashed-context bit predictors, with gated weights and refinement.

A text is its tokens (lower-case words and one end). A token is spelled as bytes and a stop byte, a
byte as the bits of its path in a binary tree. Each bit is predicted by the counts of several contexts,
whose log-odds are mixed with weights that a gate picks.

Inside a word the contexts are the bytes before, in the class or in all training texts. They are counted
as rows on the executors and joined to the words that need them; weights and the table that maps a mixed
probability to the one observed are learned over a bounded number of training words. Those costs don't depend on where
a word stands, so each distinct word's are worked out once; over classes they form a Bayesian mixture
that follows the text.

The first bits of a word, which tell the group of letters that it opens with, are predicted again with
what lies before the word: the mixture's opinion at that place, the last bytes of the word before, and how the
word before last went on in this text. Their weights are learned online along the text. The rest of the
word keeps the mixture's probability given its group.
All bit probabilities are proper, so a text's score is the logarithm of a probability over all texts.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import materialise
from .common import coded, crc_bucket, give_back, mix64, row_of, slices, split_words, sums, texts

#: Topic classes: labels beyond the most frequent CLASSES - 1 ones share a class of their own.
CLASSES = 16
#: Spelling of the end token and of a word's end: no word holds white space.
END_TOKEN, STOP = "\n", " "
#: Context predictors inside a word: (bytes of context, 0 for the whole word so far; by class).
PREDICTORS = ((3, True), (0, True), (0, False))
#: Rates of the passes over training words in which the mixing weights are learned, and bytes between updates.
RATES, LEARN_BYTES = (0.5, 0.25, 0.12, 0.06), 4000
#: Bits whose mixed values wait to be noted in the refinement table at once.
NOTE_BITS = 1 << 16
PRIOR = 0.3
WORD_BATCH = 30_000
#: Text in a chunk whose words are looked up together.
CHUNK_BYTES = 24 << 20
#: Text whose words are counted at once, and words whose bytes are counted by one task.
COUNT_BYTES, TASK_WORDS = 8 << 20, 300_000
_STEP = 0xD6E8FEB86659FD93


class ByteTree:
    """A Huffman tree over bytes: path length, and the node and bit at each depth."""

    def __init__(self, counts: np.ndarray):
        heap = [(int(c) + 1, i, i) for i, c in enumerate(counts)]
        heapq.heapify(heap)
        parent: dict[int, tuple[int, int]] = {}
        fresh = 256
        while len(heap) > 1:
            a, b = heapq.heappop(heap), heapq.heappop(heap)
            parent[a[2]], parent[b[2]] = (fresh, 0), (fresh, 1)
            heapq.heappush(heap, (a[0] + b[0], fresh, fresh))
            fresh += 1
        paths = []
        for i in range(256):
            path, at = [], i
            while at in parent:
                at, bit = parent[at]
                path.append((at, bit))
            paths.append(path[::-1])
        self.length = np.array([len(p) for p in paths], dtype=np.int64)
        self.node = np.zeros((256, int(self.length.max())), dtype=np.uint64)
        self.bit = np.zeros(self.node.shape, dtype=np.int64)
        for i, p in enumerate(paths):
            for d, (n, b) in enumerate(p):
                self.node[i, d], self.bit[i, d] = n, b


def spelled(words: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of all words, each with its stop byte, and where each word begins."""
    if not len(words):
        return np.zeros(0, dtype=np.uint8), np.zeros(1, dtype=np.int64)
    joined = pc.binary_join_element_wise(words, "", STOP)
    offsets = np.frombuffer(joined.buffers()[1], dtype=np.int32)[joined.offset : joined.offset + len(joined) + 1].astype(np.int64)
    return np.frombuffer(joined.buffers()[2], dtype=np.uint8)[offsets[0] : offsets[-1]], offsets - offsets[0]


def word_hash(words: pa.Array) -> np.ndarray:
    """A 64-bit hash of each word's bytes, the same in all tasks."""
    data, offsets = spelled(words)
    if not len(data):
        return np.zeros(0, dtype=np.int64)
    powers, inverse = _powers(len(data))
    total = np.concatenate([np.zeros(1, dtype=np.uint64), np.cumsum((data.astype(np.uint64) + np.uint64(1)) * powers, dtype=np.uint64)])
    return mix64((total[offsets[1:]] - total[offsets[:-1]]) * inverse[offsets[:-1]]).view(np.int64)


_POWERS: list[np.ndarray] = []


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of an odd number and of its inverse, kept from call to call."""
    if not _POWERS or len(_POWERS[0]) < n:
        first = np.ones(1, dtype=np.uint64)
        size = max(n, 1 << 20)
        _POWERS[:] = [np.cumprod(np.concatenate([first, np.full(size, x, dtype=np.uint64)]), dtype=np.uint64) for x in (_STEP, pow(_STEP, -1, 1 << 64))]
    return _POWERS[0][:n], _POWERS[1][:n]


class Contexts:
    """Hashed contexts of every byte of some words, without the class."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray):
        n = len(data)
        self.data, self.word = data, row_of(offsets)
        place = np.arange(n) - offsets[:-1][self.word]
        self.start = place == 0
        self.hash = []
        wide = data.astype(np.uint64) + np.uint64(1)
        for length, _ in PREDICTORS:
            if length:
                h = np.zeros(n, dtype=np.uint64)
                for i in range(1, length + 1):
                    h[i:] |= np.where(place[i:] >= i, wide[:-i], np.uint64(0)) << np.uint64(9 * (i - 1))
            else:
                powers, inverse = _powers(n)
                total = np.concatenate([np.zeros(1, dtype=np.uint64), np.cumsum(wide * powers, dtype=np.uint64)])
                first = offsets[:-1][self.word]
                h = (total[:-1] - total[first]) * inverse[first]
            self.hash.append(mix64(h * np.uint64(2 * len(self.hash) + 3) + np.uint64(length)))


def odds(n0: np.ndarray, n1: np.ndarray) -> np.ndarray:
    return np.log((n1 + PRIOR) / (n0 + PRIOR)).astype(np.float32)


def level(n: np.ndarray) -> np.ndarray:
    """How often a context was seen (a whole number), in six steps."""
    return LEVELS.take(np.clip(n, 0, len(LEVELS) - 1).astype(np.int64))


LEVELS = np.searchsorted(np.array([0.5, 1.5, 3.5, 15.5, 127.5]), np.arange(129)).astype(np.uint8)


def gates(own: np.ndarray, shared: np.ndarray, three: np.ndarray, start: np.ndarray, depth: int) -> np.ndarray:
    """The weight set of a bit: how well the longest known context is known, whether the word begins, how deep in the tree.

    own, shared: levels of the word so far, within the class and in all; three: whether that context is known.
    """
    rank = np.where(own > 0, own - 1, np.where(shared > 0, 4 + np.minimum(shared, 3), np.where(three, 8, 9))).astype(np.int64)
    return (rank * 2 + start) * 4 + min(depth, 3)


N_GATES = 80
BUCKETS = 41


def squash(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -16, 16)))


def bucket(x: np.ndarray) -> np.ndarray:
    return np.clip(np.rint(x * 2.5) + BUCKETS // 2, 0, BUCKETS - 1).astype(np.int64)


class Mixer:
    """Gated weights, learned bit by bit in small batches, and the refinement table behind them."""

    def __init__(self):
        self.weights = np.full((N_GATES, len(PREDICTORS) + 1), 0.25)
        self.weights[:, -1] = 0
        grid = squash((np.arange(BUCKETS) - BUCKETS // 2) / 2.5)
        self.seen = np.stack([np.tile(1 - grid, (N_GATES, 1)), np.tile(grid, (N_GATES, 1))]) * 20
        self.mass = np.zeros(N_GATES)

    def step(self, x: np.ndarray, gate: np.ndarray, bit: np.ndarray, weight: np.ndarray, mass: np.ndarray, rate: float) -> np.ndarray:
        """Moves the weights of some bits, whose weights by gate are mass, and returns what was mixed before."""
        mixed = np.einsum("ij,ij->i", x, self.weights.take(gate, axis=0))
        error = (bit - squash(mixed)) * weight
        by = rate / np.maximum(mass, 1)
        for j in range(x.shape[1]):
            self.weights[:, j] += by * np.bincount(gate, weights=error * x[:, j], minlength=N_GATES)
        self.mass += mass
        return mixed

    def note(self, mixed: np.ndarray, gate: np.ndarray, bit: np.ndarray, weight: np.ndarray) -> None:
        """What was observed where so much was mixed; no step looks at it, so those of many steps are noted at once."""
        at = (bit * N_GATES + gate) * BUCKETS + bucket(mixed)
        self.seen += np.bincount(at, weights=weight, minlength=self.seen.size).reshape(self.seen.shape)

    def freeze(self) -> tuple[np.ndarray, np.ndarray]:
        return self.weights.astype(np.float32), (self.seen[1] / self.seen.sum(axis=0)).astype(np.float32)


def final(mixed: np.ndarray, gate: np.ndarray, refined: np.ndarray) -> np.ndarray:
    return np.clip(0.5 * squash(mixed) + 0.5 * refined[gate, bucket(mixed)], 1e-6, 1 - 1e-6)


#: Groups of first bytes; contexts of two bytes are hashed to so many.
GROUPS, PAIR_CONTEXTS = 8, 4096


def group_of(byte: np.ndarray) -> np.ndarray:
    """Eight groups of neighbouring letters: the first three bits of a word's first byte."""
    return (np.asarray(byte, dtype=np.int64) & 31) >> 2


class Tokens:
    """The tokens of the texts of a slice: words, and an end behind each text's last word."""

    def __init__(self, text: pa.Array):
        flat, self.offsets = split_words(text, lower=True)
        self.codes, self.distinct = coded(flat)
        n, row = len(text), row_of(self.offsets)
        size = len(flat) + n
        at, ends = np.arange(len(flat)) + row, self.offsets[1:] + np.arange(n)
        self.row = np.repeat(np.arange(n), np.diff(self.offsets) + 1)
        self.code = np.full(size, len(self.distinct), dtype=np.int64)  # the end: one more than the words
        self.code[at] = self.codes
        self.begin = np.concatenate([[0], ends[:-1] + 1]) if n else np.zeros(0, dtype=np.int64)
        data, bounds = spelled(self.distinct)
        first = np.append(data[bounds[:-1]], ord(END_TOKEN)).astype(np.int64) if len(data) else np.array([ord(END_TOKEN)])
        length = np.diff(bounds) - 1
        last = data[bounds[1:] - 2].astype(np.int64) if len(data) else np.zeros(0, dtype=np.int64)
        before = np.where(length > 1, data[np.maximum(bounds[1:] - 3, 0)], 0).astype(np.int64) if len(data) else last
        self.first = first[self.code]
        opens = np.zeros(size, dtype=bool)
        opens[self.begin] = True
        self.opens = opens
        # the token before, -1 where a text opens; a hash of the two bytes before, 0 there
        self.before = np.where(opens, -1, np.concatenate([[-1], self.code[:-1]])) if size else self.code
        two = np.append((before * 257 + last) * 40503 >> 4 & PAIR_CONTEXTS - 1, 0)
        self.two = np.where(opens, 0, two[np.maximum(self.before, 0)]) if size else self.code


def word_counts(docs: DataFrame, classes: int) -> DataFrame:
    """word, h, c0.. : every distinct word with its count by class in training texts (0 in others only).

    Rows whose word is a blank are no words, but count in c0 how often a byte begins the token behind
    two given bytes in training texts: h is context * 256 + byte.
    """
    names = [f"c{i}" for i in range(classes)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pairs = np.zeros(PAIR_CONTEXTS * 256, dtype=np.int64)
        for piece in slices(batches, "text", COUNT_BYTES):
            flat, offsets = split_words(texts(piece), lower=True)
            codes, distinct = coded(flat)
            held = piece.column("held_out").to_numpy(zero_copy_only=False)
            cls = np.where(held, classes, piece.column("cls").to_numpy())
            found = np.bincount(codes * (classes + 1) + cls[row_of(offsets)], minlength=len(distinct) * (classes + 1)).reshape(-1, classes + 1)
            yield pa.RecordBatch.from_arrays([distinct, pa.array(word_hash(distinct)), *(pa.array(found[:, i].astype(np.int64)) for i in range(classes))], names=["word", "h", *names])
            del flat, codes, distinct, found
            for part in slices(iter([piece.filter(pa.array(~held))]), "text"):
                t = Tokens(texts(part))
                pairs += np.bincount(t.two * 256 + t.first, minlength=len(pairs))
        at = np.nonzero(pairs)[0]
        zeros = pa.array(np.zeros(len(at), dtype=np.int64))
        yield pa.RecordBatch.from_arrays([pa.array([" "] * len(at), pa.string()), pa.array(at), pa.array(pairs[at]), *([zeros] * (classes - 1))], names=["word", "h", *names])

    rows = docs.mapInArrow(run, f"word string, h long, {', '.join(f'{n} long' for n in names)}")
    return rows.groupBy("word", "h").agg(*(F.sum(n).alias(n) for n in names))


#: Contexts of a word's first bytes are counted over all words; longer beginnings of words are counted where those words are.
PREFIX_BYTES = 3
#: Words that one task scores at once, and parts of a small vocabulary.
SCORE_WORDS, LEAST_PARTS = 40_000, 16
#: Predictors that look up the same contexts: three bytes, the word so far (within the class and in all).
FAMILIES = 2


def summed(key: np.ndarray, byte: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct (context, byte) pairs and the sums of their counts by class."""
    _, first, inverse = np.unique(pair_key(key, byte), return_index=True, return_inverse=True)
    n = np.stack([np.bincount(inverse, weights=counts[:, c], minlength=len(first)) for c in range(counts.shape[1])], axis=1)
    return key[first], byte[first], n


def across(counts: np.ndarray) -> np.ndarray:
    """Sums over classes."""
    out = counts[:, 0].copy()
    for c in range(1, counts.shape[1]):
        out += counts[:, c]
    return out


def pair_key(key: np.ndarray, value: np.ndarray) -> np.ndarray:
    return mix64(key + (value.astype(np.uint64) + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15))


class CountedContexts:
    """The counts of all contexts of some words' bytes: none shares a slot with another, however many there are.

    All contexts of a byte are parts of the word up to it, so bytes that end equal beginnings of words are one: `data`
    are the bytes of distinct beginnings, `of` tells which one each byte of the words is. rows are the counted
    (family, context, byte) of other tasks, and longer beginnings are counted from the words, which are all that begin alike.
    """

    def __init__(self, tree: ByteTree, spelling: tuple[np.ndarray, np.ndarray], counts: np.ndarray, rows: tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray], first_only: bool = False):
        data, offsets = spelling
        ctx = Contexts(data, offsets)
        place = np.arange(len(data)) - offsets[:-1][ctx.word]
        at = np.nonzero(place == 0)[0] if first_only else np.arange(len(data))
        _, first, self.of = np.unique(pair_key(ctx.hash[FAMILIES - 1][at], data[at]), return_index=True, return_inverse=True)
        self.word, pick = ctx.word[at], at[first]
        self.tree, self.data, self.start = tree, data[pick], ctx.start[pick]
        family, key, byte, n = rows
        self.families = []
        for f in range(FAMILIES):
            own = ctx.hash[f][pick]
            r = family == f
            rk, rb, rn = key[r], byte[r], n[r]
            if f == FAMILIES - 1:
                local = np.nonzero((place >= PREFIX_BYTES) & (counts.sum(axis=1) > 0)[ctx.word])[0]
                lk, lb, ln = summed(ctx.hash[f][local], data[local], counts[ctx.word[local]])
                rk, rb, rn = np.concatenate([rk, lk]), np.concatenate([rb, lb]), np.concatenate([rn, ln])
            # contexts by number: what is looked up lies in the order of what it is looked up in
            number = np.unique(np.concatenate([own, rk]), return_inverse=True)[1].astype(np.int64)
            pairs, inverse = np.unique(number[: len(own)] * 256 + self.data, return_inverse=True)
            order = np.argsort(number[len(own) :], kind="stable")
            self.families.append((pairs >> 8, pairs & 255, inverse, number[len(own) :][order], rb[order], rn[order]))

    def at_depth(self, d: int) -> list[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """For each family the zeros and ones (pairs x classes) seen at the node of depth d, and each byte's pair."""
        out = []
        node_of = self.tree.node[:, d].astype(np.int64) - 256
        for pk, pb, inverse, rk, rb, rn in self.families:
            deep = np.nonzero(self.tree.length[rb] > d)[0]
            nodes, place = np.unique(rk[deep] * 256 + node_of[rb[deep]], return_inverse=True)
            slot = 2 * place + self.tree.bit[rb[deep], d]
            seen = np.zeros((2 * len(nodes) + 2, rn.shape[1]))  # the last two: never seen
            for c in range(rn.shape[1]):
                seen[:-2, c] = np.bincount(slot, weights=rn[deep, c], minlength=2 * len(nodes))
            want = pk * 256 + node_of[pb]
            found = np.searchsorted(nodes, want)
            known = found < len(nodes)
            known[known] = nodes[found[known]] == want[known]
            pick = np.where(known, found, len(nodes)) * 2
            out.append((seen[pick], seen[pick + 1], inverse))
        return out

    def costs(self, n_words: int, classes: int, weights: np.ndarray, refined: np.ndarray) -> np.ndarray:
        """Natural log probability of each word under each class."""
        each = np.zeros((len(self.data), classes))
        for d in range(self.tree.node.shape[1]):
            b = np.nonzero(self.tree.length[self.data] > d)[0]
            if not len(b):
                break
            bit = self.tree.bit[self.data[b], d]
            found = self.at_depth(d)
            at = [inverse[b] for _, _, inverse in found]
            three, word = (odds(n0, n1) for n0, n1, _ in found)
            every = [across(n) for n in found[1][:2]]
            whole, shared = odds(*every)[at[1]], level(every[0] + every[1])[at[1]]
            known = level(found[1][0] + found[1][1])
            for c in range(classes):
                x = [three[at[0], c], word[at[1], c], whole]
                gate = gates(known[at[1], c], shared, x[0] != 0, self.start[b], d)
                w = weights.take(gate, axis=0)
                mixed = w[:, -1].copy()
                for k, v in enumerate(x):
                    mixed += w[:, k] * v
                p = final(mixed, gate, refined)
                each[b, c] += np.log(np.where(bit == 1, p, 1 - p))
        return np.stack([np.bincount(self.word, weights=each[self.of, c], minlength=n_words) for c in range(classes)], axis=1).astype(np.float32)

    def learn(self, mixer: Mixer, counts: np.ndarray, seed: int = 11) -> None:
        """Online passes over the bits of the words' training tokens (counts: words x classes), some beginnings of words
        at a time; each is predicted from the counts without itself."""
        weight = np.stack([np.bincount(self.of, weights=counts[self.word, c], minlength=len(self.data)) for c in range(counts.shape[1])], axis=1)
        total = weight[weight > 0]
        weight = np.minimum(weight / max(total.mean() if len(total) else 1.0, 1e-9), 2000.0)
        turn_of = np.random.default_rng(seed).permutation(len(self.data)) // LEARN_BYTES
        length = self.tree.length[self.data]
        steps: list[tuple] = []
        for d in range(self.tree.node.shape[1]):
            deep = np.nonzero(length > d)[0]
            if not len(deep):
                break
            found = self.at_depth(d)
            every = [(across(n0), across(n1)) if f else None for f, (n0, n1, _) in enumerate(found)]
            for c in range(counts.shape[1]):
                b = deep[weight[deep, c] > 0]
                b = b[np.argsort(turn_of[b], kind="stable")]
                bit = self.tree.bit[self.data[b], d]
                x, levels = np.ones((len(b), len(PREDICTORS) + 1), dtype=np.float32), []
                for f, (n0, n1, inverse) in enumerate(found):
                    for k, shared in ((f, False), *(((2, True),) if f else ())):
                        m0, m1 = (n[inverse[b]] for n in (every[f] if shared else (n0[:, c], n1[:, c])))
                        x[:, k] = odds(np.maximum(m0 - (bit == 0), 0), np.maximum(m1 - (bit == 1), 0))
                        if k:
                            levels.append(level(m0 + m1 - 1))
                gate = gates(*levels, x[:, 0] != 0, self.start[b], d)
                edges = np.searchsorted(turn_of[b], np.arange(turn_of.max() + 2))
                for turn in range(len(edges) - 1):
                    part = slice(edges[turn], edges[turn + 1])
                    if edges[turn] < edges[turn + 1]:
                        w = weight[b[part], c]
                        steps.append((turn, x[part], gate[part], bit[part], w, np.bincount(gate[part], weights=w, minlength=N_GATES)))
        steps.sort(key=lambda s: s[0])
        for rate in RATES:
            waiting, bits = [], 0
            for i, (_, *step) in enumerate(steps):
                waiting.append((mixer.step(*step, rate), *step[1:4]))
                bits += len(step[1])
                if bits >= NOTE_BITS or i == len(steps) - 1:
                    mixer.note(*map(np.concatenate, zip(*waiting)))
                    waiting, bits = [], 0


#: For each group its nodes and bits in a tree of three levels, the root first.
NODES = np.array([[0, 1 + (g >> 2), 3 + (g >> 1)] for g in range(GROUPS)])
BITS = np.array([[g >> 2 & 1, g >> 1 & 1, g & 1] for g in range(GROUPS)])
#: The same for a guessed group, behind them a row for no guess; signs instead of bits.
GUESS_NODES = np.concatenate([NODES, np.full((1, 3), -1)])
GUESS_SIGNS = np.concatenate([2 * BITS - 1, np.zeros((1, 3), dtype=np.int64)]).astype(np.float32)
#: Sights of a context that weigh as much as the overall share; tokens after which weights start anew; their rate.
SHRINK, SEGMENT_TOKENS, ONLINE_RATE = 8.0, 256, 0.02
#: Weights at a segment's begin: the mixture's log-odds; the gain by two bytes; the last follower here of the word before.
START = (1.0, 0.4, 0.6)


class Openings:
    """What the first bits of a token, the group of its first byte, are predicted from.

    log_p: log probability of each byte as a token's first under each class, the end token's included.
    two: how often a byte opened a token behind two given bytes, in all training texts.
    """

    def __init__(self, log_p: np.ndarray, two: np.ndarray):
        member = np.eye(GROUPS)[group_of(np.arange(256))]
        self.p = np.exp(log_p) @ member
        seen, ones = (v[0] for v in node_counts((two.sum(axis=0) @ member)[None]))
        self.overall = (ones + 0.5) / (seen + 1)
        self.base = np.log(self.overall / (1 - self.overall))
        # by context and node: what the context adds to the overall log-odds; little where it is rare
        self.two = np.clip(self.gain(*node_counts(two @ member), np.arange(7)), -8, 8).astype(np.float32)

    def gain(self, seen: np.ndarray, ones: np.ndarray, node: np.ndarray) -> np.ndarray:
        p = (ones + SHRINK * self.overall[node]) / (seen + SHRINK)
        return np.log(p / (1 - p)) - self.base[node]


def node_counts(by_group: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """From counts by group the counts under each of the seven nodes, and those on its side of ones."""
    pairs = by_group[:, 0::2] + by_group[:, 1::2]
    halves = pairs[:, 0::2] + pairs[:, 1::2]
    return np.concatenate([halves.sum(axis=1, keepdims=True), halves, pairs], axis=1), np.concatenate([halves[:, 1:], pairs[:, 1::2], by_group[:, 1::2]], axis=1)


def path_counts(by_group: np.ndarray, group: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The `node_counts` of rows at, only under the three nodes of their groups."""
    flat = np.ascontiguousarray(by_group).reshape(-1)
    pairs = flat[0::2] + flat[1::2]
    halves = pairs[0::2] + pairs[1::2]
    half, pair = 2 * at + (group >> 2), 4 * at + (group >> 1)
    mass, ones = (np.empty((len(at), 3), dtype=flat.dtype) for _ in range(2))
    mass[:, 0], mass[:, 1], mass[:, 2] = (halves[0::2] + halves[1::2]).take(at), halves.take(half), pairs.take(pair)
    ones[:, 0], ones[:, 1], ones[:, 2] = halves.take(2 * at + 1), pairs.take(2 * half + 1), flat.take(2 * pair + 1)
    return mass, ones


def followers(t: Tokens) -> np.ndarray:
    """The first byte of what followed the same word the last time in the same text, -1 if it is new there."""
    out = np.full(len(t.code), -1, dtype=np.int64)
    inner = np.nonzero(~t.opens)[0]
    key = t.row[inner] * (len(t.distinct) + 1) + t.before[inner]
    order = np.argsort(key, kind="stable")
    again = np.concatenate([[False], key[order][1:] == key[order][:-1]]) if len(order) else np.zeros(0, dtype=bool)
    out[inner[order[again]]] = t.first[inner[order[np.nonzero(again)[0] - 1]]]
    return out


def opening_costs(f: Openings, t: Tokens, mixture: np.ndarray) -> np.ndarray:
    """Natural log probability of the group that each token opens with, mixed online along segments of the texts.

    mixture: the class mixture's probability of each group before each token.
    """
    n = len(t.code)
    if not n:
        return np.zeros(0)
    # lanes: segments of texts, all one token further at a time; the longest are the first, so those still live are in front
    place = (np.arange(n) - t.begin[t.row]) % SEGMENT_TOKENS
    first = np.nonzero(place == 0)[0]
    length = np.diff(np.append(first, n))
    rank = np.empty(len(first), dtype=np.int64)
    rank[np.argsort(-length, kind="stable")] = np.arange(len(first))
    live = np.cumsum(np.bincount(length)[::-1])[::-1][1:]  # lanes of more than 0, 1, .. tokens
    ends = np.cumsum(live)
    # tokens in the order in which they are learned from: a step's lie side by side
    turn = np.empty(n, dtype=np.int64)
    turn[(ends - live)[place] + np.repeat(rank, length)] = np.arange(n)
    group = group_of(t.first[turn])
    node, bit = NODES.take(group, axis=0), BITS.take(group, axis=0).astype(np.float32).reshape(-1)
    mass, ones = path_counts(mixture, group, turn)
    share = np.clip(ones / np.maximum(mass, 1e-300), 1e-6, 1 - 1e-6).astype(np.float32)
    mix = np.clip(np.log(share / (1 - share)), -8, 8).reshape(-1)
    guess = followers(t)[turn]
    guessed = np.where(guess >= 0, group_of(np.maximum(guess, 0)), GROUPS)
    on = GUESS_NODES.take(guessed, axis=0) == node
    two = f.two.reshape(-1).take((t.two[turn, None] * 7 + node).reshape(-1))
    sign = (GUESS_SIGNS.take(guessed, axis=0) * on).reshape(-1)
    # the three bits of a lane have weights of their own, those of mix and two also by whether a guess is on
    slot = np.arange(3 * len(first)) * 2
    w_mix, w_two = (np.full(2 * len(slot), w, dtype=np.float32) for w in START[:2])
    w_sign = np.full(len(slot), START[2], dtype=np.float32)
    on = on.reshape(-1).astype(np.int8)
    p = np.empty(3 * n, dtype=np.float32)
    for a, b in zip((3 * (ends - live)).tolist(), (3 * ends).tolist()):
        own = slot[: b - a] + on[a:b]
        x, y, z = mix[a:b], two[a:b], sign[a:b]
        u, v, w = w_mix.take(own), w_two.take(own), w_sign[: b - a]
        total = x * u
        total += y * v
        total += z * w
        q = p[a:b]
        np.exp(np.negative(total, out=total), out=total)
        total += 1
        np.divide(1, total, out=q)
        change = ONLINE_RATE * (bit[a:b] - q)
        w_mix[own] = u + change * x
        w_two[own] = v + change * y
        w += change * z
    p = np.clip(p, 1e-6, 1 - 1e-6)
    out = np.empty(n)
    each = np.log(np.where(bit == 1, p, 1 - p)).reshape(-1, 3).astype(np.float64)
    out[turn] = across(each)
    return out


def context_rows(used: DataFrame, classes: int, tasks: int) -> DataFrame:
    """f, key, byte, c0.. : how often each byte follows each short context or beginning of a word, over all training words."""
    names = [f"c{i}" for i in range(classes)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list = [[] for _ in range(FAMILIES)]

        def merge() -> None:
            for f, parts in enumerate(held):
                if len(parts) > 1:
                    held[f] = [summed(*(np.concatenate(x) for x in zip(*parts)))]

        waiting = 0
        for batch in batches:
            for a in range(0, batch.num_rows, WORD_BATCH):
                part = batch.slice(a, WORD_BATCH)
                counts = np.stack([part.column(n).to_numpy() for n in names], axis=1).astype(np.float64)
                data, offsets = spelled(part.column("word"))
                ctx = Contexts(data, offsets)
                early = np.nonzero(np.arange(len(data)) - offsets[:-1][ctx.word] < PREFIX_BYTES)[0]
                for f in range(FAMILIES):
                    at = early if f == FAMILIES - 1 else np.arange(len(data))
                    held[f].append(summed(ctx.hash[f][at], data[at], counts[ctx.word[at]]))
                waiting += 1
                if waiting % 16 == 0:
                    merge()
        merge()
        for f, parts in enumerate(held):
            for key, byte, n in parts:
                for a in range(0, len(key), 100_000):
                    cut = slice(a, a + 100_000)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(key[cut]), f, dtype=np.int32)), pa.array(key[cut].view(np.int64)), pa.array(byte[cut].astype(np.int32)), *(pa.array(n[cut, i].astype(np.int64)) for i in range(classes))], names=["f", "key", "byte", *names])

    rows = used.coalesce(tasks).mapInArrow(run, f"f int, key long, byte int, {', '.join(f'{n} long' for n in names)}")
    return rows.groupBy("f", "key", "byte").agg(*(F.sum(n).alias(n) for n in names))


def with_contexts(words: DataFrame, contexts: DataFrame, chosen: np.ndarray | None = None) -> DataFrame:
    """p, f, key, byte, c0.. : the counted contexts that the words of each part p need; only of the words whose h is chosen, if given."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if chosen is not None:
                b = b.filter(pa.array(np.isin(b.column("h").to_numpy(), chosen)))
            if not b.num_rows:
                continue
            data, offsets = spelled(b.column("word"))
            ctx = Contexts(data, offsets)
            early = np.arange(len(data)) - offsets[:-1][ctx.word] < PREFIX_BYTES
            own = b.column("p").to_numpy()
            for p in np.unique(own):
                mine = (own == p)[ctx.word]
                for f in range(FAMILIES):
                    key = np.unique(ctx.hash[f][mine & early if f == FAMILIES - 1 else mine])
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(key), p, dtype=np.int64)), pa.array(np.full(len(key), f, dtype=np.int32)), pa.array(key.view(np.int64))], names=["p", "f", "key"])

    needed = words.sortWithinPartitions("p").mapInArrow(run, "p long, f int, key long").distinct()
    return needed.join(contexts, ["f", "key"]).select("p", *contexts.columns)


def numbers(table: pa.Table, names: list[str]) -> np.ndarray:
    return np.stack([table[n].to_numpy() for n in names], axis=1).astype(np.float64)


def even_labels(spark: SparkSession, n: int) -> DataFrame:
    """place 0..n-1 and a label each, such that rows dealt by the label's hash to n partitions lie in as many partitions as there are labels."""
    tries = spark.range(n * 40 + 200).select(F.pmod(F.hash("id"), F.lit(n)).alias("place"), F.col("id").alias("label"))
    return tries.groupBy("place").agg(F.min("label").alias("label"))


class WordScorer:
    """Counted contexts in parts by the words' first bytes, and the mixing learned over them."""

    def __init__(self, spark: SparkSession, vocabulary: DataFrame, train_docs: list[int], n_words: int):
        self.classes = len(train_docs)
        self.names = [f"c{i}" for i in range(self.classes)]
        words = vocabulary.where("NOT startswith(word, ' ')")
        end_hash = int(word_hash(pa.array([END_TOKEN]))[0])
        end = spark.createDataFrame([(END_TOKEN, end_hash, *map(int, train_docs))], vocabulary.schema)
        parts = max(LEAST_PARTS, n_words // SCORE_WORDS + 1)  # by the words alone: scores don't depend on the cluster
        part = F.pmod(F.xxhash64(F.expr(f"substring(CAST(word AS BINARY), 1, {PREFIX_BYTES})")), F.lit(parts)).alias("p")
        self.words = materialise(spark, words.unionByName(end).select("word", "h", *self.names, part).repartition(parts, "p"), "scored-words")
        used = self.words.where(" + ".join(self.names) + " > 0")
        self.tree = self._tree(used)
        contexts = materialise(spark, context_rows(used, self.classes, n_words // TASK_WORDS + 1), "contexts")
        self.near = materialise(spark, with_contexts(self.words, contexts), "near-contexts")
        self.weights, self.refined = self._mixer(used).freeze()
        self.shares = (np.array(train_docs) + 0.5) / (sum(train_docs) + 0.5 * self.classes)
        self.first = self._openings(vocabulary, contexts)

    def _tree(self, used: DataFrame) -> ByteTree:
        names = self.names

        def byte_counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total = np.zeros(256)
            for b in batches:
                data, offsets = spelled(b.column("word"))
                count = sum(b.column(n).to_numpy() for n in names)
                total += np.bincount(data, weights=count[row_of(offsets)], minlength=256)
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(256)), pa.array(total.astype(np.int64))], names=["byte", "n"])

        counts = np.zeros(256)
        for r in used.mapInArrow(byte_counts, "byte long, n long").groupBy("byte").agg(F.sum("n").alias("n")).collect():
            counts[r["byte"]] = r["n"]
        return ByteTree(counts)

    def _mixer(self, used: DataFrame) -> Mixer:
        """Each part of the vocabulary learns online over all its training words, each without itself in the counts; the
        parts' weights are averaged by what each has seen, their refinement counts added."""
        tree, names, classes = self.tree, self.names, self.classes

        def run(left: pa.Table, right: pa.Table) -> pa.Table:
            counts = numbers(left, names)
            words = left["word"].combine_chunks()
            words = words.chunk(0) if isinstance(words, pa.ChunkedArray) else words
            mixer = Mixer()
            empty = mixer.seen.copy()
            if len(counts):
                CountedContexts(tree, spelled(words), counts, _rows(right, names)).learn(mixer, counts)
                give_back()
            values = np.concatenate([(mixer.weights * mixer.mass[:, None]).ravel(), mixer.mass, (mixer.seen - empty).ravel()])
            return pa.table({"cell": pa.array(np.arange(len(values))), "value": pa.array(values)})

        out = Mixer()
        total = np.zeros(out.weights.size + N_GATES + out.seen.size)
        learned = used.groupBy("p").cogroup(self.near.groupBy("p")).applyInArrow(run, "cell long, value double")
        for r in learned.groupBy("cell").agg(F.sum("value").alias("value")).collect():  # as many rows as the mixer has numbers
            total[r["cell"]] = r["value"]
        weights, mass, seen = np.split(total, [out.weights.size, out.weights.size + N_GATES])
        some = mass > 0
        out.weights[some] = weights.reshape(out.weights.shape)[some] / mass[some, None]
        out.seen += seen.reshape(out.seen.shape)
        return out

    def _openings(self, vocabulary: DataFrame, contexts: DataFrame) -> Openings:
        tree, names = self.tree, self.names
        data, offsets = np.stack([np.arange(256, dtype=np.uint8), np.full(256, ord(STOP), dtype=np.uint8)], axis=1).reshape(-1), np.arange(257, dtype=np.int64) * 2
        keys = [int(x) for x in {int(h[0]) for h in Contexts(data, offsets).hash}]
        keys = np.array(keys, dtype=np.uint64).view(np.int64).tolist()
        rows = contexts.where(F.col("key").isin(keys)).toArrow()  # 256 bytes a family
        found = CountedContexts(tree, (data, offsets), np.zeros((256, self.classes)), _rows(rows, names), first_only=True)
        log_p = found.costs(256, self.classes, self.weights, self.refined).T.astype(np.float64)
        rows = vocabulary.where("startswith(word, ' ')").select("h", "c0").toArrow()  # bounded by contexts x bytes
        two = np.bincount(rows["h"].to_numpy(), weights=rows["c0"].to_numpy(), minlength=PAIR_CONTEXTS * 256).reshape(PAIR_CONTEXTS, 256)
        return Openings(log_p, two)

    def scored(self) -> DataFrame:
        """h, c (training tokens), cost (log probability under each class) of every word and of the end token."""
        tree, names, classes, weights, refined = self.tree, self.names, self.classes, self.weights, self.refined

        def run(left: pa.Table, right: pa.Table) -> pa.Table:
            counts = numbers(left, names)
            words = left["word"].combine_chunks()
            words = words.chunk(0) if isinstance(words, pa.ChunkedArray) else words
            found = CountedContexts(tree, spelled(words), counts, _rows(right, names))
            cost = found.costs(len(counts), classes, weights, refined)
            del found
            give_back()
            raw = pa.py_buffer(np.ascontiguousarray(cost).tobytes())
            return pa.table({"h": left["h"], "c": pa.array(counts.sum(axis=1).astype(np.int64)), "cost": pa.FixedSizeBinaryArray.from_buffers(pa.binary(4 * classes), len(counts), [None, raw]).cast(pa.binary())})

        return self.words.groupBy("p").cogroup(self.near.groupBy("p")).applyInArrow(run, "h long, c long, cost binary")


def _rows(table: pa.Table, names: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    return table["f"].to_numpy(), table["key"].to_numpy().view(np.uint64), table["byte"].to_numpy(), numbers(table, names)


def text_scores(first: Openings, t: Tokens, cost: np.ndarray, log_shares: np.ndarray) -> np.ndarray:
    """Natural log probability of each text; cost: of each token under each class."""
    total = np.cumsum(cost, axis=0, dtype=np.float64)
    before = total - cost
    before -= before.take(t.begin[t.row], axis=0)
    before += log_shares
    post = (before - _peak(before)[:, None]).astype(np.float32)
    post -= _log_sum(post)[:, None]
    token = _log_sum(post + cost)
    mixture = np.exp(post) @ first.p.astype(np.float32)
    opening = np.log(mixture[np.arange(len(mixture)), group_of(t.first)])
    return np.bincount(t.row, weights=token - opening + opening_costs(first, t, mixture), minlength=len(t.begin))


def _peak(x: np.ndarray) -> np.ndarray:
    out = x[:, 0].copy()
    for c in range(1, x.shape[1]):
        np.maximum(out, x[:, c], out=out)
    return out


def _log_sum(x: np.ndarray) -> np.ndarray:
    peak = _peak(x)
    return peak + np.log(across(np.exp(x - peak[:, None])))


def score_documents(spark: SparkSession, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", class_col: str | None = "lang", buckets: int = 5, held: int = 1, classes: int = CLASSES) -> DataFrame:
    """Base and model scores of all whole texts, learned from those whose id's crc32 mod 5 isn't 1.

    Null or empty text is the end token alone. class_col names classes of training texts (a null label
    counts as the first class; of more than `classes` labels the rarer ones share the last class); it is
    never looked at when a text is scored. Without it, or with one value, there is one class.
    Rows that repeat are scored each; other columns are not looked at; an empty table gives no row.
    Returns doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score, bits_per_byte.
    """
    held_out = crc_bucket(id_col, buckets) == held
    label = F.col(class_col).cast("string") if class_col else F.lit(None).cast("string")
    light = docs.select(label.alias("label"), held_out.alias("held_out"), F.coalesce(F.octet_length(text_col), F.lit(0)).alias("size"))
    by = light.groupBy("label", "held_out").agg(F.count(F.lit(1)).alias("n"), F.sum("size").alias("size"))
    top = by.where(~F.col("held_out") & F.col("label").isNotNull()).orderBy(F.col("n").desc(), "label").limit(classes + 1).collect()
    labels = [r["label"] for r in top][: classes if len(top) <= classes else classes - 1]
    overall = by.agg(F.coalesce(F.sum("size"), F.lit(0)).alias("size"), F.coalesce(F.sum(F.when(~F.col("held_out"), F.col("n"))), F.lit(0)).alias("train"), F.coalesce(F.sum(F.when(~F.col("held_out") & F.col("label").isNull(), F.col("n"))), F.lit(0)).alias("unnamed")).first()
    train_docs = [r["n"] for r in top][: len(labels)] or [0]
    train_docs[0] += overall["unnamed"]
    if len(top) > classes:
        train_docs.append(overall["train"] - sum(train_docs))
    classes = len(train_docs)
    number = F.when(label.isNull(), F.lit(0))
    for i, x in enumerate(labels):
        number = number.when(label == x, F.lit(i))
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"), held_out.alias("held_out"), number.otherwise(F.lit(classes - 1)).cast("int").alias("cls"))
    vocabulary = materialise(spark, word_counts(rows, classes), "vocabulary")
    c = " + ".join(f"c{i}" for i in range(classes))
    words = vocabulary.where("NOT startswith(word, ' ')")
    size = words.agg(F.coalesce(F.sum(F.expr(c)), F.lit(0)).alias("n"), F.count(F.when(F.expr(c) > 0, 1)).alias("v"), F.count(F.lit(1)).alias("all")).first()
    n_train, v = size["n"] + overall["train"], size["v"] + (overall["train"] > 0)
    scorer = WordScorer(spark, vocabulary, train_docs, int(size["all"]))
    scored = scorer.scored()
    log_shares, first = np.log(scorer.shares), spark.sparkContext.broadcast(scorer.first)  # tables of fixed size
    end_hash = word_hash(pa.array([END_TOKEN]))
    # no fewer chunks than shuffle partitions: else the text would be dealt out a second time
    chunks = max(int(overall["size"] // CHUNK_BYTES) + 1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    placed = rows.drop("cls").withColumn("place", F.pmod(F.xxhash64("doc_id", "text"), F.lit(chunks)).cast("int"))
    chunked = placed.join(F.broadcast(even_labels(spark, chunks)), "place").drop("place").withColumnRenamed("label", "chunk").repartition(chunks, "chunk")

    def needed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list[np.ndarray]] = {}
        for piece in slices(batches, "text"):
            own = piece.column("chunk").to_numpy()
            for c in np.unique(own).tolist():
                flat, _ = split_words(texts(piece.filter(pa.array(own == c))), lower=True)
                parts = held.setdefault(c, [end_hash])
                parts.append(word_hash(pc.unique(flat)))
                if len(parts) > 8:
                    held[c] = [np.unique(np.concatenate(parts))]
        for c, parts in held.items():
            h = np.unique(np.concatenate(parts))
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(h), c)), pa.array(h)], names=["chunk", "h"])

    looked_up = chunked.mapInArrow(needed, "chunk long, h long").join(scored, "h").select("chunk", "h", "c", "cost")
    ln10 = np.log(10)
    base_end = np.log10(overall["train"] + 0.5)
    norm = np.log10(n_train + 0.5 * (v + 1))

    def combine(left: pa.Table, right: pa.Table) -> pa.Table:
        h = right["h"].to_numpy()
        order = np.argsort(h, kind="stable")
        cost_column = right["cost"].combine_chunks()
        cost_column = cost_column.chunk(0) if isinstance(cost_column, pa.ChunkedArray) else cost_column
        table = np.frombuffer(b"".join(cost_column.to_pylist()), dtype=np.float32).reshape(-1, classes)[order]
        h, count = h[order], right["c"].to_numpy()[order]
        end_cost = table[np.searchsorted(h, end_hash[0])]
        out = []
        for piece in slices(iter(left.combine_chunks().to_batches()), "text"):
            t = Tokens(texts(piece))
            own = word_hash(t.distinct)
            by = np.argsort(own)
            at = np.empty(len(own), dtype=np.int64)
            at[by] = np.searchsorted(h, own[by])  # in order: near places in memory
            seen = count[at] if len(at) else np.zeros(0, dtype=np.int64)
            base = sums(np.log10(seen + 0.5)[t.codes], t.offsets) + base_end
            n_tokens = np.diff(t.offsets) + 1
            cost = np.concatenate([table.take(at, axis=0), end_cost[None]]).take(t.code, axis=0)
            score = text_scores(first.value, t, cost, log_shares) / ln10
            letters = pc.binary_length(t.distinct).to_numpy(zero_copy_only=False).astype(np.int64)
            spelled_bytes = sums(letters[t.codes] + 1, t.offsets) + 2
            known = sums((seen > 0)[t.codes].astype(np.int64), t.offsets) + int(overall["train"] > 0)
            out.append(pa.RecordBatch.from_arrays([piece.column("doc_id"), piece.column("held_out"), pa.array(n_tokens), pa.array(known), pa.array(np.full(len(n_tokens), n_train)), pa.array(base - n_tokens * norm), pa.array(score), pa.array(-score * ln10 / np.log(2) / spelled_bytes)], names=["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score", "bits_per_byte"]))
        return pa.Table.from_batches(out, schema=_OUT)

    return chunked.groupBy("chunk").cogroup(looked_up.groupBy("chunk")).applyInArrow(combine, "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double, bits_per_byte double")


_OUT = pa.schema([("doc_id", pa.int64()), ("held_out", pa.bool_()), ("n_tokens", pa.int64()), ("n_known", pa.int64()), ("train_tokens", pa.int64()), ("base_score", pa.float64()), ("score", pa.float64()), ("bits_per_byte", pa.float64())])
