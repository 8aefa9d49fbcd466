"""Counted contexts of the scoring model against plain counting."""

from __future__ import annotations

import collections

import numpy as np
import pyarrow as pa
import pytest

from gridcluster.llm import lm_scoring


def test_no_two_contexts_share_a_count(spark):
    """Every (context, node, bit) of every part has exactly its own counts: nothing is added up in a slot."""
    rng = np.random.default_rng(3)
    words = sorted({"".join(rng.choice(list("abcdeé"), rng.integers(1, 9))) for _ in range(600)})
    counts = rng.integers(0, 4, (len(words), 2))
    tree = lm_scoring.ByteTree(rng.integers(0, 50, 256))
    expected = [collections.Counter() for _ in range(2)]

    def contexts(word):
        data = (word + lm_scoring.STOP).encode()
        for i, byte in enumerate(data):
            for f, length in enumerate((3, len(data))):
                before = data[max(0, i - length) : i]
                for d in range(tree.length[byte]):
                    yield f, i, d, (before, int(tree.node[byte, d]), int(tree.bit[byte, d]))

    for w, n in zip(words, counts):
        for f, _, _, key in contexts(w):
            for c in (0, 1):
                expected[f][(*key, c)] += int(n[c])
    rows = [(w, i, int(n[0]), int(n[1]), sum(w.encode()[:3]) % 4) for i, (w, n) in enumerate(zip(words, counts))]
    table = spark.createDataFrame(rows, "word string, h long, c0 long, c1 long, p long").repartition(4, "p").cache()
    found = lm_scoring.context_rows(table.where("c0 + c1 > 0"), 2, 2).cache()
    near = lm_scoring.with_contexts(table, found).toPandas()
    for p in range(4):
        mine, part = [r for r in rows if r[4] == p], near[near.p == p]
        joined = (part.f.to_numpy(), part.key.to_numpy().view(np.uint64), part.byte.to_numpy(), part[["c0", "c1"]].to_numpy().astype(float))
        got = lm_scoring.CountedContexts(tree, lm_scoring.spelled(pa.array([r[0] for r in mine])), np.array([r[2:4] for r in mine], dtype=float), joined)
        at_depth = [got.at_depth(d) for d in range(int(tree.length.max()))]
        first = 0
        for r in mine:
            for f, i, d, (before, node, _) in contexts(r[0]):
                n0, n1, pair = at_depth[d][f]
                for c in (0, 1):
                    assert n0[pair[got.of[first + i]], c] == expected[f][(before, node, 0, c)] and n1[pair[got.of[first + i]], c] == expected[f][(before, node, 1, c)]
            first += len(r[0].encode()) + 1


def test_parts_give_the_score_of_one_part(spark, monkeypatch):
    """With the same weights, however the vocabulary is parted."""
    monkeypatch.setattr(lm_scoring.WordScorer, "_mixer", lambda self, used: lm_scoring.Mixer())
    texts = [(i, " ".join(f"w{(i * j) % 97}x{j % 7}" for j in range(1, 60)), "ab"[i % 2]) for i in range(40)]
    docs = spark.createDataFrame(texts, "doc_id long, text string, lang string")
    one = {r["doc_id"]: r["score"] for r in lm_scoring.score_documents(spark, docs).collect()}
    monkeypatch.setattr(lm_scoring, "LEAST_PARTS", 1)
    many = {r["doc_id"]: r["score"] for r in lm_scoring.score_documents(spark, docs).collect()}
    assert many == pytest.approx(one, rel=1e-6)


def test_weights_are_learned_from_all_parts(spark, monkeypatch):
    """What the mixer has seen is the sum over all parts of the vocabulary, however many there are."""
    made = []

    class Kept(lm_scoring.WordScorer):
        def __init__(self, *args):
            super().__init__(*args)
            made.append(self)

    monkeypatch.setattr(lm_scoring, "WordScorer", Kept)
    monkeypatch.setattr(lm_scoring, "LEAST_PARTS", 24)
    rng = np.random.default_rng(5)
    docs = spark.createDataFrame([(i, " ".join("".join(rng.choice(list("abcdefgh"), 5)) for _ in range(20)), "a") for i in range(30)], "doc_id long, text string, lang string")
    lm_scoring.score_documents(spark, docs)
    scorer, start = made[0], lm_scoring.Mixer().seen
    used = scorer.words.where("c0 > 0")
    late, early = (scorer._mixer(used.where(c)).seen - start for c in ("p >= 16", "p < 16"))
    assert late.sum() > 0 and early.sum() > 0
    assert scorer._mixer(used).seen - start == pytest.approx(late + early)
