"""Scoring, language ID, sharding and quality rules: brute force, held-out accuracy, laws."""

from __future__ import annotations

import collections
import math
import re
import zlib

import numpy as np
import pyarrow as pa
import pytest

from gridcluster.llm import language_id, lm_scoring, quality, sharding
from gridcluster.llm.common import crc_bucket

WORD = re.compile(r"[^\x20\x09-\x0D]+")
LOW = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def crc(i, m):
    return zlib.crc32(str(i).encode()) % m


def test_base_scores_and_probability(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet").select("doc_id", "text", "lang")
    extra = spark.createDataFrame([(900_001, None, None), (900_002, "", "en")], docs.schema)
    docs = docs.unionAll(extra)
    got = lm_scoring.score_documents(spark, docs).collect()
    rows = docs.collect()
    tokens = {r["doc_id"]: [w.translate(LOW) for w in WORD.findall(r["text"] or "")] + [None] for r in rows}
    train = collections.Counter(t for i, ts in tokens.items() if crc(i, 5) != 1 for t in ts)
    n, v = sum(train.values()), len(train)
    assert len(got) == len(rows)
    for r in got:
        ts = tokens[r["doc_id"]]
        assert r["n_tokens"] == len(ts) and r["n_known"] == sum(train[t] > 0 for t in ts) and r["train_tokens"] == n
        assert r["held_out"] == (crc(r["doc_id"], 5) == 1)
        assert r["base_score"] == pytest.approx(sum(math.log10((train[t] + 0.5) / (n + 0.5 * (v + 1))) for t in ts), rel=1e-9)
        assert r["score"] < 0 and r["bits_per_byte"] > 0
    assert lm_scoring.score_documents(spark, docs.limit(0)).count() == 0


def test_trees_are_distributions():
    rng = np.random.default_rng(0)
    tree = lm_scoring.ByteTree(rng.integers(0, 50, 256))
    assert sum(2.0 ** -int(n) for n in tree.length) == pytest.approx(1.0)
    p = rng.random((2, 256))
    f = lm_scoring.Openings(np.log(p / p.sum(axis=1, keepdims=True)), rng.integers(0, 3, (lm_scoring.PAIR_CONTEXTS, 256)))
    assert f.p.sum(axis=1) == pytest.approx([1.0, 1.0])
    # whatever a node's probability, its two sides share it: the eight groups have all of it
    q = rng.random(7)
    paths = [np.prod([q[n] if v else 1 - q[n] for n, v in zip(lm_scoring.NODES[g], lm_scoring.BITS[g])]) for g in range(8)]
    assert sum(paths) == pytest.approx(1.0)
    mass, ones = lm_scoring.node_counts(f.p)
    for g in range(8):
        shares = [ones[0, n] / mass[0, n] for n in lm_scoring.NODES[g]]
        assert np.prod([s if v else 1 - s for s, v in zip(shares, lm_scoring.BITS[g])]) == pytest.approx(f.p[0, g])


class Scalar:
    """The same model in plain Python, one bit at a time, from counted training tokens."""

    def __init__(self, scorer, train):  # train: (tokens, class) of each training text
        self.s, self.f, self.k = scorer, scorer.first, scorer.classes
        self.counts = collections.defaultdict(lambda: np.zeros(self.k))  # (predictor length, context, byte) -> by class
        for tokens, cls in train:
            for t in tokens:
                for length, context, byte in self.contexts(t):
                    self.counts[length, context, byte][cls] += 1

    def contexts(self, token):
        word = token + b" "
        for i, byte in enumerate(word):
            for length in (3, 0):
                yield length, word[max(0, i - length) if length else 0 : i], byte

    def cost(self, token, first_only=False):
        """Log probability under each class."""
        tree, out, word = self.s.tree, np.zeros(self.k), token + b" "
        for i, byte in enumerate(word[:1] if first_only else word):
            for d in range(int(tree.length[byte])):
                node, bit = tree.node[byte, d], tree.bit[byte, d]
                n = {}
                for length in (3, 0):
                    context = word[max(0, i - length) if length else 0 : i]
                    n[length] = np.zeros((2, self.k))
                    for b in range(256):
                        if tree.length[b] > d and tree.node[b, d] == node and (length, context, b) in self.counts:
                            n[length][tree.bit[b, d]] += self.counts[length, context, b]
                odds = lambda a: math.log((a[1] + lm_scoring.PRIOR) / (a[0] + lm_scoring.PRIOR))
                level = lambda a: int(np.searchsorted([0.5, 1.5, 3.5, 15.5, 127.5], a))
                whole = odds(n[0].sum(axis=1))
                for c in range(self.k):
                    x = [odds(n[3][:, c]), odds(n[0][:, c]), whole]
                    own, shared = level(n[0][:, c].sum()), level(n[0].sum())
                    rank = own - 1 if own else 4 + min(shared, 3) if shared else 8 if x[0] else 9
                    gate = (rank * 2 + (i == 0)) * 4 + min(d, 3)
                    w = self.s.weights[gate]
                    mixed = float(w[-1] + sum(a * b for a, b in zip(w[:-1], x)))
                    p = 1 / (1 + math.exp(-max(-16, min(16, mixed))))
                    bucket = max(0, min(lm_scoring.BUCKETS - 1, round(mixed * 2.5) + lm_scoring.BUCKETS // 2))
                    p = max(1e-6, min(1 - 1e-6, 0.5 * p + 0.5 * float(self.s.refined[gate, bucket])))
                    out[c] += math.log(p if bit else 1 - p)
        return out

    def score(self, tokens):
        f, total, before = self.f, 0.0, np.log(self.s.shares)
        weights, seen = None, {}
        for i, t in enumerate(tokens):
            if i % lm_scoring.SEGMENT_TOKENS == 0:
                weights = collections.defaultdict(lambda: np.array(lm_scoring.START, dtype=np.float64))
            post = np.exp(before - before.max())
            post /= post.sum()
            cost = self.cost(t)
            byte, prev = t[0], tokens[i - 1] if i else None
            group = (byte & 31) >> 2
            total += math.log(post @ np.exp(cost)) - math.log(post @ f.p[:, group])
            two = ((prev[-2] if len(prev) > 1 else 0) * 257 + prev[-1]) * 40503 >> 4 & lm_scoring.PAIR_CONTEXTS - 1 if i else 0
            mixture = post @ f.p
            guess = seen.get(prev, -1) if i else -1
            for d in range(3):
                # the groups under this node share the bits above; those on the side of ones have the next bit set
                under = [g for g in range(8) if g >> (3 - d) == group >> (3 - d)]
                ones = [g for g in under if g >> (2 - d) & 1]
                node, bit = [0, 1 + (group >> 2), 3 + (group >> 1)][d], group >> (2 - d) & 1
                share = max(1e-6, min(1 - 1e-6, mixture[ones].sum() / mixture[under].sum()))
                x = [math.log(share / (1 - share)), float(f.two[two, node]), 0.0]
                if guess >= 0 and (guess & 31) >> 2 in under:
                    x[2] = 1.0 if (guess & 31) >> 2 in ones else -1.0
                x = np.clip(x, -8, 8)
                gate = d * 2 + int(x[2] != 0)
                w = weights[gate]
                p = max(1e-6, min(1 - 1e-6, 1 / (1 + math.exp(-float(w @ x)))))
                total += math.log(p if bit else 1 - p)
                weights[gate] = w + lm_scoring.ONLINE_RATE * (bit - p) * x
            if i:
                seen[prev] = byte
            before = before + cost
        return total / math.log(10)


def test_scores_agree_with_a_scalar_model(spark, monkeypatch):
    made = []

    class Kept(lm_scoring.WordScorer):
        def __init__(self, *args):
            super().__init__(*args)
            made.append(self)

    monkeypatch.setattr(lm_scoring, "WordScorer", Kept)
    rng = np.random.default_rng(4)
    vocab = {"a": ["the", "cat", "sat", "mät", "on", "it"], "b": ["der", "hund", "ist", "the", "so"], None: ["x1", "x2", "the"]}
    rows = [(i, " ".join(rng.choice(vocab[lang], int(rng.integers(0, 14)))), lang) for i, lang in enumerate(["a", "b", "a", None, "b"] * 5)]
    rows += [(100, None, "a"), (101, " ".join(["the cat sat"] * 300), "b"), (102, "new wörds Here", None), (None, "the cat", "a"), (None, "so ist it", "b")]
    docs = spark.createDataFrame([(*r, 1) for r in rows], "doc_id long, text string, lang string, h int")
    got = {(r["doc_id"], r["n_tokens"]): r["score"] for r in lm_scoring.score_documents(spark, docs).collect()}
    tokens = lambda t: [w.translate(LOW).encode() for w in WORD.findall(t or "")] + [b"\n"]
    key = lambda i: crc("" if i is None else i, 5)
    train = [(tokens(t), lang) for i, t, lang in rows if key(i) != 1]
    named = collections.Counter(lang for _, lang in train if lang)
    order = sorted(named, key=lambda x: (-named[x], x))  # a null label counts as the first
    scalar = Scalar(made[0], [(ts, order.index(lang) if lang else 0) for ts, lang in train])
    for i, t, _ in [*rows[:6], *rows[-5:]]:
        assert got[i, len(tokens(t))] == pytest.approx(scalar.score(tokens(t)), rel=2e-4)


def test_rare_labels_share_a_class(spark):
    docs = spark.createDataFrame([(i, f"w{i % 7} v{i % 3} the", f"l{i % 6}") for i in range(120)], "doc_id long, text string, lang string")
    few, many = (lm_scoring.score_documents(spark, docs, classes=k).agg({"score": "sum"}).first()[0] for k in (3, 6))
    assert few < 0 and many < 0 and few != many


def test_model_beats_the_base_on_held_out_text(spark):
    docs = spark.read.parquet("/root/testdata/sf0.1/documents.parquet").select("doc_id", "text", "lang")
    s = lm_scoring.score_documents(spark, docs).where("held_out").selectExpr("sum(score) AS s", "sum(base_score) AS b").first()
    assert s["s"] > s["b"]


def test_suffix_automaton_by_brute_force():
    rng = np.random.default_rng(1)
    for _ in range(40):
        text = "".join(rng.choice(list("abc"), 30))
        other = "".join(rng.choice(list("abcd"), 25))
        a = language_id.SuffixAutomaton(text)
        count, i = 0, 0
        while i < len(other):
            k = 1
            while i + k < len(other) and other[i : i + k + 1] in text and other[i] in text:
                k += 1
            count, i = count + 1, i + k
        assert a.phrases(other) == count
        model = language_id.LanguageModel({"x": text, "y": other})
        got = model.phrases([other, "", text, "zz" + text])
        assert got[:, 0].tolist() == [count, 0, 1, 3] and got[0, 1] == 1


def test_letters_and_languages_have_no_cap(spark):
    """Alphabets of 1,500 letters and 70 languages; phrases run over words; segments add one phrase each at most."""
    rng = np.random.default_rng(2)
    draw = lambda low, n: "".join(chr(low + int(x)) for x in rng.integers(0, 1500, n))
    latin = " ".join("".join(rng.choice(list("aeiou lmn"), 6)) for _ in range(300))
    model = language_id.LanguageModel({"han": f" {draw(0x4E00, 9000)} ", "hangul": f" {draw(0xAC00, 9000)} ", "latin": f" {latin} "})
    import pyarrow as pa

    texts = [draw(0x4E00, 300) for _ in range(20)] + [draw(0xAC00, 300) for _ in range(20)] + [latin[50:200]]
    assert model.predict(pa.array(texts))[0] == ["han"] * 20 + ["hangul"] * 20 + ["latin"]
    many = spark.createDataFrame([(f"l{i:02d}", " ".join(f"{chr(97 + i % 26)}{chr(97 + i // 26)}{w}" for w in "abcdefgh") * 4) for i in range(70)], "lang string, text string")
    found = language_id.fit_language_model(many)
    assert len(found.langs) == 70 and found.predict(pa.array([r["text"] for r in many.collect()]))[0] == [r["lang"] for r in many.collect()]
    whole = language_id.LanguageModel({"x": " one two three "})
    assert whole.phrases([" one two three ", " two three "]).tolist() == [[1], [1]]
    long = "abc " * 100_000
    bound = language_id.LanguageModel({"x": f" {long[:4000]}"})
    assert bound.phrases([" " + long])[0, 0] <= 400_001 / 1024 + 400_001 / 4000 + 2


def test_notes_may_wait_and_paths_are_counted_alone(monkeypatch):
    """The mixer's observations may be noted for many steps at once; only the nodes of a token's own group are counted."""
    rng = np.random.default_rng(6)
    made = []
    for bits in (1, 1 << 16):
        monkeypatch.setattr(lm_scoring, "NOTE_BITS", bits)
        words = lm_scoring.pa.array(["".join(np.random.default_rng(i).choice(list("abcde"), 1 + i % 7)) + str(i) for i in range(300)])
        counts = np.random.default_rng(1).integers(0, 9, (300, 2)).astype(np.float64)
        none = np.zeros(0, dtype=np.int32), np.zeros(0, dtype=np.uint64), np.zeros(0, dtype=np.int32), np.zeros((0, 2))
        found = lm_scoring.CountedContexts(lm_scoring.ByteTree(np.arange(256)), lm_scoring.spelled(words), counts, none)
        made.append(lm_scoring.Mixer())
        found.learn(made[-1], counts)
    assert (made[0].weights == made[1].weights).all() and (made[0].mass == made[1].mass).all() and np.allclose(made[0].seen, made[1].seen, rtol=1e-12)
    assert made[0].seen.sum() > lm_scoring.Mixer().seen.sum() + 1000
    by_group, at = rng.random((50, lm_scoring.GROUPS)), rng.permutation(50)
    group = rng.integers(0, lm_scoring.GROUPS, 50)
    for whole, own in zip(lm_scoring.node_counts(by_group), lm_scoring.path_counts(by_group, group, at)):
        assert np.allclose(np.take_along_axis(whole[at], lm_scoring.NODES[group], axis=1), own, rtol=1e-14)


def test_letters_that_a_reference_lacks_cost_more_than_phrases():
    """A short reference without a text's script loses to the text's own, however much longer that is; both count alike."""
    import pyarrow as pa

    rng = np.random.default_rng(4)
    draw = lambda n: "".join(chr(0x4E00 + int(x)) for x in rng.integers(0, 1500, n))
    model = language_id.LanguageModel({"han": f" {draw(9000)} ", "short": " ab "})
    texts = [draw(300) for _ in range(20)] + ["ab ab", "a\u4e00" + chr(0x3042)]
    assert model.predict(pa.array(texts))[0][:21] == ["han"] * 20 + ["short"]
    _, lacking = model.parsed([" ab ", "", f" {texts[0]} ", " \u3042a "])
    assert lacking.tolist() == [[2, 0], [0, 0], [sum(c not in model_letters(model, "han") for c in texts[0]), 300], [2, 1]]


def model_letters(model, lang):
    return {chr(p) for p, lacks in zip(model.points, model.lacks[1:, model.langs.index(lang)]) if not lacks}


def test_languages_on_held_out_rows(spark, middle):
    docs = spark.read.parquet(f"{middle}/documents.parquet").select("doc_id", "text", "lang")
    odd = spark.createDataFrame([(-1, None, "en"), (-2, "", None), (-3, "123 !?", "de"), (-3, "123 !?", "de")], docs.schema)
    docs = docs.unionAll(odd)
    model = language_id.fit_language_model(docs.where(crc_bucket("doc_id", 4) != 2))
    got = {(r["doc_id"]): r for r in language_id.predict_languages(spark, docs, model).collect()}
    truth = {r["doc_id"]: r["lang"] for r in docs.collect() if r["doc_id"] >= 0}
    held = [i for i in truth if crc(i, 4) == 2]
    assert np.mean([got[i]["lang_pred"] == truth[i] for i in held]) > 0.97
    assert all(got[i]["held_out"] == (crc(i, 4) == 2) and 0 <= got[i]["score"] <= 1 for i in truth)
    assert [got[i]["lang_pred"] for i in (-1, -2, -3)] == ["und"] * 3
    nothing = language_id.fit_language_model(docs.limit(0))
    assert {r["lang_pred"] for r in language_id.predict_languages(spark, docs.limit(3), nothing).collect()} == {"und"}


@pytest.mark.parametrize("n", [1, 2, 3, 10, 257, 4096, 5000])
def test_permutation_and_inverse(n):
    rows = np.arange(n)
    image = sharding.permute(rows, n, 5)
    assert sorted(image) == list(range(n))
    assert (sharding.permute(image, n, 5, inverse=True) == rows).all()
    if n > 1000:
        assert abs(np.corrcoef(rows, image)[0, 1]) < 0.1
        assert (image != sharding.permute(rows, n, 6)).mean() > 0.9


def test_shards_follow_the_law(spark, monkeypatch):
    monkeypatch.setattr(sharding, "BLOCK_ROWS", 16)
    rows = [(i * 3, f"text {i}") for i in range(700)] + [(5, "same")] * 40 + [(None, None), (None, "x"), (2, None)] + [(None, f"hot {i}") for i in range(400)]
    docs = spark.createDataFrame([(i, t, 1) for i, t in rows], "doc_id long, text string, shard int").repartition(4)
    got = sharding.feistel_shards(docs).collect()
    assert len(got) == len(rows)
    by = collections.defaultdict(list)
    for r in got:
        by[r["shard"]].append(r["slot"])
    assert max(map(len, by.values())) - min(map(len, by.values())) <= 1
    assert all(sorted(v) == list(range(len(v))) for v in by.values()) and set(by) == set(range(8))
    assert collections.Counter((r["doc_id"], r["size"], r["text_crc32"]) for r in got) == collections.Counter((i, len((t or "").encode()) + 1, zlib.crc32((t or "").encode())) for i, t in rows)
    order = sorted(got, key=lambda r: r["row_number"])
    assert [r["row_number"] for r in order] == list(range(len(rows)))
    ids = [-1 if r["doc_id"] is None else r["doc_id"] for r in order]
    assert ids == sorted(ids)
    r = order[123]
    assert sharding.place(123, len(rows), 8, 20_231) == (r["shard"], r["slot"])
    assert sharding.row_at(r["shard"], r["slot"], len(rows), 8, 20_231) == 123
    assert sharding.feistel_shards(docs.limit(0)).count() == 0


def base_by_hand(text):
    text = text or ""
    w = WORD.findall(text)
    grams = collections.Counter(tuple(w[i : i + 3]) for i in range(len(w) - 2))
    covered = {p for i in range(len(w) - 2) if grams[tuple(w[i : i + 3])] > 1 for p in (i, i + 1, i + 2)}
    seen, dup = set(), 0
    for line in text.split("\n"):
        if WORD.search(line):
            dup += line in seen
            seen.add(line)
    return (len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in text), dup, len(covered))


def test_quality_base_by_hand(spark):
    texts = [None, "", " \n\n", "one", "a b c a b c", "x y x y x y", "Line one here\nLine one here\n \n#*|", "é ü " * 40, "\n".join(["same line of words"] * 30), " lead  and\ttabs\x0bmore\x0c ", "wörd " * 60, " ".join(f"word{chr(97 + i // 26)}{chr(97 + i % 26)}" for i in range(80))]
    docs = spark.createDataFrame([(i, t, True) for i, t in enumerate(texts)], "doc_id long, text string, kept boolean")
    got = {r["doc_id"]: r for r in quality.quality_verdicts(docs).collect()}
    for i, t in enumerate(texts):
        n, chars, symbols, dup, repeat = base_by_hand(t)
        r = got[i]
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == (n, chars, symbols, dup, repeat), t
        assert r["base_failed"] == (n < 50 or 100 * repeat > 50 * n)
        assert not (r["base_failed"] and r["kept"])
    assert got[11]["kept"]
    assert quality.quality_verdicts(docs.limit(0)).count() == 0
    assert quality.keep_good(docs).columns == docs.columns


def test_order_of_the_cascade_changes_no_verdict(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    names = [r.name for r in quality.RULES]
    verdict = lambda order: {r["doc_id"]: r["kept"] for r in quality.quality_verdicts(docs, order=order).collect()}
    assert verdict(names) == verdict(names[::-1]) == {r["doc_id"]: r["kept"] for r in quality.quality_verdicts(docs).collect()}
    plan = quality.plan_cascade(docs)
    worth = [share / max(cost, 1e-9) for _, share, cost in plan]
    assert worth == sorted(worth, reverse=True)
