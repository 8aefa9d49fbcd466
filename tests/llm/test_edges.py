"""Every operator and stage on nulls, empty and very long texts, ties, repeated rows, a hot id, clashing columns and no rows."""

from __future__ import annotations

import random

import pytest

import corpus_pipeline
from gridcluster.llm import decontaminate, language_id, lm_scoring, near_dups, quality, sentence_pieces, sharding, substring_dedup, token_files
from gridcluster.llm.queries import tokenizer_file

#: Names that the operators use inside.
CLASHING = ["__id", "__text_hash", "__units", "__kept", "__doc", "h", "m", "chunk", "place", "label", "size", "row_number", "shard", "start", "score", "kept", "lang_pred", "n", "v", "word", "slot", "n_chars"]


def rows():
    rng = random.Random(9)
    word = lambda: "".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(rng.randint(2, 9)))
    line = lambda n: " ".join(word() for _ in range(n))
    long = "\n".join(line(12) for _ in range(22_000))  # over 1.5 MB
    out = [(1, None, None), (2, "", "en"), (3, " \n\t ", "en"), (4, long, "en"), (5, "x" * 300_000, "de"), (6, "é\u0301 \U0001F600 漢字 " * 40, None)]
    out += [(7, line(80), "de")] * 3 + [(8, None, "de")] * 2
    out += [(None, line(60), "en") for _ in range(300)] + [(None, "one and the same text of a null id", None)] * 60
    return out


@pytest.fixture(scope="module")
def docs(spark):
    schema = "doc_id long, text string, lang string, " + ", ".join(f"`{c}` string" for c in CLASHING)
    return spark.createDataFrame([(*r, *CLASHING) for r in rows()], schema).repartition(5).cache()


@pytest.fixture(scope="module")
def bench(spark):
    return spark.createDataFrame([(1, "what is the name of the river that runs past the old mill"), (2, None), (None, "x"), (3, "")], "item_id long, text string")


def model(spark, docs):
    return language_id.fit_language_model(docs)


OPERATORS = {
    "substring_dedup": lambda s, d, b: substring_dedup.remove_repeats(s, d),
    "lines": lambda s, d, b: substring_dedup.remove_repeats(s, d, kind="lines", min_words=1, report=False),
    "scores": lambda s, d, b: lm_scoring.score_documents(s, d),
    "shards": lambda s, d, b: sharding.feistel_shards(d),
    "token_files": lambda s, d, b: token_files.read_files(token_files.encode_to_files(s, d, tokenizer_file("byte_bpe_50k.json")), 4),
    "quality": lambda s, d, b: quality.quality_verdicts(d),
    "near_duplicates": lambda s, d, b: near_dups.near_components(s, d),
    "language": lambda s, d, b: language_id.predict_languages(s, d, model(s, d)),
    "sentence_pieces": lambda s, d, b: sentence_pieces.sentence_piece_digests(s, d, tokenizer_file("piece_bpe_32k.model")),
}


@pytest.mark.parametrize("name", OPERATORS)
def test_one_row_a_document(spark, docs, bench, name):
    got = OPERATORS[name](spark, docs, bench)
    assert len(set(c.lower() for c in got.columns)) == len(got.columns)
    found = got.select("doc_id").collect()
    assert sorted(r["doc_id"] or 0 for r in found) == sorted(r[0] or 0 for r in rows())
    assert OPERATORS[name](spark, docs.limit(0), bench).count() == 0


FILTERS = {
    "quality": lambda s, d, b: quality.keep_good(d),
    "near_duplicates": lambda s, d, b: near_dups.keep_one_of_each(s, d),
    "decontamination": lambda s, d, b: decontaminate.drop_contaminated(s, d, b),
}


@pytest.mark.parametrize("name", FILTERS)
def test_filters_keep_all_columns(spark, docs, bench, name):
    got = FILTERS[name](spark, docs, bench)
    assert got.schema.names == docs.schema.names
    kept = got.collect()
    assert kept and all(list(r)[3:] == CLASHING for r in kept)
    assert FILTERS[name](spark, docs.limit(0), bench).count() == 0
    if name == "decontamination":
        assert len(kept) == len(rows()) and decontaminate.contaminated_spans(spark, docs, bench).count() == 0


def test_stages_run_on_such_rows(spark, docs, small):
    """Each stage on the same odd rows; all but the last return the columns they were given."""
    given = docs.drop("n_chars").selectExpr("*", "CAST(length(text) AS INT) AS n_chars")
    for name, stage in corpus_pipeline.STAGES:
        for some in (given, given.limit(0)):
            out = stage(spark, some, small)
            n = out.count()
            if name != corpus_pipeline.STAGES[-1][0]:
                assert out.columns == given.columns, name
            assert n <= some.count()


def test_lines_and_paragraphs_by_brute_force(spark):
    rng = random.Random(3)
    pool = [" ".join(rng.choice("abcdef") for _ in range(rng.randint(1, 4))) for _ in range(30)]
    rows = [(i, "\n".join(rng.choice([*pool, ""]) for _ in range(rng.randint(0, 9)))) for i in range(50)] + [(3, "a b\nc d"), (None, "a b\nq")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = {(r["doc_id"], tuple(k for k in r["original"].split("\n"))): r["text"] for r in substring_dedup.remove_repeats(spark, docs.selectExpr("*", "text AS original"), kind="lines", min_words=1).collect()}
    order = docs.selectExpr("doc_id", "text", "xxhash64(coalesce(text, '')) AS h").collect()
    seen, want = set(), {}
    for r in sorted(order, key=lambda r: (r["doc_id"] is not None, r["doc_id"] or 0, r["h"])):
        kept = []
        for line in r["text"].split("\n"):
            form = " ".join(line.lower().split())
            if form and form not in seen:
                kept.append(form)
            seen.add(form)
        want[r["doc_id"], tuple(r["text"].split("\n"))] = kept
    assert {k: [" ".join(x.split()) for x in v.split("\n") if x.strip()] for k, v in got.items()} == want
    text = "one two\nthree\n\nfour five\n\n\none two\nthree\n\nfour"
    out = substring_dedup.remove_repeats(spark, spark.createDataFrame([(1, text), (2, "FOUR  five\n\nsix")], "doc_id long, text string"), kind="paragraphs", min_words=2).collect()
    assert {r["doc_id"]: r["text"].split() for r in out} == {1: "one two three four five four".split(), 2: ["six"]}


def test_passages_by_brute_force(spark):
    """Windows of pieces and whole lines, by plain Python."""
    import re

    rng = random.Random(8)
    vocab = ["The", "old", "mill", "Stands.", "by", "a", "river", "And", "so", "on!", "it", "runs", "Here", "we"]
    passages = [" ".join(rng.choice(vocab) for _ in range(14)) for _ in range(6)]
    texts = []
    for _ in range(60):
        parts = [rng.choice(passages) if rng.random() < 0.4 else " ".join(rng.choice(vocab) + str(rng.randrange(30)) for _ in range(rng.randint(1, 9))) for _ in range(rng.randint(1, 5))]
        texts.append("".join(p + rng.choice([" ", "\n", "\n\n"]) for p in parts))
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r["doc_id"]: r["text"] for r in substring_dedup.remove_repeats(spark, docs).collect()}
    seen, want = set(), {}
    for i, t in enumerate(texts):
        words = [(m.group(), m.start()) for m in re.finditer(r"\S+", t)]
        lines = [t.count("\n", 0, s) for _, s in words]
        cut = [k for k, (w, _) in enumerate(words) if k == 0 or lines[k] != lines[k - 1] or words[k - 1][0][-1] in ".!?" or w[0].isupper()]
        ends = [*cut[1:], len(words)]
        units = set()
        for a, k in enumerate(cut):
            b = next((b for b in range(a, len(cut)) if ends[b] - k >= substring_dedup.MIN_WORDS), None)
            if b is not None:
                units.add((a, b))
            if k == 0 or lines[k] != lines[k - 1]:
                b = max(b for b in range(a, len(cut)) if lines[cut[b]] == lines[k])
                if ends[b] - k >= substring_dedup.LINE_WORDS:
                    units.add((a, b))
        gone, fresh = set(), set()
        for a, b in sorted(units):
            form = " ".join(w.lower() for w, _ in words[cut[a] : ends[b]])
            if form in seen or form in fresh:
                gone |= set(range(a, b + 1))
            fresh.add(form)
        seen |= fresh
        bounds = [words[k][1] for k in cut] + [len(t)]
        keep = t[: bounds[0]] + "".join(t[bounds[a] : bounds[a + 1]] for a in range(len(cut)) if a not in gone)
        want[i] = keep
    assert got == want and any(got[i] != t for i, t in enumerate(texts))
