"""Token files, byte-level pieces and merge-type segmentation against the libraries and round trips."""

from __future__ import annotations

import hashlib
import zlib

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from gridcluster.llm import sentence_pieces, token_files
from gridcluster.llm.bpe_pieces import PieceEncoder
from gridcluster.llm.queries import tokenizer_file
from gridcluster.llm.sentence_pieces import MergeEncoder

ODD = ["", " ", "a", "hello  world", " x", "x ", "a\nb", "a \n b\t", "don't we'll", "foo <|endoftext|> bar", "x  y", "x  y", "“q” – z", "▁▁a ▁", " " * 40 + "x", "<s> </s> <0x41>", "é ü ñ ① 漢字", "\x1c a", "A" * 3000, "ab " * 500]
words = st.text(alphabet=st.sampled_from(list("abcdefgh ETAO\n\t.,é①▁'0189")), max_size=40)


@pytest.fixture(scope="module")
def bpe():
    return PieceEncoder(tokenizer_file("byte_bpe_50k.json"))


@pytest.fixture(scope="module")
def merger():
    return MergeEncoder(tokenizer_file("piece_bpe_32k.model"))


def check_bpe(bpe, texts):
    lengths, ids = bpe.encode(pa.array(texts, pa.string()), 0)
    want = [e.ids + [0] for e in bpe.tokenizer.encode_batch(texts, add_special_tokens=False)]
    assert lengths.tolist() == [len(w) for w in want]
    assert ids.tolist() == [i for w in want for i in w]


def check_pieces(merger, texts):
    lengths, ids = merger.encode(pa.array(texts, pa.string()))
    want = merger.processor.encode(texts, add_bos=True, add_eos=True)
    assert lengths.tolist() == [len(w) for w in want]
    assert ids.tolist() == [i for w in want for i in w]


def test_odd_texts(bpe, merger):
    check_bpe(bpe, ODD)
    check_pieces(merger, ODD)


@settings(max_examples=150, deadline=None)
@given(st.lists(words, min_size=1, max_size=5))
def test_random_texts(bpe, merger, texts):
    check_bpe(bpe, texts)
    check_pieces(merger, texts)


def test_segmentation_takes_back_tokens(merger):
    """Some words need a step back: the longest first entry isn't always part of the result."""
    rng = np.random.default_rng(0)
    back = 0
    for _ in range(2000):
        w = "▁" + "".join(rng.choice(list("aeinrstlo"), 9))
        out = merger.segment(w)
        assert out == merger.remerge(w)
        back += out[0] != merger._longest(w)[0]
    assert back


@settings(max_examples=80, deadline=None)
@given(st.lists(st.one_of(st.integers(0, 3), st.integers(0, 50_256), st.integers(0, 2**64 - 1)), max_size=2600))
def test_packing_round_trip(values):
    v = np.array(values, dtype=np.uint64)
    packed, offsets = token_files.pack(v)
    assert (token_files.unpack(packed) == v).all()
    for i, a in enumerate(offsets):
        z = offsets[i + 1] if i + 1 < len(offsets) else len(packed)
        assert (token_files.unpack(packed[a:z]) == v[i * token_files.BLOCK : (i + 1) * token_files.BLOCK]).all()


def test_long_runs_take_few_words():
    assert len(token_files.pack(np.zeros(960, dtype=np.uint64))[0]) == 8
    assert len(token_files.pack(np.full(1, 2**60, dtype=np.uint64))[0]) == 2


def test_files_against_brute_force(spark, monkeypatch):
    monkeypatch.setattr(token_files, "FILE_IDS", 50)
    rows = [(7, "seven words here"), (3, None), (5, ""), (9, "x  y"), (3, "again three"), (None, "no id")] + [(100 + i, "word " * i) for i in range(40)]
    docs = spark.createDataFrame([(i, t, 1) for i, t in rows], "doc_id long, text string, ids int")
    manifest = token_files.encode_to_files(spark, docs, tokenizer_file("byte_bpe_50k.json"), files=3)
    got = token_files.read_files(manifest, 2).collect()
    encoder = PieceEncoder(tokenizer_file("byte_bpe_50k.json")).tokenizer
    want = {}
    for i, t in rows:
        ids = np.array(encoder.encode(t or "", add_special_tokens=False).ids + [0], dtype="<u4")
        want.setdefault(i, []).append((len(ids), zlib.crc32(ids.tobytes())))
    for i, expect in want.items():
        assert sorted((r["n_tokens"], r["ids_crc32"]) for r in got if r["doc_id"] == i) == sorted(expect)
    ordered = sorted(got, key=lambda r: r["start"])
    assert [r["start"] for r in ordered] == np.cumsum([0] + [r["n_tokens"] for r in ordered])[:-1].tolist()
    ids = [-1 if r["doc_id"] is None else r["doc_id"] for r in ordered]
    assert ids == sorted(ids)


def test_digests_and_empty_table(spark, merger):
    docs = spark.createDataFrame([(1, "Hello  world"), (2, None), (2, None)], "doc_id long, text string")
    got = sentence_pieces.sentence_piece_digests(spark, docs, tokenizer_file("piece_bpe_32k.model"), with_ids=True).collect()
    by = {r["doc_id"]: r for r in got}
    ids = merger.processor.encode("Hello  world", add_bos=True, add_eos=True)
    assert by[1]["ids"] == ids and by[1]["round_trip"]
    assert by[1]["ids_sha256"] == hashlib.sha256(np.array(ids, dtype="<u4").tobytes()).hexdigest()
    assert by[2]["n_tokens"] == 2 and by[2]["decoded"] == "" and len(got) == 3
    assert sentence_pieces.sentence_piece_digests(spark, docs.limit(0), tokenizer_file("piece_bpe_32k.model")).count() == 0


def test_pieces_work_on_bounded_text(spark, merger, monkeypatch):
    """A batch of 6 MB goes through the encoder in parts of 2 MB."""
    from gridcluster.llm import common, sentence_pieces

    class Docs:
        def select(self, *columns):
            return self

        def mapInArrow(self, run, schema):
            return run

    sizes = []

    class Seen:
        processor = merger.processor

        def encode(self, text):
            sizes.append(text.nbytes)
            return merger.encode(text)

    monkeypatch.setattr(sentence_pieces, "encoder_of", lambda model: Seen())
    run = sentence_pieces.sentence_piece_digests(spark, Docs(), b"")
    batch = pa.RecordBatch.from_arrays([pa.array(range(60)), pa.array(["some words " * 9000] * 60)], names=["doc_id", "text"])
    assert sum(b.num_rows for b in run(iter([batch]))) == 60
    assert len(sizes) > 1 and max(sizes) < common.SLICE_BYTES + 10_000
