"""The corpus pipeline: stages in order, each a decision that takes effect."""

from __future__ import annotations

import duckdb
import pytest

import corpus_pipeline
from gridcluster.llm import oracles, quality
from gridcluster.llm.queries import tokenizer_file
from gridcluster.llm.sentence_pieces import MergeEncoder


def test_stages_against_their_parts(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert names == ["quality_rules", "near_duplicates", "substring_dedup", "benchmark_decontamination", "sentence_pieces"]
    seen = docs
    kept = []
    for name, stage in corpus_pipeline.STAGES[:-1]:
        seen = stage(spark, seen, small)
        assert seen.columns == docs.columns, name
        seen = seen.cache()
        kept.append({r["doc_id"]: r["text"] for r in seen.collect()})
    assert set(kept[0]) == {r["doc_id"] for r in quality.quality_verdicts(docs).where("kept").collect()}
    assert set(kept[1]) < set(kept[0]) and set(kept[2]) == set(kept[1]) and set(kept[3]) <= set(kept[2])
    out = {r["doc_id"]: r for r in corpus_pipeline.run(spark, small).collect()}
    assert set(out) == set(kept[3])
    encoder = MergeEncoder(tokenizer_file("piece_bpe_32k.model")).processor
    for i, t in list(kept[3].items())[:30]:
        assert out[i]["n_tokens"] == len(encoder.encode(t, add_bos=True, add_eos=True))


@pytest.mark.parametrize("name", ["op7_quality_rules", "op8_near_duplicates", "op2_chat_formatting"])
def test_queries_equal_sql(spark, small, name):
    import __spark_entry__ as entry

    con = duckdb.connect()
    for t in ("documents", "conversations"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{small}/{t}.parquet'")
    df = entry.queries()[name](spark, small)
    found = con.execute(entry.oracle_sql()[name])
    names = [d[0] for d in found.description]
    order = sorted(names)
    assert order == sorted(df.columns)
    assert sorted(repr([r[c] for c in order]) for r in df.collect()) == sorted(repr([r[names.index(c)] for c in order]) for r in found.fetchall())
    assert oracles.QUALITY
