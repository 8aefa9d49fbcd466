"""Near copies of which one holds the other, at the limit."""

from __future__ import annotations

import random

from gridcluster.llm import near_dups


def test_texts_cut_short_at_the_limit_are_linked(spark):
    """160 of 200 shingles: exactly 80 percent, where one set holds the other."""
    rng = random.Random(8)
    rows = []
    for i in range(4000):
        w = [f"{rng.getrandbits(40):x}" for _ in range(204)]
        rows += [(2 * i, " ".join(w)), (2 * i + 1, " ".join(w[:164]))]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    assert near_dups.near_components(spark, docs, 5, 80).where("kept").count() == 4000
