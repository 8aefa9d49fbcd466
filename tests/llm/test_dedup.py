"""Near duplicates, substring dedup, decontamination and chat collapse against brute force."""

from __future__ import annotations

import itertools
import random
import re

import numpy as np
import pytest

from gridcluster.llm import chat, components, decontaminate, near_dups, substring_dedup

WORD = re.compile(r"[^\x20\x09-\x0D]+")
LOW = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def shingles(text, words):
    w = [x.translate(LOW) for x in WORD.findall(text or "")]
    return {tuple(w[i : i + words]) for i in range(len(w) - words + 1)} if len(w) >= words else ({tuple(w)} if w else set())


def brute(rows, words, percent):
    sets = {i: shingles(t, words) for i, t in rows}
    parent = {i: i for i in sets}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in itertools.combinations(sorted(sets), 2):
        common = len(sets[a] & sets[b])
        if common and 100 * common >= percent * (len(sets[a]) + len(sets[b]) - common):
            x, y = root(a), root(b)
            parent[max(x, y)] = min(x, y)
    return {i: (len(sets[i]), root(i)) for i in sets}


def corpus(seed, n=160):
    rng = random.Random(seed)
    vocab = [f"w{i}" for i in range(300)]
    bases = [[rng.choice(vocab) for _ in range(rng.randint(1, 120))] for _ in range(25)]
    passage = [rng.choice(vocab) for _ in range(60)]
    rows = []
    for i in range(n):
        w = list(rng.choice(bases))
        for _ in range(rng.randint(0, 4)):
            w[rng.randrange(len(w))] = rng.choice(vocab)
        if rng.random() < 0.3:
            w += passage
        rows.append((i, " ".join(w) if rng.random() < 0.9 else " ".join(w).upper()))
    return rows + [(n, None), (n + 1, ""), (n + 2, " \n "), (n + 3, "two words"), (n + 4, "Two  WORDS")]


@pytest.mark.parametrize("words,percent,chunk,exact", [(3, 85, 512, False), (5, 80, 512, True), (3, 85, 7, False), (5, 80, 3, False)])
def test_components_are_brute_force(spark, monkeypatch, words, percent, chunk, exact):
    monkeypatch.setattr(near_dups, "CHUNK", chunk)
    rows = corpus(words + chunk)
    docs = spark.createDataFrame([(i, t, "x") for i, t in rows], "doc_id long, text string, n string").repartition(3)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in near_dups.near_components(spark, docs, words, percent, exact=exact).collect()}
    assert got == brute(rows, words, percent)


@pytest.mark.parametrize("percent", [85, 80])
def test_shortened_copies_at_the_limit_share_enough(percent):
    """10,000 pairs whose smaller set is part of the larger one, similarity just at the limit: none is lost by lists or sketches."""
    import numpy as np

    rng, n = np.random.default_rng(percent), 400
    need, least = near_dups.shared_values(near_dups.INDEXED, percent), near_dups.shared_values(near_dups.SKETCH, percent) / near_dups.SKETCH
    for _ in range(10_000):
        whole = np.sort(rng.integers(0, 2**63, n, dtype=np.uint64))
        part = np.sort(rng.choice(whole, n * percent // 100, replace=False))
        assert len(np.intersect1d(whole[: near_dups.INDEXED], part[: near_dups.INDEXED])) >= need
        flat = np.concatenate([whole[: near_dups.SKETCH], part[: near_dups.SKETCH]])
        similar = near_dups.alike_by_sketch(flat, np.array([0, near_dups.SKETCH, 2 * near_dups.SKETCH]), np.array([n, len(part)]), least)
        assert similar(0, np.array([1]))[0]


@pytest.mark.parametrize("exact", [False, True])
def test_shortened_copies_are_linked(spark, exact):
    rng = random.Random(4)
    rows = []
    for i in range(150):
        w = [f"u{i}x{rng.randrange(10**6)}" for _ in range(402)]
        rows += [(2 * i, " ".join(w)), (2 * i + 1, " ".join(w[: 2 + 340]))]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r["doc_id"]: r["component_id"] for r in near_dups.near_components(spark, docs, 3, 85, exact=exact).collect()}
    assert all(got[2 * i + 1] == 2 * i for i in range(150))


def test_clashing_columns_in_both_dedup_stages(spark):
    names = ["__id", "__text_hash", "__units", "__kept", "__doc", "n", "v", "d1", "unit", "w"]
    text = "one line of well over eight words that is in both of them. "
    rows = [(1, text + "end", *names), (1, text + "end", *names), (2, text + "end", *names), (None, None, *names), (3, text + "Quite other words here.", *names)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, " + ", ".join(f"{n} string" for n in names))
    kept = near_dups.keep_one_of_each(spark, docs, 3, 85)
    assert kept.columns == docs.columns and sorted(r["doc_id"] or 0 for r in kept.collect()) == [0, 1, 1, 3]
    assert all(list(r)[2:] == names for r in kept.collect())
    cut = substring_dedup.remove_repeats(spark, docs, report=False)
    assert cut.columns == docs.columns and all(list(r)[2:] == names for r in cut.collect())
    assert {r["doc_id"]: r["text"] for r in cut.collect()} == {1: text + "end", 2: "", None: None, 3: "Quite other words here."}
    full = substring_dedup.remove_repeats(spark, docs)
    assert len(full.columns) == len(set(full.columns)) == len(docs.columns) + 3


def test_near_duplicates_edge_cases(spark):
    docs = spark.createDataFrame([(None, "a b c d"), (4, "a b c d"), (4, "a b c d"), (9, "q r s t")], "doc_id long, text string")
    got = near_dups.near_components(spark, docs, 3, 85).collect()
    assert len(got) == 4
    assert {(r["doc_id"], r["component_id"], r["kept"]) for r in got} == {(None, None, True), (4, None, False), (9, 9, True)}
    empty = docs.limit(0)
    assert near_dups.near_components(spark, empty, 3, 85).count() == 0
    assert near_dups.keep_one_of_each(spark, docs, 3, 85).count() == 2


def test_long_chains_settle(spark):
    links = spark.createDataFrame([(i, i + 1) for i in range(200)] + [(500, 501), (501, 501)], "a long, b long")
    got = {r["node"]: r["component"] for r in components.components(spark, links).collect()}
    assert all(got[i] == 0 for i in range(201)) and got[501] == 500
    assert components.components(spark, links.limit(0)).count() == 0


PASSAGE = "The first part of it is here. Then comes a second one with many more words in it. And a third sentence closes the whole passage at last."


def test_repeats_go_and_offsets_stay(spark):
    rows = [(1, f"Own words of one. {PASSAGE} More of one."), (2, f"Two begins so {PASSAGE} and goes on"), (3, "Nothing that repeats anywhere in this table at all, sir."), (4, None), (5, ""), (6, "Short. Short. Short.")]
    docs = spark.createDataFrame([(i, t, t) for i, t in rows], "doc_id long, text string, d1 string")
    out = {r["doc_id"]: r for r in substring_dedup.remove_repeats(spark, docs).collect()}
    for i, t in rows:
        assert "".join((t or "")[k["start"] : k["end"]] for k in out[i]["__kept"]) == (out[i]["text"] or "")
        assert out[i]["d1"] == t
    assert out[1]["text"] == rows[0][1] and out[3]["text"] == rows[2][1] and out[4]["text"] is None and out[6]["text"] == rows[5][1]
    assert "second one" not in out[2]["text"] and "third sentence" not in out[2]["text"]
    assert out[2]["text"].startswith("Two begins so ")


def test_copies_and_repeats_within_a_text(spark):
    line = "A line of more than eight words which is said twice here.\n"
    rows = [(5, line * 3 + "End."), (8, line + "Other end."), (2, "é " * 4 + "Ünique words follow here and there and everywhere again. ") , (3, "é " * 4 + "Ünique words follow here and there and everywhere again. ")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    out = {r["doc_id"]: r["text"] for r in substring_dedup.remove_repeats(spark, docs).collect()}
    assert out[5] == line + "End." and out[8] == "Other end."
    assert out[2] == rows[2][1] and "follow" not in out[3]
    twice = substring_dedup.remove_repeats(spark, docs.unionAll(docs)).collect()
    assert len(twice) == 8 and sorted(r["text"] for r in twice if r["doc_id"] == 5) == [out[5]] * 2
    assert substring_dedup.remove_repeats(spark, docs.limit(0)).count() == 0


ITEM = "what is the name of the small river that runs past the old mill near the town of green hills"


@pytest.mark.parametrize("every", [None, 9, 6, 5])
def test_leaks_are_found_with_substitutions(spark, every):
    w = ITEM.split()
    if every:
        w = [f"x{i}" if i % every == every - 1 else t for i, t in enumerate(w)]
    rng = random.Random(1)
    filler = lambda n: " ".join(f"f{rng.randrange(500)}" for _ in range(n))
    rows = [(1, f"{filler(40)} {' '.join(w).upper()} {filler(30)}"), (2, filler(80) + " the name of the river"), (3, None), (4, ""), (1, filler(5))]
    docs = spark.createDataFrame([(i, t, 0) for i, t in rows], "doc_id long, text string, item_id int")
    bench = spark.createDataFrame([(7, ITEM), (8, None), (None, ITEM), (9, "short item")], "item_id long, text string")
    got = decontaminate.contaminated_spans(spark, docs, bench).collect()
    assert [(r["doc_id"], r["item_id"], r["first_token"]) for r in got] == [(1, 7, 40)]
    clean = decontaminate.drop_contaminated(spark, docs, bench)
    assert clean.count() == 4 and clean.columns == docs.columns
    blocks = decontaminate.contaminated_spans(spark, docs, bench, block_bytes=30).collect()
    assert [tuple(r) for r in blocks] == [tuple(r) for r in got]
    assert decontaminate.contaminated_spans(spark, docs.limit(0), bench).count() == 0
    assert decontaminate.drop_contaminated(spark, docs, bench.limit(0)).count() == 5


def test_stretch_by_brute_force():
    import numpy as np

    rng = np.random.default_rng(2)
    for _ in range(300):
        same = rng.random(rng.integers(1, 30)) < 0.75
        begin, end, good = decontaminate.best_stretch(same, 0.8)
        spans = [(j - i, i, j) for i in range(len(same)) for j in range(i + 1, len(same) + 1) if 100 * same[i:j].sum() >= 80 * (j - i)]
        if not spans:
            assert good == 0
            continue
        longest = max(s[0] for s in spans)
        assert 100 * good >= 80 * (end - begin) and good == same[begin:end].sum() and same[begin] and same[end - 1]
        assert good >= 0.8 * longest - 1e-9


def test_hits_are_brute_force(spark):
    """Every pair whose best diagonal passes is found, on texts with single and regular substitutions."""
    import numpy as np
    import pyarrow as pa

    rng = random.Random(5)
    vocab = [f"v{i}" for i in range(80)]
    items = [(i, " ".join(rng.choice(vocab) for _ in range(rng.randint(14, 40)))) for i in range(12)]
    docs = []
    for i in range(60):
        w = [rng.choice(vocab) for _ in range(rng.randint(0, 30))]
        if i % 2:
            leak = rng.choice(items)[1].split()
            for _ in range(rng.randint(0, 2)):
                leak[rng.randrange(len(leak))] = "zz"
            w = w + leak + [rng.choice(vocab) for _ in range(10)]
        docs.append(" ".join(w))
    index = decontaminate.BenchmarkIndex(items)
    got = {(h[0], h[1]) for h in index.hits(pa.array(docs))}
    want = set()
    for r, t in enumerate(docs):
        d = np.array(t.split(), dtype=object)
        for q, (_, text) in enumerate(items):
            x = np.array(text.split(), dtype=object)
            for shift in range(-len(x) + 1, len(d)):
                lo, hi = max(0, -shift), min(len(x), len(d) - shift)
                if hi > lo and decontaminate.best_stretch(np.array(x[lo:hi] == d[lo + shift : hi + shift], dtype=bool), 0.8)[2] >= 12:
                    want.add((r, q))
    assert got == want and want


def test_chat_collapse(spark):
    say = lambda c, *texts: [(c, i, "user" if i % 2 == 0 else "assistant", t) for i, t in enumerate(texts)]
    rows = say(1, "a", "b") + say(2, "a", "b", "c") + say(3, "a", "b", "c") + say(4, "a", "x") + say(5, None) + say(6, "a")
    rows += [(7, 0, None, "q"), (7, 0, None, "q"), (8, None, "user", "q"), (None, 0, "user", "lost"), (None, 1, "user", "row")]
    turns = spark.createDataFrame([(*r, 1) for r in rows], "conv_id long, turn long, role string, text string, pos int")
    got = {r["conv_id"]: r for r in chat.render_conversations(turns).collect()}
    assert set(got) == {2, 4, 5, 7, 8, None}
    assert got[2]["n_equal"] == 2 and got[2]["n_turns"] == 3
    assert got[2]["text"] == "<|user|>\na<|end|>\n<|assistant|>\nb<|end|>\n<|user|>\nc<|end|>\n"
    assert got[7]["text"] == "<|unknown|>\nq<|end|>\n" and got[5]["text"] == "<|user|>\n<|end|>\n"
    assert got[None]["n_turns"] == 2
    assert chat.render_conversations(turns.limit(0)).count() == 0


def test_long_conversations_run_over_segments(spark):
    turns = spark.range(50).selectExpr("1L AS conv_id", "id AS turn", "'user' AS role", "string(id) AS text").unionAll(spark.range(30).selectExpr("2L", "id", "'user'", "string(id)"))
    got = sorted(chat.render_conversations(turns, segment=16).collect(), key=lambda r: r["segment"])
    assert [r["conv_id"] for r in got] == [1] * 4 and [r["segment"] for r in got] == [0, 1, 2, 3]
    whole = chat.render_conversations(turns).collect()
    assert "".join(r["text"] for r in got) == whole[0]["text"]


@pytest.mark.parametrize("length,wrong", [(12, 0), (13, 1), (14, 2), (15, 3), (16, 3), (18, 3), (20, 4)])
def test_no_pattern_of_substitutions_escapes_the_masks(length, wrong):
    """Every overlap of that many tokens, so many of them replaced (never the ends), is hit and verified."""
    import pyarrow as pa

    words = [f"t{i}" for i in range(length)]
    docs = [" ".join("zz" if i in gone else w for i, w in enumerate(words)) for gone in itertools.combinations(range(1, length - 1), wrong)]
    index = decontaminate.BenchmarkIndex([(1, " ".join(words))])
    assert {h[0] for h in index.hits(pa.array(docs))} == set(range(len(docs)))


def test_short_items_and_phrases_that_are_everywhere(monkeypatch):
    import pyarrow as pa

    index = decontaminate.BenchmarkIndex([(1, "three word item"), (2, "two words"), (3, "just one more four"), (4, "")])
    assert [h[:2] for h in index.hits(pa.array(["a three word item b", "two words", "one more four just one more four", "three word"]))] == [(0, 0), (2, 2)]
    phrase = "this phrase of seven words is common"
    items = [(i, f"{phrase} own{i} " + " ".join(f"x{i}y{j}" for j in range(12))) for i in range(40)]
    text = " ".join([phrase] * 50) + " " + items[7][1]
    index = decontaminate.BenchmarkIndex(items)
    want = index.hits(pa.array([text]))
    assert [h[:2] for h in want] == [(0, 7)] and want[0][4] == 20
    monkeypatch.setattr(decontaminate, "PAIRS", 13)  # blocks cut inside the postings of one position
    assert index.hits(pa.array([text])) == want


def chat_by_hand(rows):
    """Maximal conversations of (conv, turn, role, text) rows, in plain Python."""
    low = lambda v: (v is not None, v)
    convs = {}
    for c, *rest in set(rows):
        convs.setdefault(c, []).append(tuple(rest))
    turns = {c: tuple((r, t) for _, r, t in sorted(x, key=lambda y: tuple(map(low, y)))) for c, x in convs.items()}
    prefixes = {t[:k] for t in turns.values() for k in range(1, len(t))}
    out = {}
    for t in set(turns.values()) - prefixes:
        same = [c for c in turns if turns[c] == t]
        out[min(same, key=low)] = (len(t), len(same), "".join(f"<|{r or 'unknown'}|>\n{x or ''}<|end|>\n" for r, x in t))
    return out


@pytest.mark.parametrize("broadcast", [150_000, 0])
def test_chat_by_brute_force_with_ties_and_null_turns(spark, monkeypatch, broadcast):
    monkeypatch.setattr(chat, "BROADCAST_ROWS", broadcast)
    rng = random.Random(broadcast)
    rows = []
    for c in [*range(60), None]:
        for i in range(rng.randint(1, 6)):
            for _ in range(rng.choice([1, 1, 1, 2])):
                rows.append((c, rng.choice([i, i, i, None]), rng.choice(["user", "assistant", None]) if rng.random() < 0.2 else "user", rng.choice(["a", "b", "b" * 70 + "x", "b" * 70 + "y", "", None])))
    rows += [(99, None, "user", f"hot {i % 700}") for i in range(3000)]  # one conversation without numbers, rows repeated
    turns = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").repartition(5)
    got = {}
    for r in sorted(chat.render_conversations(turns, segment=256).collect(), key=lambda r: r["segment"]):
        n, k, t = got.get(r["conv_id"], (r["n_turns"], r["n_equal"], ""))
        got[r["conv_id"]] = (n, k, t + r["text"])
    assert got == chat_by_hand(rows)


def test_chat_plan_is_native(spark, small):
    plan = chat.render_conversations(spark.read.parquet(f"{small}/conversations.parquet"))._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Arrow|Pandas", plan)


@pytest.mark.parametrize("few", [-1, 1 << 20])
def test_few_links_on_the_driver_give_the_components_of_the_rounds(spark, monkeypatch, few):
    """Few links take no round of jobs; many give the same."""
    monkeypatch.setattr(components, "FEW_LINKS", few)
    rounds = []
    monkeypatch.setattr(components, "_hook", lambda *a, hook=components._hook, **o: rounds.append(1) or hook(*a, **o))
    rng = np.random.default_rng(8)
    links = [(i, i + 1) for i in range(50, 90)] + [tuple(map(int, rng.integers(-40, 40, 2))) for _ in range(30)] + [(-(1 << 63), 200), (5, 5)]
    got = {r["node"]: r["component"] for r in components.components(spark, spark.createDataFrame(links, "a long, b long")).collect()}
    least = {n: n for a, b in links if a != b for n in (a, b)}
    for _ in range(len(least)):
        for a, b in links:
            if a != b:
                least[a] = least[b] = min(least[a], least[b])
    assert got == least
    assert bool(rounds) == (few < 0)
