import random
import re

import numpy as np

from runstore.llm import near_dup as nd


def brute(rows, percent=85):
    """component and set size by plain sets and all pairs."""
    sets = []
    for _, t in rows:
        words = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
        sets.append({tuple(words[i : i + 5]) for i in range(len(words) - 4)} if len(words) >= 5 else {tuple(words)} if words else set())
    comp = {d: d for d, _ in rows}

    def root(d):
        while comp[d] != d:
            d = comp[d]
        return d

    for i in range(len(rows)):
        for j in range(i):
            if sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= percent * len(sets[i] | sets[j]):
                a, b = root(rows[i][0]), root(rows[j][0])
                comp[max(a, b)] = min(a, b)
    return {(d, len(s), root(d)) for (d, _), s in zip(rows, sets)}


def test_against_brute_force(spark, monkeypatch):
    rnd = random.Random(8)
    word = lambda: rnd.choice("ab") + "".join(rnd.choice("etaoin") for _ in range(4))
    rows = [(5, None), (6, ""), (7, " \n"), (8, "Two words"), (9, "two WORDS"), (10, "two\twords é"), (11, "É é"), (12, "é é")]
    for g in range(12):
        text = [word() for _ in range(rnd.choice([6, 30, 120]))]
        for _ in range(rnd.choice([1, 2, 25])):
            copy = list(text)
            for _ in range(rnd.randint(0, 4)):
                copy[rnd.randrange(len(copy))] = word()
            rows.append((len(rows) * 7 % 1009 + 20, " ".join(copy)))
    df = spark.createDataFrame([(d, t, 1, "x") for d, t in rows], "doc_id long, text string, component_id int, kept string").repartition(3)
    for block in (128, 4):
        monkeypatch.setattr(nd, "BLOCK", block)
        got = nd.near_duplicates(df).collect()
        assert len(got) == len(rows)
        assert {(r["doc_id"], r["n_shingles"], r["component_id"]) for r in got} == brute(rows)
        assert all(r["kept"] == (r["doc_id"] == r["component_id"]) for r in got)


def test_estimate_is_unbiased():
    rng = np.random.default_rng(2)
    got = []
    for seed in range(30):
        a = rng.integers(0, 1 << 63, 800, dtype=np.uint64)
        h = nd.MinMaxHasher(24, 6, seed)
        x, y = h.signature(a[:600]), h.signature(a[200:])
        got.append((x == y).mean())
    assert abs(np.mean(got) - 0.5) < 0.03


def test_documents(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    rows = [(r["doc_id"], r["text"]) for r in docs.collect()]
    assert {(r["doc_id"], r["n_shingles"], r["component_id"]) for r in nd.near_duplicates(docs).collect()} == brute(rows)
    assert nd.deduplicate(docs).count() == len({c for _, _, c in brute(rows)})


def test_other_thresholds(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    rows = [(r["doc_id"], r["text"]) for r in docs.collect()]
    got = nd.near_duplicates(docs, percent=80, bands=nd.bands_for(80))
    assert {(r["doc_id"], r["n_shingles"], r["component_id"]) for r in got.collect()} == brute(rows, 80)
    assert nd.bands_for(85, miss=1.2e-5) == nd.BANDS < nd.bands_for(85) < nd.bands_for(80) and 1 - (1 - 0.8**nd.BAND_ROWS) ** nd.bands_for(80) >= 1 - 1e-5


def test_recall(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    for every in (1, 100):
        n, hit = nd.recall_of(docs, nd.near_duplicates(docs), every=every)
        assert hit == n and (every > 1 or n > 0)


def test_open_bands(spark, monkeypatch):
    """Documents that share a band and are not all alike go through every round and the full comparison."""
    rnd = random.Random(3)
    base_text = [f"w{k}" for k in range(60)]
    rows = []
    for k in range(40):
        text = list(base_text)
        text[k % 5 * 12] = f"x{rnd.randrange(4)}"
        text[-1] = f"y{k % 3}"
        rows.append((k, " ".join(text)))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    for rounds in (0, 1):
        monkeypatch.setattr(nd, "ROUNDS", rounds)
        monkeypatch.setattr(nd, "STAR", 7)
        monkeypatch.setattr(nd, "BLOCK", 5)
        got = nd.near_duplicates(df, bands=48, rows=2)
        assert {(r["doc_id"], r["n_shingles"], r["component_id"]) for r in got.collect()} == brute(rows)


def test_many_near_copies_are_compared_with_one(spark):
    """A group of m near copies costs m comparisons, not m * m."""
    text = [f"w{k}" for k in range(200)]
    rows = [(k, " ".join([*text, f"v{k}"])) for k in range(3000)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    sent = []
    ask = nd._set_rows

    def count(docs, tasks, id_col, text_col):
        sent.append(tasks.count())
        return ask(docs, tasks, id_col, text_col)

    nd._set_rows = count
    try:
        got = nd.near_duplicates(docs).agg({"component_id": "max"}).first()[0]
    finally:
        nd._set_rows = ask
    assert got == 0 and sum(sent) < 2 * len(rows)


def test_edges(spark):
    schema = "doc_id long, text string"
    assert nd.near_duplicates(spark.createDataFrame([], schema)).count() == 0
    got = nd.near_duplicates(spark.createDataFrame([(None, "a b c"), (None, "a b c"), (1, "a b c"), (1, "a b c")], schema)).collect()
    assert sorted((r["doc_id"] or 0, r["component_id"]) for r in got if r["doc_id"]) == [(1, 1), (1, 1)] and len(got) == 4
    assert all(r["kept"] is None for r in got if r["doc_id"] is None)
