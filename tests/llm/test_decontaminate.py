import random

from runstore.llm import decontaminate as dc


def brute_distance(p, t):
    """Least edit distance of p to a stretch of t, and its first end, by the plain table."""
    col = list(range(len(p) + 1))
    best = (len(p), 0)
    for j, c in enumerate(t):
        new = [0]
        for i, d in enumerate(p):
            new.append(min(col[i] + (c != d), col[i + 1] + 1, new[i] + 1))
        col = new
        if col[-1] < best[0]:
            best = (col[-1], j + 1)
    return best


def test_myers():
    rnd = random.Random(2)
    for _ in range(3000):
        p = "".join(rnd.choice("abc") for _ in range(rnd.randint(1, 12)))
        t = "".join(rnd.choice("abc") for _ in range(rnd.randint(0, 20)))
        d, end = brute_distance(p, t)
        for most in (d, len(p) - 1):
            got = dc.distance_in(p, t, most)
            assert got == ((d, end) if d <= most and end else None) or d == len(p)
        assert d == 0 or dc.distance_in(p, t, d - 1) is None


def edited(rnd, s, n):
    s = list(s)
    for _ in range(n):
        i = rnd.randrange(len(s))
        k = rnd.randrange(3)
        if k == 0:
            s[i] = rnd.choice("xyz")
        elif k == 1:
            del s[i]
        else:
            s.insert(i, rnd.choice("qwv"))
    return "".join(s)


def test_against_brute_force(spark):
    rnd = random.Random(3)
    word = lambda: "".join(rnd.choice("aeionrst") for _ in range(rnd.randint(2, 7)))
    items = [(i, " ".join(word() for _ in range(rnd.randint(6, 14)))) for i in range(12)]
    docs = []
    for d in range(60):
        text = [" ".join(word() for _ in range(rnd.randint(0, 20)))]
        for _ in range(rnd.randint(0, 2)):
            item = rnd.choice(items)[1]
            text += [edited(rnd, item, rnd.randint(0, int(0.12 * len(item)))).upper(), " ".join(word() for _ in range(5))]
        docs.append((d, rnd.choice([" ", " -- ", "\n"]).join(text)))
    docs += [(100, None), (101, ""), (None, items[0][1]), (101, items[1][1])]
    df = spark.createDataFrame([(*x, 3) for x in docs], "doc_id long, text string, item_id int")
    bench = spark.createDataFrame([*items, (50, None), (51, "too short"), (52, "")], "item_id long, text string")
    want = set()
    for d, t in docs:
        for i, s in items:
            dist, _ = brute_distance(dc.normal(s), dc.normal(t or ""))
            if dist <= int(0.08 * len(dc.normal(s))):
                want.add((d, i, dist))
    for block in (10**9, 200):
        got = dc.find_items(df, bench, block_chars=block).collect()
        assert {(r["doc_id"], r["item_id"], r["distance"]) for r in got} == want and len(got) == len(want)
    for r in got:
        if r["doc_id"] is not None and r["doc_id"] < 60 and r["distance"] == 0:
            text = dict(docs)[r["doc_id"]]
            assert dc.normal(dict(items)[r["item_id"]]) in dc.normal(text[r["span_start"] : r["span_end"]])
    clean = dc.is_clean(df, bench, "ok").collect()
    assert len(clean) == len(docs) and {r["doc_id"] for r in clean if not r["ok"]} == {w[0] for w in want}


def test_empty(spark):
    none = spark.createDataFrame([], "item_id long, text string")
    docs = spark.createDataFrame([(1, "a b c d e f")], "doc_id long, text string")
    assert dc.find_items(docs, none).count() == 0
    assert dc.find_items(docs.limit(0), docs.toDF("item_id", "text")).count() == 0
    assert [r["ok"] for r in dc.is_clean(docs, none, "ok").collect()] == [True]


def test_short_items(spark):
    items = [(1, "Prime number"), (2, "水は百度で沸騰する"), (3, "太陽は東から昇り西に沈むのは地球が自転しているからである、と先生は言った"), (4, "?!")]
    docs = [(1, "A prime, number!"), (2, "a prime numbers"), (3, "subprime number"), (4, "prime numbr"), (5, "先生は水は百度で沸騰すると言った"), (6, "水は百度で沸かする"), (7, "昔、太陽は東から昇り西に沈むのは地球が公転しているからである、と先生は言った"), (8, "?!"), (9, "prime numbers, prime number")]
    df, bench = spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")
    got = {(r["doc_id"], r["item_id"], r["distance"], r["places"]) for r in dc.find_items(df, bench).collect()}
    assert got == {(1, 1, 0, 1), (5, 2, 0, 1), (7, 3, 1, 1), (9, 1, 0, 1)}
    assert {r["doc_id"] for r in dc.is_clean(df, bench, "ok").collect() if not r["ok"]} == {1, 5, 7, 9}


def test_spans_are_places_in_the_original_text():
    text = "İİİİ xx the quick brown fox"
    norm = dc.normal(text)
    at = norm.index("quick")
    a, b = dc.raw_span(text, at, at + 5)
    assert text[a:b] == "quick"
    a, b = dc.raw_span("ab İCİ de", 3, 4)
    assert "ab İCİ de"[a:b] == "İ"
    a, b = dc.raw_span("x İ", 2, 3)
    assert "x İ"[a:b] == "İ"


def test_empty_tables_and_clashing_columns(spark):
    docs = spark.createDataFrame([(1, "one two three four five six seven", 5, "x")], "doc_id long, text string, item_id long, clean string")
    none = spark.createDataFrame([], "item_id long, text string")
    bench = spark.createDataFrame([(9, "one two three four five six seven")], "item_id long, text string")
    assert dc.find_items(docs, none).count() == 0 and dc.find_items(docs.limit(0), bench).count() == 0
    assert [r["clean"] for r in dc.is_clean(docs, bench, "clean").collect()] == [False]
    long = spark.createDataFrame([(2, "word " * 200000 + "one two three four five six seven")], "doc_id long, text string")
    assert [(r["doc_id"], r["distance"]) for r in dc.find_items(long, bench).collect()] == [(2, 0)]
