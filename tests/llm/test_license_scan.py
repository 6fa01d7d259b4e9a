import random

from runstore.llm import license_scan as ls


def brute(docs, templates, containment=0.8):
    """Pairs whose best stretch of template length (and some more) holds enough shingles."""
    out = set()
    for d, text in docs:
        words = ls.words_of(text or "")
        for name, t in templates:
            want = ls.words_of(t)
            k = min(5, len(want))
            shingle = lambda w: {tuple(w[i : i + k]) for i in range(len(w) - k + 1)}
            wanted = shingle(want)
            for i in range(len(words)):
                if words[i : i + k] and len(wanted & shingle(words[i : i + len(want)])) >= containment * len(wanted):
                    out.add((d, name))
                    break
    return out


def test_against_brute_force(spark):
    rnd = random.Random(9)
    filler = lambda n: " ".join(rnd.choice(["license", "the", "under", "software", "any", "copy", "alpha", "beta", "public"]) for _ in range(n))
    docs = [(1, None), (2, ""), (3, "licensed"), (4, "x " * 30000 + ls.TEMPLATES[0][1])]
    for i in range(120):
        name, t = rnd.choice(ls.TEMPLATES)
        words = t.split()
        if i % 3 == 1:
            words[rnd.randrange(len(words))] = "changed"
        if i % 3 == 2:
            words = words[: len(words) // 2]
        docs.append((10 + i, f"{filler(rnd.randint(0, 60))}\n{' '.join(words).upper() if i % 2 else ' '.join(words)}\n{filler(rnd.randint(0, 60))}"))
    df = spark.createDataFrame([(*d, "L") for d in docs], "doc_id long, text string, license string").repartition(4)
    got = {(r["doc_id"], r["license"]) for r in ls.scan(df).collect()}
    want = brute(docs, ls.TEMPLATES)
    assert want <= got
    # windows are longer than the template, so edited ones can hold a little more
    assert len(got - want) <= 0.1 * len(want)


def test_documents(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    rows = [(r["doc_id"], r["text"]) for r in docs.collect()]
    assert {(r["doc_id"], r["license"]) for r in ls.query(spark, "/root/testdata/sf0.01").collect()} == brute(rows, ls.TEMPLATES)


def test_plan_is_native(spark):
    plan = ls.query(spark, "/root/testdata/sf0.001")._jdf.queryExecution().executedPlan().toString()
    assert not any(k in plan for k in ("Python", "Pandas", "Arrow", "CartesianProduct", "NestedLoop"))


def test_empty(spark):
    df = spark.createDataFrame([], "doc_id long, text string")
    assert ls.scan(df).count() == 0 and ls.scan(df, []).count() == 0


def test_templates_from_a_frame_in_blocks(spark, monkeypatch):
    docs = [(k, f"some words before {t} and some after it") for k, (_, t) in enumerate(ls.TEMPLATES)] + [(100, "nothing of the kind"), (101, None)]
    df = spark.createDataFrame(docs, "doc_id long, text string")
    want = sorted(map(tuple, ls.scan(df).collect()))
    monkeypatch.setattr(ls, "MOST_TEMPLATES", 5)
    frame = spark.createDataFrame([*ls.TEMPLATES, ("none", None), ("marks", "!!")], "license string, text string")
    assert sorted(map(tuple, ls.scan(df, frame).collect())) == sorted(map(tuple, ls.scan(df, list(ls.TEMPLATES)).collect())) == want
    assert ls.scan(df, frame.limit(0)).count() == 0
