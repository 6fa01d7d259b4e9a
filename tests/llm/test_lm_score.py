import duckdb
import numpy as np

from runstore.llm import lm_score as lm

SCHEMA = "doc_id long, text string, score string"


def test_probabilities_sum_to_one():
    c = np.random.default_rng(1).integers(0, 5, (4, 3)).astype(float)
    c[2] = 0
    assert np.allclose(np.exp(-lm.losses(c, 0.7)).sum(1), 1)


def test_against_sql(spark):
    d = "/root/testdata/sf0.001"
    con = duckdb.connect()
    for t in ("documents", "labels"):
        con.execute(f"create view {t} as select * from '{d}/{t}.parquet'")
    want = sorted(con.execute(lm.ORACLE).fetchall())
    got = sorted(tuple(r) for r in lm.query(spark, d).collect())
    assert len(got) == len(want) == 200
    for a, b in zip(got, want):
        assert a[:2] == b[:2] and np.allclose(a[2:], b[2:], atol=2e-6)


def test_target_scores_lower(spark):
    rows = [(i, "red green blue " * 5 if i % 2 else "one two three " * 5, "") for i in range(20)]
    got = lm.score(spark.createDataFrame(rows, SCHEMA), spark.createDataFrame([(1,), (3,), (3,), (None,), (99,)], "x long")).collect()
    assert max(r["score"] for r in got if r["doc_id"] % 2) < min(r["score"] for r in got if not r["doc_id"] % 2)


def test_edges(spark):
    none = spark.createDataFrame([], "x long")
    got = lm.score(spark.createDataFrame([(1, None, ""), (2, "", ""), (None, "a A", ""), (1, "b " * 90000, "")], SCHEMA), none).collect()
    assert sorted(r["n_tokens"] for r in got) == [0, 0, 2, 90000]
    assert all((r["score"] is None) == (r["n_tokens"] == 0) for r in got)
    assert lm.score(spark.createDataFrame([], SCHEMA), none).count() == 0


def test_whole_against_sql(spark):
    d = "/root/testdata/sf0.001"
    con = duckdb.connect()
    for t in ("documents", "labels"):
        con.execute(f"create view {t} as select * from '{d}/{t}.parquet'")
    want = sorted(con.execute(lm.ORACLE_WHOLE).fetchall())
    assert lm.ORACLE_WHOLE != lm.ORACLE and want != sorted(con.execute(lm.ORACLE).fetchall())
    docs, good = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet").where("quality = 1").select("doc_id")
    for most in (lm._HOT, 50, 0):
        got = sorted(tuple(r) for r in lm.score_whole(docs, good, most=most).collect())
        assert len(got) == len(want) == 200
        for a, b in zip(got, want):
            assert a[:2] == b[:2] and np.allclose(a[2:], b[2:], atol=2e-6)


def test_whole_tells_rare_words_apart(spark):
    common = [(i, " ".join(f"w{k}" for k in range(1100)), "") for i in range(3)]
    rows = [*common, (10, "w1 rareone raretwo", ""), (11, "w1 rarethree rarefour", ""), (12, "w1 rareone raretwo", "")]
    docs, good = spark.createDataFrame(rows, SCHEMA), spark.createDataFrame([(10,)], "x long")
    cut = {r["doc_id"]: r["score"] for r in lm.score(docs, good).collect()}
    whole = {r["doc_id"]: r["score"] for r in lm.score_whole(docs, good).collect()}
    assert cut[10] == cut[11] and whole[10] < whole[11] and whole[10] == whole[12]


def test_whole_edges(spark):
    none = spark.createDataFrame([], "x long")
    got = lm.score_whole(spark.createDataFrame([(1, None, ""), (2, "", ""), (None, "a A", ""), (1, "b " * 90000, "")], SCHEMA), none).collect()
    assert sorted(r["n_tokens"] for r in got) == [0, 0, 2, 90000]
    assert all((r["score"] is None) == (r["n_tokens"] == 0) for r in got)
    assert lm.score_whole(spark.createDataFrame([], SCHEMA), none).count() == 0


def test_whole_in_several_pieces_and_ranges(spark, monkeypatch):
    d = "/root/testdata/sf0.001"
    docs, good = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet").where("quality = 1").select("doc_id")
    want = sorted(tuple(r) for r in lm.score_whole(docs, good).collect())
    monkeypatch.setattr(lm, "_FIRST_BYTES", 40_000)
    got = sorted(tuple(r) for r in lm.score_whole(docs, good, most=30_000).collect())
    assert [g[:2] for g in got] == [x[:2] for x in want] and np.allclose([g[2:] for g in got], [x[2:] for x in want], atol=1e-9)


def test_keys_that_agree_in_their_first_bits_stay_apart():
    key, more = np.array([9, 4, 9, 9, 4], np.uint64), np.array([2, 7, 1, 2, 7], np.uint8)
    k, m, at = lm._distinct(key, more)
    assert k.tolist() == [4, 9, 9] and m.tolist() == [7, 1, 2] and at.tolist() == [2, 0, 1, 2, 0]


def test_packed_columns_come_back():
    for n in (0, 1, 1000):
        cols = [np.random.default_rng(n + c).integers(0, 1 << 63, n).astype(np.uint64) for c in range(3)]
        assert all((a == b).all() for a, b in zip(cols, lm._unpacked(lm._packed(cols, n), 3)))


def test_whole_shuffles_little_more_than_its_text(spark):
    """Of words that hardly repeat: no row is made of a bigram, keys go one way only."""
    rnd = np.random.default_rng(5)
    rows = [(i, " ".join(f"w{x}" for x in rnd.integers(0, 20_000, 600)), "") for i in range(300)]
    docs, good = spark.createDataFrame(rows, SCHEMA), spark.createDataFrame([(10,), (20,)], "x long")
    store, jvm = spark.sparkContext._jsc.sc().statusStore(), spark.sparkContext._jvm

    def written() -> int:
        none = spark.sparkContext._gateway.new_array(jvm.double, 0)
        return sum(x.shuffleWriteBytes() for x in jvm.scala.jdk.javaapi.CollectionConverters.asJava(store.stageList(None, False, False, none, None)))

    before = written()
    assert lm.score_whole(docs, good).count() == 300
    assert written() - before < 5 * sum(len(r[1]) for r in rows)
