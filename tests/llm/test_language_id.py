import math

import numpy as np
import pytest

from runstore.llm import language_id as li


@pytest.fixture(scope="module")
def vocab():
    return li.Vocabulary("piece_bpe_32k.model")


def brute(word, vocab, p):
    """Sum over all segmentations by plain recursion."""
    where = {s: k for k, s in enumerate(vocab.pieces)}
    s = li.MARK + word

    def total(i):
        if i == len(s):
            return 1.0
        out = sum(p[where[s[i:j]]] * total(j) for j in range(i + 1, min(len(s), i + li.MAX_PIECE) + 1) if s[i:j] in where)
        return out + (li.STRANGE * total(i + 1) if s[i] not in where else 0.0)

    return total(0)


def test_forward_sums_all_segmentations(vocab):
    rng = np.random.default_rng(3)
    p = rng.random((len(vocab.pieces), 2))
    p /= p.sum(0)
    words = ["the", "a", "there", "straße", "xqzж", "中a", "ouverture", "étéü"]
    got = li.Lattice(words, vocab).totals(p)
    for k, w in enumerate(words):
        for lang in range(2):
            assert got[k, lang] == pytest.approx(math.log(brute(w, vocab, p[:, lang])), rel=1e-9)


def test_long_words_are_not_cut(vocab):
    """A word summed alone equals the same word summed among others; no length loses pieces over a cut."""
    rng = np.random.default_rng(5)
    p = rng.random((len(vocab.pieces), 3))
    p /= p.sum(0)
    words = ["the", "internationalization", "xqzж", "ouvertureinformation", "étéü" * 8]
    assert vocab.longest > 8 and any(len(x) == vocab.longest for x in vocab.pieces)
    got = li.Lattice(words, vocab).totals(p)
    for k, w in enumerate(words):
        assert li.LongWord(w, vocab).total(p) == pytest.approx(got[k], rel=1e-9)
    assert li.log_chances([*words, "the" * 400], vocab, p)[:-1] == pytest.approx(got)
    long = li.log_chances(["there" * 3000, "there" * 6000], vocab, p)
    assert np.isfinite(long).all() and long[1] == pytest.approx(2 * long[0], rel=0.01)


def test_expected_counts_of_long_words(vocab):
    rng = np.random.default_rng(6)
    p = rng.random(len(vocab.pieces))
    p /= p.sum()
    for w in ("there", "internationalж"):
        assert li.LongWord(w, vocab).expected(p) == pytest.approx(li.Lattice([w], vocab).expected(p, np.array([1.0])), abs=1e-9)


def test_expected_counts(vocab):
    """Expected counts equal counts times the derivative of log probability by log piece probability."""
    rng = np.random.default_rng(4)
    p = rng.random(len(vocab.pieces))
    p /= p.sum()
    words, counts = ["there", "the", "eau"], np.array([2.0, 1.0, 5.0])
    got = li.Lattice(words, vocab).expected(p, counts)
    for k in np.argsort(-got)[:10]:
        up, down = p.copy(), p.copy()
        up[k] *= 1 + 1e-5
        down[k] *= 1 - 1e-5
        slope = sum(c * (math.log(brute(w, vocab, up)) - math.log(brute(w, vocab, down))) / 2e-5 for w, c in zip(words, counts))
        assert got[k] == pytest.approx(slope, rel=1e-4)


def test_held_out_accuracy(spark):
    got = li.query(spark, "/root/testdata/sf0.01").join(spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "lang"), "doc_id").collect()
    held = [r for r in got if r["held_out"]]
    assert len(got) == 1000 and len(held) > 200
    assert sum(r["lang"] == r["lang_pred"] for r in held) / len(held) >= 0.97
    assert all(0 <= r["score"] <= 1 for r in got)


def test_edges(spark):
    train = spark.createDataFrame([(1, "the and of", "en"), (2, "le la les", "fr"), (3, None, "en"), (4, "x", None)], "doc_id long, text string, lang string")
    model = li.train(train)
    assert model.languages == ["en", "fr"]
    rows = [(1, None, "a"), (2, "", "b"), (3, "12 !! 7", "c"), (4, "the" * 4000, "d"), (None, "les les", "e"), (4, "the", None)]
    got = li.identify(spark.createDataFrame(rows, "doc_id long, text string, score string"), model).collect()
    assert [r["lang_pred"] for r in got] == ["und", "und", "und", "en", "fr", "en"]
    assert li.identify(train.limit(0), model).count() == 0
    none = li.train(train.limit(0))
    assert {r["lang_pred"] for r in li.identify(train, none).collect()} == {"und"}
