import hashlib

import public_tokenizers
import sentencepiece

import corpus_pipeline as cp
from runstore.llm import base, decontaminate, language_id, quality
from tests.llm.test_near_dup import brute


def test_run_against_brute_force(spark):
    d = "/root/testdata/sf0.001"
    docs = base.table(spark, d, "documents")
    got = {r["doc_id"]: r for r in cp.run(spark, d).collect()}
    rows = {r["doc_id"]: r["text"] for r in docs.collect()}
    model = language_id.train(docs.where(language_id.fold("doc_id", 3) != 1))
    scorer = language_id.Scorer(model)
    kept = {k: t for k, t in rows.items() if scorer.document(t)[0] != "und" and scorer.document(t)[1] >= 0.5}
    assert len(kept) >= 0.95 * len(rows)
    after = docs.where(docs.doc_id.isin(list(kept)))
    net = quality.fit_on_tables(after, base.table(spark, d, "labels"))
    kept = {k: t for k, t in kept.items() if net.scores(quality.features(t)[None])[0] >= 0.3}
    first = {d for d, _, c in brute(sorted(kept.items())) if d == c}
    kept = {k: t for k, t in kept.items() if k in first}
    items = [decontaminate.normal(r["text"]) for r in base.table(spark, d, "benchmark").collect()]
    kept = {k: t for k, t in kept.items() if not any(len(i.split()) >= 5 and decontaminate.distance_in(i, decontaminate.normal(t), int(0.08 * len(i))) for i in items)}
    assert set(got) == set(kept)
    lib = sentencepiece.SentencePieceProcessor(model_file=public_tokenizers.path("piece_bpe_32k.model"))
    for k, t in kept.items():
        assert list(got[k]["ids"]) == lib.encode(t, add_bos=True, add_eos=True)
        assert got[k]["decoded_sha256"] == hashlib.sha256(lib.decode(list(got[k]["ids"])).encode()).hexdigest()


def test_columns(spark):
    docs = base.table(spark, "/root/testdata/sf0.001", "documents")
    for _, stage in cp.STAGES[:-1]:
        assert stage(spark, docs, "/root/testdata/sf0.001").columns == docs.columns


ODD = "doc_id long, text string, lang string, source string, n_chars long, node long, score double, lang_pred string, band string, t string, component_id int, ids string"


#: Beyond the ids of the given documents.
FAR = 10**6


def odd_rows():
    words = "the people and their work in the house of the old town were there for a long time before the others came".split()
    text = " ".join(words * 6)
    rows = [(1, None), (2, ""), (3, " \n"), (4, text), (4, text), (5, text), (6, "12 34 !!"), (None, text + " end"), (None, None), (7, " ".join(words * 6000)), (8, "a" * 300000)]
    return [(d and FAR + d, x, None, "s", None, 1, 0.5, "zz", None, "t", 3, None) for d, x in rows]


def test_stages_on_odd_rows(spark):
    """Nulls in any column, empty and very long texts, ties, repeated rows, clashing extra columns: no crash, and rows pass unchanged."""
    d = "/root/testdata/sf0.001"
    docs = spark.createDataFrame(odd_rows(), ODD)
    known = base.table(spark, d, "documents")
    mixed = docs.unionByName(known, allowMissingColumns=True)
    given = {tuple(r) for r in mixed.collect()}
    for name, stage in cp.STAGES[:-1]:
        out = stage(spark, mixed, d)
        rows = [tuple(r) for r in out.collect()]
        assert out.columns == mixed.columns and set(rows) <= given, name
        if name == "language_id":
            assert not [r for r in rows if r[0] in (FAR + 1, FAR + 2, FAR + 3, FAR + 6)] and len([r for r in rows if r[0] == FAR + 4]) == 2
        if name == "near_dup":
            assert len([r for r in rows if r[0] == FAR + 4]) == 2 and not [r for r in rows if r[0] == FAR + 5] and len([r for r in rows if r[0] is None]) == 2
        if name == "decontaminate":
            assert [r for r in rows if r[0] == FAR + 1]
    last = cp.tokenized(spark, docs, d).collect()
    assert len(last) == len(odd_rows()) and {r["n_tokens"] for r in last if r["doc_id"] in (FAR + 1, FAR + 2)} == {2}


def test_stages_on_an_empty_table(spark):
    d = "/root/testdata/sf0.001"
    none = base.table(spark, d, "documents").limit(0)
    for _, stage in cp.STAGES:
        assert stage(spark, none, d).count() == 0
