import random
import zlib

import numpy as np
import public_tokenizers
import pytest
from tokenizers import Tokenizer

from runstore.llm import token_store as ts


@pytest.mark.parametrize("values", [[], [0], [0, 0, 0], [5], [1, 2, 3, 1000, 1000, 70000], list(range(0, 100000, 7)), [3, 3, 2**40]])
def test_elias_fano_round_trip(values):
    ef = ts.EliasFano.encode(np.array(values, dtype=np.uint64))
    assert ef.decode().tolist() == values
    for i in list(range(len(values)))[:: max(1, len(values) // 50)]:
        assert ef.select(i) == values[i]


def test_space_is_near_minimal():
    v = np.cumsum(np.random.default_rng(1).integers(1, 3000, 4096))
    ef = ts.EliasFano.encode(v)
    bits = 64 * (len(ef.low) + len(ef.high))
    assert bits < 4096 * (2.2 + np.log2(v[-1] / 4096)) + 128


def test_words_equal_library():
    tok = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    enc = ts.WordEncoder("word_bpe_49k.json", True)
    rnd = random.Random(4)
    bits = ["a", "Be", "the", "'s", "'", "’", "é", "é", "́", "É", "ß", "İ", "ſ", "Ω", "中文", "12", "3", "!!", ".", "_", "\n", "\t", "\x1c", " ", " ", "  ", "<|endoftext|>", "<|", "😀", "don't", "I'll", "ª", "×", "%%%", "　", "\x85"]
    for _ in range(3000):
        text = "".join(rnd.choice(bits) for _ in range(rnd.randint(0, 12)))
        assert np.frombuffer(enc.encode(text), "<u4").tolist() == tok.encode(text, add_special_tokens=False).ids, repr(text)


def test_table(spark, tmp_path):
    rows = [(3, "a b"), (1, None), (2, ""), (7, "The same. " * 3000), (None, "x"), (3, "zz"), (-5, "word")]
    df = spark.createDataFrame([(i, t, i, t) for i, t in rows], "doc_id long, text string, start long, segment string").repartition(3)
    ts.write_token_table(df, f"file://{tmp_path}/t")
    got = sorted(ts.read_token_table(spark, f"file://{tmp_path}/t").collect(), key=lambda r: r["start"])
    tok = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    at = 0
    for row, (i, t) in zip(got, sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0, r[1] or "")), strict=True):
        ids = [*tok.encode(t or "", add_special_tokens=False).ids, 1]
        assert (row["doc_id"], row["start"], row["n_tokens"], row["ids_crc32"]) == (i, at, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
        at += len(ids)
    files = ts.export_files(spark, f"file://{tmp_path}/t", str(tmp_path / "flat"))
    assert sum(len(ts.unpack(open(f, "rb").read())[0]) for f in files) == at


def test_select_of_many_and_its_space():
    rng = np.random.default_rng(3)
    for v in (np.sort(rng.integers(0, 1 << 33, 5000)), np.repeat([7, 1 << 20], 3000), np.arange(70000) // 1000 * 5000):
        ef = ts.EliasFano.encode(v)
        at = rng.integers(0, len(v), 4000)
        assert (ef.select(at) == v[at]).all() and (ef.select(np.arange(len(v))) == ef.decode()).all()
        assert ef.samples.nbytes * 8 <= 32 * (len(v) / ts.SAMPLE + 1)
        assert not any(isinstance(x, np.ndarray) and x is not ef.low and x is not ef.high and x is not ef.samples for x in vars(ef).values())


def test_documents_by_id(spark, tmp_path, monkeypatch):
    monkeypatch.setattr(ts, "SEGMENT_DOCS", 7)
    monkeypatch.setattr(ts, "SEGMENT_TOKENS", 50)
    tok = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    rows = [(i * 3, "word " * (i % 40)) for i in range(100)] + [(None, "x"), (6, "again")]
    ts.write_token_table(spark.createDataFrame(rows, "doc_id long, text string").repartition(3), f"file://{tmp_path}/d")
    got = sorted((r["doc_id"], list(r["ids"])) for r in ts.read_documents(spark, f"file://{tmp_path}/d", [6, 0, 297, 5, 150]).collect())
    assert got == sorted((d, [*tok.encode(t, add_special_tokens=False).ids, 1]) for d, t in rows if d in (6, 0, 297, 150))
    sizes = ts.read_token_table(spark, f"file://{tmp_path}/d").orderBy("start").collect()
    assert all(a["start"] + a["n_tokens"] == b["start"] for a, b in zip(sizes, sizes[1:])) and len(sizes) == len(rows)


def test_long_texts_and_words():
    tok = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    enc = ts.WordEncoder("word_bpe_49k.json", True)
    for text in ("ab" * 5000, "the cat\n" * 20000, "x" * 65 + "! " + "é" * 70):
        assert np.frombuffer(enc.encode(text), "<u4").tolist() == tok.encode(text, add_special_tokens=False).ids


def test_empty_table(spark, tmp_path):
    ts.write_token_table(spark.createDataFrame([], "doc_id long, text string"), f"file://{tmp_path}/e")
    assert ts.read_token_table(spark, f"file://{tmp_path}/e").count() == 0
