import hashlib
import random

import numpy as np
import public_tokenizers
import pytest
import sentencepiece

from runstore.llm import piece_codec as pc


@pytest.fixture(scope="module")
def lib():
    return sentencepiece.SentencePieceProcessor(model_file=public_tokenizers.path("piece_bpe_32k.model"))


@pytest.fixture(scope="module")
def enc():
    return pc.PrefixTableEncoder("piece_bpe_32k.model")


def same(enc, lib, text):
    want = lib.encode(text, add_bos=True, add_eos=True)
    assert np.frombuffer(enc.encode(text), "<u4").tolist() == want, repr(text)


def test_odd_strings(enc, lib):
    for text in ["", " ", "  ", "a", " a", "a ", "a  b", "\n", "\n\n", "\0", "a\0b", "▁", "▁▁x", "<s>", "<0x41>", "<unk>", "é", "﻿", "　", "😀 😀", "中文字", "\x1f", "a\tb", "aaaaaaaaaaa", "======", "\r\n", "x" * 5000, "ab" * 3000]:
        same(enc, lib, text)


def test_random_strings(enc, lib):
    rnd = random.Random(5)
    pieces = [lib.id_to_piece(i).replace("▁", " ") for i in range(259, 32000)]
    chars = "abcdefghijklmnopqrstuvwxyz     etaoinshr.,!$#%&|*'\n\téèüñß0123456789ABCDE中😀"
    for k in range(20000):
        if k % 2:
            text = "".join(rnd.choice(pieces) for _ in range(rnd.randint(1, 12)))
        else:
            text = "".join(rnd.choice(chars) for _ in range(rnd.randint(1, 60)))
        same(enc, lib, text)


def test_repeats(enc, lib):
    rnd = random.Random(6)
    for _ in range(5000):
        unit = "".join(rnd.choice("abeinst ") for _ in range(rnd.randint(1, 3)))
        same(enc, lib, (unit * rnd.randint(1, 30))[: rnd.randint(1, 60)])


def test_documents(spark, enc, lib):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    got = pc.encode_decode(docs, digest=True).collect()
    assert len(got) == len(texts)
    for r in got:
        ids = lib.encode(texts[r["doc_id"]], add_bos=True, add_eos=True)
        assert r["n_tokens"] == len(ids)
        assert r["ids_sha256"] == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest()
        assert r["decoded_sha256"] == hashlib.sha256(lib.decode(ids).encode()).hexdigest()


def test_null_and_clashing_columns(spark):
    df = spark.createDataFrame([(1, None, 5), (1, "", 6), (None, "a b", 7)], "doc_id long, text string, n_tokens int")
    got = pc.encode_decode(df).collect()
    assert sorted((r["n_tokens"], r["decoded"]) for r in got) == [(2, ""), (2, ""), (4, "a b")]
    assert pc.encode_decode(df.limit(0)).count() == 0
