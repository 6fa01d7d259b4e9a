import hashlib
import zlib
from collections import Counter, defaultdict

from runstore.llm import interleave as il


def brute(rows, shards, seed=7):
    groups = defaultdict(list)
    for d, t, s in rows:
        key = hashlib.md5(f"{seed}:{'null' if d is None else d}".encode()).hexdigest()
        b = (t or "").encode()
        groups[s].append((key, d is not None, d or 0, zlib.crc32(b), len(b) + 1))
    line = []
    for s, g in groups.items():
        g.sort()
        line += [((2 * r + 1) / (2 * len(g)), s is not None, s or "", *x) for r, x in enumerate(g)]
    line.sort()
    n, out, slots = len(line), [], Counter()
    for p, x in enumerate(line):
        k = p * shards // n
        out.append((x[5] if x[4] else None, x[7], x[6], k, slots[k]))
        slots[k] += 1
    return sorted(out, key=str)


def check(spark, rows, shards):
    df = spark.createDataFrame([(d, t, s, 1, 2) for d, t, s in rows], "doc_id long, text string, source string, shard int, rank int").repartition(3)
    got = il.interleave(df, shards).collect()
    assert sorted([(r["doc_id"], r["size"], r["text_crc32"], r["shard"], r["slot"]) for r in got], key=str) == brute(rows, shards)


def test_against_brute_force(spark, monkeypatch):
    monkeypatch.setattr(il, "STRETCH_ROWS", 7)
    rows = [(i, f"text é {i}" if i % 7 else None, "hot" if i % 3 else f"s{i % 11}") for i in range(500)]
    rows += [(None, "n", None), (1, "again", "hot"), (1, "again", "hot"), (2, "", None)]
    check(spark, rows, 8)
    check(spark, rows[:5], 8)
    check(spark, rows[:100], 1)


def test_mixture_and_sizes(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    got = il.interleave(docs, 8).collect()
    sizes = Counter(r["shard"] for r in got)
    assert len(got) == 1000 and max(sizes.values()) - min(sizes.values()) <= 1
    by = Counter((r["shard"], r["source"]) for r in got)
    for s, n in Counter(r["source"] for r in got).items():
        assert all(abs(by[k, s] - n / 8) <= 2 for k in range(8))
    for k in range(8):
        assert sorted(r["slot"] for r in got if r["shard"] == k) == list(range(sizes[k]))


def test_empty(spark):
    assert il.interleave(spark.createDataFrame([], "doc_id long, text string, source string"), 8).count() == 0
