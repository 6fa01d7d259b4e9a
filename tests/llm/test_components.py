import random

from runstore.llm import base


def test_components(spark):
    rnd = random.Random(1)
    for n, m in ((50, 30), (200, 150), (40, 400)):
        edges = [(rnd.randrange(n), rnd.randrange(n)) for _ in range(m)] + [(0, k) for k in range(n // 3)] + [(k, k + 1) for k in range(n, n + 40)]
        parent = list(range(n + 50))

        def root(i):
            while parent[i] != i:
                i = parent[i]
            return i

        for a, b in edges:
            x, y = root(a), root(b)
            parent[max(x, y)] = min(x, y)
        got = {r["node"]: r["component"] for r in base.components(spark.createDataFrame(edges, "a long, b long")).collect()}
        assert all(root(k) == c for k, c in got.items())
        assert set(got) >= {k for e in edges for k in e if e[0] != e[1]}


def test_no_edges(spark):
    assert base.components(spark.createDataFrame([], "a long, b long")).count() == 0
