import numpy as np

from runstore.llm import vector_dup as vd


def brute(rows, threshold=0.98):
    unit, links = {}, [0] * len(rows)
    for k, (_, v, label) in enumerate(rows):
        x = np.array([np.nan if a is None else a for a in v] if v else [], dtype=float)
        if rows[k][0] is not None and label is not None and len(x) and np.isfinite(x).all() and np.abs(x).max() > 0:
            x = x / np.abs(x).max()
            unit[k] = x / np.sqrt((x * x).sum())
    comp = {r[0]: r[0] for r in rows if r[0] is not None}

    def root(d):
        while comp[d] != d:
            d = comp[d]
        return d

    for i in unit:
        for j in unit:
            if i < j and rows[i][2] == rows[j][2] and len(unit[i]) == len(unit[j]) and unit[i] @ unit[j] >= threshold:
                links[i] += 1
                links[j] += 1
                a, b = root(rows[i][0]), root(rows[j][0])
                comp[max(a, b)] = min(a, b)
    return sorted([(d, n, root(d) if d is not None else None) for (d, _, _), n in zip(rows, links)], key=str)


def test_against_brute_force(spark):
    rng = np.random.default_rng(4)
    vectors = []
    for label, n in ((0, 150), (1, 60), (None, 5)):
        x = rng.normal(size=(n, 12))
        vectors += [(v.tolist(), label) for v in x]
        vectors += [((x[0] + rng.normal(size=12) * 0.1).tolist(), label) for _ in range(70 if label == 0 else 5)]
        vectors += [((x[1] + rng.normal(size=12) * 0.2).tolist(), label) for _ in range(10)]
        vectors += [((x[2] * 3).tolist(), label)] * 4
    vectors += [(None, 0), ([], 0), ([0.0] * 12, 0), ([float("nan")] + [1.0] * 11, 0), ([None] + [1.0] * 11, 0), ([float("inf")] * 12, 1), ([1.0, 2.0], 0), ([1.0, 2.0], 0), ([1e-300] * 12, 1), ([1e300] * 12, 1)]
    rows = [(int(i), v, label) for i, (v, label) in zip(rng.permutation(len(vectors)), vectors)]
    rows.append((None, [1.0, 2.0], 0))
    df = spark.createDataFrame([(*r, 1) for r in rows], "vec_id long, embedding array<double>, label int, n_links int").repartition(3)
    got = vd.near_duplicate_vectors(df, k=8, most=16, trees=6).collect()
    assert sorted([(r["vec_id"], r["n_links"], r["component_id"]) for r in got], key=str) == brute(rows)
    assert all(r["kept"] == (r["vec_id"] == r["component_id"]) for r in got if r["vec_id"] is not None)


def test_empty(spark):
    assert vd.near_duplicate_vectors(spark.createDataFrame([], "vec_id long, embedding array<float>, label int")).count() == 0


def test_at_the_threshold(spark):
    """Cosines a billionth above and below the threshold."""
    rows = []
    for g, c in enumerate((0.98 - 1e-9, 0.98 - 5e-10, 0.98 + 5e-10, 0.98 + 1e-9)):
        angle = 0.3 + 1.3 * g
        for k, turn in enumerate((angle, angle + np.arccos(c))):
            rows.append((10 * g + k, [float(np.cos(turn)), float(np.sin(turn))], g))
    got = {r["vec_id"]: (r["n_links"], r["component_id"]) for r in vd.near_duplicate_vectors(spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int")).collect()}
    assert [got[10 * g] for g in range(4)] == [(0, 0), (0, 10), (1, 20), (1, 30)]


def test_crowded_and_exhaustive(spark):
    """A group far over `most` is counted, not listed; an audit that is never content ends in the comparison of all."""
    rng = np.random.default_rng(9)
    centre = rng.normal(size=16)
    rows = [(k, (centre + rng.normal(size=16) * 0.05).tolist(), 1) for k in range(120)] + [(200 + k, rng.normal(size=16).tolist(), 1) for k in range(30)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int")
    want = brute([(i, v, l) for i, v, l in rows])
    for options in ({"k": 4, "most": 8}, {"k": 4, "most": 8, "recall": 2.0, "attempts": 1}):
        got = vd.near_duplicate_vectors(df, **options).collect()
        assert sorted([(r["vec_id"], r["n_links"], r["component_id"]) for r in got], key=str) == want
        assert {r["recall"] for r in got} == {1.0}


def test_clashing_columns_and_repeats(spark):
    rows = [(1, [1.0, 0.0], 0, "x", 9, 9), (1, [0.0, 1.0], 0, "x", 9, 9), (2, [0.0, 1.0], 0, "x", 9, 9), (3, [1.0, 0.001], 0, "x", 9, 9), (4, None, 0, None, None, None)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int, node string, part int, kept int")
    got = sorted((r["vec_id"], r["n_links"], r["component_id"], r["kept"]) for r in vd.near_duplicate_vectors(df).collect())
    assert got == [(1, 1, 1, True), (1, 1, 1, True), (2, 1, 1, False), (3, 1, 1, False), (4, 0, 4, True)]
