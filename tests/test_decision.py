import math
import random

import pytest

from dnfblock.operators import decision, matcher

FIELDS = "rid string, a array<string>, b array<string>"
MAPPINGS = ((("a",), ("a",)), (("a", "b"), ("b",)))


def _sides(spark):
    rng = random.Random(5)
    words = "oak oaks red reed ash ashes elm elms pine pines".split()
    make = lambda: [rng.choice([" ".join(rng.choices(words, k=rng.randrange(4)))]) for _ in range(rng.randrange(3))]
    rows = [(f"r{i}", make(), make()) for i in range(12)] + [("none", None, None), ("gap", [None, ""], ["oak"])]
    return rows, spark.createDataFrame(rows, FIELDS)


def test_classify_equals_brute_force(spark):
    rows, df = _sides(spark)
    w = matcher.weights(df, df, ["a", "b"], ["a", "b"])
    n = w.select("side", "rid").distinct().count()
    idf = {r.token: math.log(n / r.df) for r in w.select("token", "df").distinct().collect()}
    words = lambda values: [t for v in values or [] if v for t in v.split()]
    pairs = [(x[0], y[0]) for x in rows for y in rows]
    want = {}
    for x in rows:
        for y in rows:
            cells = [(words(x[1]), words(y[1])), (words(x[1]) + words(x[2]), words(y[2]))]
            cells = [c for c in cells if all(any(idf[t] > 0 for t in side) for side in c)]
            s = sum(matcher.soft_tfidf(*c, idf) for c in cells) / len(cells) if cells else 0.0
            want[x[0], y[0]] = s
    got = decision.classify(spark.createDataFrame(pairs, "l_rid string, r_rid string"), w, df, df, MAPPINGS, 0.8, 0.4).collect()
    assert len(got) == len(pairs) and len({r.decision for r in got}) == 3
    for r in got:
        assert r.score == pytest.approx(want[r.l_rid, r.r_rid], abs=1e-9)
        assert r.decision == ("duplicate" if r.score >= 0.8 else "probable" if r.score >= 0.4 else "non-duplicate")


def test_classify_edge_cases(spark):
    _, df = _sides(spark)
    w = matcher.weights(df, df, ["a", "b"], ["a", "b"])
    pairs = spark.createDataFrame([("r0", "r0"), ("r0", "r0"), ("none", "r1")], "l_rid string, r_rid string")
    assert [r.score for r in decision.classify(pairs, w, df, df, ()).collect()] == [0.0] * 3
    assert decision.classify(pairs, w, df, df, MAPPINGS).count() == 3
    assert decision.classify(pairs.limit(0), w, df, df, MAPPINGS).count() == 0
    with pytest.raises(ValueError):
        decision.classify(pairs, w, df, df, MAPPINGS, 0.2, 0.5)
