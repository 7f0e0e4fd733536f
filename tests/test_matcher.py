import itertools

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from dnfblock.operators import matcher


@settings(max_examples=60, deadline=None)
@given(st.integers(1, 4), st.integers(0, 2), st.randoms(use_true_random=False))
def test_hungarian_is_optimal(n, more, rng):
    cost = np.array([[rng.randrange(20) for _ in range(n + more)] for _ in range(n)], float)
    found = matcher.hungarian(cost)
    assert len({i for i, _ in found}) == len({j for _, j in found}) == n
    best = min(sum(cost[i, j] for i, j in enumerate(p)) for p in itertools.permutations(range(n + more), n))
    assert abs(sum(cost[i, j] for i, j in found) - best) < 1e-9


def test_jaro_winkler():
    assert matcher.jaro_winkler("martha", "marhta") == pytest.approx(0.9611, abs=1e-4)
    assert matcher.jaro_winkler("dixon", "dicksonx") == pytest.approx(0.8133, abs=1e-4)
    assert matcher.jaro_winkler("abc", "xyz") == 0 and matcher.jaro_winkler("a", "a") == 1


def test_soft_tfidf():
    idf = {"oak": 1.0, "oaks": 1.0, "red": 1.0}
    assert matcher.soft_tfidf(["red", "oak"], ["red", "oak"], idf) == pytest.approx(1.0)
    assert 0.9 < matcher.soft_tfidf(["red", "oak"], ["red", "oaks"], idf, 0.9) < 1
    assert matcher.soft_tfidf(["red", "oak"], ["red", "oaks"], idf, 1.0) == pytest.approx(0.5)
    assert matcher.soft_tfidf([], ["red"], idf) == 0


def test_assign_drops_what_is_not_alike():
    sim = {("a", "x"): 0.9, ("b", "y"): 0.4, ("c", "x"): 0.95}
    assert matcher.assign(sim, ["a", "b", "c"], ["x", "y"]) == ((("b",), ("y",)), (("c",), ("x",)))
    assert matcher.assign({}, ["a"], ["x", "y"]) == ()


def test_exhaustive_guard():
    assert len(matcher.exhaustive_simple("abc", "xy")) == 6 and len(matcher.exhaustive_complex("ab", "xy")) == 9
    with pytest.raises(ValueError):
        matcher.exhaustive_complex("abcdefgh", "abcdefgh")


@pytest.mark.parametrize("t", [1, 5, 40])
def test_prefix_strategy_equals_exact(spark, t):
    import random

    rng = random.Random(3)
    words = [f"w{i}" for i in range(60)] + ["the"] * 20
    make = lambda n: spark.createDataFrame([(f"{n}{i}", [" ".join(rng.choices(words, k=6))]) for i in range(60)], "rid string, v array<string>")
    w = matcher.weights(make("l"), make("r"), ["v"], ["v"])
    rows = lambda s: [tuple(r) for r in matcher.top_duplicates(w, t, s).orderBy("rank").collect()]
    assert rows("prefix") == rows("exact")


def test_nulls_among_values_lose_no_tokens(spark):
    df = spark.createDataFrame([("a", [None, "Red oak"], None), ("b", [None], ["elm", None])], "rid string, v array<string>, x array<string>")
    assert sorted(map(tuple, matcher.record_tokens(df, ["v", "x"]).collect())) == [("a", "oak"), ("a", "red"), ("b", "elm")]


@pytest.mark.parametrize("t, heavy", [(1, 20_000), (40, 4), (300, 4), (100_000, 4)])
def test_top_pairs_of_classes_equal_exact(spark, monkeypatch, t, heavy):
    """Copies, ties and large blocks included: no rank, id or score changes."""
    import random

    from dnfblock.operators import top_pairs

    monkeypatch.setattr(top_pairs, "HEAVY", heavy)
    rng = random.Random(5)
    words = [f"w{i}" for i in range(12)] + ["the"] * 8
    texts = [" ".join(rng.choices(words, k=5)) for _ in range(25)]
    make = lambda n: spark.createDataFrame([(f"{n}{i:03d}", [rng.choice(texts), rng.choice(["", "x y", f"only {n}{i}"])]) for i in range(60)], "rid string, v array<string>")
    left, right = make("l"), make("r")
    v = top_pairs.vectors(left, right, ["v"], ["v"])
    rows = lambda df: [tuple(r) for r in df.orderBy("rank").collect()]
    want = rows(matcher.top_duplicates(matcher.weights(left, right, ["v"], ["v"]), t))
    assert rows(top_pairs.top_pairs(v, left, right, ["v"], ["v"], t)) == want


@pytest.mark.parametrize("t, frequent", [(15, 12)])
def test_top_pairs_by_keys_equal_exact_and_leave_no_consumed_tables(spark, monkeypatch, t, frequent):
    """Few left records first, most tokens known within bounds only; what a step has used up is deleted."""
    import os
    import random

    from dnfblock.operators import top_pairs
    from dnfblock.storage import shared_root

    monkeypatch.setattr(top_pairs, "FREQUENT", frequent)
    monkeypatch.setattr(top_pairs, "FIRST", 1)
    monkeypatch.setattr(top_pairs, "MORE", 4)
    rng = random.Random(7)
    words = [f"w{i}" for i in range(150)] + ["the", "of"] * 20
    right = [(f"r{i:03d}", [" ".join(rng.choices(words, k=6))]) for i in range(150)]
    left = [(f"l{i:03d}", [right[rng.randrange(150)][1][0] + rng.choice([" the", " w3", " w4 w5", f" own{i}"])]) for i in range(100)]
    left, right = (spark.createDataFrame(x, "rid string, v array<string>") for x in (left, right))
    root = f"{shared_root(spark).removeprefix('file://')}/{spark.sparkContext.applicationId}"
    before = set(os.listdir(root)) if os.path.isdir(root) else set()
    rows = lambda df: [tuple(r) for r in df.orderBy("rank").collect()]
    got = rows(top_pairs.top_pairs(top_pairs.vectors(left, right, ["v"], ["v"]), left, right, ["v"], ["v"], t))
    assert got == rows(matcher.top_duplicates(matcher.weights(left, right, ["v"], ["v"]), t))
    labels = {x.rsplit("-", 1)[0] for x in set(os.listdir(root)) - before if not x.startswith(".")}
    assert not labels & {"first", "next", "blocks", "keys", "rids", "some", "rarest", "held"}


@pytest.mark.parametrize("known, marks", [(3_000_000, 1 << 28), (30, 1 << 12)])
def test_top_pairs_leave_out_records_and_keys_before_any_shuffle(spark, monkeypatch, known, marks):
    """Bounds below 1, some or all tokens known, crowded bits: same rows, and most records and keys are gone before they are written."""
    import random

    from dnfblock.operators import top_pairs

    monkeypatch.setattr(top_pairs, "KNOWN", known)
    monkeypatch.setattr(top_pairs, "MARKS", marks)
    monkeypatch.setattr(top_pairs, "FIRST", 1)
    rng = random.Random(11)
    # a right record has a token of its own; only left records with few numbers can be near
    right = [(f"r{i:03d}", [f"total{i % 90} c{rng.randrange(4)} d{rng.randrange(9)} label{i}"]) for i in range(240)]
    left = [(f"l{i:03d}", [f"total{rng.randrange(90)} c{rng.randrange(4)} d{rng.randrange(9)} " + (f"no{i}" if i % 20 else "d1")]) for i in range(300)]
    left, right = (spark.createDataFrame(x, "rid string, v array<string>") for x in (left, right))
    seen = {}
    real = top_pairs._met
    monkeypatch.setattr(top_pairs, "_met", lambda fs, bags, bounds, few: (seen.update(left=bags[0].count(), bounds=bounds), real(fs, bags, bounds, few))[1])
    rows = lambda df: [tuple(r) for r in df.orderBy("rank").collect()]
    made = [top_pairs.with_bags(df, ["v"]) for df in (left, right)]
    got = rows(top_pairs.top_pairs(top_pairs.vectors(*made, ["v"], ["v"]), *made, ["v"], ["v"], 9))
    assert got == rows(matcher.top_duplicates(matcher.weights(left, right, ["v"], ["v"]), 9))
    if known > 1000:
        assert seen["left"] <= 15 and seen["bounds"][0] > got[-1][3]


def test_marks_keep_every_key(spark):
    from dnfblock.operators import top_pairs

    keys = [0, 1, -1, 2**62 + 5, -(2**63), 123456789012345]
    bits = top_pairs._marks(spark.createDataFrame([(k,) for k in keys], "key long")).value
    at = [k & (top_pairs.MARKS - 1) for k in keys]
    assert all(bits[i >> 3] >> (i & 7) & 1 for i in at)
    assert sum(bin(b).count("1") for b in bits if b) == len(set(at))
