"""Worked examples in our own records, and properties over random schemes."""

import random

import pytest
from pyspark.sql import functions as F

from dnfblock.functions.indexing import G_FULL, REGISTRY, predicate
from dnfblock.operators import blocking, metrics
from dnfblock.operators.scheme import Atom, Scheme


@pytest.fixture(scope="module")
def people(spark):
    rows = [
        ("a", ["Ana"], ["Torres"], ["70112"]), ("b", ["Bo"], ["Lind"], ["61230"]), ("c", ["Cy"], ["Webb"], ["64555"]),
        ("d", ["Ann"], ["V. Torres Sr."], ["70900"]), ("e", ["Eve"], ["Osei"], []),
    ]
    return spark.createDataFrame(rows, "rid string, first array<string>, last array<string>, zip array<string>")


def test_raw_tokens_keep_case_and_marks(spark):
    out = spark.range(1).select(REGISTRY["raw_token"].keys(F.lit("V. Torres Sr."))).first()[0]
    assert set(out) == {"V.", "Torres", "Sr."}


def test_disjunction_covers_duplicates_and_some_others(people):
    s = Scheme.of(Atom.simple("token", "last"), Atom.simple("first_digit", "zip"))
    assert s.is_disjunctive and s.k == 1
    pairs = {(r.l_rid, r.r_rid) for r in blocking.candidates(people, people, s, self_pairs=True).collect()}
    assert pairs == {("a", "d"), ("b", "c")}
    both = Scheme.of((Atom.simple("token", "last"), Atom.simple("first_digit", "zip")))
    assert both.k == 2 and [tuple(r) for r in blocking.candidates(people, people, both, self_pairs=True).collect()] == [("a", "d")]


def test_keys_of_a_record(people):
    s = Scheme.of(Atom.simple("token", "last"), Atom.simple("first_digit", "zip"))
    keys = {(r.term_id, r.key) for r in blocking.index(people, s, 0).where("rid = 'a'").collect()}
    assert keys == {(0, "torres"), (1, "7")}
    assert blocking.index(people, s, 0).where("rid = 'e' AND term_id = 1").count() == 0


def test_null_is_the_empty_set(spark):
    df = spark.createDataFrame([(None, ["x"]), ([], ["x"]), ([None], ["x"])], "a array<string>, b array<string>")
    assert [r[0] for r in df.select(predicate("token", F.col("a"), F.col("b"))).collect()] == [False] * 3


def test_int_pm1_is_distance_one(spark):
    df = spark.range(12).select(F.array(F.col("id").cast("string")).alias("a"), F.col("id").alias("x"))
    other = df.select(F.col("a").alias("b"), F.col("x").alias("y"))
    rows = df.crossJoin(other).select("x", "y", predicate("int_pm1", F.col("a"), F.col("b")).alias("p")).collect()
    assert all(r.p == (abs(r.x - r.y) <= 1) for r in rows)


def test_json_and_expand():
    s = Scheme.of((Atom.complex("token", ["a", "b"], ["c"]), Atom.simple("exact", "a", "d")), Atom.simple("first3", "b", "c"))
    assert Scheme.from_json(s.to_json()) == s
    assert len(s.expand().terms) == 3 and all(len(a.left) == len(a.right) == 1 for t in s.expand().terms for a in t)


@pytest.mark.parametrize("seed", range(6))
def test_plans_agree_with_all_pairs(spark, seed):
    rng = random.Random(seed)
    word = lambda: rng.choice(["red oak", "red", "oak 12", "pine 13", "13 pine", "elm", "Elm 012", "", "birch-bark", "12"])
    side = lambda n: spark.createDataFrame([(f"{n}{i:02d}", [word() for _ in range(rng.randrange(3))], [word()] if rng.random() < 0.8 else None) for i in range(18)], "rid string, p array<string>, q array<string>")
    left, right = side("l"), side("r")
    atom = lambda: Atom(rng.choice(G_FULL), tuple(rng.sample(["p", "q"], rng.randrange(1, 3))), tuple(rng.sample(["p", "q"], rng.randrange(1, 3))))
    s = Scheme(tuple(tuple(atom() for _ in range(rng.randrange(1, 3))) for _ in range(rng.randrange(1, 4))))
    rows = lambda df: sorted(map(tuple, df.collect()))
    expected = rows(blocking.covered_pairs_bruteforce(left, right, s))
    assert rows(blocking.candidates(left, right, s)) == expected
    assert rows(blocking.candidates(left, right, s, dedup="distinct")) == expected
    assert rows(blocking.candidates(left, right, s, salts=3)) == expected
    assert rows(blocking.candidates(left, right, s.expand())) == expected
    assert rows(blocking.verified_candidates(left, right, s)) == expected
    assert set(expected) <= set(rows(blocking.candidates(left, right, s, namespaced=False)))
    assert len(expected) <= blocking.gamma_upper_bound(left, right, s)
    purged = rows(blocking.candidates(left, right, s, max_block_pairs=5))
    assert set(purged) <= set(expected) and len(set(purged)) == len(purged)


@pytest.mark.parametrize("seed, most", [(0, 8), (1, 3), (2, 0)])
def test_counted_candidates_equal_all_pairs(spark, monkeypatch, seed, most):
    from collections import Counter

    monkeypatch.setattr(blocking, "MOST_KEYS", most)
    rng = random.Random(seed)
    word = lambda: rng.choice(["red oak", "red", "oak 12", "pine 13", "13 pine", "elm", "Elm 012", "", "birch-bark", "12"])
    side = lambda n: spark.createDataFrame([(f"{n}{i:02d}", [word() for _ in range(rng.randrange(3))], [word()] if rng.random() < 0.8 else None) for i in range(18)], "rid string, p array<string>, q array<string>")
    left, right = side("l"), side("r")
    atom = lambda: Atom(rng.choice(["exact", "token", "qgram2", "int_pm1", "first3"]), tuple(rng.sample(["p", "q"], rng.randrange(1, 3))), tuple(rng.sample(["p", "q"], rng.randrange(1, 3))))
    s = Scheme(tuple(tuple(atom() for _ in range(rng.randrange(1, 3))) for _ in range(rng.randrange(1, 4))))
    pairs = [tuple(r) for r in blocking.covered_pairs_bruteforce(left, right, s).collect()]
    assert blocking.count_candidates(left, right, s).first()[0] == len(pairs)
    many = [Counter(p[i] for p in pairs) for i in (0, 1)]
    for found in (blocking.links(left, right, s).collect(), blocking.verified_links(left, right, s).collect()):
        assert {(r.side, r.rid): r.links for r in found} == {(i, f"{'lr'[i]}{k:02d}"): many[i][f"{'lr'[i]}{k:02d}"] for i in (0, 1) for k in range(18)}
        assert len(found) == 36 and all(r.class_id <= r.rid for r in found)
    truth = spark.createDataFrame([(f"l{i:02d}", f"r{i:02d}") for i in range(18)], "l_rid string, r_rid string")
    want = metrics.blocking_metrics(spark.createDataFrame(pairs, truth.schema), truth, left, right).first()
    assert metrics.scheme_metrics(s, truth, left, right).first() == want


def test_counted_candidates_plan_joins_no_pairs(spark, people):
    """Neither side meets the other: both are summed by subset of keys, in one aggregate."""
    s = Scheme.of(Atom.simple("exact", "last"), Atom.simple("soundex", "first"))
    plan = blocking.count_candidates(people, people, s)._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan


def test_candidate_plan_has_no_loop_and_no_python(spark, people):
    s = Scheme.of(Atom.simple("token", "last"), Atom.simple("soundex", "first"))
    plan = blocking.candidates(people, people, s)._jdf.queryExecution().executedPlan().toString()
    assert not any(x in plan for x in ("CartesianProduct", "NestedLoop", "Python", "Arrow"))


def test_candidate_plan_broadcasts_no_keys(spark, people, tmp_path):
    """At the session's own limit for broadcasts, which the files of a table can be below while their exploded keys fill the driver."""
    people.write.parquet(f"{tmp_path}/people")
    kept = spark.read.parquet(f"{tmp_path}/people")
    s = Scheme.of(Atom.simple("token", "last"), Atom.simple("soundex", "first"))
    for salts in (1, 8):
        plan = blocking.candidates(kept, kept, s, salts=salts)._jdf.queryExecution().executedPlan().toString()
        assert "Broadcast" not in plan and "SortMergeJoin" in plan


def test_measures(spark, people):
    truth = spark.createDataFrame([("a", "d"), ("b", "e")], "l_rid string, r_rid string")
    gamma = spark.createDataFrame([("a", "d"), ("a", "b"), ("b", "c")], "l_rid string, r_rid string")
    m = metrics.blocking_metrics(gamma, truth, people, people).first()
    assert (m.gamma, int(m.omega), m.truth) == (3, 25, 2)
    assert m.pc == 0.5 and abs(m.rr - 0.88) < 1e-12 and abs(m.pq - 1 / 3) < 1e-12
    assert abs(m.pq - m.truth / 25 * m.pc / (1 - m.rr)) < 1e-12
    empty = metrics.blocking_metrics(gamma.limit(0), truth.limit(0), people, people).first()
    assert empty.pc is None and empty.pq is None and empty.rr == 1


def test_linked_view_and_records(spark, people):
    pairs = spark.createDataFrame([("a", "d")], "l_rid string, r_rid string")
    v = {(r.l_rid, r.r_rid): r.name for r in blocking.linked_view(pairs, people, people, {"name": ("last", "last")}).collect()}
    assert v[("a", "d")] == "Torres" and v[(None, "b")] == "Lind" and len(v) == 9
    assert blocking.with_records(pairs, people, people).first().r_last == ["V. Torres Sr."]


def test_metaphones_in_atoms_terms_and_coverage(spark):
    """Functions of all values at once stand in conjunctions, indexes and predicates like the others."""
    from dnfblock.functions import phonetic
    from dnfblock.functions.indexing import G_FULL
    from dnfblock.operators import blocking, search_space
    from dnfblock.operators.scheme import Atom, Scheme

    assert {"metaphone", "double_metaphone"} <= set(G_FULL)
    left = spark.createDataFrame([("1", ["Smith", "Jon 7"], ["x y"]), ("2", ["Brown"], ["z"]), ("3", None, ["x"]), ("4", [None, "smyth"], ["y"])], "rid string, a array<string>, b array<string>")
    right = left.select("rid", "a", "b")
    code = lambda vs: {phonetic.metaphone(t) for v in vs or [] if v for t in v.lower().split() if t.isalpha()} - {""}
    rows = {r.rid: (code(r.a), {t for v in r.b for t in v.split()}) for r in left.collect()}
    scheme = Scheme.of((Atom.simple("metaphone", "a"), Atom.simple("token", "b")))
    want = {(x, y) for x in rows for y in rows if rows[x][0] & rows[y][0] and rows[x][1] & rows[y][1]}
    assert {tuple(r) for r in blocking.candidates(left, right, scheme).collect()} == want == {tuple(r) for r in blocking.covered_pairs_bruteforce(left, right, scheme).collect()}
    pairs = spark.createDataFrame([(1, "1", "4"), (2, "1", "2")], "tp_id long, l_rid string, r_rid string")
    cov = search_space.collect_coverage(pairs, pairs.where("tp_id = 2"), left, right, search_space.atoms(G_FULL, ((("a",), ("a",)),)))
    at = G_FULL.index("double_metaphone")
    assert cov.dups[at].tolist() == [True, False] and cov.nondups[at].tolist() == [False]


def test_sql_functions_equal_indexing_functions(spark):
    from pyspark.sql import functions as F

    from dnfblock import sql
    from dnfblock.functions.indexing import REGISTRY

    sql.register(spark)
    texts = ["Mary had 007 little-lambs, 12 of them!", "", " ", "9", "x", "00", "999999999999999999 1234567890123456789", "É naïve  a b c d e f g", "a\tb\nc  D", "12.50"]
    df = spark.createDataFrame([(t,) for t in texts], "x string")
    for name in sql.KEY_FUNCTIONS:
        rows = df.select("x", F.expr(f"{name}(x)").alias("a"), REGISTRY[name[4:]].keys(F.col("x")).alias("b")).collect()
        assert all(sorted(r.a) == sorted(r.b) for r in rows), (name, rows)
    assert spark.sql("SELECT gbp_round10('15', 'no 19'), gbp_round10('9007199254740993', '9007199254740989')").first() == (True, False)


@pytest.mark.parametrize("num, den", [(7, 10), (8, 10), (1, 2), (1, 1)])
def test_near_sets_equal_brute_force(spark, num, den):
    from dnfblock.operators.near_sets import near_pairs

    draw = random.Random(num)
    base = [[f"w{draw.randrange(40)}" for _ in range(draw.randrange(1, 25))] for _ in range(40)]
    near = [[w for w in b if draw.random() > 0.1] + ["z"] * draw.randrange(2) for b in base for _ in range(3)]
    rows = [(f"{i:03d}", w) for i, w in enumerate(base + near + [[], None, ["q"], ["q", "q"]])]
    got = near_pairs(spark.createDataFrame(rows, "rid string, w array<string>"), num, den).collect()
    least = {}
    for rid, w in rows:
        if w:
            least.setdefault(frozenset(w), rid)
    sets = sorted((rid, w) for w, rid in least.items())
    wanted = [(a, b) for i, (a, x) in enumerate(sets) for b, y in sets[i + 1 :] if len(x & y) * den >= len(x | y) * num]
    assert sorted(map(tuple, got)) == wanted
    assert (num == den) == (not wanted)


def test_bitmaps_leave_few_pairs_that_are_not_near(spark):
    import numpy as np

    from dnfblock.operators import near_sets

    draw = np.random.default_rng(5)
    sets = [draw.integers(-(1 << 62), 1 << 62, n) for n in (30, 200, 290, 2_000, 5_000)]
    for a in sets:
        for b in (a[: len(a) * 3 // 4], np.r_[a[5:], a[:3] + 1]):
            x, y = near_sets._bitmap(a).view(np.uint64), near_sets._bitmap(b).view(np.uint64)
            x, y = (v.reshape(-1, min(len(x), len(y))) for v in (x, y))
            bits = np.bitwise_count(np.bitwise_xor.reduce(x) ^ np.bitwise_xor.reduce(y)).sum()
            assert bits <= len(np.setxor1d(a, b))
    # all share their rarest elements with all others, but only the planted pair is near
    words = draw.integers(-(1 << 62), 1 << 62, 420).tolist()  # hashes, as bitmaps are of their upper bits
    rows = [(i, sorted({*words[:20], *(words[20 + j] for j in draw.integers(0, 400, 150))})) for i in range(40)]
    rows.append((40, rows[0][1][:-2]))
    prefixes = near_sets._prefixes(spark.createDataFrame(rows, "rid int, w array<long>"), 7, 10)
    found = {tuple(r) for p in range(near_sets.PASSES) for r in near_sets._candidates(prefixes, 7, 10, p).collect()}
    assert found == {(40, 0)}


def test_gamma_sketches_merge(spark):
    left = spark.createDataFrame([(f"l{i}", [f"k{i % 50}", f"j{i % 7}"]) for i in range(300)], "rid string, v array<string>")
    right = spark.createDataFrame([(f"r{i}", [f"k{i % 40}", f"j{i % 9}"]) for i in range(200)], "rid string, v array<string>")
    s = Scheme.of(Atom.simple("token", "v"), Atom.simple("exact", "v"))
    exact = blocking.candidates(left, right, s).count()
    once = blocking.gamma_sketches(left, right, s)
    assert abs(blocking.gamma_estimate(once).first()[0] - exact) <= 0.05 * exact
    halves = [blocking.gamma_sketches(left.where(f"int(substr(rid, 2)) % 2 = {i}"), right, s, 12) for i in (0, 1)]
    both = halves[0].unionByName(halves[1]).unionByName(once)  # sketches of other sizes merge too
    assert abs(blocking.gamma_estimate(both).first()[0] - exact) <= 0.05 * exact
    assert blocking.gamma_estimate(once.limit(0)).first()[0] == 0
    for salts in (3, "auto"):
        assert blocking.candidates(left, right, s, salts=salts).exceptAll(blocking.candidates(left, right, s)).isEmpty()
        assert blocking.candidates(left, right, s, salts=salts).count() == exact
    assert {r.k for r in blocking.hot_keys(*(blocking.keyed(d, s, i).select(F.explode("keys").alias("k")) for i, d in enumerate((left, right)))).collect()}


def test_count_differences(spark):
    make = lambda rows: spark.createDataFrame(rows, "l_rid string, r_rid string")
    a = make([("a", "x"), ("a", "y"), ("b", "x"), ("c", "x"), ("c", "x")])
    b = make([("a", "y"), ("a", "x"), ("b", "y"), ("c", "x"), ("d", "x")])
    assert blocking.count_differences(a, b).first()[0] == 4 and blocking.count_differences(a, a).first()[0] == 0
    plan = blocking.count_differences(a, a)._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan and "Except" not in plan


def test_bruteforce_query_has_no_limit_of_pairs(spark, monkeypatch):
    from dnfblock.queries.blocking import candidates_bruteforce_p1

    def refused(*_):
        raise ValueError("too many pairs")

    monkeypatch.setattr(blocking, "covered_pairs_bruteforce", refused)
    assert candidates_bruteforce_p1(spark, "/root/testdata/sf0.001").count() > 0
