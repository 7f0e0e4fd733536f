import itertools
import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from dnfblock.operators import learners, search_space, training
from dnfblock.operators.scheme import Atom
from dnfblock.operators.search_space import Coverage

A = [Atom.simple("exact", f"f{i}") for i in range(8)]


def cover(dups, nondups, n=10, m=10) -> Coverage:
    d, x = np.zeros((len(dups), n), bool), np.zeros((len(dups), m), bool)
    for i, (a, b) in enumerate(zip(dups, nondups)):
        d[i, [j - 1 for j in a]] = True
        x[i, [j - 1 for j in b]] = True
    return Coverage([(A[i],) for i in range(len(dups))], d, x)


def chosen(result):
    return [i for i, _, _ in result.chosen]


def test_price_modes_differ():
    c = cover([range(1, 11), range(1, 9), [1, 2, 3, 4, 5, 9], [1, 2, 3, 4, 5, 10]], [[1, 2, 3], [], [], []])
    assert chosen(learners.scored_cover(c, 0.0, "shifted")) == [1, 0]
    assert chosen(learners.scored_cover(c, 0.0, "literal")) == [1, 2, 0]
    assert chosen(learners.scored_cover(c, 0.0, "score_first")) == [1, 0]


def test_purged_and_unreachable():
    c = cover([[1, 2]], [[1]])
    assert learners.scored_cover(c, 0.9).status == "FAILED_PURGED"
    assert learners.red_blue(c, 1.0, 0.0).status == "FAILED_COVERAGE"
    assert learners.feature_selection(c, 1.0, 0.0).status == "FAILED_COVERAGE"
    assert learners.sequential_cover(c, 1.0).status == "FAILED_COVERAGE"
    empty = cover([[]], [[]], 0, 0)
    assert learners.scored_cover(empty).status == "FAILED_PURGED" and learners.red_blue(empty).status == "FAILED_COVERAGE"


def test_universe_is_what_survivors_cover():
    c = cover([[1, 2, 3, 4], [5]], [[], []])
    r = learners.scored_cover(c, 0.3)
    assert chosen(r) == [0] and r.stats["universe"] == 4


def test_terms_share_a_pair():
    c = cover([[1, 3], [2, 3], [4]], [[], [], []], 5, 0)
    s = search_space.supplement(c, 2)
    assert s.elements[3:] == [(A[0], A[1])] and s.dups[3].tolist() == [False, False, True, False, False]
    assert len(search_space.supplement(c, 1).elements) == 3


matrices = st.integers(2, 6).flatmap(
    lambda k: st.tuples(
        st.lists(st.lists(st.booleans(), min_size=8, max_size=8), min_size=k, max_size=k), st.lists(st.lists(st.booleans(), min_size=6, max_size=6), min_size=k, max_size=k)
    )
)


@settings(max_examples=80, deadline=None)
@given(matrices, st.sampled_from([0.0, 0.25, 0.5]))
def test_properties(m, kappa):
    d, n = np.array(m[0]), np.array(m[1])
    c = Coverage([(A[i],) for i in range(len(d))], d, n)
    scores = c.scores()
    alive = [i for i in range(len(d)) if d[i].any() and scores[i] >= kappa - 1e-12]
    for price in ("shifted", "literal", "score_first"):
        r = learners.scored_cover(c, kappa, price)
        if alive:
            assert (d[chosen(r)].any(0) == d[alive].any(0)).all() and set(chosen(r)) <= set(alive)
        else:
            assert r.status == "FAILED_PURGED"
    if alive:
        cost = lambda s: sum(1 - scores[i] for i in s)
        whole = d[alive].any(0)
        best = min(cost(s) for k in range(1, len(alive) + 1) for s in itertools.combinations(alive, k) if (d[list(s)].any(0) == whole).all())
        bound = sum(1 / k for k in range(1, int(d[alive].sum(1).max()) + 1))
        assert cost(chosen(learners.scored_cover(c, kappa))) <= bound * best + 1e-6
    full, cut = search_space.supplement(c, 3), search_space.supplement(c, 3, max(kappa, 0.01))
    passing = lambda x: {t for t, s in zip(x.elements, x.scores()) if s >= max(kappa, 0.01)}
    assert passing(full) == passing(cut)
    for learner in (learners.red_blue, learners.feature_selection):
        r = learner(c, 0.75, 0.5)
        if r.status == "OK":
            assert d[chosen(r)].any(0).sum() >= math.ceil(0.75 * 8)
            assert all(n[i].sum() <= 0.5 * 6 + 1e-9 for i in chosen(r))
            _, least = learners.best_by_brute_force(c, 0.75)
            assert learners.objective(c, chosen(r), 0.75)[1] >= least


def test_fisher_scores():
    c = cover([[1, 2, 3, 4, 5], range(1, 11), []], [[], [1], [1]], 10, 10)
    s = learners.fisher_scores(c)
    assert abs(s[0] - (10 * 0.25**2 * 2) / (10 * 0.25)) < 1e-12 and s[1] > s[0] and s[2] < 0


def test_permutation_is_a_derangement(spark):
    dups = spark.createDataFrame([(i, f"l{i}", f"r{i}") for i in range(1, 30)], "tp_id long, l_rid string, r_rid string")
    negs = training.permute_negatives(dups).collect()
    assert len(negs) == 29 and all(r.l_rid[1:] != r.r_rid[1:] for r in negs) and len({r.r_rid for r in negs}) == 29
    assert training.permute_negatives(dups.limit(1)).count() == 0 and training.permute_negatives(dups.limit(0)).count() == 0
    again = training.permute_negatives(dups, "1").collect()
    assert {(r.l_rid, r.r_rid) for r in negs} != {(r.l_rid, r.r_rid) for r in again}


def test_records_in_several_pairs_are_guarded(spark):
    dups = spark.createDataFrame([(1, "a", "x"), (2, "a", "y"), (3, "b", "z")], "tp_id long, l_rid string, r_rid string")
    negs = {(r.l_rid, r.r_rid) for r in training.permute_negatives(dups).collect()}
    assert not negs & {("a", "x"), ("a", "y"), ("b", "z")}


def test_non_duplicates_are_as_many_as_duplicates(spark):
    """Records in many pairs collide at the first shift; the next ones fill up."""
    rows = [(i, f"l{i % 4}", f"r{i % 6}") for i in range(1, 13)] + [(20 + i, f"x{i}", f"y{i}") for i in range(20)]
    dups = spark.createDataFrame(rows, "tp_id long, l_rid string, r_rid string")
    negs = training.permute_negatives(dups).collect()
    assert len(negs) == len(rows) and not {(r.l_rid, r.r_rid) for r in negs} & {r[1:] for r in rows}
    assert sorted(r.tp_id for r in negs) == sorted(r[0] for r in rows)


def test_semi_supervised_caps_wide_elements():
    c = cover([range(1, 11), range(1, 11)], [[], [1]])
    wide = np.array([[True] * 10, [False] * 10])
    assert chosen(learners.semi_supervised(c, wide)) == [1]
    with pytest.raises(ValueError):
        learners.best_by_brute_force(cover([[1]] * 8, [[]] * 8), 0.5, most=3)


def test_model_round_trip(spark, tmp_path):
    from dnfblock.operators.scheme import Atom, Scheme
    from dnfblock.plans.pipeline import Model

    scheme = Scheme.of((Atom.simple("token", "a", "b"), Atom.complex("exact", ("a", "c"), ("b",))), Atom.simple("first3", "c", "b"))
    Model(scheme, "OK", ((("a",), ("b",)),)).save(f"file://{tmp_path}/model")
    again = Model.load(f"file://{tmp_path}/model")
    assert (again.scheme, again.status, again.mappings) == (scheme, "OK", ((("a",), ("b",)),))


def test_coverage_of_several_runs_is_that_of_each(spark):
    from dnfblock.operators import search_space
    from dnfblock.operators.scheme import Atom

    left = spark.createDataFrame([(str(i), [f"v{i % 5}"]) for i in range(20)], "rid string, a array<string>")
    runs = [[(i, str(i), str(j)) for i, j in ((1, 6), (2, 3), (4, 9))], [(i, str(i), str(j)) for i, j in ((1, 2), (5, 10))]]
    kind = "tp_id long, l_rid string, r_rid string"
    elements = [Atom.simple("exact", "a"), Atom.simple("token", "a")]
    every = spark.createDataFrame([(i + r * 100, a, b) for r, x in enumerate(runs) for i, a, b in x], kind)
    split = search_space.split_runs(search_space.collect_coverage(every, every, left, left, elements), 2, 100)
    for cov, rows in zip(split, runs):
        own = spark.createDataFrame(rows, kind)
        one = search_space.collect_coverage(own, own, left, left, elements)
        assert (cov.dups == one.dups).all() and (cov.nondups == one.nondups).all() and cov.evaluations == one.evaluations


def test_learners_share_one_pass_and_leave_no_shuffle_files(spark, monkeypatch):
    from pyspark.sql import functions as F

    from dnfblock.plans import experiments

    def files():
        kept = spark.sparkContext._jsc.sc().env().blockManager().diskBlockManager().getAllFiles().mkString(" ")
        return kept.count("/shuffle_")

    passes, one_pass = [], search_space.coverage
    monkeypatch.setattr(search_space, "coverage", lambda *a: passes.append(1) or one_pass(*a))
    bench, before = experiments.Bench(spark, "/root/testdata/sf0.001", "p1"), files()
    with experiments.files_of_shuffles_removed(spark):
        rows = experiments._compare(bench, 2, 1, False)
    assert len(passes) == 1 and len(rows) == 6
    assert files() <= before
    for kind in experiments.LEARNERS:
        dups, nondups = bench.training(kind, None, 2)
        alone = search_space.collect_coverage(dups, nondups, bench.left, bench.right, search_space.atoms(mappings=bench.q))
        for got, wanted in zip(bench.coverages(kind, runs=2), search_space.split_runs(alone, 2, experiments.STEP)):
            assert (got.dups == wanted.dups).all() and (got.nondups == wanted.nondups).all() and got.evaluations == wanted.evaluations
    seeds = ["0", "1"]
    both = training.labelled_negatives_of_runs(bench.left, bench.right, bench.truth, 5, seeds)
    for run, seed in enumerate(seeds):
        one = training.labelled_negatives(bench.left, bench.right, bench.truth, 5, seed).collect()
        assert one and sorted(both.where(F.col("run") == run).drop("run").collect()) == sorted(one)


def test_functions_stand_once_a_side_in_the_plan_and_cover_as_before(spark):
    """Whatever the number of mappings; pairs that share their values are covered together, and what comes back is the same."""
    from pyspark.sql import functions as F

    from dnfblock.operators.blocking import with_records

    kind = "rid string, a array<string>, b array<string>"
    left = spark.createDataFrame([("l1", ["Ana Li"], ["12"]), ("l2", ["Ana Li"], []), ("l3", None, ["7", "12"]), ("l4", [None], ["x"])], kind)
    right = spark.createDataFrame([("r1", ["li ana"], ["12"]), ("r2", ["Anna"], None), ("r3", ["li ana"], ["12"])], kind)
    pairs = spark.createDataFrame([(i, f"l{1 + i % 4}", f"r{1 + i % 3}", i % 2) for i in range(12)], "tp_id long, l_rid string, r_rid string, label int")
    gbps = ("token", "exact", "int_pm1", "metaphone")
    mappings = ((("a",), ("a",)), (("b",), ("b",)), (("a", "b"), ("b",)), (("b",), ("a", "b")))
    elements = search_space.atoms(gbps, mappings)[1:]
    rows = with_records(pairs, left, right)
    wanted = set()
    for i, e in enumerate(elements):
        hit = e.covers(lambda f: F.col(f"l_{f}"), lambda f: F.col(f"r_{f}"))
        wanted |= {(i, r.tp_id, r.label) for r in rows.where(hit).select("tp_id", "label").collect()}
    found = search_space.coverage(pairs, left, right, elements)
    assert sorted(map(tuple, found.collect())) == sorted(wanted)
    cov = search_space.collect_coverage(pairs.where("label = 1"), pairs.where("label = 0"), left, right, elements)
    got = {(i, int(cov.stats[k][j]), n) for n, k, m in ((1, "dup_ids", cov.dups), (0, "nondup_ids", cov.nondups)) for i, j in zip(*m.nonzero())}
    assert got == wanted
    plan = found._jdf.queryExecution().optimizedPlan().toString()
    line = next(x for x in plan.splitlines() if "ArrowEvalPython" in x)
    assert line.count("coded(") == 2


def test_runs_are_drawn_in_one_pass(spark):
    """The same pairs as seed by seed, also where so few rows stay that nothing can be held back."""
    truth = spark.createDataFrame([(f"l{i}", f"r{i}") for i in range(300)], "l_rid string, r_rid string")
    seeds = ["0", "1", "2"]
    for many in (300, 10**9):
        found = training.labelled_duplicates_of_runs(truth, 7, seeds, many).collect()
        for run, s in enumerate(seeds):
            assert sorted(tuple(r)[1:] for r in found if r.run == run) == sorted(map(tuple, training.labelled_duplicates(truth, 7, s).collect()))
    assert len(training.labelled_duplicates_of_runs(truth, 1000, seeds, 300).collect()) == 900
    dups = training.labelled_duplicates(truth, 20).union(truth.limit(1).selectExpr("cast(21 as long)", "l_rid", "r_rid"))
    both = training.permute_negatives_of_runs(dups, seeds).collect()
    for run, s in enumerate(seeds):
        assert sorted(tuple(r)[1:] for r in both if r.run == run) == sorted(map(tuple, training.permute_negatives(dups, s).collect()))
