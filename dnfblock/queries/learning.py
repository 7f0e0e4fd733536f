"""Queries on training pairs, coverage, the learners and the experiments."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql.window import Window

from dnfblock.operators import learners, metrics, search_space, training
from dnfblock.operators.generator import generate_training
from dnfblock.plans import experiments, pipeline
from dnfblock.plans.experiments import Bench
from dnfblock.queries import twins
from dnfblock.queries.catalogue import query, table
from dnfblock.queries.matching import ranked_ctes
from dnfblock.sources import datasets
from dnfblock.sources.datasets import P1, P2, P6

#: Functions that SQL twins of the learners use; the experiments use the full set.
G_SQL = ("exact", "first3", "last3", "token", "common_int", "int_pm1", "qgram3", "soundex")
ATOMS1 = search_space.atoms(G_SQL, P1.mappings)
N1 = 50


def negative_ctes(seed: str = "0") -> str:
    """CTE negs: the permutation of CTE dups."""
    return f"""po AS (SELECT *, row_number() OVER (ORDER BY md5('{seed}|' || CAST(tp_id AS VARCHAR)), tp_id) AS n, count(*) OVER () AS many FROM dups),
    negs AS (SELECT po.tp_id, po.l_rid, sh.r_rid FROM po JOIN range(1, {training.SHIFTS + 1}) AS s(i) ON s.i < po.many JOIN po AS sh ON sh.n = (po.n - 1 + s.i) % po.many + 1
      WHERE NOT EXISTS (SELECT 1 FROM dups x WHERE x.l_rid = po.l_rid AND x.r_rid = sh.r_rid) QUALIFY row_number() OVER (PARTITION BY po.tp_id, po.l_rid ORDER BY s.i) = 1)"""


def dup_ctes(pair: datasets.Pair, n: int, seed: str = "0") -> str:
    """CTEs dups and negs: labelled duplicates in hash order, and their permutation."""
    return f"""dups AS (SELECT row_number() OVER (ORDER BY md5('{seed}' || l_rid || r_rid), l_rid, r_rid) AS tp_id, l_rid, r_rid FROM truth QUALIFY tp_id <= {n}),
    {negative_ctes(seed)}"""


def cov_ctes(pair: datasets.Pair, atoms, n: int) -> str:
    """CTE cov: elem_id, tp_id, label."""
    parts = []
    for i, a in enumerate(atoms):
        rhs = twins.atom_keys(a, 1).replace('flatten(list_transform("', 'flatten(list_transform(r."')
        lhs = twins.atom_keys(a, 0).replace('flatten(list_transform("', 'flatten(list_transform(l."')
        parts.append(f"SELECT {i} AS elem_id, tp.tp_id, tp.label FROM tp JOIN l ON l.rid = l_rid JOIN r ON r.rid = r_rid WHERE list_has_any({lhs}, {rhs})")
    return f"WITH RECURSIVE {twins.sides(pair)}, {dup_ctes(pair, n)}, tp AS (SELECT *, 1 AS label FROM dups UNION ALL SELECT *, 0 FROM negs), cov AS ({' UNION ALL '.join(parts)})"


SCORES = """, sc AS (SELECT elem_id, count(*) FILTER (label = 1) / (SELECT count(*) FROM dups) AS dup_share,
    count(*) FILTER (label = 0) / greatest((SELECT count(*) FROM negs), 1) AS nondup_share FROM cov GROUP BY elem_id)"""


def _pairs(spark, d, pair, n):
    left, right, truth = datasets.load(spark, d, pair)
    dups = training.labelled_duplicates(truth, n)
    return left, right, truth, dups, training.permute_negatives(dups)


def _coverage(spark, d, pair, atoms, n):
    left, right, _, dups, negs = _pairs(spark, d, pair, n)
    tp = dups.withColumn("label", F.lit(1)).unionByName(negs.withColumn("label", F.lit(0)))
    return search_space.coverage(tp, left, right, atoms), dups, negs


def _matrices(spark, d):
    left, right, _, dups, negs = _pairs(spark, d, P1, N1)
    return search_space.collect_coverage(dups, negs, left, right, ATOMS1)


@query("permuted_negatives_p1", f"{ranked_ctes(P1, 100)}, dups AS (SELECT rank AS tp_id, l_rid, r_rid FROM k), {negative_ctes()} SELECT tp_id, l_rid, r_rid FROM negs")
def permuted_negatives_p1(spark, d):
    from dnfblock.queries.matching import _weights
    from dnfblock.operators import matcher
    from dnfblock.storage import materialize

    dups = materialize(training.take_duplicates(matcher.top_duplicates(_weights(spark, d, P1)[0], 100), 100), "dups")
    return training.permute_negatives(dups)


SIZES = (50, 100, 200, 500, 1_000, 2_000, 5_000, 10_000)
TRIALS = 10


@query(
    "nondup_accuracy_p6",
    " UNION ALL ".join(
        f"(WITH truth AS ({datasets.duck(P6.truth_sql)}), {dup_ctes(P6, n, str(s))} SELECT {n} AS n_dups, {s} AS run, count(*) AS size, round(1 - count(t.l_rid) / count(*), 6) AS accuracy FROM negs LEFT JOIN truth t USING (l_rid, r_rid))"
        for n in SIZES
        for s in range(TRIALS)
    ),
)
def nondup_accuracy_p6(spark, d):
    truth = datasets.truth(spark, d, P6)
    out = None
    for n in SIZES:
        for run in range(TRIALS):
            negs = training.permute_negatives(training.labelled_duplicates(truth, n, str(run)), str(run))
            row = metrics.nondup_accuracy(negs, truth).select(F.lit(n).alias("n_dups"), F.lit(run).alias("run"), "size", F.round("accuracy", 6).alias("accuracy"))
            out = row if out is None else out.unionByName(row)
    return out


@query("labelled_sample_p1", f"WITH truth AS ({datasets.duck(P1.truth_sql)}), {dup_ctes(P1, N1)} SELECT tp_id, l_rid, r_rid FROM dups")
def labelled_sample_p1(spark, d):
    return training.labelled_duplicates(datasets.truth(spark, d, P1), N1)


@query("labelled_negatives_p1")
def labelled_negatives_p1(spark, d):
    left, right, truth = datasets.load(spark, d, P1)
    return training.labelled_negatives(left, right, truth, N1)


COV1 = cov_ctes(P1, ATOMS1, N1)


@query("coverage_p1", f"{COV1} SELECT elem_id, tp_id, label FROM cov")
def coverage_p1(spark, d):
    return _coverage(spark, d, P1, ATOMS1, N1)[0]


ATOMS2 = search_space.atoms(("token", "common_int", "first3", "int_pm1"), P2.mappings)


@query("complex_coverage_p2", f"{cov_ctes(P2, ATOMS2, 100)} SELECT elem_id, tp_id, label FROM cov")
def complex_coverage_p2(spark, d):
    return _coverage(spark, d, P2, ATOMS2, 100)[0]


@query("multimap_reverse_p1", f"{COV1} SELECT tp_id, label, array_to_string(list_sort(list(elem_id)), '|') AS elements FROM cov GROUP BY tp_id, label")
def multimap_reverse_p1(spark, d):
    cov = _coverage(spark, d, P1, ATOMS1, N1)[0]
    return cov.groupBy("tp_id", "label").agg(F.array_join(F.array_sort(F.collect_list("elem_id")).cast("array<string>"), "|").alias("elements"))


@query("scores_p1", f"{COV1}{SCORES} SELECT elem_id, round(dup_share, 6) AS dup_share, round(nondup_share, 6) AS nondup_share, round(dup_share - nondup_share, 6) AS score FROM sc")
def scores_p1(spark, d):
    cov, dups, negs = _coverage(spark, d, P1, ATOMS1, N1)
    share = lambda label, base: F.sum((F.col("label") == label).cast("int")) / F.lit(max(base.count(), 1))
    s = cov.groupBy("elem_id").agg(share(1, dups).alias("a"), share(0, negs).alias("b"))
    return s.select("elem_id", F.round("a", 6).alias("dup_share"), F.round("b", 6).alias("nondup_share"), F.round(F.col("a") - F.col("b"), 6).alias("score"))


KAPPAS = (0.0, 0.25, 0.5, 0.75, 0.9, 0.95, 1.0)


@query("kappa_sweep_p1", f"{COV1}{SCORES} SELECT CAST(kappa AS DOUBLE) AS kappa, count(*) FILTER (dup_share > 0 AND dup_share - nondup_share >= kappa - 1e-12) AS survivors FROM sc, (VALUES {', '.join(f'({x})' for x in KAPPAS)}) AS v(kappa) GROUP BY kappa")
def kappa_sweep_p1(spark, d):
    cov = _matrices(spark, d)
    rows = [(k, learners.scored_cover(cov, k).stats["survivors"]) for k in KAPPAS]
    return spark.createDataFrame(rows, "kappa double, survivors long")


@query("supplement_terms_p1", f"""{COV1} SELECT a.elem_id AS e1, b.elem_id AS e2, count(*) FILTER (a.label = 1) AS dups, count(*) FILTER (a.label = 0) AS nondups
    FROM cov a JOIN cov b ON a.tp_id = b.tp_id AND a.label = b.label AND a.elem_id < b.elem_id GROUP BY ALL""")  # fmt: skip
def supplement_terms_p1(spark, d):
    cov = _matrices(spark, d)
    full, at = search_space.supplement(cov, 2), {t[0]: i for i, t in enumerate(cov.elements)}
    rows = [(at[t[0]], at[t[1]], int(a.sum()), int(b.sum())) for t, a, b in zip(full.elements, full.dups, full.nondups) if len(t) == 2]
    return spark.createDataFrame(rows, "e1 int, e2 int, dups long, nondups long")


@query("k2_pruned_equals_unpruned", "SELECT CAST(0 AS BIGINT) AS n_diff")
def k2_pruned_equals_unpruned(spark, d):
    cov = _matrices(spark, d)
    alive = lambda c: {t for t, s in zip(c.elements, c.scores()) if s >= 0.9}
    n = len(alive(search_space.supplement(cov, 2)) ^ alive(search_space.supplement(cov, 2, 0.9)))
    return spark.createDataFrame([(n,)], "n_diff long")


def _greedy_sql(price: str, usable: str, goal: str) -> str:
    return f""", u AS ({usable}), sets AS (SELECT elem_id, list(tp_id) AS tps, any_value(weight) AS weight FROM cov JOIN u USING (elem_id) WHERE label = 1 GROUP BY elem_id),
    univ AS (SELECT coalesce(list(DISTINCT tp_id), []) AS ids FROM cov JOIN u USING (elem_id) WHERE label = 1),
    g(step, elem_id, new_pairs, price, open_, covered) AS (
      SELECT 0, -1, 0::BIGINT, 0.0::DOUBLE, ids, 0::BIGINT FROM univ
      UNION ALL
      SELECT g.step + 1, b.elem_id, b.n, b.price, list_filter(g.open_, lambda x: NOT list_contains(b.tps, x)), g.covered + b.n
      FROM g, LATERAL (SELECT elem_id, tps, n, {price} AS price FROM (SELECT elem_id, tps, weight, len(list_intersect(tps, g.open_))::BIGINT AS n FROM sets) WHERE n > 0
        ORDER BY round({price}, 9), n DESC, elem_id LIMIT 1) AS b WHERE g.covered < {goal})
    SELECT step, elem_id, new_pairs, round(price, 6) AS price FROM g WHERE step > 0"""


def _steps(spark, result):
    rows = [(i + 1, e, n, round(float(p), 6)) for i, (e, n, p) in enumerate(result.chosen)]
    return spark.createDataFrame(rows, "step int, elem_id int, new_pairs long, price double")


@query(
    "learn_scored_cover_p1",
    f"{COV1}{SCORES}"
    + _greedy_sql("(1 - weight + 1e-9) / n", "SELECT elem_id, dup_share - nondup_share AS weight FROM sc WHERE dup_share > 0 AND dup_share - nondup_share >= 0.5 - 1e-12", "(SELECT len(ids) FROM univ)"),
)
def learn_scored_cover_p1(spark, d):
    return _steps(spark, learners.scored_cover(_matrices(spark, d), 0.5))


@query(
    "learn_scored_cover_literal_p1",
    f"{COV1}{SCORES}"
    + _greedy_sql("-weight / n", "SELECT elem_id, dup_share - nondup_share AS weight FROM sc WHERE dup_share > 0 AND dup_share - nondup_share >= 0.5 - 1e-12", "(SELECT len(ids) FROM univ)"),
)
def learn_scored_cover_literal_p1(spark, d):
    return _steps(spark, learners.scored_cover(_matrices(spark, d), 0.5, "literal"))


GOAL = "ceil(0.95 * (SELECT count(*) FROM dups) - 1e-9)"
ETA_OK = f"SELECT e.elem_id FROM range({len(ATOMS1)}) AS e(elem_id) LEFT JOIN cov ON cov.elem_id = e.elem_id AND label = 0 GROUP BY e.elem_id HAVING count(tp_id) <= 0.05 * (SELECT count(*) FROM negs) + 1e-9"


@query(
    "learn_red_blue_p1",
    f"{COV1}, ok AS ({ETA_OK}), hit AS (SELECT tp_id, count(*) AS k FROM cov JOIN ok USING (elem_id) WHERE label = 0 GROUP BY tp_id), "
    "few AS (SELECT tp_id FROM hit WHERE k <= sqrt((SELECT count(*) FROM ok) / ln(greatest((SELECT count(*) FROM dups), 3)))), "
    "wt AS (SELECT ok.elem_id, count(few.tp_id) AS weight FROM ok LEFT JOIN cov ON cov.elem_id = ok.elem_id AND label = 0 LEFT JOIN few ON few.tp_id = cov.tp_id GROUP BY ok.elem_id)"
    + _greedy_sql("greatest(weight, 1e-9) / n", "SELECT elem_id, weight FROM wt", GOAL),
)
def learn_red_blue_p1(spark, d):
    return _steps(spark, learners.red_blue(_matrices(spark, d), 0.95, 0.05))


@query(
    "learn_feature_sel_p1",
    f"""{COV1}{SCORES}, ok AS ({ETA_OK}), z AS (SELECT count(*) AS nd, (SELECT count(*) FROM negs) AS nn FROM dups),
    f AS (SELECT elem_id, dup_share AS a, nondup_share AS b, nd, nn, (dup_share * nd + nondup_share * nn) / (nd + nn) AS m FROM sc JOIN ok USING (elem_id), z WHERE dup_share > nondup_share),
    s AS (SELECT elem_id, CASE WHEN nd * a * (1 - a) + nn * b * (1 - b) > 1e-12 THEN least(1e12, (nd * (a - m) ** 2 + nn * (b - m) ** 2) / (nd * a * (1 - a) + nn * b * (1 - b))) ELSE 1e12 END AS score FROM f),
    ord AS (SELECT elem_id, score, row_number() OVER (ORDER BY round(score, 9) DESC, elem_id) AS i FROM s),
    firsts AS (SELECT tp_id, min(i) AS i FROM cov JOIN ord USING (elem_id) WHERE label = 1 GROUP BY tp_id),
    n AS (SELECT i, count(*) AS new_pairs FROM firsts GROUP BY i), c AS (SELECT *, sum(new_pairs) OVER (ORDER BY i) - new_pairs AS before, sum(new_pairs) OVER () AS whole FROM n)
    SELECT CAST(row_number() OVER (ORDER BY i) AS INTEGER) AS step, elem_id, new_pairs, round(score, 6) AS price FROM c JOIN ord USING (i) WHERE before < {GOAL} AND whole >= {GOAL}""",
)
def learn_feature_sel_p1(spark, d):
    return _steps(spark, learners.feature_selection(_matrices(spark, d), 0.95, 0.05))


@query("learn_sequential_p1")
def learn_sequential_p1(spark, d):
    return _steps(spark, learners.sequential_cover(_matrices(spark, d)))


@query("learn_semi_p1")
def learn_semi_p1(spark, d):
    left, right, truth, dups, negs = _pairs(spark, d, P1, N1)
    cov = search_space.collect_coverage(dups, negs, left, right, ATOMS1)
    sampled = training.labelled_negatives(left, right, truth.limit(0), 200, "u")
    wide = search_space.collect_coverage(dups.limit(1), sampled, left, right, ATOMS1).nondups
    return _steps(spark, learners.semi_supervised(cov, wide))


@query("learn_k2_p5")
def learn_k2_p5(spark, d):
    result, _ = Bench(spark, d, "p5").learn("proposed", k=2, support=0.9)
    return _steps(spark, result)


@query("cover_price_modes")
def cover_price_modes(spark, d):
    rows = [r for n in ("p1", "p5") for r in experiments.price_modes(Bench(spark, d, n), 0.7)]
    return spark.createDataFrame([(r["pair"], r["mode"], r["terms"], r["pc"], r["rr"]) for r in rows], "pair string, mode string, n_terms int, pc double, rr double")


@query("generate_training_customer")
def generate_training_customer(spark, d):
    c = table(spark, d, "customer").join(table(spark, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey"))
    rows = c.select(F.col("c_custkey").cast("string").alias("rid"), F.array("c_mktsegment").alias("a"), F.array("n_name").alias("b"), F.array(F.round("c_acctbal").cast("long").cast("string")).alias("c"))
    return generate_training(rows, ["a", "b", "c"])


@query("sweep_red_blue_p1")
def sweep_red_blue_p1(spark, d):
    return _sweep(spark, d, "p1")


def _sweep(spark, d, name):
    bench = Bench(spark, d, name)
    grid = learners.sweep(learners.red_blue, bench.coverage("supervised"), experiments.EPSILONS, experiments.ETAS)
    rows = [(e, n, r.status, len(r.scheme.terms), bench.measure(r)["fscore"]) for e, n, r in grid]
    return spark.createDataFrame(rows, "eps double, eta double, status string, terms int, fscore double")


@query("sweep_red_blue_p2")
def sweep_red_blue_p2(spark, d):
    return _sweep(spark, d, "p2")


@query("sweep_red_blue_p3")
def sweep_red_blue_p3(spark, d):
    return _sweep(spark, d, "p3")


@query("failure_eta0_eps1")
def failure_eta0_eps1(spark, d):
    """The extreme setting; how many of the duplicates elements without any non-duplicate can cover."""
    out = []
    for n in ("p1", "p5", "p6"):
        cov = Bench(spark, d, n).coverage("supervised")
        r = learners.red_blue(cov, 1.0, 0.0)
        usable = learners.prune_by_negatives(cov, 0.0)
        out.append((n, r.status, float(cov.dups[usable].any(0).mean()) if usable else 0.0))
    return spark.createDataFrame(out, "pair string, status string, reachable double")


ROW = "pair string, learner string, run int, status string, terms int, pc double, rr double, pq double, fscore double, gamma double, h_c int"


def _table(spark, rows, extra: str = "", more=lambda r: ()):
    base = [(r["pair"], r["learner"], r["run"], r["status"], r["terms"], r["pc"], r["rr"], r["pq"], r["fscore"], r["gamma"], r["h_c"], *more(r)) for r in rows]
    return spark.createDataFrame(base, ROW + extra)


RUNS = 10


@query("exp1_table")
def exp1_table(spark, d):
    return _table(spark, experiments.comparison(spark, d, ("p1", "p5", "p7"), RUNS))


def _exp1(name: str) -> None:
    @query(f"exp1_{name}")
    def run(spark, d):
        return _table(spark, experiments.comparison(spark, d, (name,), RUNS))


for _n in datasets.PAIRS:
    _exp1(_n)


@query("exp2_k2_table")
def exp2_k2_table(spark, d):
    return _table(spark, experiments.comparison(spark, d, ("p1", "p3", "p5", "p7"), k=2))


@query("learn_truth_mappings_p2")
def learn_truth_mappings_p2(spark, d):
    return _table(spark, experiments.comparison(spark, d, ("p2",), RUNS, true_mappings=True))


@query("learn_truth_mappings_p4")
def learn_truth_mappings_p4(spark, d):
    return _table(spark, experiments.comparison(spark, d, ("p4",), RUNS, true_mappings=True))


@query("significance")
def significance(spark, d):
    rows = experiments.significance(experiments.comparison(spark, d, ("p1", "p5", "p7"), RUNS))
    return spark.createDataFrame(
        [(r["pair"], r["measure"], r["rival"], r["mean_proposed"], r["mean_rival"], r["p"], r["level"]) for r in rows],
        "pair string, measure string, rival string, mean_proposed double, mean_rival double, p double, level string",
    )


@query("fscore_vs_n_p1")
def fscore_vs_n_p1(spark, d):
    """Up to past the number of true pairs, where further retrieved pairs are noise."""
    bench = Bench(spark, d, "p1", retrieve=2_000)
    return _table(spark, experiments.fscore_by_n(bench, (10, 50, 100, 200, 500, 700, 1_000, 2_000)), ", n int", lambda r: (r["n"],))


@query("ablate_G")
def ablate_g(spark, d):
    rows = [r for name in ("p1", "p5") for r in experiments.ablate_functions(Bench(spark, d, name))]
    return _table(spark, rows, ", functions string, k int", lambda r: (r["functions"], r["k"]))


@query("fallback_exhaustive_p1")
def fallback_exhaustive_p1(spark, d):
    bench = Bench(spark, d, "p1")
    dups, nondups = bench.training("proposed")
    m = pipeline.Pipeline(matcher=None, options={"kappa": 0.9}).fit(bench.left, bench.right, dups=dups, nondups=nondups)
    row = m.metrics(bench.left, bench.right, bench.truth).first()
    return spark.createDataFrame([(m.stats["h"], len(bench.q) * len(pipeline.G_FULL), m.status, row["pc"], row["rr"])], "h int, h_matched int, status string, pc double, rr double")


@query("unsupervised_pipeline_p1")
def unsupervised_pipeline_p1(spark, d):
    left, right, truth = datasets.load(spark, d, P1)
    m = pipeline.unsupervised(n=100).fit(left, right)
    return m.metrics(left, right, truth).withColumn("scheme", F.lit(m.explain()))


@query("learn_homogeneous_customer")
def learn_homogeneous_customer(spark, d):
    from dnfblock.queries.indexing import _customers

    c = _customers(spark, d)
    dups = c.select(F.row_number().over(Window.orderBy("rid")).cast("long").alias("tp_id"), F.col("rid").alias("l_rid"), F.col("rid").alias("r_rid")).limit(100)
    m = pipeline.homogeneous(c, c, dups, kappa=0.5)
    return spark.createDataFrame([(m.status, m.explain())], "status string, scheme string")
