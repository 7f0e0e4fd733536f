"""The experiments on the stand-in pairs: three learners, k = 1 and 2, true mappings, |D|, kappa, G.

A :class:`Bench` keeps what the learners share for one pair: both sides, the truth, the matcher's
output and the training pairs. What is shared is made before a learner's clock starts and timed apart; a
learner's own seconds are those of its coverage, its conjunctions and its cover.
"""

from __future__ import annotations

import time
from functools import cached_property, partial, reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dnfblock.functions.indexing import G_CLASSIC, G_FULL
from dnfblock.operators import learners, matcher, metrics, search_space, top_pairs, training
from dnfblock.plans.pipeline import DuplicateDrivenMatcher
from dnfblock.sources import datasets
from dnfblock.storage import files_of_shuffles_removed, materialize, together

EPSILONS = (0.90, 0.95)
ETAS = (0.0, 0.02, 0.05)
LEARNERS = ("proposed", "semi", "supervised")
STEP = 1 << 24
#: Pairs whose true pairs are kept on disk: reading them from the tables again costs a shuffle of the lines or a parse of the pages.
KEPT = ("p3", "p7")


class Bench:
    def __init__(self, spark: SparkSession, sf_dir: str, name: str, most: int = 1000, retrieve: int = 100):
        self.spark, self.pair, self.most, self.retrieve = spark, datasets.PAIRS[name], most, retrieve
        self._trained: dict[tuple, DataFrame] = {}
        self._covered: dict[tuple, search_space.PairCoverage] = {}
        self._measured: dict[str, dict] = {}
        left, right, truth = datasets.load(spark, sf_dir, self.pair)
        self.truth = materialize(truth, "truth") if name in KEPT else truth
        # a dozen passes read the sides; from the tables each would join and hash again
        self._bagged = together(spark, *(partial(materialize, top_pairs.with_bags(df, df.columns[1:]), s, "zstd") for df, s in ((left, "left"), (right, "right"))))
        self.left, self.right = (df.drop(top_pairs.BAG) for df in self._bagged)
        self.n_truth = self.truth.count()

    @property
    def n(self) -> int:
        """Half of the true pairs, as in the reference, but no more than ``most``, where its curves are flat."""
        return max(2, min(self.most, self.n_truth // 2))

    @cached_property
    def weights(self) -> DataFrame:
        w = matcher.weights(self.left, self.right, self.left.columns[1:], self.right.columns[1:])
        return materialize(w, "weights")

    @cached_property
    def vectors(self) -> top_pairs.Vectors:
        return top_pairs.vectors(*self._bagged, self.left.columns[1:], self.right.columns[1:])

    @cached_property
    def ranked(self) -> DataFrame:
        t = max(2 * self.n, self.retrieve)
        return materialize(top_pairs.top_pairs(self.vectors, *self._bagged, self.left.columns[1:], self.right.columns[1:], t), "ranked")

    def mappings(self, t: int = 50, theta: float = 0.5) -> tuple:
        pairs = self.ranked.where(f"rank <= {t}")
        lf, rf = self.left.columns[1:], self.right.columns[1:]
        sims = matcher.similarity_matrix(pairs, self.vectors, self.left, self.right, lf, rf, theta).collect()
        return matcher.assign({(r["f1"], r["f2"]): r["sim"] for r in sims}, lf, rf)

    @cached_property
    def q(self) -> tuple:
        return self.mappings()

    @cached_property
    def matching_seconds(self) -> dict[str, float]:
        """Time for what the learners share, each part made once: vectors, ranked pairs, mappings."""
        out = {}
        for part in ("vectors", "ranked", "q"):
            began = time.time()
            getattr(self, part)
            out[part] = time.time() - began
        return out

    def training(self, kind: str, n: int | None = None, runs: int = 1) -> tuple[DataFrame, DataFrame]:
        """D and N of a learner: noisy and permuted, noisy and labelled, or both labelled; made once.

        Pairs of run r have the ids from r * ``STEP`` on.
        """
        return (
            self._pairs("labelled" if kind == "supervised" else "retrieved", n or self.n, runs),
            self._pairs("permuted" if kind == "proposed" else "sampled", n or self.n, runs),
        )

    def _pairs(self, what: str, n: int, runs: int) -> DataFrame:
        """One half of a training set, which learners share."""
        if (what, n, runs) not in self._trained:
            seeds = list(map(str, range(runs)))
            if what == "sampled":
                made = training.labelled_negatives_of_runs(self.left, self.right, self.truth, n, seeds)
            elif what == "labelled":
                made = training.labelled_duplicates_of_runs(self.truth, n, seeds, self.n_truth)
            elif what == "permuted":
                made = training.permute_negatives_of_runs(training.take_duplicates(self.ranked, n), seeds)
            else:
                made = training.take_duplicates(self.ranked, n).withColumn("run", F.explode(F.sequence(F.lit(0), F.lit(runs - 1))))
            made = made.select((F.col("tp_id") + F.col("run") * F.lit(STEP)).alias("tp_id"), "l_rid", "r_rid")
            self._trained[what, n, runs] = materialize(made, what)
        return self._trained[what, n, runs]

    def cover_together(self, kinds, runs: int, mappings=None) -> None:
        """Cover the training pairs of several learners in one pass; :meth:`coverages` then reads off what a learner has."""
        elements = search_space.atoms(G_FULL, mappings or self.q)
        sets = [x.select("l_rid", "r_rid") for kind in kinds for x in self.training(kind, None, runs)]
        self._covered[tuple(elements), self.n, runs] = search_space.cover_pairs(reduce(DataFrame.unionByName, sets), self.left, self.right, elements)

    def coverages(self, kind: str, gbps=G_FULL, mappings=None, n: int | None = None, runs: int = 1) -> list[search_space.Coverage]:
        """The coverage of every run, all in one pass over the records."""
        dups, nondups = self.training(kind, n, runs)
        elements = search_space.atoms(gbps, mappings or self.q)
        known = self._covered.get((tuple(elements), n or self.n, runs))
        cov = known.of(dups, nondups, elements) if known else search_space.collect_coverage(dups, nondups, self.left, self.right, elements)
        return search_space.split_runs(cov, runs, STEP)

    def coverage(self, kind: str, gbps=G_FULL, mappings=None, k: int = 1, n: int | None = None, support: float = 0.0) -> search_space.Coverage:
        cov = self.coverages(kind, gbps, mappings, n)[0]
        return search_space.supplement(cov, k, support) if k > 1 else cov

    @cached_property
    def sizes(self) -> tuple[int, int, int]:
        """Of the truth and both sides."""
        return self.n_truth, self.left.count(), self.right.count()

    def measure_all(self, results: list[learners.LearnResult]) -> None:
        """Measure all schemes at once; :meth:`measure` then knows them."""
        _ = self.sizes
        together(self.spark, *(partial(self.measure, r) for r in {str(r.scheme): r for r in results}.values()))

    def measure(self, result: learners.LearnResult) -> dict:
        """Measures of a scheme; runs that learn the same one share them."""
        if str(result.scheme) not in self._measured:
            row = metrics.scheme_metrics(result.scheme, self.truth, self.left, self.right, apart=True, sizes=self.sizes).first().asDict()
            self._measured[str(result.scheme)] = {k: float(v) if v is not None else None for k, v in row.items()}
        return self._measured[str(result.scheme)]

    def learn(self, kind: str, **options) -> tuple[learners.LearnResult, dict]:
        """The result of one run, and its cost."""
        return self.learn_runs(kind, 1, **options)[0]

    def learn_runs(self, kind: str, runs: int, kappa: float = 0.9, k: int = 1, support: float = 0.0, **options) -> list[tuple[learners.LearnResult, dict]]:
        """Results and costs of several runs; each costs its share of the pass that covers all."""
        shared = sum(self.matching_seconds.values())
        self.training(kind, options.get("n"), runs)
        began = time.time()
        covs = self.coverages(kind, runs=runs, **options)
        seconds = (time.time() - began) / runs
        return [self._learnt(kind, cov, kappa, k, support, {"coverage": seconds}, shared) for cov in covs]

    def _learnt(self, kind: str, cov: search_space.Coverage, kappa: float, k: int, support: float, laps: dict, shared: float):
        """A learner's best result: baselines over their grid, by training f-score of the two shares."""
        mark = time.time()
        cov = search_space.supplement(cov, k, support) if k > 1 else cov
        laps["supplement"], mark = time.time() - mark, time.time()
        if kind == "proposed":
            best = learners.scored_cover(cov, kappa)
        else:
            learner = learners.red_blue if kind == "supervised" else learners.feature_selection
            tried = [r for _, _, r in learners.sweep(learner, cov, EPSILONS, ETAS)]
            done = [r for r in tried if r.status == "OK"]

            def quality(r: learners.LearnResult) -> tuple[float, int]:
                at = [i for i, _, _ in r.chosen]
                pc, rr = cov.dups[at].any(0).mean(), 1 - cov.nondups[at].any(0).mean()
                return (2 * pc * rr / (pc + rr) if pc + rr else 0.0, -len(at))

            best = max(done, key=quality) if done else tried[0]
        laps["cover"] = time.time() - mark
        return best, {"seconds": sum(laps.values()), "laps": laps, "matching": shared, "evaluations": cov.evaluations, "h_c": len(cov.elements)}


def experiment_rows(bench: Bench, kind: str, learnt: list[tuple[learners.LearnResult, dict]]) -> list[dict]:
    """One learner on one pair, per run: status, terms, PC, RR, PQ, f-score, sizes."""
    rows = []
    for run, (result, cost) in enumerate(learnt):
        row = {"pair": bench.pair.name, "learner": kind, "run": run, "status": result.status, "terms": len(result.scheme.terms), "scheme": str(result.scheme)}
        rows.append(row | bench.measure(result) | cost)
    return rows


def experiment_row(bench: Bench, kind: str, **options) -> dict:
    return experiment_rows(bench, kind, bench.learn_runs(kind, 1, **options))[0]


_compared: dict[tuple, list[dict]] = {}


def comparison(spark: SparkSession, sf_dir: str, names=("p1", "p5"), runs: int = 1, k: int = 1, true_mappings: bool = False) -> list[dict]:
    """Experiments 1 (k=1), 2 (k=2) and 3 (true mappings for the baselines).

    A few numbers per run are kept for the session, so that tables over the same runs make them once.
    """
    rows = []
    for name in names:
        key = (spark.sparkContext.applicationId, sf_dir, name, runs, k, true_mappings)
        if key not in _compared:
            with files_of_shuffles_removed(spark):
                _compared[key] = _compare(Bench(spark, sf_dir, name), runs, k, true_mappings)
        rows += _compared[key]
    return rows


def _compare(bench: Bench, runs: int, k: int, true_mappings: bool) -> list[dict]:
    given = {kind: bench.pair.mappings if true_mappings and kind != "proposed" else None for kind in LEARNERS}
    for mappings in dict.fromkeys(given.values()):
        bench.cover_together([kind for kind in LEARNERS if given[kind] == mappings], runs, mappings)
    learnt = {}
    for kind in LEARNERS:
        support = 0.9 if k > 1 and kind == "proposed" else 0.5 if k > 1 else 0.0
        learnt[kind] = bench.learn_runs(kind, runs, k=k, mappings=given[kind], support=support)
    bench.measure_all([result for found in learnt.values() for result, _ in found])
    return [row for kind in LEARNERS for row in experiment_rows(bench, kind, learnt[kind])]


def significance(rows: list[dict]) -> list[dict]:
    """Per pair and measure: the proposed learner against the better baseline, paired over runs."""
    out = []
    for name in dict.fromkeys(r["pair"] for r in rows):
        for measure in ("pc", "rr"):
            by = {k: [r[measure] or 0.0 for r in rows if r["pair"] == name and r["learner"] == k] for k in LEARNERS}
            rival = max(("semi", "supervised"), key=lambda k: sum(by[k]) / len(by[k]))
            p, level = metrics.paired_t(by["proposed"], by[rival])
            out.append({"pair": name, "measure": measure, "rival": rival, "mean_proposed": metrics.mean_sd(by["proposed"])[0], "mean_rival": metrics.mean_sd(by[rival])[0], "p": p, "level": level})
    return out


def fscore_by_n(bench: Bench, sizes=(10, 25, 50, 100, 200)) -> list[dict]:
    """Experiment 4: the proposed learner against the number of duplicates it is given."""
    return [experiment_row(bench, "proposed", n=n) | {"n": n} for n in sizes]


def ablate_functions(bench: Bench) -> list[dict]:
    """The classic set of functions against the full one, at k of 1 and 2."""
    rows = []
    for label, gbps in (("classic", G_CLASSIC), ("full", G_FULL)):
        for k in (1, 2):
            rows.append(experiment_row(bench, "proposed", gbps=gbps, k=k, support=0.9 if k > 1 else 0.0) | {"functions": label, "k": k})
    return rows


def price_modes(bench: Bench, kappa: float = 0.9) -> list[dict]:
    cov = bench.coverage("proposed")
    rows = []
    for mode in ("shifted", "literal", "score_first"):
        result = learners.scored_cover(cov, kappa, mode)
        rows.append({"pair": bench.pair.name, "mode": mode, "terms": len(result.scheme.terms)} | bench.measure(result))
    return rows
