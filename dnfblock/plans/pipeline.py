"""Pipelines: two datasets in, a blocking scheme out; the fitted model makes candidates of any size."""

from __future__ import annotations

import json
import time
from collections.abc import Callable
from dataclasses import dataclass, field
from typing import Protocol

from pyspark.sql import DataFrame, SparkSession

from dnfblock.functions.indexing import G_FULL
from dnfblock.operators import blocking, learners, matcher, metrics, search_space, training
from dnfblock.operators.scheme import Scheme
from dnfblock.storage import materialize

AUTO_N = 700


class Matcher(Protocol):
    """Anything that gives mappings and ranked likely duplicates."""

    def match(self, left: DataFrame, right: DataFrame) -> tuple[tuple, DataFrame]: ...


@dataclass
class DuplicateDrivenMatcher:
    """Cosine duplicates, Soft-TFIDF on the first ``t`` of them, assignment."""

    t: int = matcher.T
    theta: float = matcher.THETA
    retrieve: int = 1000
    strategy: str = "prefix"
    max_df: float | None = None

    def match(self, left: DataFrame, right: DataFrame) -> tuple[tuple, DataFrame]:
        lf, rf = left.columns[1:], right.columns[1:]
        w = materialize(matcher.weights(left, right, lf, rf, self.max_df), "weights")
        ranked = materialize(matcher.top_duplicates(w, max(self.retrieve, self.t), self.strategy), "ranked")
        sims = matcher.similarity_matrix(ranked.where(f"rank <= {self.t}"), w, left, right, lf, rf, self.theta).collect()
        return matcher.assign({(r["f1"], r["f2"]): r["sim"] for r in sims}, lf, rf), ranked


@dataclass
class Model:
    """A learned scheme with what led to it."""

    scheme: Scheme
    status: str
    mappings: tuple
    stats: dict = field(default_factory=dict)
    coverage: search_space.Coverage | None = None

    def candidates(self, left: DataFrame, right: DataFrame, **options) -> DataFrame:
        return blocking.candidates(left, right, self.scheme, **options)

    def index(self, df: DataFrame, side: int) -> DataFrame:
        return blocking.index(df, self.scheme, side)

    def metrics(self, left: DataFrame, right: DataFrame, truth: DataFrame) -> DataFrame:
        return metrics.scheme_metrics(self.scheme, truth, left, right)

    def explain(self) -> str:
        return str(self.scheme)

    def save(self, path: str) -> None:
        """Scheme, status and mappings as one line of text below ``path``, on any file system that Spark writes."""
        line = json.dumps({"scheme": self.scheme.to_json(), "status": self.status, "mappings": self.mappings})
        SparkSession.active().createDataFrame([(line,)], "value string").coalesce(1).write.mode("overwrite").text(path)

    @staticmethod
    def load(path: str) -> Model:
        found = json.loads(SparkSession.active().read.text(path).first()[0])
        mappings = tuple((tuple(a), tuple(b)) for a, b in found["mappings"])
        return Model(Scheme.from_json(found["scheme"]), found["status"], mappings)


@dataclass
class Pipeline:
    """The generic pipeline. Sides are ``rid`` and set-valued fields, as tables or as property tables.

    Without a matcher every 1:1 mapping is used. Training pairs come from the caller, or from the
    matcher's duplicates and their permutation.
    """

    learner: Callable[..., learners.LearnResult] = learners.scored_cover
    matcher: Matcher | None = field(default_factory=DuplicateDrivenMatcher)
    gbps: tuple[str, ...] = G_FULL
    k: int = 1
    n: int | str = "auto"
    options: dict = field(default_factory=dict)
    support_pruning: float = 0.0

    def fit(
        self, left: DataFrame, right: DataFrame, *, mappings: tuple | None = None, dups: DataFrame | None = None,
        nondups: DataFrame | None = None, ranked: DataFrame | None = None, seed: str = "0",
    ) -> Model:
        clock, seconds = time.time(), {}

        def lap(name: str) -> None:
            nonlocal clock
            seconds[name], clock = time.time() - clock, time.time()

        found = ()
        if self.matcher is None:
            found = matcher.exhaustive_simple(left.columns[1:], right.columns[1:])
        elif mappings is None or (dups is None and ranked is None):
            found, ranked = self.matcher.match(left, right)
        mappings = mappings or found
        lap("match")
        if dups is None:
            n = AUTO_N if self.n == "auto" else int(self.n)
            dups = materialize(training.take_duplicates(ranked, n), "dups")
        if nondups is None:
            nondups = materialize(training.permute_negatives(dups, seed), "nondups")
        cov = search_space.collect_coverage(dups, nondups, left, right, search_space.atoms(self.gbps, mappings))
        lap("coverage")
        h = len(cov.elements)
        if self.k > 1:
            cov = search_space.supplement(cov, self.k, self.support_pruning)
        lap("supplement")
        result = self.learner(cov, **self.options)
        lap("learn")
        stats = {"h": h, "h_c": len(cov.elements), "dups": cov.n_dups, "nondups": cov.n_nondups, "evaluations": cov.evaluations}
        return Model(result.scheme, result.status, mappings, stats | result.stats | {"seconds": seconds}, cov)


def unsupervised(t: int = matcher.T, theta: float = matcher.THETA, n: int | str = "auto", kappa: float = 0.9, k: int = 1, **options) -> Pipeline:
    """The instantiation that needs no labels: two parameters of learning, ``kappa`` and ``k``."""
    retrieve = AUTO_N if n == "auto" else int(n)
    own = DuplicateDrivenMatcher(t, theta, retrieve)
    return Pipeline(learners.scored_cover, own, k=k, n=n, options={"kappa": kappa}, support_pruning=max(kappa, 0.0) if k > 1 else 0.0, **options)


def homogeneous(left: DataFrame, right: DataFrame, dups: DataFrame, learner=learners.scored_cover, gbps=G_FULL, **options) -> Model:
    """The special case of one schema: a field is mapped to itself."""
    same = tuple(((f,), (f,)) for f in left.columns[1:])
    return Pipeline(learner, None, gbps, options=options).fit(left, right, mappings=same, dups=dups)
