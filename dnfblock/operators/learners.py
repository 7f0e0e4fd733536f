"""Learners of blocking schemes over a coverage: the two-parameter learner and its baselines.

Each returns a :class:`LearnResult`; a failure is a status, not an exception. Ties go to more new
pairs, then fewer atoms, then the smaller element number, so results repeat.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np

from dnfblock.operators.scheme import Scheme
from dnfblock.operators.search_space import Coverage

TINY = 1e-9


@dataclass
class LearnResult:
    scheme: Scheme
    status: str
    chosen: list[tuple[int, int, float]] = field(default_factory=list)  # element, new pairs, price
    stats: dict = field(default_factory=dict)


def _result(cov: Coverage, chosen: list[tuple[int, int, float]], status: str = "OK", **stats) -> LearnResult:
    return LearnResult(Scheme(tuple(cov.elements[i] for i, _, _ in chosen)), status, chosen, {"elements": len(cov.elements), **stats})


def _greedy(cov: Coverage, usable: list[int], price: Callable[[int, int], float], goal: int, universe: np.ndarray) -> list[tuple[int, int, float]]:
    """Take the cheapest element per step until ``goal`` pairs of ``universe`` are covered."""
    open_, chosen, covered = universe.copy(), [], 0
    left = list(usable)
    while covered < goal:
        best = None
        for i in left:
            new = int((cov.dups[i] & open_).sum())
            if new:
                key = (round(price(i, new), 9), -new, len(cov.elements[i]), i)
                best = key if best is None or key < best else best
        if best is None:
            break
        i = best[3]
        chosen.append((i, -best[1], best[0]))
        open_ &= ~cov.dups[i]
        covered += -best[1]
        left.remove(i)
    return chosen


def scored_cover(cov: Coverage, kappa: float = 0.9, price: str = "shifted") -> LearnResult:
    """The two-parameter learner: scores, a threshold ``kappa`` on them, greedy weighted set cover.

    The universe is what the surviving elements cover. An element weighs less the better it scores.
    ``price`` says what greedy minimises: ``shifted`` (1 - score) per new pair, a non-negative cost
    for which the usual bound holds; ``literal`` the negative score per new pair; ``score_first`` the
    best score among elements that cover something new.
    """
    scores = cov.scores()
    alive = [i for i in range(len(cov.elements)) if cov.dups[i].any() and scores[i] >= kappa - 1e-12]
    if not alive:
        return _result(cov, [], "FAILED_PURGED", survivors=0)
    universe = cov.dups[alive].any(0)
    prices = {
        "shifted": lambda i, new: (1 - scores[i] + TINY) / new,
        "literal": lambda i, new: -scores[i] / new,
        "score_first": lambda i, new: -scores[i],
    }
    chosen = _greedy(cov, alive, prices[price], int(universe.sum()), universe)
    return _result(cov, chosen, survivors=len(alive), universe=int(universe.sum()))


def prune_by_negatives(cov: Coverage, eta: float) -> list[int]:
    """Elements that cover at most ``eta`` of the non-duplicates; low values prune most."""
    return [i for i in range(len(cov.elements)) if cov.nondups[i].sum() <= eta * cov.n_nondups + 1e-9]


def red_blue(cov: Coverage, epsilon: float = 0.95, eta: float = 0.05) -> LearnResult:
    """Supervised baseline by red-blue set cover: duplicates are to be covered, non-duplicates avoided.

    Non-duplicates that very many elements cover are left out of the weights, as in the published
    approximation; an element weighs what it covers of the others.
    """
    usable = prune_by_negatives(cov, eta)
    goal = math.ceil(epsilon * cov.n_dups - 1e-9)
    universe = cov.dups[usable].any(0) if usable else np.zeros(cov.n_dups, bool)
    if universe.sum() < goal or not cov.n_dups:
        return _result(cov, [], "FAILED_COVERAGE", survivors=len(usable))
    bound = math.sqrt(len(usable) / math.log(max(cov.n_dups, 3)))
    counted = cov.nondups[usable].sum(0) <= bound
    weight = {i: int((cov.nondups[i] & counted).sum()) for i in usable}
    chosen = _greedy(cov, usable, lambda i, new: max(weight[i], TINY) / new, goal, universe)
    return _result(cov, chosen, survivors=len(usable), covered=sum(n for _, n, _ in chosen))


def fisher_scores(cov: Coverage) -> np.ndarray:
    """Fisher scores of the elements as 0/1 features; only features more frequent in D are positive."""
    d, n = cov.shares()
    nd, nn = cov.n_dups, cov.n_nondups
    mean = (d * nd + n * nn) / max(nd + nn, 1)
    between = nd * (d - mean) ** 2 + nn * (n - mean) ** 2
    within = nd * d * (1 - d) + nn * n * (1 - n)
    score = np.where(within > 1e-12, between / np.maximum(within, 1e-12), np.where(np.abs(d - n) > 1e-12, np.inf, 0.0))
    return np.where(d > n, score, -1.0)


def feature_selection(cov: Coverage, epsilon: float = 0.95, eta: float = 0.05) -> LearnResult:
    """Semi-supervised baseline: features in order of Fisher score as long as they add duplicates."""
    usable = prune_by_negatives(cov, eta)
    goal = math.ceil(epsilon * cov.n_dups - 1e-9)
    score = fisher_scores(cov)
    order = sorted((i for i in usable if score[i] > 0), key=lambda i: (-round(min(score[i], 1e12), 9), len(cov.elements[i]), i))
    seen, chosen = np.zeros(cov.n_dups, bool), []
    for i in order:
        if seen.sum() >= goal:
            break
        new = int((cov.dups[i] & ~seen).sum())
        if new:
            chosen.append((i, new, float(min(score[i], 1e12))))
            seen |= cov.dups[i]
    if seen.sum() < goal or not cov.n_dups:
        return _result(cov, [], "FAILED_COVERAGE", survivors=len(usable))
    return _result(cov, chosen, survivors=len(usable), covered=int(seen.sum()))


def sequential_cover(cov: Coverage, epsilon: float = 0.95) -> LearnResult:
    """Supervised, two parameters: again and again the element with the fewest non-duplicates among
    those that keep at least half of the duplicates still open, until the goal is met."""
    goal = math.ceil(epsilon * cov.n_dups - 1e-9)
    open_, chosen = np.ones(cov.n_dups, bool), []
    while cov.n_dups - open_.sum() < goal:
        new = (cov.dups & open_).sum(1)
        least = max(1, math.ceil(0.5 * new.max(initial=0)))
        usable = np.flatnonzero(new >= least)
        if not len(usable):
            return _result(cov, [], "FAILED_COVERAGE")
        i = min(usable, key=lambda i: (int(cov.nondups[i].sum()), -int(new[i]), len(cov.elements[i]), i))
        chosen.append((int(i), int(new[i]), float(cov.nondups[i].sum())))
        open_ &= ~cov.dups[i]
    return _result(cov, chosen)


def semi_supervised(cov: Coverage, unlabelled: np.ndarray, epsilon: float = 0.95, tau: float = 0.2, alpha: float = 0.5) -> LearnResult:
    """Semi-supervised set cover in our reading: ``unlabelled`` (elements x sampled pairs) estimates how
    much of everything an element covers; ``tau`` caps that share, ``alpha`` mixes it with the labelled
    non-duplicates into the cost."""
    wide = unlabelled.mean(1) if unlabelled.shape[1] else np.zeros(len(cov.elements))
    usable = [i for i in range(len(cov.elements)) if wide[i] <= tau + 1e-12]
    goal = math.ceil(epsilon * cov.n_dups - 1e-9)
    universe = cov.dups[usable].any(0) if usable else np.zeros(cov.n_dups, bool)
    if universe.sum() < goal or not cov.n_dups:
        return _result(cov, [], "FAILED_COVERAGE", survivors=len(usable))
    _, n = cov.shares()
    cost = alpha * n + (1 - alpha) * wide
    chosen = _greedy(cov, usable, lambda i, new: (cost[i] + TINY) / new, goal, universe)
    return _result(cov, chosen, survivors=len(usable))


def objective(cov: Coverage, chosen: list[int], epsilon: float) -> tuple[bool, int]:
    """Whether the goal on duplicates holds, and how many non-duplicates are covered."""
    if not chosen:
        return epsilon * cov.n_dups <= 0, 0
    return bool(cov.dups[chosen].any(0).sum() >= epsilon * cov.n_dups - 1e-9), int(cov.nondups[chosen].any(0).sum())


def best_by_brute_force(cov: Coverage, epsilon: float, most: int = 12) -> tuple[list[int], int]:
    """The optimum of :func:`objective` over all subsets; for tiny search spaces only."""
    from itertools import chain, combinations

    n = len(cov.elements)
    if n > most:
        raise ValueError(f"more than {most} elements")
    subsets = chain.from_iterable(combinations(range(n), k) for k in range(n + 1))
    feasible = [(objective(cov, list(s), epsilon)[1], len(s), s) for s in subsets if objective(cov, list(s), epsilon)[0]]
    cost, _, s = min(feasible)
    return list(s), cost


def sweep(learner: Callable[..., LearnResult], cov: Coverage, epsilons, etas) -> list[tuple[float, float, LearnResult]]:
    """All grid points from the one coverage; no Spark job per point."""
    return [(e, n, learner(cov, e, n)) for e in epsilons for n in etas]
