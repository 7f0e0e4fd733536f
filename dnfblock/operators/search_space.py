"""The search space: atoms from functions and mappings, their coverage of training pairs, terms.

Coverage is computed in one pass over the few training pairs: functions see each two sets of values that meet
once. What comes back is a bit matrix of (elements x pairs), bounded by the training sets.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dnfblock.functions.indexing import G_FULL, predicate
from dnfblock.operators.blocking import with_few_records
from dnfblock.operators.scheme import Atom, Term
from dnfblock.storage import discard, materialize


def atoms(gbps=G_FULL, mappings=()) -> list[Atom]:
    """H: every function with every mapping."""
    return [Atom(g, tuple(a), tuple(b)) for a, b in mappings for g in gbps]


@dataclass(frozen=True)
class _Space:
    """Elements by mapping and function: ``at`` has the ids of the elements of each."""

    mappings: list[tuple]
    gbps: list[str]
    at: dict[tuple[int, int], list[int]]

    @staticmethod
    def of(elements: list[Atom]) -> _Space:
        mappings, gbps = list(dict.fromkeys((a.left, a.right) for a in elements)), list(dict.fromkeys(a.gbp for a in elements))
        at: dict[tuple[int, int], list[int]] = {}
        for i, a in enumerate(elements):
            at.setdefault((mappings.index((a.left, a.right)), gbps.index(a.gbp)), []).append(i)
        return _Space(mappings, gbps, at)


def _met_values(pairs: DataFrame, left: DataFrame, right: DataFrame, space: _Space) -> DataFrame:
    """``l, r, of``: values that a mapping puts side by side in some pair, and ``tp_id, label, m`` of all these pairs and mappings.

    Functions see each two sets of values once, whatever the mapping and however many pairs have them; the plan has every
    function once a side, not once a field.
    """
    lf, rf = (list(dict.fromkeys(f for m in space.mappings for f in m[side])) for side in (0, 1))
    rows = with_few_records(pairs, left.select("rid", *lf), right.select("rid", *rf))

    def values(side: str, fields: tuple[str, ...]):
        return F.concat(*(F.coalesce(f"{side}_{f}", F.array().cast("array<string>")) for f in fields))

    sets = [F.struct(F.lit(m).alias("m"), values("l", a).alias("l"), values("r", b).alias("r")) for m, (a, b) in enumerate(space.mappings)]
    rows = rows.select("tp_id", "label", F.explode(F.array(*sets)).alias("s")).select("tp_id", "label", "s.*")
    # few bytes, but much work a row: adaptive plans would leave all of it to one task
    rows = rows.repartition(2 * pairs.sparkSession.sparkContext.defaultParallelism, "l", "r")
    return rows.groupBy("l", "r").agg(F.collect_list(F.struct("tp_id", "label", "m")).alias("of"))


def coverage(pairs: DataFrame, left: DataFrame, right: DataFrame, elements: list[Atom], packed: bool = False) -> DataFrame:
    """``elem_id, tp_id, label`` of the elements that cover a pair (``tp_id, l_rid, r_rid, label``).

    ``packed`` gives bytes for the driver instead, a few rows a task: ``numbers`` (``tp_id, label, m``) and ``bits``, a character a function.
    """
    space = _Space.of(elements)
    if not elements:
        return pairs.select(F.lit(0).alias("elem_id"), "tp_id", "label").limit(0)
    rows = _met_values(pairs, left, right, space)
    hits = [predicate(g, F.col("l"), F.col("r")) for g in space.gbps]
    if not packed:
        rows = rows.select("of", F.explode(F.array_compact(F.array(*(F.when(h, F.lit(i)) for i, h in enumerate(hits))))).alias("g"))
        names = pairs.sparkSession.createDataFrame([(m, g, i) for (m, g), ids in space.at.items() for i in ids], "m int, g int, elem_id int")
        return rows.select("g", F.explode("of").alias("s")).select("g", "s.*").join(F.broadcast(names), ["m", "g"]).select("elem_id", "tp_id", "label")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in batches:
            numbers = frame[["tp_id", "label", "m"]].to_numpy(np.int64)
            yield pd.DataFrame({"numbers": [numbers.tobytes()], "bits": ["".join(frame["bits"]).encode()]})

    bits = F.concat(*(F.when(h, F.lit("1")).otherwise(F.lit("0")) for h in hits))
    rows = rows.select(bits.alias("bits"), F.explode("of").alias("s")).select("bits", "s.*")
    return rows.mapInPandas(run, "numbers binary, bits binary")


def _covered(pairs: DataFrame, left: DataFrame, right: DataFrame, elements: list[Atom], ids: dict[int, np.ndarray]) -> dict[int, np.ndarray]:
    """Per label a matrix of bits, elements by pairs in order of ``ids`` (sorted)."""
    out, space = {k: np.zeros((len(elements), len(v)), bool) for k, v in ids.items()}, _Space.of(elements)
    if not elements:
        return out
    for part in coverage(pairs, left, right, elements, True).collect():
        tp, label, m = np.frombuffer(bytes(part["numbers"]), np.int64).reshape(-1, 3).T
        hit = np.frombuffer(bytes(part["bits"]), np.uint8).reshape(len(tp), -1) == ord("1")
        for (own, g), elems in space.at.items():
            for k, known in ids.items():
                use = (m == own) & (label == k) & hit[:, g]
                for i in elems:
                    out[k][i, np.searchsorted(known, tp[use])] = True
    return out


@dataclass
class Coverage:
    """Elements (terms) and what they cover: boolean matrices over duplicates and non-duplicates."""

    elements: list[Term]
    dups: np.ndarray
    nondups: np.ndarray
    evaluations: int = 0
    stats: dict = field(default_factory=dict)

    @property
    def n_dups(self) -> int:
        return self.dups.shape[1]

    @property
    def n_nondups(self) -> int:
        return self.nondups.shape[1]

    def shares(self) -> tuple[np.ndarray, np.ndarray]:
        return self.dups.sum(1) / max(self.n_dups, 1), self.nondups.sum(1) / max(self.n_nondups, 1)

    def scores(self) -> np.ndarray:
        """Share of duplicates covered less the share of non-duplicates covered."""
        d, n = self.shares()
        return d - n


def collect_coverage(dups: DataFrame, nondups: DataFrame, left: DataFrame, right: DataFrame, elements: list[Atom]) -> Coverage:
    """Coverage of D and N as matrices; both are training sets, so this is small."""
    pairs = dups.select("tp_id", "l_rid", "r_rid", F.lit(1).alias("label")).unionByName(
        nondups.select("tp_id", "l_rid", "r_rid", F.lit(0).alias("label"))
    )
    ids = {k: np.sort(np.array([r[0] for r in df.select("tp_id").collect()], np.int64)) for k, df in ((1, dups), (0, nondups))}
    out = _covered(pairs, left, right, elements, ids)
    cov = Coverage([(a,) for a in elements], out[1], out[0], len(elements) * (len(ids[0]) + len(ids[1])))
    cov.stats = {"dup_ids": ids[1], "nondup_ids": ids[0]}
    return cov


@dataclass
class PairCoverage:
    """Which elements cover which of some pairs: bits (elements x pairs), and the place of each ``l_rid, r_rid``."""

    at: dict[tuple[str, str], int]
    bits: np.ndarray

    def of(self, dups: DataFrame, nondups: DataFrame, elements: list[Atom]) -> Coverage:
        """What :func:`collect_coverage` gives for D and N that consist of these pairs."""
        ids, parts = [], []
        for df in (dups, nondups):
            rows = sorted((r["tp_id"], r["l_rid"], r["r_rid"]) for r in df.select("tp_id", "l_rid", "r_rid").collect())
            ids.append(np.array([i for i, _, _ in rows], np.int64))
            parts.append(self.bits[:, np.array([self.at[l, r] for _, l, r in rows], int)])
        cov = Coverage([(a,) for a in elements], *parts, len(elements) * sum(map(len, ids)))
        cov.stats = {"dup_ids": ids[0], "nondup_ids": ids[1]}
        return cov


def cover_pairs(pairs: DataFrame, left: DataFrame, right: DataFrame, elements: list[Atom]) -> PairCoverage:
    """The coverage of all training pairs (``l_rid, r_rid``) that learners share, each covered once, in one pass."""
    once = materialize(pairs.select("l_rid", "r_rid").distinct().withColumn("tp_id", F.monotonically_increasing_id()), "pairs")
    known = sorted((r["tp_id"], r["l_rid"], r["r_rid"]) for r in once.collect())
    bits = _covered(once.withColumn("label", F.lit(1)), left, right, elements, {1: np.array([tp for tp, _, _ in known], np.int64)})[1]
    discard(once)
    return PairCoverage({(l_rid, r_rid): i for i, (_, l_rid, r_rid) in enumerate(known)}, bits)


def split_runs(cov: Coverage, runs: int, step: int) -> list[Coverage]:
    """Coverage of several training sets that was collected in one pass: run r has the ids from r * ``step`` on."""
    out = []
    for r in range(runs):
        d, n = (cov.stats[k] // step == r for k in ("dup_ids", "nondup_ids"))
        out.append(Coverage(cov.elements, cov.dups[:, d], cov.nondups[:, n], len(cov.elements) * int(d.sum() + n.sum())))
    return out


def supplement(cov: Coverage, k: int, min_support: float = 0.0) -> Coverage:
    """Conjunctions of up to ``k`` atoms that some training pair satisfies, added level by level.

    With ``min_support`` only atoms that cover that share of the duplicates are combined: a term's
    score is at most its share of duplicates, which is at most each atom's, so for a threshold of
    ``min_support`` on scores nothing that could pass is left out.
    """
    n = len(cov.elements)
    support = cov.dups.mean(1) if cov.n_dups else np.zeros(n)
    usable = [i for i in range(n) if support[i] >= min_support - 1e-12]
    elements, dups, nondups = list(cov.elements), [cov.dups], [cov.nondups]
    level = [((i,), cov.dups[i], cov.nondups[i]) for i in usable]
    evaluations = cov.evaluations
    for _ in range(2, k + 1):
        grown = []
        for combo, d, m in level:
            for j in usable:
                if j <= combo[-1]:
                    continue
                evaluations += cov.n_dups + cov.n_nondups
                nd, nm = d & cov.dups[j], m & cov.nondups[j]
                if not (nd.any() or nm.any()) or (min_support > 0 and nd.mean() < min_support - 1e-12):
                    continue
                grown.append(((*combo, j), nd, nm))
        if not grown:
            break
        elements += [tuple(cov.elements[i][0] for i in combo) for combo, _, _ in grown]
        dups.append(np.stack([d for _, d, _ in grown]))
        nondups.append(np.stack([m for _, _, m in grown]))
        level = grown
    return Coverage(elements, np.concatenate(dups), np.concatenate(nondups), evaluations)
