"""Measures of blocking, matching and training data, and the paired t-test."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dnfblock.operators.scheme import Scheme
from dnfblock.storage import discard, materialize


def omega_size(left: DataFrame, right: DataFrame) -> int:
    """All pairs, as a product of two counts."""
    return left.count() * right.count()


def blocking_metrics(gamma: DataFrame, truth: DataFrame, left: DataFrame, right: DataFrame) -> DataFrame:
    """One row: ``pc, rr, pq, fscore, gamma, omega, truth`` of distinct candidate pairs.

    Shares are null where their base is zero; the f-score is the harmonic mean of PC and RR.
    """
    counts = gamma.join(truth.withColumn("hit", F.lit(1)), ["l_rid", "r_rid"], "left").agg(
        F.count("*").alias("gamma"), F.count("hit").alias("found")
    )
    return _measures(counts, truth, left, right)


def scheme_metrics(scheme: Scheme, truth: DataFrame, left: DataFrame, right: DataFrame, apart: bool = False, sizes: tuple[int, int, int] | None = None) -> DataFrame:
    """The row of :func:`blocking_metrics` for the candidates of ``scheme``, which are counted, not made.

    True pairs are looked up by the keys of their records; ids travel as 128-bit hashes. ``apart`` counts one thing after
    the other at once, so that the shuffle files of one are gone when the next begins. ``sizes`` are those of the truth and
    both sides where they are known.
    """
    from dnfblock.operators.blocking import count_candidates, keyed

    gamma = count_candidates(left, right, scheme)
    if not scheme.terms:
        return _measures(gamma.withColumn("found", F.lit(0).cast("long")), truth, left, right, sizes)
    rows = truth.select(*(F.unhex(F.md5(f"{s}_rid")).alias(s) for s in "lr"))
    for i, (df, s) in enumerate(((left, "l"), (right, "r"))):
        keys = keyed(df, scheme, i).where(F.size("keys") > 0)
        rows = rows.join(keys.select(F.unhex(F.md5("rid")).alias(s), F.col("keys").alias(f"{s}_keys")), s).drop(s)
        if apart and not i:
            rows = half = materialize(rows, "half", "zstd")
    found = rows.where(F.arrays_overlap("l_keys", "r_keys")).agg(F.count("*").alias("found"))
    if not apart:
        return _measures(gamma.crossJoin(found), truth, left, right)
    n_found, n_gamma = found.first()[0], gamma.first()[0]
    discard(half)
    return _measures(truth.sparkSession.createDataFrame([(n_gamma, n_found)], "gamma long, found long"), truth, left, right, sizes)


def _measures(counts: DataFrame, truth: DataFrame, left: DataFrame, right: DataFrame, sizes: tuple[int, int, int] | None = None) -> DataFrame:
    if sizes:
        row = counts.withColumns({"truth": F.lit(sizes[0]).cast("long"), "omega": F.lit(str(sizes[1] * sizes[2])).cast("decimal(38,0)")})
    else:
        known = truth.agg(F.count("*").alias("truth"))
        both = left.agg(F.count("*").cast("decimal(19,0)").alias("a")).crossJoin(right.agg(F.count("*").cast("decimal(19,0)").alias("b")))
        row = counts.crossJoin(known).crossJoin(both.select((F.col("a") * F.col("b")).cast("decimal(38,0)").alias("omega")))
    pc, rr = F.try_divide("found", "truth"), 1 - F.try_divide(F.col("gamma").cast("double"), F.col("omega").cast("double"))
    row = row.withColumns({"pc": pc, "rr": rr, "pq": F.try_divide("found", "gamma")})
    fscore = F.coalesce(F.try_divide(2 * F.col("pc") * F.col("rr"), F.col("pc") + F.col("rr")), F.lit(0.0))
    return row.select("pc", "rr", "pq", fscore.alias("fscore"), "gamma", "omega", "truth")


def pairs_completeness_direct(scheme: Scheme, truth: DataFrame, left: DataFrame, right: DataFrame) -> DataFrame:
    """``found, truth`` by testing the scheme on the true pairs only; no candidate set is made."""
    from dnfblock.operators.blocking import with_records

    rows = with_records(truth, left, right)
    hit = scheme.covers(lambda f: F.col(f"l_{f}"), lambda f: F.col(f"r_{f}"))
    return rows.agg(F.sum(hit.cast("long")).alias("found"), F.count("*").alias("truth"))


def precision_recall_at(ranked: DataFrame, truth: DataFrame) -> DataFrame:
    """``rank, hits``, then precision and recall at every rank of ``rank, l_rid, r_rid``.

    Running sums go through buckets of ranks, so no window holds the whole list.
    """
    from pyspark.sql.window import Window

    total = truth.count()
    rows = ranked.join(truth.withColumn("hit", F.lit(1)), ["l_rid", "r_rid"], "left")
    rows = rows.select("rank", F.coalesce("hit", F.lit(0)).alias("hit"), F.floor(F.col("rank") / 4096).alias("bucket"))
    sums = rows.groupBy("bucket").agg(F.sum("hit").alias("n"))
    before = F.sum("n").over(Window.orderBy("bucket")) - F.col("n")
    sums = sums.select("bucket", before.alias("before"))
    inside = F.sum("hit").over(Window.partitionBy("bucket").orderBy("rank"))
    rows = rows.withColumn("inside", inside).join(sums, "bucket").withColumn("hits", F.col("before") + F.col("inside"))
    return rows.select(
        F.col("rank").alias("k"), (F.col("hits") / F.col("rank")).alias("precision"), F.try_divide(F.col("hits"), F.lit(total)).alias("recall")
    )


def mapping_quality(found, true) -> tuple[float, float, float]:
    """Precision, recall over 1:1 components, and the share of true mappings that are hit.

    A found mapping is right when both of its sides lie inside one true mapping.
    """
    parts = {(a, b) for left, right in true for a in left for b in right}
    right = [m for m in found if any(set(m[0]) <= set(x) and set(m[1]) <= set(y) for x, y in true)]
    hit = [t for t in true if any(set(m[0]) <= set(t[0]) and set(m[1]) <= set(t[1]) for m in found)]
    components = {(a, b) for m in right for a in m[0] for b in m[1]}
    return (
        len(right) / len(found) if found else 0.0,
        len(components & parts) / len(parts) if parts else 0.0,
        len(hit) / len(true) if true else 0.0,
    )


def nondup_accuracy(negatives: DataFrame, truth: DataFrame) -> DataFrame:
    """``size, accuracy``: the share of supposed non-duplicates that are none."""
    rows = negatives.join(truth.withColumn("hit", F.lit(1)), ["l_rid", "r_rid"], "left")
    return rows.agg(F.count("*").alias("size"), (1 - F.try_divide(F.count("hit"), F.count("*"))).alias("accuracy"))


def _beta_fraction(a: float, b: float, x: float) -> float:
    tiny, c, d = 1e-300, 1.0, 1 - (a + b) * x / (a + 1)
    d = 1 / (d if abs(d) > tiny else tiny)
    h = d
    for m in range(1, 300):
        for num in (m * (b - m) * x / ((a + 2 * m - 1) * (a + 2 * m)), -(a + m) * (a + b + m) * x / ((a + 2 * m) * (a + 2 * m + 1))):
            d = 1 + num * d
            d = 1 / (d if abs(d) > tiny else tiny)
            c = 1 + num / (c if abs(c) > tiny else tiny)
            h *= d * c
        if abs(d * c - 1) < 1e-14:
            break
    return h


def incomplete_beta(a: float, b: float, x: float) -> float:
    """The regularised incomplete beta function."""
    if x <= 0 or x >= 1:
        return float(x >= 1)
    front = math.exp(math.lgamma(a + b) - math.lgamma(a) - math.lgamma(b) + a * math.log(x) + b * math.log(1 - x))
    if x < (a + 1) / (a + b + 2):
        return front * _beta_fraction(a, b, x) / a
    return 1 - front * _beta_fraction(b, a, 1 - x) / b


def paired_t(a: list[float], b: list[float]) -> tuple[float, str]:
    """Two-sided p of the paired t-test and its level: NS, WS (0.1), SS (0.05) or HS (0.01).

    Without variance p is 1 for equal means and 0 for different ones.
    """
    d = [x - y for x, y in zip(a, b, strict=True)]
    mean = sum(d) / len(d)
    var = sum((x - mean) ** 2 for x in d) / (len(d) - 1) if len(d) > 1 else 0.0
    if var <= 1e-24:
        p = 1.0 if abs(mean) <= 1e-12 else 0.0
    else:
        t, free = mean / math.sqrt(var / len(d)), len(d) - 1
        p = incomplete_beta(free / 2, 0.5, free / (free + t * t))
    return p, "HS" if p <= 0.01 else "SS" if p <= 0.05 else "WS" if p <= 0.1 else "NS"


def mean_sd(values: list[float]) -> tuple[float, float]:
    mean = sum(values) / len(values)
    return mean, math.sqrt(sum((v - mean) ** 2 for v in values) / (len(values) - 1)) if len(values) > 1 else 0.0
