"""The duplicate-driven matcher: likely duplicates by cosine, then field mappings from them.

Records are bags of tokens over all fields with weights ln(1 + tf) * ln(N / df), N and df over both
datasets, in vectors of length one. The most similar pairs come in order; Soft-TFIDF compares their
fields; the averaged similarities are an assignment problem, whose solution gives 1:1 mappings.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from dnfblock.functions.indexing import normalized
from dnfblock.storage import materialize

T, THETA = 50, 0.5


def words_of(fields: list[str]) -> Column:
    """Tokens, repeats included, over all values of set-valued ``fields``; nulls among them have none."""
    values = F.flatten(F.array(*(F.coalesce(f, F.array().cast("array<string>")) for f in fields)))
    known = F.filter(values, lambda v: v.isNotNull())
    return F.flatten(F.transform(known, lambda v: F.filter(F.split(normalized(v), " "), lambda t: t != "")))


def record_tokens(df: DataFrame, fields: list[str]) -> DataFrame:
    """``rid, token``, repeats included, over all values of ``fields``."""
    return df.select("rid", F.explode(words_of(fields)).alias("token"))


def weights(left: DataFrame, right: DataFrame, left_fields: list[str], right_fields: list[str], max_df: float | None = None) -> DataFrame:
    """``side, rid, token, df, w``: unit-length TF-IDF vectors of all records.

    ``max_df`` leaves out tokens of more than that share of the records; None keeps the exact cosine.
    """
    both = record_tokens(left, left_fields).withColumn("side", F.lit(0)).unionByName(
        record_tokens(right, right_fields).withColumn("side", F.lit(1))
    )
    n = left.count() + right.count()
    tf = both.groupBy("side", "rid", "token").agg(F.count("*").alias("tf"))
    df = tf.groupBy("token").agg(F.count("*").alias("df"))
    if max_df is not None:
        df = df.where(F.col("df") <= max_df * n)
    w = tf.join(df, "token").withColumn("w", F.log1p("tf") * F.ln(F.lit(float(n)) / F.col("df")))
    norms = w.groupBy("side", "rid").agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("norm"))
    w = w.join(norms, ["side", "rid"])
    return w.select("side", "rid", "token", "df", F.when(F.col("norm") > 0, F.col("w") / F.col("norm")).otherwise(0.0).alias("w"))


def _scored(w: DataFrame) -> DataFrame:
    l = w.where("side = 0").select(F.col("rid").alias("l_rid"), "token", F.col("w").alias("lw"))  # noqa: E741
    r = w.where("side = 1").select(F.col("rid").alias("r_rid"), "token", F.col("w").alias("rw"))
    return l.join(r, "token").groupBy("l_rid", "r_rid").agg(F.sum(F.col("lw") * F.col("rw")).alias("score"))


def _ranked(pairs: DataFrame, t: int) -> DataFrame:
    top = pairs.where("score > 0").withColumn("score", F.round("score", 9)).orderBy(F.desc("score"), "l_rid", "r_rid").limit(t)
    order = Window.orderBy(F.desc("score"), "l_rid", "r_rid")
    return top.withColumn("rank", F.row_number().over(order).cast("long")).select("rank", "l_rid", "r_rid", "score")


def top_duplicates(w: DataFrame, t: int = T, strategy: str = "exact") -> DataFrame:
    """``rank, l_rid, r_rid, score`` of the ``t`` most similar pairs, ties by ids.

    ``exact`` scores every pair that shares a token. ``prefix`` first takes the t-th score among
    pairs that share a rare token as a bound, then scores only pairs whose rare-token prefixes meet:
    a pair at the bound or above cannot miss. Where rare tokens give fewer than ``t`` pairs, less rare ones
    join them step by step. Both give the same rows.
    """
    if strategy == "exact":
        return _ranked(_scored(w), t)
    n = w.select("side", "rid").distinct().count()
    most = max(2, n // 200)
    while True:
        found = materialize(_ranked(_verified(w, _meeting(w.where(F.col("df") <= most))), t), "found")
        many, bound = found.agg(F.count("*"), F.min("score")).first()
        if many >= t:
            break
        if most >= n:
            return found
        most *= 8
    order = Window.partitionBy("side", "rid").orderBy(F.desc("df"), F.desc("token")).rowsBetween(Window.unboundedPreceding, 0)
    prefix = w.withColumn("rest", F.sqrt(F.sum(F.col("w") * F.col("w")).over(order))).where(F.col("rest") >= bound - 1e-6)
    return _ranked(_verified(w, _meeting(prefix)), t)


def _meeting(w: DataFrame) -> DataFrame:
    l = w.where("side = 0").select(F.col("rid").alias("l_rid"), "token")  # noqa: E741
    return l.join(w.where("side = 1").select(F.col("rid").alias("r_rid"), "token"), "token").select("l_rid", "r_rid").distinct()


def _verified(w: DataFrame, pairs: DataFrame) -> DataFrame:
    l = w.where("side = 0").select(F.col("rid").alias("l_rid"), "token", F.col("w").alias("lw"))  # noqa: E741
    r = w.where("side = 1").select(F.col("rid").alias("r_rid"), "token", F.col("w").alias("rw"))
    return pairs.join(l, "l_rid").join(r, ["r_rid", "token"]).groupBy("l_rid", "r_rid").agg(F.sum(F.col("lw") * F.col("rw")).alias("score"))


def jaro_winkler(a: str, b: str) -> float:
    """Similarity of two tokens from 0 to 1; a shared prefix of up to four characters counts extra."""
    if a == b:
        return 1.0
    reach = max(max(len(a), len(b)) // 2 - 1, 0)
    used, ma = [False] * len(b), []
    for i, c in enumerate(a):
        for j in range(max(0, i - reach), min(len(b), i + reach + 1)):
            if not used[j] and b[j] == c:
                used[j] = True
                ma.append(c)
                break
    if not ma:
        return 0.0
    mb = [c for c, u in zip(b, used) if u]
    m, half = len(ma), sum(x != y for x, y in zip(ma, mb)) / 2
    jaro = (m / len(a) + m / len(b) + (m - half) / m) / 3
    prefix = 0
    for x, y in zip(a[:4], b[:4]):
        if x != y:
            break
        prefix += 1
    return jaro + prefix * 0.1 * (1 - jaro)


def soft_tfidf(a: list[str], b: list[str], idf: dict[str, float], theta: float = THETA) -> float:
    """Mean of both directions: tokens with a partner of at least ``theta``, weighted and summed."""

    def vector(words: list[str]) -> dict[str, float]:
        w = {t: math.log1p(words.count(t)) * idf.get(t, 0.0) for t in set(words)}
        norm = math.sqrt(sum(x * x for x in w.values()))
        return {t: x / norm for t, x in w.items()} if norm else {}

    return soft_cosine(vector(a), vector(b), theta)


def soft_cosine(va: dict[str, float], vb: dict[str, float], theta: float = THETA) -> float:
    """Soft-TFIDF of two vectors of length one: the mean of both directions."""

    def one_way(x: dict[str, float], y: dict[str, float]) -> float:
        total = 0.0
        for t, w in sorted(x.items()):
            near, partner = max(((1.0 if t == u else jaro_winkler(t, u) if theta < 1 else 0.0, u) for u in sorted(y)), default=(0.0, ""))
            if partner and near >= theta:
                total += w * y[partner] * near
        return total

    return (one_way(va, vb) + one_way(vb, va)) / 2


def similarity_matrix(pairs: DataFrame, w, left: DataFrame, right: DataFrame, left_fields, right_fields, theta: float = THETA) -> DataFrame:
    """``f1, f2, sim``: field similarities averaged over ``pairs``; a missing value counts 0.

    The pairs are few by contract; the idf of their tokens is all that is sent to the tasks. ``w`` are weights, or
    the vectors of :mod:`dnfblock.operators.top_pairs`.
    """
    from dnfblock.operators.blocking import with_few_records
    from dnfblock.operators.top_pairs import Vectors

    rows = with_few_records(pairs.select("l_rid", "r_rid"), left.select("rid", *left_fields), right.select("rid", *right_fields))
    texts = [F.transform(F.coalesce(f"{s}_{f}", F.array().cast("array<string>")), normalized) for s, fs in (("l", left_fields), ("r", right_fields)) for f in fs]
    rows = rows.select("l_rid", "r_rid", *(F.array_join(x, " ").alias(f"t{i}") for i, x in enumerate(texts)))
    n = w.known if isinstance(w, Vectors) else w.select("side", "rid").distinct().count()
    often = w.df.select("token", "df") if isinstance(w, Vectors) else w.select("token", "df").distinct()
    used = rows.select(F.explode(F.split(F.concat_ws(" ", *(f"t{i}" for i in range(len(texts)))), " ")).alias("token")).distinct()
    known = often.join(used, "token").collect()
    idf = {r["token"]: math.log(n / r["df"]) for r in known}
    a, b = list(left_fields), list(right_fields)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in batches:
            out = []
            for row in frame.itertuples(index=False):
                words = [str(x).split() for x in row[2:]]
                out += [(f, g, soft_tfidf(words[i], words[len(a) + j], idf, theta)) for i, f in enumerate(a) for j, g in enumerate(b)]
            yield pd.DataFrame(out, columns=["f1", "f2", "sim"])

    return rows.mapInPandas(run, "f1 string, f2 string, sim double").groupBy("f1", "f2").agg(F.avg("sim").alias("sim"))


def hungarian(cost: np.ndarray) -> list[tuple[int, int]]:
    """A cheapest assignment of rows to columns, rows not more than columns, by potentials."""
    n, m = cost.shape
    u, v = np.zeros(n + 1), np.zeros(m + 1)
    owner, back = np.zeros(m + 1, int), np.zeros(m + 1, int)
    for i in range(1, n + 1):
        owner[0], j0 = i, 0
        least, seen = np.full(m + 1, np.inf), np.zeros(m + 1, bool)
        while True:
            seen[j0] = True
            i0, delta, j1 = owner[j0], np.inf, 0
            for j in range(1, m + 1):
                if not seen[j]:
                    now = cost[i0 - 1, j - 1] - u[i0] - v[j]
                    if now < least[j]:
                        least[j], back[j] = now, j0
                    if least[j] < delta:
                        delta, j1 = least[j], j
            for j in range(m + 1):
                if seen[j]:
                    u[owner[j]] += delta
                    v[j] -= delta
                else:
                    least[j] -= delta
            j0 = j1
            if owner[j0] == 0:
                break
        while j0:
            owner[j0], j0 = owner[back[j0]], back[j0]
    return sorted((int(owner[j]) - 1, j - 1) for j in range(1, m + 1) if owner[j])


def assign(sim: dict[tuple[str, str], float], left_fields, right_fields, least: float = 0.0):
    """1:1 mappings of the largest total similarity; those not above ``least`` are dropped."""
    a, b = list(left_fields), list(right_fields)
    table = np.array([[sim.get((f, g), 0.0) for g in b] for f in a])
    chosen = hungarian(-table) if len(a) <= len(b) else [(i, j) for j, i in hungarian(-table.T)]
    return tuple(((a[i],), (b[j],)) for i, j in sorted(chosen) if table[i, j] > least)


def exhaustive_simple(left_fields, right_fields):
    """The fall-back without a matcher: every 1:1 mapping."""
    return tuple(((a,), (b,)) for a in left_fields for b in right_fields)


def exhaustive_complex(left_fields, right_fields, limit: int = 10_000):
    """Every pair of non-empty field sets; refused beyond ``limit``."""
    from itertools import chain, combinations

    if (2 ** len(left_fields) - 1) * (2 ** len(right_fields) - 1) > limit:
        raise ValueError(f"more than {limit} mappings")
    sets = lambda fs: list(chain.from_iterable(combinations(fs, n) for n in range(1, len(fs) + 1)))
    return tuple((a, b) for a in sets(left_fields) for b in sets(right_fields))
