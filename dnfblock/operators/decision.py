"""The step after blocking: a three-way decision on candidate pairs by two thresholds.

Each record carries one weighted bag of tokens per mapping, made by joins before the pairs are met,
so that nothing which grows with the corpus is sent to the tasks; pairs are then compared in Arrow
batches, narrow over the candidate set.
"""

from __future__ import annotations

import math

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dnfblock.operators.matcher import THETA, soft_cosine, words_of

DUPLICATE, PROBABLE, NON_DUPLICATE = "duplicate", "probable", "non-duplicate"


def token_bags(df: DataFrame, fields: list[tuple[str, ...]], idf: DataFrame) -> DataFrame:
    """``rid, bag``: (position of the field set, token, ln(1 + tf) * idf) of every token of a record."""
    sets = [F.struct(F.lit(i).alias("i"), words_of(names).alias("words")) for i, names in enumerate(fields)]
    rows = df.select("rid", F.explode(F.array(*sets)).alias("s")).select("rid", "s.i", F.explode("s.words").alias("token"))
    tf = rows.groupBy("rid", "i", "token").agg(F.count("*").alias("tf"))
    item = F.struct("i", "token", (F.log1p("tf") * F.col("idf")).alias("w"))
    return tf.join(idf, "token").groupBy("rid").agg(F.array_sort(F.collect_list(item)).alias("bag"))


def classify(
    pairs: DataFrame, w: DataFrame, left: DataFrame, right: DataFrame, mappings, hi: float = 0.8, lo: float = 0.5, theta: float = THETA
) -> DataFrame:
    """``l_rid, r_rid, score, decision`` of every pair.

    ``w`` are the matcher's weights, which give the idf. The score is the mean Soft-TFIDF over the
    ``mappings`` that have tokens on both sides, 0 without any: from ``hi`` a duplicate, from ``lo``
    probable, else none. Tokens that all records have weigh nothing; repeated pairs stay.
    """
    if lo > hi:
        raise ValueError(f"the lower threshold {lo} is above the upper one {hi}")
    n, k = w.select("side", "rid").distinct().count(), len(mappings)
    idf = w.select("token", "df").distinct().select("token", F.ln(F.lit(float(n)) / F.col("df")).alias("idf"))
    scored = pairs.select("l_rid", "r_rid")
    if not k:
        scored = scored.withColumn("score", F.lit(0.0))
    else:
        a = token_bags(left, [m[0] for m in mappings], idf).select(F.col("rid").alias("l_rid"), F.col("bag").alias("l_bag"))
        b = token_bags(right, [m[1] for m in mappings], idf).select(F.col("rid").alias("r_rid"), F.col("bag").alias("r_bag"))
        parts = [F.coalesce(F.col(s)[x], F.array().cast(t)) for s in ("l_bag", "r_bag") for x, t in (("i", "array<int>"), ("token", "array<string>"), ("w", "array<double>"))]
        scored = scored.join(a, "l_rid", "left").join(b, "r_rid", "left").select("l_rid", "r_rid", _score(k, theta)(*parts).alias("score"))
    decision = F.when(F.col("score") >= hi, DUPLICATE).when(F.col("score") >= lo, PROBABLE).otherwise(NON_DUPLICATE)
    return scored.select("l_rid", "r_rid", "score", decision.alias("decision"))


def _score(k: int, theta: float):
    def vectors(at, tokens, weights) -> list[dict[str, float]]:
        out: list[dict[str, float]] = [{} for _ in range(k)]
        for i, t, x in zip(at, tokens, weights):
            if x > 0:
                out[i][t] = x
        for v in out:
            norm = math.sqrt(sum(x * x for x in v.values()))
            for t in v:
                v[t] /= norm
        return out

    @F.pandas_udf("double")
    def score(li: pd.Series, lt: pd.Series, lw: pd.Series, ri: pd.Series, rt: pd.Series, rw: pd.Series) -> pd.Series:
        out = []
        for row in zip(li, lt, lw, ri, rt, rw):
            both = [(x, y) for x, y in zip(vectors(*row[:3]), vectors(*row[3:])) if x and y]
            out.append(sum(soft_cosine(x, y, theta) for x, y in both) / len(both) if both else 0.0)
        return pd.Series(out, dtype="float64")

    return score
