"""Training pairs: recycled duplicates, permuted negatives, labelled samples. All are small by contract."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from dnfblock.storage import discard, materialize

SHIFTS = 32


def take_duplicates(ranked: DataFrame, n: int) -> DataFrame:
    """``tp_id, l_rid, r_rid``: the first ``n`` retrieved pairs, fewer if there are fewer."""
    return ranked.where(F.col("rank") <= n).select(F.col("rank").alias("tp_id"), "l_rid", "r_rid")


def permute_negatives(dups: DataFrame, seed: str = "0") -> DataFrame:
    """Non-duplicates by shifting the partners of hash-ordered pairs by one: nobody keeps a partner row.

    A pair that is a duplicate after all, as one record can be in several, takes the partner of the next shift,
    of ``SHIFTS`` at most, that makes none; so there are as many non-duplicates as duplicates wherever that is possible.
    """
    return permute_negatives_of_runs(dups, [seed]).drop("run")


def permute_negatives_of_runs(dups: DataFrame, seeds: list[str]) -> DataFrame:
    """``run, tp_id, l_rid, r_rid``: :func:`permute_negatives` of several seeds in one plan."""
    runs = F.explode(F.array(*(F.struct(F.lit(run).alias("run"), F.lit(f"{s}|").alias("seed")) for run, s in enumerate(seeds)))).alias("s")
    rows = dups.select("tp_id", "l_rid", "r_rid", runs).select("tp_id", "l_rid", "r_rid", "s.*")
    order = Window.partitionBy("run").orderBy(F.md5(F.concat("seed", F.col("tp_id").cast("string"))), "tp_id")
    rows = rows.withColumn("n", F.row_number().over(order))
    many = F.count("*").over(Window.partitionBy("run"))
    rows = rows.withColumn("many", many)
    shift = F.explode(F.sequence(F.lit(1), F.lit(SHIFTS))).alias("shift")
    tried = rows.select("run", "tp_id", "l_rid", "n", "many", shift).where("shift < many")
    tried = tried.withColumn("n", F.pmod(F.col("n") - 1 + F.col("shift"), F.col("many")) + 1)
    out = tried.join(rows.select("run", "n", "r_rid"), ["run", "n"]).join(dups.select("l_rid", "r_rid"), ["l_rid", "r_rid"], "left_anti")
    return out.groupBy("run", "tp_id", "l_rid").agg(F.min(F.struct("shift", "r_rid")).alias("m")).select("run", "tp_id", "l_rid", F.col("m.r_rid").alias("r_rid"))


def _first_of_runs(df: DataFrame, hashed: Callable[[str], Column], n: int, seeds: list[str], many: int) -> DataFrame:
    """``run, i`` and the columns of ``df``: the first ``n`` of its ``many`` rows in order of each seed's hash, ``i`` from 1; one pass for all seeds.

    Tasks hold back hashes well above the ``n``-th as far as it can be foreseen; if too few are left, nothing is held back.
    """
    ids = df.columns
    every = F.array(*(F.struct(F.lit(run).alias("run"), hashed(s).alias("h")) for run, s in enumerate(seeds)))
    cut = min(int((2 * n + 100) / max(many, 1) * 16**8), 16**8)

    def lowest(kept: Column) -> DataFrame:
        return materialize(df.select(*ids, F.explode(kept).alias("s")).select("s.*", *ids), "lowest")

    rows = lowest(F.filter(every, lambda s: s["h"] < f"{cut:08x}") if cut < 16**8 else every)
    if cut < 16**8 and rows.groupBy("run").count().where(F.col("count") >= min(n, many)).count() < len(seeds):
        discard(rows)
        rows = lowest(every)
    place = F.row_number().over(Window.partitionBy("run").orderBy("h", *ids))
    return rows.withColumn("i", place).where(F.col("i") <= n).drop("h")


def labelled_duplicates(truth: DataFrame, n: int, seed: str = "0") -> DataFrame:
    """``n`` true pairs in hash order."""
    top = truth.withColumn("h", F.md5(F.concat(F.lit(seed), "l_rid", "r_rid"))).orderBy("h", "l_rid", "r_rid").limit(n)
    rank = F.row_number().over(Window.orderBy("h", "l_rid", "r_rid")).cast("long")
    return top.select(rank.alias("tp_id"), "l_rid", "r_rid")


def labelled_duplicates_of_runs(truth: DataFrame, n: int, seeds: list[str], many: int) -> DataFrame:
    """``run, tp_id, l_rid, r_rid``: :func:`labelled_duplicates` of several seeds, in one pass over the ``many`` true pairs."""
    found = _first_of_runs(truth.select("l_rid", "r_rid"), lambda s: F.md5(F.concat(F.lit(s), "l_rid", "r_rid")), n, seeds, many)
    return found.select("run", F.col("i").cast("long").alias("tp_id"), "l_rid", "r_rid")


def labelled_negatives(left: DataFrame, right: DataFrame, truth: DataFrame, n: int, seed: str = "0") -> DataFrame:
    """``n`` hash-chosen pairs that are not true: the first records of either side in hash order meet."""
    return labelled_negatives_of_runs(left, right, truth, n, [seed]).drop("run")


def labelled_negatives_of_runs(left: DataFrame, right: DataFrame, truth: DataFrame, n: int, seeds: list[str]) -> DataFrame:
    """``run, tp_id, l_rid, r_rid``: :func:`labelled_negatives` of several seeds; the true pairs are read once for all, and not shuffled."""

    def first(df: DataFrame, name: str, many: int) -> DataFrame:
        found = _first_of_runs(df.select(F.col("rid").alias(name)), lambda s: F.md5(F.concat(F.lit(s + name), name)), 2 * n, seeds, many)
        return found.withColumn("i", F.col("i") - 1)

    n_right = right.count()
    m = min(2 * n, n_right)
    lf, rf = first(left, "l_rid", left.count()), first(right, "r_rid", n_right)
    met = lf.withColumn("i", F.pmod(F.col("i") * 7 + 3, F.lit(max(m, 1)))).join(rf, ["run", "i"])
    pairs = materialize(met.select("run", "l_rid", "r_rid"), "pairs")
    right_ones = truth.join(F.broadcast(pairs.select("l_rid", "r_rid").distinct()), ["l_rid", "r_rid"], "left_semi")
    pairs = pairs.join(right_ones, ["l_rid", "r_rid"], "left_anti")
    rank = F.row_number().over(Window.partitionBy("run").orderBy("l_rid", "r_rid")).cast("long")
    return pairs.select("run", rank.alias("tp_id"), "l_rid", "r_rid").where(F.col("tp_id") <= n)


def swap_partners(dups: DataFrame, share: float) -> DataFrame:
    """Noise for tests of robustness: the first ``share`` of the pairs exchange partners."""
    n = int(dups.count() * share)
    bad = permute_negatives(dups.where(F.col("tp_id") <= n), "noise")
    return bad.unionByName(dups.where(F.col("tp_id") > n))
