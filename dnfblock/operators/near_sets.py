"""Pairs of near-equal sets, exactly: prefixes of the rarest elements, parity bitmaps, then the sets themselves."""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from dnfblock.storage import discard, files_of_shuffles_removed, materialize

#: Elements are counted by that many buckets of their hashes; what is sent to the tasks is a byte a bucket, whatever the input.
BUCKETS = 1 << 21
#: Shared prefix elements are joined in so many passes, each of which leaves only its candidates behind.
PASSES = 8
#: Numbers of 64-bit words of a bitmap; a set takes the first with four bits an element, else the last.
WORDS = (4, 8, 16, 32, 64)


def _levels(sets: DataFrame) -> np.ndarray:
    """How frequent the elements of a bucket are together, in half powers of two; 0 where it is one element of one set."""
    counts = sets.select(F.explode("w").alias("t")).groupBy(F.expr(f"t & {BUCKETS - 1}").cast("int").alias("b")).agg(F.count("*").alias("n")).where("n > 1")
    found = counts.select("b", F.floor(2 * F.log2("n")).cast("int").alias("level")).toPandas()
    out = np.zeros(BUCKETS, np.uint8)
    out[found["b"].to_numpy(int)] = found["level"].to_numpy()
    return out


def _bitmap(w: np.ndarray) -> np.ndarray:
    """Bit i is the parity of the elements whose hash says i, so two sets differ in as many elements at least as their bitmaps in bits."""
    size = next((x for x in WORDS if 64 * x >= 4 * len(w)), WORDS[-1])
    bits = np.bincount((w.view(np.uint64) >> np.uint64(32)).astype(np.int64) & (64 * size - 1), minlength=64 * size) & 1
    return np.packbits(bits.astype(np.uint8), bitorder="little").view(np.int64)


def _prefixes(sets: DataFrame, num: int, den: int) -> DataFrame:
    """``rid, n, alone, short, c, bits``: the ``c`` rarest elements after the ``alone`` first ones, which are in no other set.

    Elements go by level, then by hash. Two near sets share one of the first ``short`` elements of the smaller set with
    one of ``alone + size(c)`` of the larger one.
    """
    levels = sets.sparkSession.sparkContext.broadcast(_levels(sets))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in batches:
            out = []
            for rid, w in zip(frame["rid"], frame["w"]):
                w = np.asarray(w, np.int64)
                n, level = len(w), levels.value[w & (BUCKETS - 1)]
                alone = int((level == 0).sum())
                prefix = n - -(-n * num // den) + 1
                short = n - -(-2 * n * num // (num + den)) + 1
                out.append((rid, n, alone, short, w[np.lexsort((w, level))][alone:prefix], _bitmap(w)))
            yield pd.DataFrame(out, columns=["rid", "n", "alone", "short", "c", "bits"])

    kind = sets.schema["rid"].dataType.simpleString()
    return sets.mapInPandas(run, f"rid {kind}, n int, alone int, short int, c array<long>, bits array<long>")


def _differing(l_bits: Column, r_bits: Column) -> Column:
    """In how many bits two bitmaps differ; the right one, of the larger set, is folded to the size of the left one."""
    folded = F.aggregate(
        F.sequence(F.lit(1), F.lit(len(WORDS) - 1)),
        r_bits,
        lambda b, _: F.when(
            F.size(b) > F.size(l_bits),
            F.zip_with(F.slice(b, F.lit(1), (F.size(b) / 2).cast("int")), F.slice(b, (F.size(b) / 2).cast("int") + 1, F.size(b)), lambda x, y: x.bitwiseXOR(y)),
        ).otherwise(b),
    )
    return F.aggregate(F.zip_with(l_bits, folded, lambda x, y: F.bit_count(x.bitwiseXOR(y))), F.lit(0), lambda a, x: a + x)


def _candidates(prefixes: DataFrame, num: int, den: int, at: int) -> DataFrame:
    """``l_rid, r_rid`` of pairs that share a prefix element of pass ``at`` and that positions, sizes and bitmaps leave possible."""
    folded = [reduce(lambda x, y: x.bitwiseXOR(y), (F.get("bits", F.lit(i)) if i < WORDS[0] else F.coalesce(F.get("bits", F.lit(i)), F.lit(0)) for i in range(k, WORDS[-1], WORDS[0]))) for k in range(WORDS[0])]
    rows = prefixes.withColumns({f"b{k}": x for k, x in enumerate(folded)})
    rows = rows.select("rid", "n", "alone", "short", "bits", *(f"b{k}" for k in range(WORDS[0])), F.posexplode("c").alias("i", "t"))
    rows = rows.where(F.pmod(F.col("t"), F.lit(PASSES)) == at).withColumn("at", F.col("alone") + F.col("i"))
    carried = ["rid", "n", "at", "bits", *(f"b{k}" for k in range(WORDS[0]))]
    left = rows.where("at < short").select("t", *(F.col(c).alias(f"l_{c}") for c in carried))
    right = rows.select("t", *(F.col(c).alias(f"r_{c}") for c in carried))
    both = F.col("l_n") + F.col("r_n")
    rest = F.least(F.col("l_n") - F.col("l_at"), F.col("r_n") - F.col("r_at"))  # what both can share from here on
    few = sum((F.bit_count(F.col(f"l_b{k}").bitwiseXOR(F.col(f"r_b{k}"))) for k in range(1, WORDS[0])), F.bit_count(F.col("l_b0").bitwiseXOR(F.col("r_b0"))))
    met = left.join(right, "t").where(
        ((F.col("l_n") < F.col("r_n")) | ((F.col("l_n") == F.col("r_n")) & (F.col("l_rid") < F.col("r_rid"))))
        & (F.col("l_n") * den >= F.col("r_n") * num)
        # at the first element that two prefixes share, all shared ones are still to come
        & (rest * (num + den) >= both * num)
        & (few * (num + den) <= both * (den - num))
    )
    met = met.where(_differing(F.col("l_bits"), F.col("r_bits")) * (num + den) <= both * (den - num))
    return met.select("l_rid", "r_rid").distinct()


def near_pairs(sets: DataFrame, num: int, den: int) -> DataFrame:
    """``l_rid, r_rid``: pairs of ``sets`` (``rid, w``) whose Jaccard similarity is at least ``num / den``.

    Equal sets are stood for by their smallest id, so a pair is one of different sets; empty and null sets are in
    none. Elements are compared by 64-bit hashes. Two sets that are that near share one of their rarest elements, with few
    enough elements before it on either side; what is joined on these carries a bitmap, which leaves few other pairs.
    """
    once = sets.where(F.size("w") > 0).select("rid", F.array_sort(F.array_distinct(F.transform("w", lambda t: F.xxhash64(t)))).alias("w"))
    once = materialize(once.groupBy("w").agg(F.min("rid").alias("rid")), "sets")
    with files_of_shuffles_removed(sets.sparkSession):
        prefixes = materialize(_prefixes(once, num, den), "prefixes")
    parts = [materialize(_candidates(prefixes, num, den, p), "candidates") for p in range(PASSES)]
    discard(prefixes)
    first = reduce(DataFrame.unionByName, parts).distinct()
    rows = first.join(once.select(F.col("rid").alias("l_rid"), F.col("w").alias("lw")), "l_rid")
    rows = rows.join(once.select(F.col("rid").alias("r_rid"), F.col("w").alias("rw")), "r_rid")
    same = F.size(F.array_intersect("lw", "rw"))
    rows = rows.where(same * den >= (F.size("lw") + F.size("rw") - same) * num)
    found = materialize(rows.select(F.least("l_rid", "r_rid").alias("l_rid"), F.greatest("l_rid", "r_rid").alias("r_rid")), "near")
    discard(once, *parts)
    return found
