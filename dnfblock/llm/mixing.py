"""Mixing sources to target weights by a multivariate-hypergeometric splitting tree.

Documents fall into blocks of their source by a hash of their id. A source with a target of t words
and z words of its own gives t/z times its blocks: whole epochs, then those blocks of a permutation
that fit what is still wanted. A block that does not fit is passed over and pooled; blocks are tried
until ``POOL`` are pooled and their documents that fit cover the rest. Pooled blocks are split into
smaller ones by another hash, which are tried in the same way, until at most ``POOL_ROWS`` documents
are left to choose from; these are taken one by one as far as they fit. A source thus misses its
target by less than the shortest document that its pool leaves, or by less than any that it could
still take.

How many blocks every source gives are the exact quotas, the balls of an urn. A tree over the output shards
splits them in two again and again, each time by a multivariate hypergeometric draw; its leaves say
how many blocks of every source a shard gets, and a shard draws that many from where the shard
before it stopped in a permutation of the source's blocks. Draws of shards are disjoint, and what a
document gives to the mix is the sum of what the shards drew of it. Inside a shard, documents stand
in the order of a hash.

The driver holds one row per source and one per block and power of two of document sizes; blocks are
a fixed number (``blocks``) plus one per source, and so are those that pooled ones are split into.
Rows of a hot source are spread over its blocks.

Defined cases: null text has size 0 and a document of size 0 adds nothing; a null source is a source
of its own, last in order; null ids fall in one block; repeated rows are drawn like others; an empty
table gives an empty result; further columns are kept by :func:`mix` and not read by :func:`decide`.
"""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from dnfblock.storage import materialize

SEED = 17
MAX_EPOCHS = 3
BLOCKS = 1 << 14
LEAST_BLOCK = 4096
POOL = 8
POOL_ROWS = 8192
SPLIT_ROWS = 512
LEVELS = 4
SHARD_WORDS = 1 << 20
LEAST_SHARDS, MOST_SHARDS = 16, 4096


def n_words(text: Column) -> Column:
    """Words are runs of anything but ASCII blanks."""
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def in_order(sources: list[str | None]) -> list[str | None]:
    """By code point, null last."""
    return sorted(sources, key=lambda s: (s is None, s or ""))


def targets(sizes: list[int], weights: list[float], most: float = MAX_EPOCHS) -> list[float]:
    """Shares of the total by weight, none above ``most`` times its size; the excess is reshared."""
    out, left, open_ = [0.0] * len(sizes), float(sum(sizes)), set(range(len(sizes)))
    while open_:
        whole = sum(weights[i] for i in open_)
        full = {i for i in open_ if left * weights[i] / whole > most * sizes[i]}
        if not full:
            for i in open_:
                out[i] = left * weights[i] / whole
            break
        for i in sorted(full):
            out[i] = most * float(sizes[i])
        left -= sum(out[i] for i in sorted(full))
        open_ -= full
    return out


def splitting_tree(quotas: np.ndarray, shards: int, seed: int = SEED) -> np.ndarray:
    """Quotas per (shard, source); every column sums to the quota of its source exactly.

    A node's draw depends on the seed and its range of shards only, so any subtree can be made alone.
    """
    out = np.zeros((shards, len(quotas)), np.int64)

    def split(own: np.ndarray, lo: int, hi: int) -> None:
        if hi - lo == 1:
            out[lo] = own
            return
        mid = (lo + hi) // 2
        many = int(own.sum()) * (mid - lo) // (hi - lo)
        rng = np.random.default_rng([seed, lo, hi])
        left = rng.multivariate_hypergeometric(own, many, method="marginals") if many else own * 0
        split(left, lo, mid)
        split(own - left, mid, hi)

    if len(quotas):
        split(np.asarray(quotas, np.int64), 0, shards)
    return out


@dataclass
class MixPlan:
    """What the driver decides: sources and their targets, and what each shard draws."""

    sources: pd.DataFrame  # source, rank, size, target
    fans: list[list[int]]  # by level and rank: how many blocks a source, or a pooled block of the level before, has
    draws: list[pd.DataFrame]  # by level: rank, block, epoch, shard, wanted (words that the pooled blocks give together, else -1)
    shards: int


def _blocked(docs: DataFrame, sources: pd.DataFrame, fans: list[list[int]], seed: int) -> DataFrame:
    """``docs`` with ``__rank, __source_size, __target`` and a ``__block`` per level; docs has ``__id, __source``."""
    spark = docs.sparkSession
    rows = [(r.source, int(r.rank), int(r.size), float(r.target), [int(f[r.rank]) for f in fans]) for r in sources.itertuples()]
    table = spark.createDataFrame(rows, "__src string, __rank int, __source_size long, __target double, __fans array<long>")
    out = docs.join(F.broadcast(table), docs["__source"].eqNullSafe(table["__src"]))
    for level in range(len(fans)):
        fan = F.col("__fans")[level]
        own = F.pmod(F.xxhash64(F.col("__id"), F.lit(seed + 1000 * level)), fan)
        out = out.withColumn(f"__block{level}", F.col(f"__block{level - 1}") * fan + own if level else own)
    return out.drop("__src", "__fans")


def _kinds(blocked: DataFrame, block: str) -> dict[int, dict[int, np.ndarray]]:
    """Per rank and block, rows (words, shortest, longest, how many) of its documents by the power of two of their size."""
    kind = F.length(F.bin("__size"))
    found = blocked.groupBy("__rank", block, kind.alias("kind")).agg(
        F.sum("__size").alias("n"), F.min("__size").alias("low"), F.max("__size").alias("high"), F.count("*").alias("many")
    )
    table = np.stack([c.to_numpy() for c in found.drop("kind").toArrow().columns], axis=1).astype(np.int64)
    table = table[np.lexsort((table[:, 2], table[:, 1], table[:, 0]))]
    out: dict[int, dict[int, np.ndarray]] = {}
    starts = np.flatnonzero(np.any(np.diff(table[:, :2], axis=0, prepend=-1), axis=1))
    for rows in np.split(table, starts[1:]):
        if len(rows):
            out.setdefault(int(rows[0, 0]), {})[int(rows[0, 1])] = rows[:, 2:]
    return out


def covered(kinds: np.ndarray, left: float) -> int:
    """Words, at least, of documents that are no longer than ``left``."""
    words, low, high, _ = kinds.T
    return int(words[high <= left].sum() + low[(low <= left) & (left < high)].sum())


def choose(target: float, tries: Iterable[list[tuple[int, int]]], kinds: dict[int, np.ndarray]) -> tuple[list, list, float]:
    """``(epoch, block)`` given whole, those pooled, and the words wanted of the pool; ``tries`` are epochs in order."""
    left, whole, pooled, pool = target, [], [], np.empty((0, 4), np.int64)
    for epoch in tries:
        for ball in epoch:
            if left < 0.5 or (len(pooled) >= POOL and covered(pool, left) >= left):
                break
            if ball[1] not in kinds:
                continue
            words = int(kinds[ball[1]][:, 0].sum())
            if words <= left + 1e-6:
                whole.append(ball)
                left -= words
            else:
                pooled.append(ball)
                pool = np.concatenate((pool, kinds[ball[1]]))
        if left < 0.5 or covered(pool, left) >= left:
            break
    return whole, [x for x in pooled if covered(kinds[x[1]], left)] if left >= 0.5 else [], left


def _quotas(sized: DataFrame, sources: pd.DataFrame, n_blocks: list[int], blocks: int, seed: int) -> tuple[list[list[int]], list[list[tuple]]]:
    """Fans by level, and for each source the balls ``(level, epoch, block, wanted)`` that it gives."""
    fans, order = [n_blocks], range(len(sources))
    kinds = _kinds(_blocked(sized, sources, fans, seed), "__block0")
    left = dict(zip(order, sources["target"].tolist()))
    rng = lambda *x: np.random.default_rng([seed, *x])
    tries = {s: [[(e, b) for b in rng(s, e).permutation(n_blocks[s]).tolist()] for e in range(MAX_EPOCHS)] for s in order}
    balls: list[list[tuple]] = [[] for _ in order]
    for level in range(LEVELS):
        fan, pools = [1] * len(sources), {}
        for s in sorted(tries):
            known = kinds.get(s, {})
            whole, pooled, left[s] = choose(left[s], tries[s], known)
            balls[s] += [(level, e, b, -1.0) for e, b in whole]
            many = {b: int(known[b][known[b][:, 1] <= left[s], 3].sum()) for _, b in pooled}
            if sum(many[b] for _, b in pooled) <= POOL_ROWS or level == LEVELS - 1:
                balls[s] += [(level, e, b, left[s]) for e, b in pooled]
            else:
                pools[s] = pooled
                fan[s] = min(-(-max(many.values()) // SPLIT_ROWS), max(2, blocks // len(many)))
        if not pools:
            break
        fans.append(fan)
        chosen = sized.sparkSession.createDataFrame([(s, b) for s in pools for b in {b for _, b in pools[s]}], "r int, b long")
        rows = _blocked(sized, sources, fans, seed)
        here = (F.col("__rank") == chosen["r"]) & (F.col(f"__block{level}") == chosen["b"])
        kinds = _kinds(rows.join(F.broadcast(chosen), here, "left_semi"), f"__block{level + 1}")
        tries = {}
        for s, pooled in pools.items():
            units = [(e, b * fan[s] + k) for e, b in pooled for k in range(fan[s])]
            tries[s] = [[units[i] for i in rng(s, MAX_EPOCHS + level).permutation(len(units)).tolist()]]
    return fans, balls


def plan(
    sized: DataFrame, weights=(1, 2, 3), seed: int = SEED, blocks: int = BLOCKS, shard_words: int = SHARD_WORDS
) -> MixPlan:
    """Decide on ``sized`` (``__id, __source, __size``)."""
    found = sized.groupBy("__source").agg(F.sum("__size").alias("n"), F.count("*").alias("docs")).collect()
    known = {r["__source"]: (r["n"], r["docs"]) for r in found}
    order = in_order(list(known))
    sizes = [known[s][0] for s in order]
    share = targets(sizes, [weights[i % len(weights)] for i in range(len(order))])
    total = sum(sizes)
    block_words = max(LEAST_BLOCK, -(-total // blocks))
    n_blocks = [max(1, min(known[s][1], n // block_words)) for s, n in zip(order, sizes)]
    sources = pd.DataFrame({"source": order, "rank": range(len(order)), "size": sizes, "target": share})
    fans, balls = _quotas(sized, sources, n_blocks, blocks, seed)
    shards = int(min(MOST_SHARDS, max(LEAST_SHARDS, -(-total // shard_words))))
    leaves = splitting_tree(np.array([len(x) for x in balls], np.int64), shards, seed)
    draws: list[list[tuple]] = [[] for _ in fans]
    for s, own in enumerate(balls):
        urn = np.random.default_rng([seed, s, MAX_EPOCHS + LEVELS]).permutation(len(own)).tolist()
        ends = leaves[:, s].cumsum().tolist()
        for shard, (lo, hi) in enumerate(zip([0, *ends], ends)):
            for i in urn[lo:hi]:
                level, epoch, block, wanted = own[i]
                draws[level].append((s, block, epoch, shard, wanted))
    columns = ["rank", "block", "epoch", "shard", "wanted"]
    return MixPlan(sources, fans, [pd.DataFrame(x, columns=columns) for x in draws], shards)


def _drawn(docs: DataFrame, made: MixPlan, seed: int) -> DataFrame:
    """``docs`` with ``__draws``, what shards drew of its blocks: array of (epoch, shard, wanted), maybe empty."""
    spark = docs.sparkSession
    kind = "array<struct<epoch:int,shard:int,wanted:double>>"
    out, parts = _blocked(docs, made.sources, made.fans, seed), []
    for level, draws in enumerate(made.draws):
        rows = [
            (int(s), int(b), [(int(e), int(h), float(w)) for e, h, w in zip(g.epoch, g.shard, g.wanted)])
            for (s, b), g in draws.groupby(["rank", "block"])
        ]
        table = spark.createDataFrame(rows, f"__r int, __b long, __draws{level} {kind}")
        out = out.join(F.broadcast(table), (out["__rank"] == table["__r"]) & (out[f"__block{level}"] == table["__b"]), "left")
        out = out.drop("__r", "__b")
        parts.append(F.coalesce(f"__draws{level}", F.array().cast(kind)))
    return out.withColumn("__draws", F.concat(*parts)).drop(*(f"__{x}{i}" for x in ("draws", "block") for i in range(len(parts))))


def _picked(blocked: DataFrame, seed: int) -> DataFrame:
    """``__rank, __id, __size, __nth, __epochs`` of the documents that pooled blocks give, in hash order as far as they fit.

    A source's documents that can fit are some ``POOL_ROWS`` at most, as pooled blocks were split until
    then. One that is longer than what is still wanted is passed over.
    """

    def take(rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values(["epoch", "order", "__id", "__size"], kind="stable")
        left, kept = rows["wanted"].iloc[0], []
        for n in rows["__size"]:
            kept.append(n <= left)
            left -= n if n <= left else 0
        rows = rows.assign(__nth=rows.groupby(["__id", "__size", "epoch"], dropna=False).cumcount())
        taken = rows.loc[kept].groupby(["__rank", "__id", "__size", "__nth"], dropna=False)["epoch"]
        return taken.agg(list).rename("__epochs").reset_index()

    part = blocked.select(
        "__rank", "__id", "__size",
        F.xxhash64("__id", "__size", F.lit(seed + 1)).alias("order"),
        F.explode(F.filter("__draws", lambda d: (d["wanted"] >= 0) & F.col("__size").between(1, d["wanted"]))).alias("d"),
    ).select("__rank", "__id", "__size", "order", "d.epoch", "d.wanted")
    return part.groupBy("__rank").applyInPandas(take, "__rank int, __id long, __size long, __nth int, __epochs array<int>")


def _copies(docs: DataFrame, made: MixPlan, seed: int) -> DataFrame:
    """``docs`` with ``__copies``: array of (epoch, shard), one entry per time a row is taken."""
    from pyspark.sql.window import Window

    drawn = _drawn(docs, made, seed)
    last = F.exists("__draws", lambda d: d["wanted"] >= 0)
    none = F.array().cast("array<int>")

    def taken(epochs: Column) -> Column:
        found = F.filter("__draws", lambda d: (d["wanted"] < 0) | F.array_contains(epochs, d["epoch"]))
        return F.transform(found, lambda d: F.struct(d["epoch"], d["shard"]))

    sure = drawn.where(~last).withColumn("__copies", taken(none))
    part = drawn.where(last)
    nth = F.row_number().over(Window.partitionBy("__rank", "__id", "__size").orderBy("__id")) - 1
    part = part.withColumn("__nth", nth)
    picks = _picked(drawn, seed).select(
        F.col("__rank").alias("__prank"), F.col("__id").alias("__pid"), F.col("__size").alias("__psize"),
        F.col("__nth").alias("__pnth"), "__epochs",
    )
    same = (part["__rank"] == picks["__prank"]) & part["__id"].eqNullSafe(picks["__pid"])
    same = same & (part["__size"] == picks["__psize"]) & (part["__nth"] == picks["__pnth"])
    part = part.join(picks, same, "left").withColumn("__copies", taken(F.coalesce("__epochs", none)))
    return sure.unionByName(part.drop("__nth", "__prank", "__pid", "__psize", "__pnth", "__epochs"))


def _sized(docs: DataFrame, id_col: str, text_col: str, source_col: str) -> DataFrame:
    return docs.select(
        docs[id_col].cast("long").alias("__id"), docs[source_col].alias("__source"), n_words(docs[text_col]).alias("__size")
    )


def _order(copy: Column, seed: int) -> Column:
    return F.xxhash64("__id", copy["epoch"], copy["shard"], F.lit(seed + 2))


def decide(
    docs: DataFrame, weights=(1, 2, 3), seed: int = SEED, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source"
) -> DataFrame:
    """``doc_id, size, source_size, target, taken, copies`` per document; no text is moved.

    ``copies`` has, for each time the document is taken, the epoch, the shard that drew it and its place in
    the order of that shard.
    """
    sized = materialize(_sized(docs, id_col, text_col, source_col), "sizes")
    out = _copies(sized, plan(sized, weights, seed), seed)
    copies = F.transform("__copies", lambda c: F.struct(c["epoch"].alias("epoch"), c["shard"].alias("shard"), _order(c, seed).alias("place")))
    return out.select(
        F.col("__id").alias("doc_id"),
        F.col("__size").alias("size"),
        F.col("__source_size").alias("source_size"),
        F.col("__target").alias("target"),
        (F.col("__size") * F.size("__copies")).alias("taken"),
        F.array_sort(copies).alias("copies"),
    )


def mix(
    docs: DataFrame, weights=(1, 2, 3), seed: int = SEED, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source",
    placed: bool = False,
) -> DataFrame:
    """The rows of the mix, a document once for each time it is taken, shard by shard, each shard shuffled.

    Columns are as in ``docs``; ``placed`` adds ``mix_shard`` and ``mix_order``, by which the rows are range-sorted.
    """
    sized = materialize(_sized(docs, id_col, text_col, source_col), "sizes")
    made = plan(sized, weights, seed)
    row = F.struct(*(docs[f"`{c}`"] for c in docs.columns)).alias("__row")  # no column can clash inside
    tagged = docs.select(
        row, docs[id_col].cast("long").alias("__id"), docs[source_col].alias("__source"), n_words(docs[text_col]).alias("__size")
    )
    out = _copies(tagged, made, seed).select("__row", "__id", F.explode("__copies").alias("__copy"))
    out = out.select("__row", F.col("__copy.shard").alias("mix_shard"), _order(F.col("__copy"), seed).alias("mix_order"))
    out = out.repartitionByRange("mix_shard", "mix_order").sortWithinPartitions("mix_shard", "mix_order")
    columns = [F.col(f"__row.`{c}`").alias(c) for c in docs.columns]
    return out.select(*columns, *["mix_shard", "mix_order"] * placed)
