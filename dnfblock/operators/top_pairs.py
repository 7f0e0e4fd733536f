"""The most similar pairs of two large datasets, exactly, without meeting all pairs that share a token.

A pair at a bound or above shares a set T of tokens whose weights have at least that norm on both sides. Read in one
order of all tokens, T starts with one of few sequences of tokens that a record can have, given how much weight it can
do without; these sequences are the record's keys. Weights need no join for that: a fixed number of tokens, the most
frequent ones, is sent to all tasks, and of others the weight is known within bounds. Records that share too little at best
are left out first. Keys that one side has are marked in a bit map of fixed size, so that the tasks of the other write hardly
any but these, and only records with a key that both sides have get vectors. Among these, records of one side with the same bag of tokens are one
class, and classes are compared in blocks of the same first tokens, read from rare to frequent. A large block is dealt by one
more token, and tails that can't reach the bound are left out.

The bound comes from the left records of the smallest ids and the most promising ones. Where it is the largest score that
there is, the smallest ids already hold the first pairs, as ties go by ids; some more are searched at each step.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from hashlib import blake2b

import numpy as np
import pandas as pd
from pyspark import Broadcast
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from dnfblock.operators.matcher import words_of
from dnfblock.storage import discard, materialize

#: A block of more comparisons than that is dealt by one more token.
HEAVY = 20_000
#: Scores are rounded to nine digits; bounds keep so much away from them.
SLACK = 1e-7
#: A token of more than one in so many of all tokens of records is frequent; there are fewer than this many such tokens.
FREQUENT = 1 << 14
#: Keys are of that many tokens at most, of fewer where records would have more than ``FEW`` keys on average (``SOME`` while few left records are searched).
DEPTH, FEW, SOME = 3, 8, 32
#: Left records per wanted pair that the first bound comes from, and how many times more each step takes.
FIRST, MORE = 4, 16


#: So many tokens, the most frequent ones, are known to all tasks with their numbers of records; others within bounds.
KNOWN = 3_000_000
#: So many bits mark the keys of one side, so that tasks write next to no others of the other side.
MARKS = 1 << 28
#: So many records show whether it pays to read a side again.
TRIED = 1000
#: The first bound leaves out left records whose rarest token is one of more records than that.
HELD = 4096
#: The column of bags in frames that have them.
BAG = "_bag"


@dataclass
class Vectors:
    """``df``: token, df, both (sides have it); ``n``: all records."""

    df: DataFrame
    n: int
    #: Records that have tokens.
    known: int


def with_bags(df: DataFrame, fields: list[str]) -> DataFrame:
    """``df`` with its bags, for frames that are kept: bags cost more than all else of a pass over the records."""
    return df.withColumn(BAG, F.array_sort(words_of(fields)))


def _bags(df: DataFrame, fields: list[str]) -> DataFrame:
    bags = df if BAG in df.columns else with_bags(df, fields)
    return bags.select("rid", F.col(BAG).alias("bag")).where(F.size("bag") > 0)


def vectors(left: DataFrame, right: DataFrame, left_fields: list[str], right_fields: list[str]) -> Vectors:
    """What the unit-length TF-IDF vectors of :func:`dnfblock.operators.matcher.weights` are made of."""
    n = left.count() + right.count()
    bags = _bags(left, left_fields).withColumn("side", F.lit(0)).unionByName(_bags(right, right_fields).withColumn("side", F.lit(1)))
    one = bags.select("side", F.explode(F.array_distinct("bag")).alias("token"))
    df = one.groupBy("token").agg(F.count("*").alias("df"), (F.min("side") < F.max("side")).alias("both"))
    return Vectors(materialize(df, "df"), n, bags.count())


def _sequences(cells: list[tuple[int, int, float, float]], missed: float, spare: float, depth: int) -> list[tuple[int, ...]]:
    """Every sequence of the first ``depth`` tokens that a record can share with one at the bound, fewer if it shares no more.

    ``cells`` are the tokens that can be shared: df, hash, least and largest squared weight, from rare to frequent; ``missed`` is
    the weight of the others. ``spare`` is how much squared weight can be missed for each that is shared.
    """
    rest = [0.0]
    for c in reversed(cells):
        rest.append(rest[-1] + c[3])
    rest.reverse()
    out: list[tuple[int, ...]] = []

    def go(i: int, shared: float, missed: float, chosen: tuple[int, ...]) -> None:
        if len(chosen) == depth:
            out.append(chosen)
            return
        for j in range(i, len(cells)):
            if missed > spare * (shared + rest[j]) + 1e-9:
                return
            _, token, least, largest = cells[j]
            go(j + 1, shared + largest, missed, (*chosen, token))
            missed += least
        if chosen and missed <= spare * shared + 1e-9:
            out.append(chosen)

    go(0, 0.0, missed, ())
    return out


@dataclass
class _Cells:
    """The distinct tokens of some records: record, hash, df (0: unknown), squared weight within ``least`` and ``largest``, and if it can be shared."""

    n: int
    rec: np.ndarray
    h: np.ndarray
    df: np.ndarray
    least: np.ndarray
    largest: np.ndarray
    both: np.ndarray

    def masses(self) -> tuple[np.ndarray, np.ndarray]:
        """Per record the squared weight that can be shared at most, and that can't at least."""
        one = lambda w: np.bincount(self.rec, np.where(w[0], w[1], 0.0), self.n)
        return one((self.both, self.largest)), one((~self.both, self.least))

    def reach(self) -> np.ndarray:
        """The largest norm that the shared part of a record's vector of length one can have."""
        shared, missed = self.masses()
        return np.sqrt(np.divide(shared, shared + missed, out=np.zeros(self.n), where=shared > 0))

    def promise(self) -> np.ndarray:
        """How much of the weight can be shared without the second heaviest token: records with much of it need but one rare token of a partner."""
        shared, missed = self.masses()
        order = np.lexsort((self.least, self.rec))
        ends = np.cumsum(np.bincount(self.rec, minlength=self.n))
        many = np.diff(np.r_[0, ends])
        second = np.where(many > 1, self.least[order[np.maximum(ends - 2, 0)]], 0.0)
        return np.divide(shared - second, shared + missed, out=np.zeros(self.n), where=shared > 0)


@dataclass
class _Filter:
    """``often``: the frequent tokens; ``table``: sorted hashes and df (negative where one side has the token) of all but tokens of up to ``most`` records."""

    often: dict[str, tuple[int, bool]]
    n: int
    most: float
    table: tuple[np.ndarray, np.ndarray]
    sent: Broadcast

    def cells(self, table: tuple[np.ndarray, np.ndarray], bags: pd.Series) -> _Cells:
        hashes, dfs = table
        flat = np.concatenate(bags.to_list()) if len(bags) else np.zeros(0, np.int64)
        rec = np.repeat(np.arange(len(bags)), bags.map(len).to_numpy(int))
        # a bag is sorted, so repeats are beside each other
        start = np.flatnonzero(np.r_[True, (flat[1:] != flat[:-1]) | (rec[1:] != rec[:-1])]) if len(flat) else np.zeros(0, int)
        tf, h, rec = np.diff(np.r_[start, len(flat)]), flat[start], rec[start]
        known, d = np.zeros(len(h), bool), np.zeros(len(h), np.int64)
        if len(hashes):
            at = np.minimum(np.searchsorted(hashes, h), len(hashes) - 1)
            known = hashes[at] == h
            d = np.where(known, dfs[at], 0)
        df, both, x = np.abs(d), ~known | (d > 0), np.log1p(tf) ** 2
        weight = lambda other: x * np.log(np.maximum(self.n / np.where(known, df, other), 1.0)) ** 2
        return _Cells(len(bags), rec, h, df, weight(max(self.most, 1.0)), weight(2.0), both)

    def only(self, bags: DataFrame) -> _Filter:
        """The same, but that tokens which no record of ``bags`` has can't be shared."""
        hs = bags.select(F.explode("bag").alias("token")).distinct().select(F.xxhash64("token").alias("h"), F.lit(1).cast("long").alias("d"))
        hs = materialize(hs, "keys")
        many = hs.count()
        if many > KNOWN:
            discard(hs)
            return self
        own, (hashes, dfs) = _packed(hs)[0], self.table
        discard(hs)
        there = own[np.minimum(np.searchsorted(own, hashes), len(own) - 1)] == hashes if len(own) else np.zeros(len(hashes), bool)
        table = hashes, np.where(there, dfs, -np.abs(dfs))
        return _Filter(self.often, self.n, self.most, table, bags.sparkSession.sparkContext.broadcast(table))

    def mapped(self, bags: DataFrame, make: Callable[[pd.DataFrame, _Cells], pd.DataFrame], schema: str) -> DataFrame:
        """``make`` of batches of ``rid, text, hs`` (a bag as text and as hashes) and their cells."""
        me, sent = _Filter({}, self.n, self.most, (), None), self.sent

        def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for frame in batches:
                yield make(frame, me.cells(sent.value, frame["hs"]))

        rows = bags.select("rid", F.array_join("bag", " ").alias("text"), F.transform("bag", lambda t: F.xxhash64(t)).alias("hs"))
        return rows.mapInPandas(run, schema)

    def reached(self, bags: DataFrame, least: float) -> DataFrame:
        """``rid, text, reach`` of records whose vector can share a part of norm ``least``."""

        def make(frame: pd.DataFrame, c: _Cells) -> pd.DataFrame:
            out = frame[["rid", "text"]].assign(reach=c.reach())
            return out[out["reach"] >= least]

        return self.mapped(bags, make, "rid string, text string, reach double")

    def largest_reach(self, bags: DataFrame) -> float:
        top = self.mapped(bags, lambda frame, c: pd.DataFrame({"reach": [c.reach().max(initial=0.0)]}), "reach double")
        return top.agg(F.coalesce(F.max("reach"), F.lit(0.0))).first()[0]

    def promising(self, bags: DataFrame, m: int) -> DataFrame:
        """``rid`` of the ``m`` most promising records, ties by ids."""
        every = self.mapped(bags, lambda frame, c: frame[["rid"]].assign(p=np.round(c.promise(), 6)), "rid string, p double")
        return every.orderBy(F.desc("p"), "rid").limit(m).select("rid")

    def keys(self, bags: DataFrame, bound: float, depth: int, marks: Broadcast | None = None) -> DataFrame:
        """``rid, key``: a hash of every sequence of a record (``rid, bag``); of those that ``marks`` lacks, hardly any."""
        spare = (1 - bound * bound) / (bound * bound)

        def make(frame: pd.DataFrame, c: _Cells) -> pd.DataFrame:
            shared, missed = c.masses()
            alive = (shared > 0) & (missed <= spare * shared + 1e-9)
            use = c.both & alive[c.rec]
            order = np.lexsort((c.h[use], c.df[use], c.rec[use]))
            rec, rows = c.rec[use][order], list(zip(*(x[use][order].tolist() for x in (c.df, c.h, c.least, c.largest))))
            at = np.searchsorted(rec, np.arange(c.n + 1)).tolist()
            rids, out = frame["rid"].to_list(), []
            for i in np.flatnonzero(alive).tolist():
                for s in _sequences(rows[at[i] : at[i + 1]], float(missed[i]), spare, depth):
                    digest = blake2b(np.array(s, np.int64).tobytes(), digest_size=8).digest()
                    out.append((rids[i], int.from_bytes(digest, "big", signed=True)))
            made = pd.DataFrame(out, columns=["rid", "key"])
            if marks is None or not out:
                return made
            at = made["key"].to_numpy(np.int64) & (MARKS - 1)
            return made[np.frombuffer(marks.value, np.uint8)[at >> 3] >> (at & 7) & 1 == 1]

        return self.mapped(bags, make, "rid string, key long")


def _marks(keys: DataFrame) -> Broadcast:
    """A bit for every ``key`` by its lowest bits, of fixed size whatever the number of keys, for all tasks."""
    size = MARKS // 512

    def bits(frame: pd.DataFrame) -> pd.DataFrame:
        at, own = frame["at"].to_numpy(np.int64), np.zeros(size, np.uint8)
        own[at % size] = 1
        return pd.DataFrame({"part": [at[0] // size], "bits": [np.packbits(own, bitorder="little").tobytes()]})

    at = keys.select(F.col("key").bitwiseAND(F.lit(MARKS - 1)).alias("at")).groupBy(F.floor(F.col("at") / size).alias("p"))
    whole = bytearray(MARKS // 8)
    for r in at.applyInPandas(bits, "part long, bits binary").collect():
        whole[r["part"] * size // 8 : (r["part"] + 1) * size // 8] = r["bits"]
    return keys.sparkSession.sparkContext.broadcast(bytes(whole))


def _packed(rows: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """``h, d`` as two arrays in order of ``h``; they come to the driver as bytes."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in batches:
            yield pd.DataFrame({c: [frame[c].to_numpy(np.int64).tobytes()] for c in "hd"})

    parts = rows.select("h", "d").mapInPandas(run, "h binary, d binary").collect()
    h, d = (np.frombuffer(b"".join(bytes(r[c]) for r in parts), np.int64) for c in "hd")
    order = np.argsort(h, kind="stable")
    return h[order], d[order]


def _filter(v: Vectors) -> _Filter:
    total = v.df.agg(F.coalesce(F.sum("df"), F.lit(0))).first()[0]
    often = v.df.where(F.col("df") > total / FREQUENT).collect()
    most, above = 0, 0
    if v.df.count() > KNOWN:
        for r in v.df.groupBy("df").count().orderBy(F.desc("df")).limit(KNOWN).collect():
            above += r["count"]
            if above > KNOWN:
                most = r["df"]
                break
    signed = F.when(F.col("both"), F.col("df")).otherwise(-F.col("df"))
    table = _packed(v.df.where(F.col("df") > most).select(F.xxhash64("token").alias("h"), signed.cast("long").alias("d")))
    return _Filter({r["token"]: (r["df"], r["both"]) for r in often}, v.n, most, table, v.df.sparkSession.sparkContext.broadcast(table))


def _forget(f: _Filter, *fs: _Filter) -> None:
    """Delete what was sent to the tasks for filters other than ``f``; it would stay on disk."""
    for x in fs:
        if x is not f:
            x.sent.destroy()


def _pruned(f: _Filter, bags: list[DataFrame], bound: float) -> tuple[list[DataFrame], list[_Filter], list[float]]:
    """``rid, bag`` of either side that can be in a pair at ``bound``, with filters and the norm that their shared parts need.

    A score is at most the product of the norms of both shared parts. So each side needs the bound divided by the largest
    norm that the other reaches, with only the tokens shared that the other side's remaining records have. Each side is
    read again with what is left of the other, unless that leaves out next to none of its first records.
    """
    top, fs, out = [1.0, min(f.largest_reach(bags[1]), 1.0)], [f, f], list(bags)
    if bound <= 2 * SLACK or not top[1]:
        return [materialize(b, "some_bags") for b in bags], fs, [bound, bound]
    for turn, i in enumerate((0, 1, 0, 1)):
        need = bound / (top[1 - i] + 1e-9)
        if turn > 1 and fs[i].reached(out[i].limit(TRIED), need).count() > 0.95 * TRIED:
            break
        before, kept = out[i], materialize(fs[i].reached(out[i], need), "some_bags", "zstd")
        if before is not bags[i]:
            discard(before)
        top[i] = min(kept.agg(F.coalesce(F.max("reach"), F.lit(0.0))).first()[0], 1.0) or 1.0
        bag = kept.select("rid", F.split("text", " ").alias("bag"))
        bag.kept_at = kept.kept_at
        out[i] = bag
        used, fs[1 - i] = fs[1 - i], f.only(bag)
        _forget(f, used)
    return out, fs, [bound / (t + 1e-9) for t in reversed(top)]


def _met(fs: list[_Filter], bags: list[DataFrame], bounds: list[float], few: int = FEW) -> list[DataFrame]:
    """``rid, bag`` of either side that have a key of the other side."""
    if min(bounds) <= 2 * SLACK:
        return [materialize(b, "bags") for b in bags]
    some = [b.limit(1000) for b in bags]
    depth = next((d for d in range(DEPTH, 1, -1) if sum(f.keys(b, x, d).count() for f, b, x in zip(fs, some, bounds)) <= few * 2000), 1)
    # left keys first: there are few of them while few left records are searched
    own = materialize(fs[0].keys(bags[0], bounds[0], depth).select("key").distinct(), "keys")
    marks = _marks(own)
    met = materialize(fs[1].keys(bags[1], bounds[1], depth, marks).join(own, "key", "left_semi"), "met", "zstd")
    marks.destroy()
    both = materialize(met.select("key").distinct(), "keys")
    marks = _marks(both)
    other = fs[0].keys(bags[0], bounds[0], depth, marks).join(both, "key", "left_semi")
    out = []
    for b, k in zip(bags, (other, met)):
        rids = materialize(k.select("rid").distinct(), "rids")
        out.append(materialize(b.join(rids, "rid", "left_semi"), "bags"))
        discard(rids)
    marks.destroy()
    discard(own, met, both)
    return out


@dataclass
class _Rows:
    """``classes``: side, id, bag, n; ``rows`` of either side: id, n, toks, ws of the tokens both sides have, rare ones first."""

    classes: DataFrame
    rows: list[DataFrame]
    written: list[DataFrame]


def _vectors_of(v: Vectors, f: _Filter, bags: list[DataFrame]) -> _Rows:
    """The vectors of some records (``rid, bag``), one row a class of equal bags.

    Only tokens that are not frequent are looked up by a join; the bag travels once, as text.
    """
    texts = [b.select(F.array_join("bag", " ").alias("bag"), F.lit(i).alias("side")) for i, b in enumerate(bags)]
    classes = texts[0].unionByName(texts[1]).groupBy("side", "bag").agg(F.count("*").alias("n"))
    classes = materialize(classes.withColumn("id", F.monotonically_increasing_id()), "classes")
    often, n = f.often, v.n
    words = classes.select("id", F.explode(F.array_distinct(F.split("bag", " "))).alias("token"))
    names = words.sparkSession.createDataFrame([(t,) for t in often], "token string")
    rare = words.join(F.broadcast(names), "token", "left_anti").join(v.df, "token")
    rare = rare.groupBy("id").agg(F.collect_list(F.struct("token", "df", "both")).alias("c"))
    known = classes.join(rare, "id", "left").select(
        "side", "id", "n", "bag", *(F.coalesce(F.col(f"c.{x}"), F.array().cast(f"array<{k}>")).alias(x) for x, k in (("token", "string"), ("df", "long"), ("both", "boolean")))
    )

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in batches:
            out = []
            for side, ident, many, bag, token, df, both in frame.itertuples(index=False, name=None):
                own = dict(zip(token, zip(df, both)))
                cells = sorted((*(own.get(t) or often[t]), t, tf) for t, tf in Counter(bag.split(" ")).items())
                ws = [math.log1p(tf) * math.log(n / d) for d, _, _, tf in cells]
                norm = math.sqrt(math.fsum(w * w for w in ws))
                got = [(c[2], w / norm) for c, w in zip(cells, ws) if c[1] and w > 0]
                if got:
                    out.append((side, ident, many, [t for t, _ in got], [w for _, w in got]))
            yield pd.DataFrame(out, columns=["side", "id", "n", "toks", "ws"])

    rows = materialize(known.mapInPandas(run, "side int, id long, n long, toks array<string>, ws array<double>"), "vectors")
    return _Rows(classes, [rows.where(F.col("side") == i).drop("side") for i in (0, 1)], [classes, rows])


def _tail(at: Column) -> Column:
    """The squared norm of the tokens after position ``at`` (from 1)."""
    return F.aggregate(F.slice("ws", at + 1, F.size("ws")), F.lit(0.0), lambda a, x: a + x * x)


def _next(rows: DataFrame, bound: float) -> DataFrame:
    """``id, key, at, s2`` by one more token than ``id, key, at, s2, toks, ws`` have; rows that can't reach ``bound`` go."""
    more = rows.where(F.col("at") < F.size("ws")).withColumn("i", F.explode(F.sequence(F.col("at") + 1, F.size("ws"))))
    weight = F.element_at("ws", F.col("i"))
    more = more.withColumn("s2", F.col("s2") + weight * weight).where(F.col("s2") + _tail(F.col("i")) >= bound * bound)
    return more.select("id", F.xxhash64("key", F.element_at("toks", F.col("i"))).alias("key"), F.col("i").alias("at"), "s2")


def _start(vec: DataFrame) -> DataFrame:
    return vec.select("id", "toks", "ws", F.lit(0).cast("long").alias("key"), F.lit(0).alias("at"), F.lit(0.0).alias("s2"))


def _compared(rows: list[DataFrame], vec: list[DataFrame], bound: float) -> DataFrame:
    """``l, r, ln, rn, score`` of classes of the same ``key`` in both ``rows``, from ``bound`` on."""
    sides = []
    for x, v, s in zip(rows, vec, "lr"):
        sides.append(x.select("id", "key").join(v, "id").select("key", *(F.col(c).alias(s + c) for c in ("id", "n", "toks", "ws"))))
    met = sides[0].join(sides[1].withColumn("rmap", F.map_from_arrays("rtoks", "rws")).drop("rtoks", "rws"), "key")
    parts = F.zip_with("ltoks", "lws", lambda t, w: w * F.coalesce(F.element_at("rmap", t), F.lit(0.0)))
    met = met.withColumn("score", F.round(F.aggregate(parts, F.lit(0.0), lambda a, x: a + x), 9)).where(F.col("score") > 0)
    return met.where(F.col("score") >= bound).select(F.col("lid").alias("l"), F.col("rid").alias("r"), "ln", "rn", "score")


def _search(vec: list[DataFrame], bound: float, bounds: list[float]) -> DataFrame:
    """All pairs of classes whose score is ``bound`` or more; the shared parts of their vectors have norms from ``bounds`` on."""
    found, rows = None, [materialize(_next(_start(v), b), "first") for v, b in zip(vec, bounds)]
    while True:
        sizes = [x.groupBy("key").agg(F.count("*").alias(s)) for x, s in zip(rows, "lr")]
        blocks = materialize(sizes[0].join(sizes[1], "key").select("key", (F.col("l") * F.col("r") > HEAVY).alias("heavy")), "blocks")
        used, rows = [*rows, blocks], [x.join(blocks, "key") for x in rows]
        now = _compared([x.where(~F.col("heavy") | (F.col("s2") >= b * b)) for x, b in zip(rows, bounds)], vec, bound)
        now = materialize(now.distinct(), "near")
        found = now if found is None else found.unionByName(now)
        if not blocks.where("heavy").limit(1).count():
            discard(*used)
            return materialize(found.distinct(), "found")
        rows = [materialize(_next(x.where("heavy").join(v.drop("n"), "id"), b), "next") for x, v, b in zip(rows, vec, bounds)]
        discard(*used)


def _reached(found: DataFrame, t: int) -> tuple[float | None, int]:
    """The score of the ``t``-th pair of records (none if there are fewer), and how many are above it."""
    scores = found.groupBy("score").agg(F.sum(F.col("ln") * F.col("rn")).alias("m")).orderBy(F.desc("score")).limit(t).collect()
    above = 0
    for r in scores:
        if above + r["m"] >= t:
            return r["score"], above
        above += r["m"]
    return None, above


def _first(v: Vectors, f: _Filter, bags: list[DataFrame], t: int, most: int | None = None) -> float | None:
    """The score of the ``t``-th of the pairs of few left records with the right ones that hold their rarest token, of ``most`` records at most."""
    words = bags[0].select("rid", F.explode(F.array_distinct("bag")).alias("token")).join(v.df.where("both"), "token")
    rarest = words.groupBy("rid").agg(F.min(F.struct("df", "token")).alias("m"))
    rarest = rarest.where(F.col("m.df") <= most) if most else rarest
    rarest = materialize(rarest.select("m.token").distinct(), "rarest")
    held = bags[1].select("rid", F.array_join("bag", " ").alias("text"), F.explode(F.array_distinct("bag")).alias("token")).join(F.broadcast(rarest), "token", "left_semi")
    held = materialize(held.groupBy("rid").agg(F.first("text").alias("text")).select("rid", F.split("text", " ").alias("bag")), "held")
    x = _vectors_of(v, f, [bags[0], held])
    keys = x.rows[0].select("id", F.xxhash64(F.element_at("toks", 1)).alias("key"))
    every = x.rows[1].select("id", F.explode("toks").alias("token")).join(rarest, "token", "left_semi").select("id", F.xxhash64("token").alias("key"))
    bound, _ = _reached(_compared([keys, every], x.rows, 0.0), t)
    discard(rarest, held, *x.written)
    return bound


def _every(x: _Rows) -> DataFrame:
    """All pairs of classes that share a token."""
    keys = [r.select("id", F.explode("toks").alias("token")).select("id", F.xxhash64("token").alias("key")) for r in x.rows]
    return materialize(_compared(keys, x.rows, 0.0).distinct(), "found")


def _found(v: Vectors, bags: list[DataFrame], t: int) -> tuple[DataFrame, _Rows, list[DataFrame]]:
    """``l, r, ln, rn, score`` of all pairs of classes that the ``t`` best pairs of records can be in, with classes and bags.

    A first bound comes from the left records of the smallest ids, or from the most promising ones, and the right ones that
    hold their rarest token; it is the score of ``t`` pairs that there are, so it leaves none out. At the largest score that
    there is, more and more left records are searched until there are enough pairs, otherwise all at once.
    """
    f, m, many = _filter(v), FIRST * t, bags[0].count()

    def first_ids(m: int) -> DataFrame:
        last = bags[0].select("rid").orderBy("rid").limit(m).agg(F.max("rid")).first()[0]
        return bags[0].where(F.col("rid") <= F.lit(last))

    bound = _first(v, f, [first_ids(m), bags[1]], t, HELD)
    if bound is None or bound < 1.0:
        chosen = materialize(f.promising(bags[0], m), "rarest")
        better = _first(v, f, [bags[0].join(F.broadcast(chosen), "rid", "left_semi"), bags[1]], t, HELD)
        bound = max((b for b in (bound, better) if b is not None), default=None)
        discard(chosen)
    while bound is None:
        bound = _first(v, f, [first_ids(m), bags[1]], t)
        if m >= many:
            break
        m *= MORE
    while True:
        whole = m >= many or bound is None or bound < 1.0
        part = [bags[0] if whole else first_ids(m), bags[1]]
        some, fs, bounds = _pruned(f, part, (bound or 0.0) - SLACK)
        met = _met(fs, some, bounds, FEW if whole else SOME)
        discard(*some)
        _forget(f, *fs)
        x = _vectors_of(v, f, met)
        found = _every(x) if bound is None else _search(x.rows, bound - SLACK, bounds)
        bound, _ = _reached(found, t)
        if whole or bound >= 1.0:
            f.sent.destroy()
            return found, x, met
        discard(found, *x.written, *met)
        m *= MORE


def top_pairs(v: Vectors, left: DataFrame, right: DataFrame, left_fields: list[str], right_fields: list[str], t: int) -> DataFrame:
    """``rank, l_rid, r_rid, score``: the rows of :func:`dnfblock.operators.matcher.top_duplicates` on the weights of the same records."""
    found, x, bags = _found(v, [_bags(left, left_fields), _bags(right, right_fields)], t)
    score, above = _reached(found, t)
    if score is not None:
        found = found.where(F.col("score") >= score)
    found = materialize(found, "best")

    def members(side: int) -> DataFrame:
        own = x.classes.where(F.col("side") == side).select("id", "bag")
        own = own.join(found.select(F.col("lr"[side]).alias("id")).distinct(), "id")
        texts = bags[side].select("rid", F.array_join("bag", " ").alias("bag"))
        return materialize(texts.join(own, "bag").select(F.col("rid").alias(f"{'lr'[side]}_rid"), F.col("id").alias("lr"[side])), "members")

    ls, rs = members(0), members(1)
    pairs = found.join(ls, "l")
    if score is not None:
        # of the ties at the end, the smallest ids: left ones until there are enough, and for each the first t right ones of a class
        tied = pairs.where(F.col("score") == score).groupBy("l_rid").agg(F.sum("rn").alias("m")).orderBy("l_rid").limit(t).collect()
        many, last = above, None
        for row in tied:
            last = row["l_rid"]
            many += row["m"]
            if many >= t:
                break
        pairs = pairs.where((F.col("score") > score) | (F.col("l_rid") <= F.lit(last)))
        rs = rs.withColumn("i", F.row_number().over(Window.partitionBy("r").orderBy("r_rid"))).where(F.col("i") <= t)
    top = pairs.join(rs, "r").select("l_rid", "r_rid", "score").orderBy(F.desc("score"), "l_rid", "r_rid").limit(t)
    order = Window.orderBy(F.desc("score"), "l_rid", "r_rid")
    return top.withColumn("rank", F.row_number().over(order).cast("long")).select("rank", "l_rid", "r_rid", "score")
