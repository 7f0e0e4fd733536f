"""Applying a scheme: keys, inverted index, blocks, candidate pairs.

A join on ``covers(left, right)`` would be a nested loop over all pairs. Instead every record is
exploded to its keys and the sides meet in an equi-join per (term, key). A pair that shares several
keys is kept only at the smallest one, a test on the two rows' own key arrays, so the candidate set
needs no distinct over pairs.
"""

from __future__ import annotations

import itertools
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from dnfblock.operators.scheme import SEPARATOR, Scheme
from dnfblock.storage import materialize

#: A key of more than one in so many rows of keys is hot; there are fewer than this many such keys.
HOT = 2048
HOT_SALTS = 32


def keyed(df: DataFrame, scheme: Scheme, side: int) -> DataFrame:
    """``rid, keys``: all keys of a record as "term<separator>key", sorted; one narrow pass."""

    def named(i: int):
        return lambda k: F.concat(F.lit(f"{i:04d}:"), k)

    sets = [F.transform(scheme.term_keys(i, side), named(i)) for i in range(len(scheme.terms))]
    every = F.array_sort(F.array_distinct(F.concat(*sets) if len(sets) > 1 else sets[0]))
    return df.select("rid", every.alias("keys"))


def index(df: DataFrame, scheme: Scheme, side: int) -> DataFrame:
    """The inverted index: ``term_id, key, side, rid``."""
    rows = keyed(df, scheme, side).select("rid", F.explode("keys").alias("k"))
    return rows.select(
        F.substring("k", 1, 4).cast("int").alias("term_id"), F.substring("k", 6, 1 << 30).alias("key"), F.lit(side).alias("side"), "rid"
    )


def block_sizes(left: DataFrame, right: DataFrame, scheme: Scheme) -> DataFrame:
    """``term_id, key, n_left, n_right, comparisons`` of every block."""
    both = index(left, scheme, 0).unionByName(index(right, scheme, 1))
    sizes = both.groupBy("term_id", "key").agg(
        F.sum((F.col("side") == 0).cast("long")).alias("n_left"), F.sum((F.col("side") == 1).cast("long")).alias("n_right")
    )
    return sizes.withColumn("comparisons", F.col("n_left") * F.col("n_right"))


def gamma_upper_bound(left: DataFrame, right: DataFrame, scheme: Scheme) -> int:
    """Sum over blocks of their comparisons: bounds the candidate set without making it."""
    return int(block_sizes(left, right, scheme).agg(F.coalesce(F.sum(F.col("comparisons").cast("decimal(38,0)")), F.lit(0))).first()[0])


def gamma_sketches(left: DataFrame, right: DataFrame, scheme: Scheme, lg: int = 14) -> DataFrame:
    """``term_id, sketch``: a HyperLogLog sketch of the candidate pairs of every term that covers any.

    Pairs are hashed where they meet, so that nothing but sketches of 2^``lg`` registers at most is shuffled for them.
    Sketches of further records can be merged with these.
    """
    a = index(left, scheme, 0).select("term_id", "key", F.col("rid").alias("l_rid"))
    b = index(right, scheme, 1).select("term_id", "key", F.col("rid").alias("r_rid"))
    pairs = a.join(b, ["term_id", "key"]).select("term_id", F.xxhash64("l_rid", "r_rid").alias("pair"))
    return pairs.groupBy("term_id").agg(F.hll_sketch_agg("pair", lg).alias("sketch"))


def gamma_estimate(sketches: DataFrame) -> DataFrame:
    """``gamma``: about how many distinct pairs the merged sketches have seen (relative deviation about 0.8 / sqrt(2^lg))."""
    return sketches.agg(F.coalesce(F.hll_sketch_estimate(F.hll_union_agg("sketch", F.lit(True))), F.lit(0)).alias("gamma"))


def purged_keys(left: DataFrame, right: DataFrame, scheme: Scheme, max_pairs: int) -> DataFrame:
    """``k``: the keys of blocks that stand for more than ``max_pairs`` comparisons."""
    sizes = block_sizes(left, right, scheme).where(F.col("comparisons") > max_pairs)
    return sizes.select(F.concat(F.lpad(F.col("term_id").cast("string"), 4, "0"), F.lit(":"), "key").alias("k"))


def hot_keys(left: DataFrame, right: DataFrame) -> DataFrame:
    """``k``: keys of more than one in ``HOT`` of all rows of keys on either side, so fewer than ``2 * HOT``."""
    found = None
    for rows in (left, right):
        sizes = rows.groupBy("k").agg(F.count("*").alias("n"))
        total = sizes.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
        hot = sizes.where(F.col("n") > total / HOT).select("k")
        found = hot if found is None else found.unionByName(hot).distinct()
    return found


def candidates(
    left: DataFrame,
    right: DataFrame,
    scheme: Scheme,
    *,
    dedup: str = "min_key",
    namespaced: bool = True,
    salts: int | str = 1,
    max_block_pairs: int | None = None,
    self_pairs: bool = False,
    single_key: bool = False,
) -> DataFrame:
    """``l_rid, r_rid``: the distinct candidate pairs of ``scheme``.

    ``namespaced=False`` lets blocks of different terms with the same key value meet. ``salts`` deals
    the left rows of every block to that many tasks, each with all right rows of the block; ``"auto"`` counts
    the blocks first and does so with hot keys only, for sessions whose adaptive skew join is off.
    ``max_block_pairs`` purges larger blocks, before the smallest shared key is looked for.
    ``single_key`` puts a record in its smallest block only, as hashing would.

    The sides are merged, never broadcast: Spark takes the size of exploded keys from that of the compressed files, many times too small.
    """
    if not scheme.terms:
        return left.select(F.col("rid").alias("l_rid")).join(right.select(F.col("rid").alias("r_rid")), F.lit(False))
    sides = [keyed(left, scheme, 0), keyed(right, scheme, 1)]
    if not namespaced:
        bare = F.array_sort(F.array_distinct(F.transform("keys", lambda k: F.substring(k, 6, 1 << 30))))
        sides = [s.withColumn("keys", bare) for s in sides]
    if max_block_pairs is not None:
        gone = purged_keys(left, right, scheme, max_block_pairs)
        sides = [
            s.select("rid", F.explode("keys").alias("k")).join(gone, "k", "left_anti").groupBy("rid").agg(F.array_sort(F.collect_list("k")).alias("keys"))
            for s in sides
        ]
    if single_key:
        sides = [s.withColumn("keys", F.slice("keys", 1, 1)) for s in sides]
    out = []
    for s, name in zip(sides, "lr"):
        carried = ["rid", "keys"] if dedup == "min_key" else ["rid"]
        out.append(s.select(*(F.col(c).alias(f"{name}_{c}") for c in carried), F.explode("keys").alias("k")))
    if salts != 1:
        many = F.lit(salts)
        if salts == "auto":
            hot = hot_keys(*out).withColumn("many", F.lit(HOT_SALTS))
            out = [rows.join(F.broadcast(hot), "k", "left") for rows in out]
            many = F.coalesce("many", F.lit(1))
        own = F.pmod(F.xxhash64("l_rid"), many).cast("int")
        out = [out[0].withColumn("salt", own), out[1].withColumn("salt", F.explode(F.sequence(F.lit(0), (many - 1).cast("int"))))]
        out = [rows.drop("many") for rows in out]
    pairs = out[0].join(out[1].hint("merge"), ["k", "salt"] if salts != 1 else "k")
    if self_pairs:
        pairs = pairs.where("l_rid < r_rid")
    if dedup == "min_key":
        shared = F.array_min(F.array_intersect("l_keys", "r_keys"))
        return pairs.where(shared == F.col("k")).select("l_rid", "r_rid")
    return pairs.select("l_rid", "r_rid").distinct()


#: Key sets of up to so many keys are counted by their subsets, which is linear in the records; larger ones by a join of classes.
MOST_KEYS = 8


def _subsets(keys: Column) -> Column:
    """Every non-empty subset of ``keys`` as 128 bits ``a, b``, with ``sign`` 1 for odd sizes and -1 for even ones."""
    start = F.array(F.struct(F.lit(0).cast("long").alias("a"), F.lit(0).cast("long").alias("b"), F.lit(-1).alias("sign")))

    def grown(s, x):
        return F.struct(F.xxhash64(s["a"], x).alias("a"), F.xxhash64(x, s["b"]).alias("b"), (-s["sign"]).alias("sign"))

    every = F.aggregate(keys, start, lambda done, x: F.concat(done, F.transform(done, lambda s: grown(s, x))))
    return F.slice(every, 2, 1 << 30)


def _exploded(rows: DataFrame, *carried: str) -> DataFrame:
    return rows.where(F.size("keys") <= MOST_KEYS).select(*carried, F.explode(_subsets(F.col("keys"))).alias("s")).select(*carried, "s.*")


def _met_classes(left: DataFrame, right: DataFrame) -> DataFrame:
    """``l_id, l_n, r_id, r_n``: pairs of classes (``id, n, keys``) that share a key, at least one of them of more than ``MOST_KEYS`` keys."""
    out = [c.select(*(F.col(x).alias(f"{s}_{x}") for x in ("id", "n", "keys")), F.explode("keys").alias("k")) for c, s in ((left, "l"), (right, "r"))]
    met = out[0].join(out[1], "k").where((F.size("l_keys") > MOST_KEYS) | (F.size("r_keys") > MOST_KEYS))
    return met.where(F.array_min(F.array_intersect("l_keys", "r_keys")) == F.col("k")).select("l_id", "l_n", "r_id", "r_n")


def _classes(rows: DataFrame) -> DataFrame:
    """``id, n, keys``: records (``rid, keys``) of equal key sets, by their smallest id."""
    return rows.groupBy("keys").agg(F.min("rid").alias("id"), F.count("*").alias("n"))


def count_candidates(left: DataFrame, right: DataFrame, scheme: Scheme) -> DataFrame:
    """One row, ``gamma``: how many pairs :func:`candidates` has, without making them.

    A pair that shares m keys shares 2^m - 1 subsets of them, and their signs add up to one; so the products of how often
    a subset occurs on either side add up to the number of pairs, exactly. Only the subsets of a record are exploded.
    """
    big = "decimal(38,0)"
    if not scheme.terms:
        return left.select(F.lit(0).cast("long").alias("gamma")).limit(0).agg(F.count("*").alias("gamma"))
    sides = [keyed(left, scheme, 0).where(F.size("keys") > 0), keyed(right, scheme, 1).where(F.size("keys") > 0)]
    one, none = F.lit(1).cast("long"), F.lit(0).cast("long")
    rows = _exploded(sides[0]).select("a", "b", "sign", one.alias("l"), none.alias("r"))
    rows = rows.unionByName(_exploded(sides[1]).select("a", "b", "sign", none.alias("l"), one.alias("r")))
    blocks = rows.groupBy("a", "b", "sign").agg(F.sum("l").alias("l"), F.sum("r").alias("r")).where("l > 0 AND r > 0")
    parts = blocks.select((F.col("sign") * F.col("l") * F.col("r")).cast(big).alias("g"))
    if sides[0].unionByName(sides[1]).where(F.size("keys") > MOST_KEYS).limit(1).count():
        met = _met_classes(*(_classes(s) for s in sides))
        parts = parts.unionByName(met.select((F.col("l_n") * F.col("r_n")).cast(big).alias("g")))
    return parts.agg(F.coalesce(F.sum("g"), F.lit(0)).cast("long").alias("gamma"))


def links(left: DataFrame, right: DataFrame, scheme: Scheme) -> DataFrame:
    """``side, rid, class_id, links``: every record, the smallest id of its side with the same keys, and how many candidates it has.

    Records of one class have the same candidates, so links are counted a class at a time, by subsets as in
    :func:`count_candidates`. A record without keys is in the class of those, and has no link.
    """
    sides = [keyed(left, scheme, 0), keyed(right, scheme, 1)]
    classes = [_classes(s) for s in sides]
    small = [_exploded(c, "id", "n") for c in classes]
    large = [c.where(F.size("keys") > MOST_KEYS).limit(1).count() > 0 for c in classes]
    met = _met_classes(*classes) if any(large) else None
    out = []
    for i in (0, 1):
        other = small[1 - i].groupBy("a", "b").agg(F.sum("n").alias("m"))
        found = small[i].join(other, ["a", "b"]).select("id", (F.col("sign") * F.col("m")).alias("x"))
        if met is not None:
            found = found.unionByName(met.select(F.col(f"{'lr'[i]}_id").alias("id"), F.col(f"{'rl'[i]}_n").alias("x")))
        counted = classes[i].join(found.groupBy("id").agg(F.sum("x").alias("x")), "id", "left")
        counted = counted.select("keys", F.col("id").alias("class_id"), F.coalesce("x", F.lit(0)).alias("links"))
        out.append(sides[i].join(counted, "keys").select(F.lit(i).alias("side"), "rid", "class_id", "links"))
    return out[0].unionByName(out[1])


def verified_links(left: DataFrame, right: DataFrame, scheme: Scheme) -> DataFrame:
    """:func:`links` by the plan of :func:`verified_candidates`: a join on the first atom of a term, the others verified.

    The join is one of classes of records with the same keys. Pairs that several terms cover are taken off again by
    joins on the first atoms of all of these terms, so that no pair is met under two of them.
    """
    sides, names = [], [[f"k{i}_{j}" for j in range(len(t))] for i, t in enumerate(scheme.terms)]
    for i, df in enumerate((left, right)):
        own = [F.array_sort(a.keys(i)).alias(names[x][y]) for x, t in enumerate(scheme.terms) for y, a in enumerate(t)]
        sides.append(df.select("rid", *own).join(keyed(df, scheme, i), "rid"))
    total = [s.select("rid", F.lit(0).cast("long").alias("x")) for s in sides]
    for size in range(1, len(scheme.terms) + 1):
        for some in itertools.combinations(range(len(scheme.terms)), size):
            columns = [n for t in some for n in names[t]]
            classes = [s.groupBy(columns).agg(F.min("rid").alias("id"), F.count("*").alias("n")) for s in sides]
            lead = reduce(lambda x, y: F.flatten(F.transform(x, lambda a: F.transform(y, lambda b: F.concat(a, F.lit(SEPARATOR), b)))), [F.col(names[t][0]) for t in some])
            rows = []
            for c, s in zip(classes, "lr"):
                c = c.withColumn("lead", lead)
                rows.append(c.select(*(F.col(x).alias(f"{s}_{x}") for x in ("id", "n", "lead", *columns)), F.explode("lead").alias("k")))
            met = rows[0].join(rows[1], "k").where(F.array_min(F.array_intersect("l_lead", "r_lead")) == F.col("k"))
            for n in (n for t in some for n in names[t][1:]):
                met = met.where(F.arrays_overlap(f"l_{n}", f"r_{n}"))
            both = F.explode(F.array(*(F.struct(F.lit(i).alias("side"), F.col(f"{a}_id").alias("id"), F.col(f"{b}_n").alias("n")) for i, (a, b) in enumerate(("lr", "rl"))))).alias("s")
            counts = met.select(both).groupBy("s.side", "s.id").agg(F.sum("s.n").alias("n"))
            for i in (0, 1):
                counted = classes[i].join(counts.where(F.col("side") == i).select("id", "n").withColumnRenamed("n", "x"), "id")
                x = F.col("x") if size % 2 else -F.col("x")
                total[i] = total[i].unionByName(sides[i].join(counted.select(*columns, x.alias("x")), columns).select("rid", "x"))
    out = []
    for i, rows in enumerate(total):
        known = sides[i].join(_classes(sides[i]).select("keys", F.col("id").alias("class_id")), "keys").select("rid", "class_id")
        out.append(known.join(rows.groupBy("rid").agg(F.sum("x").alias("links")), "rid").select(F.lit(i).alias("side"), "rid", "class_id", "links"))
    return out[0].unionByName(out[1])


def count_differences(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row, ``n_diff``: pairs (``l_rid, r_rid``) that one of ``a`` and ``b`` has more often than the other.

    The partners of a left record are summed up where they are met (number, sum and exclusive or of two hashes), so no
    pairs are shuffled; those of left records whose sums differ are compared themselves.
    """

    def sums(df: DataFrame, s: str) -> DataFrame:
        total = F.sum(F.xxhash64("r_rid").cast("decimal(38,0)"))
        return df.groupBy("l_rid").agg(F.struct(F.count("*"), total, F.bit_xor(F.xxhash64(F.lit(1), "r_rid"))).alias(s))

    odd = sums(a, "x").join(sums(b, "y"), "l_rid", "full").where(~F.col("x").eqNullSafe(F.col("y"))).select("l_rid")
    odd = materialize(odd, "differ")
    if not odd.limit(1).count():
        return odd.agg(F.count("*").alias("n_diff"))
    a, b = (x.join(odd, "l_rid", "left_semi") for x in (a, b))
    return a.exceptAll(b).unionByName(b.exceptAll(a)).agg(F.count("*").alias("n_diff"))


def verified_candidates(left: DataFrame, right: DataFrame, scheme: Scheme) -> DataFrame:
    """The candidate set by the plan that joins on one atom of a term and verifies the others.

    For conjunctions whose combined keys would be many; a pair is kept at the first term that covers it.
    """
    out = None
    for i, term in enumerate(scheme.terms):
        lead = Scheme.of(term[0])
        pairs = candidates(left, right, lead)
        lf = left.select(F.col("rid").alias("l_rid"), *(F.col(f).alias(f"l_{f}") for f in scheme.fields(0)))
        rf = right.select(F.col("rid").alias("r_rid"), *(F.col(f).alias(f"r_{f}") for f in scheme.fields(1)))
        rows = pairs.join(lf, "l_rid").join(rf, "r_rid")
        lcol, rcol = (lambda f: F.col(f"l_{f}")), (lambda f: F.col(f"r_{f}"))
        keep = Scheme((term,)).covers(lcol, rcol)
        for earlier in scheme.terms[:i]:
            keep = keep & ~Scheme((earlier,)).covers(lcol, rcol)
        rows = rows.where(keep).select("l_rid", "r_rid")
        out = rows if out is None else out.unionByName(rows)
    return out


def covered_pairs_bruteforce(left: DataFrame, right: DataFrame, scheme: Scheme, max_pairs: int = 5_000_000) -> DataFrame:
    """All pairs, tested one by one: an oracle for small data, refused beyond ``max_pairs``."""
    if left.count() * right.count() > max_pairs:
        raise ValueError(f"more than {max_pairs} pairs")
    lf = left.select(F.col("rid").alias("l_rid"), *(F.col(f).alias(f"l_{f}") for f in scheme.fields(0)))
    rf = right.select(F.col("rid").alias("r_rid"), *(F.col(f).alias(f"r_{f}") for f in scheme.fields(1)))
    keep = scheme.covers(lambda f: F.col(f"l_{f}"), lambda f: F.col(f"r_{f}"))
    return lf.crossJoin(rf).where(keep).select("l_rid", "r_rid")


def with_records(pairs: DataFrame, left: DataFrame, right: DataFrame) -> DataFrame:
    """Candidate pairs with both records, for the comparison step that follows."""
    lf = left.select(*(F.col(c).alias(f"l_{c}") for c in left.columns))
    rf = right.select(*(F.col(c).alias(f"r_{c}") for c in right.columns))
    return pairs.join(lf, "l_rid").join(rf, "r_rid")


def with_few_records(pairs: DataFrame, left: DataFrame, right: DataFrame) -> DataFrame:
    """:func:`with_records` for pairs that are few by contract: their ids go to all tasks, so that no other record is shuffled."""
    own = []
    for df, s in ((left, "l"), (right, "r")):
        own.append(df.join(F.broadcast(pairs.select(F.col(f"{s}_rid").alias("rid")).distinct()), "rid", "left_semi"))
    return with_records(pairs, *own)


def linked_view(pairs: DataFrame, left: DataFrame, right: DataFrame, mapped: dict[str, tuple[str, str]]) -> DataFrame:
    """A mediated view over both sources: linked records merged, others as they are.

    ``mapped`` names each column of the view with its field on either side; the left value wins.
    """
    lf = left.select(F.col("rid").alias("l_rid"), *(F.col(a).alias(f"l__{n}") for n, (a, _) in mapped.items()))
    rf = right.select(F.col("rid").alias("r_rid"), *(F.col(b).alias(f"r__{n}") for n, (_, b) in mapped.items()))
    rows = lf.join(pairs, "l_rid", "left").join(rf, "r_rid", "full")
    one = lambda c: F.array_join(F.array_sort(c), "|")
    pick = lambda n: one(F.when(F.size(F.coalesce(f"l__{n}", F.array().cast("array<string>"))) > 0, F.col(f"l__{n}")).otherwise(F.col(f"r__{n}")))
    return rows.select("l_rid", "r_rid", *(pick(n).alias(n) for n in mapped))
