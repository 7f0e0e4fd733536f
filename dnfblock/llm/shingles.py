"""Near copies by their sets of five-word shingles: Jaccard similarity of 0.8 or more.

Texts meet in buckets of MinHash bands (``BANDS`` of ``ROWS``; a pair at similarity s misses all of them with
probability (1 - s^ROWS)^BANDS, 7 in 100,000 at 0.8), and every drop rests on the Jaccard similarity of the
whole sets. In each of ``ROUNDS`` rounds, which are done whatever the input's size, a text with the smallest id in all of its buckets stays and is compared
with those that share one, which is linear in a group of copies; the near ones go. Of what is left, pairs are
written out only for buckets of at most ``FEW`` texts. Larger buckets are cut into blocks of some ``TILE_ROWS``,
and pairs of blocks are compared whole inside a task, which gives a spanning forest of the near ones; one
text of each component stays.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dnfblock.llm.components import connected_components
from dnfblock.llm.simhash import shingle_hashes
from dnfblock.storage import materialize

WORDS = 5
BANDS = 24
ROWS = 5
ROUNDS = 3
PAIRS_A_ROW = 4  # has no effect any more: whether a round is done must not depend on the size of the input
FEW = 6
TILE_ROWS = 128
COLUMNS = 1 << 14
_RANDOM = np.random.default_rng(5)
TIMES = _RANDOM.integers(0, 1 << 63, BANDS * ROWS, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
PLUS = _RANDOM.integers(0, 1 << 63, BANDS * ROWS, dtype=np.uint64)


def buckets(hashes: np.ndarray, step: int = 1024) -> list[int]:
    """One signed long per band of the MinHash signature of ``hashes``."""
    low = np.full(BANDS * ROWS, np.iinfo(np.uint64).max, np.uint64)
    for at in range(0, len(hashes), step):
        part = hashes[at : at + step, None].astype(np.uint64) * TIMES + PLUS
        low = np.minimum(low, part.min(axis=0))
    keys = [xxhash.xxh64_intdigest(low[b * ROWS : (b + 1) * ROWS].tobytes(), b) for b in range(BANDS)]
    return np.array(keys, np.uint64).view(np.int64).tolist()


def _mapped(docs: DataFrame, make, column: str) -> DataFrame:
    """``id`` and ``column``, an array of long that ``make`` gives for the shingle hashes of ``text``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, len(batch), 256):
                part = batch.slice(at, 256)
                made = [make(shingle_hashes(x.as_py(), WORDS)) for x in part.column(1)]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(made, pa.list_(pa.int64()))], ["id", column])

    return docs.select("id", "text").mapInArrow(run, f"id long, {column} array<long>")


def _shared(members: DataFrame) -> DataFrame:
    """The rows whose bucket has others."""
    many = members.groupBy("bucket").agg(F.count("*").alias("n")).where("n > 1").select("bucket")
    return materialize(members.join(many, "bucket", "left_semi"), "buckets")


def _near(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """The rows of ``a, b`` whose sets have a Jaccard similarity of at least 0.8."""
    left = sets.select(F.col("id").alias("a"), F.col("grams").alias("x"))
    right = sets.select(F.col("id").alias("b"), F.col("grams").alias("y"))
    n, m = F.size("x"), F.size("y")
    likely = pairs.join(left, "a").join(right, "b").where(5 * F.least(n, m) >= 4 * F.greatest(n, m))
    return likely.where(9 * F.size(F.array_intersect("x", "y")) >= 4 * (n + m)).select("a", "b")


def near_forest(sets: list[np.ndarray]) -> list[tuple[int, int]]:
    """A spanning forest, as (position, root), of the pairs of ``sets`` that are near; the sets hold no value twice."""
    sizes = np.array([len(x) for x in sets])
    row = np.repeat(np.arange(len(sets)), sizes)
    _, column, many = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    shared = many > 1
    at = (np.cumsum(shared) - 1)[column]
    keep = shared[column]
    row, at = row[keep], at[keep]
    order = np.argsort(at, kind="stable")
    row, at = row[order], at[order]
    both = np.zeros((len(sets), len(sets)), np.float32)
    for low in range(0, int(shared.sum()), COLUMNS):
        part = slice(*np.searchsorted(at, (low, low + COLUMNS)))
        has = np.zeros((len(sets), COLUMNS), np.float32)
        has[row[part], at[part] - low] = 1
        both += has @ has.T
    left, right = np.nonzero(9 * both >= 4 * (sizes[:, None] + sizes[None, :]))
    up = list(range(len(sets)))

    def root(i: int) -> int:
        while up[i] != i:
            up[i] = up[up[i]]
            i = up[i]
        return i

    for a, b in zip(left.tolist(), right.tolist()):
        x, y = root(a), root(b)
        up[max(x, y)] = min(x, y)
    return [(i, root(i)) for i in range(len(sets)) if root(i) != i]


def tile_links(members: DataFrame, sizes: DataFrame, sets: DataFrame) -> DataFrame:
    """``a, b``: links that connect the near texts of every bucket of ``sizes`` (``bucket, n``), by pairs of blocks."""
    fan = F.ceil(F.col("n") / TILE_ROWS)
    rows = members.join(sizes, "bucket").select("id", "bucket", fan.alias("fan"), F.pmod(F.xxhash64("id"), fan).alias("block"))
    other = F.explode(F.sequence(F.lit(0).cast("long"), F.col("fan") - 1)).alias("other")
    rows = rows.select("id", "bucket", "block", other)
    cell = F.concat_ws(".", F.least("block", "other"), F.greatest("block", "other"))
    rows = rows.select("id", "bucket", cell.alias("cell")).join(sets, "id")

    def links(table: pa.Table) -> pa.Table:
        ids = table.column("id").to_pylist()
        found = near_forest([np.asarray(x.values) for x in table.column("grams")])
        a, b = ([ids[pair[k]] for pair in found] for k in (0, 1))
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})

    return rows.groupBy("bucket", "cell").applyInArrow(links, "a long, b long").distinct()


def near_copies(docs: DataFrame) -> DataFrame:
    """``id`` of the rows of ``id, text`` (ids unique, none null) that go."""
    sketched = _mapped(docs, buckets, "buckets").select("id", F.explode("buckets").alias("bucket"))
    members = _shared(materialize(sketched, "sketches"))
    some = docs.join(members.select("id").distinct(), "id", "left_semi")
    sets = materialize(_mapped(some, lambda h: np.unique(h).view(np.int64), "grams"), "shingles")
    gone = []
    for _ in range(ROUNDS):
        if not members.limit(1).count():
            break
        lows = members.groupBy("bucket").agg(F.min("id").alias("low"))
        met = materialize(members.join(lows, "bucket"), "lows")
        stay = met.groupBy("id").agg(F.bool_and(F.col("id") == F.col("low")).alias("first")).where("first").select("id")
        stay = materialize(stay, "stay")
        pairs = met.where("id <> low").join(stay.select(F.col("id").alias("low")), "low", "left_semi")
        found = _near(pairs.select(F.col("id").alias("a"), F.col("low").alias("b")).distinct(), sets)
        found = materialize(found.select(F.col("a").alias("id")).distinct(), "near")
        gone.append(found)
        members = _shared(members.join(found.unionByName(stay), "id", "left_anti"))
    sizes = materialize(members.groupBy("bucket").agg(F.count("*").alias("n")), "bucket-sizes")
    few = members.join(sizes.where(F.col("n") <= FEW), "bucket").groupBy("bucket").agg(F.array_sort(F.collect_list("id")).alias("ids"))
    pair = F.explode(F.flatten(F.transform("ids", lambda b, i: F.transform(F.slice("ids", 1, i), lambda a: F.struct(b.alias("a"), a.alias("b"))))))
    links = _near(few.select(pair.alias("p")).select("p.a", "p.b").distinct(), sets)
    links = links.unionByName(tile_links(members, sizes.where(F.col("n") > FEW), sets))
    out = connected_components(links, "a", "b").where("node <> root").select(F.col("node").alias("id"))
    for found in gone:
        out = out.unionByName(found)
    return out


def drop_near_texts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs``, whose ids are unique or null, without near copies; rows without an id stay."""
    rows = docs.select(docs[id_col].cast("long").alias("id"), docs[text_col].alias("text")).where("id IS NOT NULL")
    out = near_copies(rows).select(F.col("id").alias("__gone"))
    return docs.join(out, docs[id_col].cast("long") == out["__gone"], "left_anti")
