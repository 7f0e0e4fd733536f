"""SimHash near-duplicates: exact comparison of tiles, by exclusive-or and bit counts.

A fingerprint of 64 bits has bit i set where more than half of a text's shingle hashes (XXH64,
seed 42, repeats included) have it set. Equal fingerprints are merged first, so a group of copies
costs one fingerprint, whatever its size.

Distinct fingerprints are dealt to tiles by their population counts: the ones in each of ``parts``
slices of the bits. A bit that differs changes one of these counts by one, so fingerprints within
``radius`` bits lie in tiles whose counts differ by ``radius`` at most in sum; all other pairs of
tiles are skipped, unread. A tile of many fingerprints is cut into blocks of some ``tile_rows`` by
a hash, so no task holds more than two blocks. Pairs of blocks that remain are compared whole in
numpy, and each gives a spanning forest, not its pairs.

From ``banded_from`` fingerprints on, tiles are made inside four bands: fingerprints that also agree
on one quarter of the bits, which a pair within three bits does for some quarter. The links are the
same; what is compared then grows little faster than the corpus.

Defined cases: null is the empty text; a text without words has fingerprint zero and is linked like
any other; fewer words than a shingle needs make one shingle; repeated rows and ids are kept, and a
null id is never the id of a component that has others; an empty table gives an empty result;
further columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import accumulate, product

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dnfblock.llm.components import connected_components
from dnfblock.storage import materialize

SEED = 42
RADIUS = 3
SHINGLE = 3
PARTS = 4
TILE_ROWS = 512
BANDED_FROM = 4_000_000
#: Pairs of blocks with fewer pairs of rows are compared together.
_FEW = 512
_AT_ONCE = 1 << 21


def shingle_hashes(text: str | None, shingle: int = SHINGLE) -> np.ndarray:
    """XXH64 of every word shingle of ``text``; A-Z are lower-cased, words end at ASCII blanks."""
    words = (text or "").encode().lower().split()
    if not words:
        return np.empty(0, np.uint64)
    joined = b" ".join(words)
    digest = xxhash.xxh64_intdigest
    if len(words) <= shingle:
        return np.array([digest(joined, SEED)], np.uint64)
    ends = list(accumulate(len(w) + 1 for w in words))
    starts = [0, *ends[: len(words) - shingle]]
    return np.array([digest(joined[a : b - 1], SEED) for a, b in zip(starts, ends[shingle - 1 :])], np.uint64)


def fingerprint(hashes: np.ndarray, step: int = 1 << 16) -> int:
    """Majority bits of ``hashes``; counted ``step`` hashes at a time."""
    if not len(hashes):
        return 0
    ones = np.zeros(64, np.int64)
    for at in range(0, len(hashes), step):
        part = hashes[at : at + step].astype("<u8").view(np.uint8).reshape(-1, 8)
        ones += np.unpackbits(part, axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    bits = (2 * ones > len(hashes)).astype(np.uint8)
    return int(np.packbits(bits, bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = SHINGLE) -> DataFrame:
    """``doc_id, fp`` with the fingerprint as a signed long, one row per row of ``docs``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fps = [fingerprint(shingle_hashes(x.as_py(), shingle)) for x in batch.column(1)]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(np.array(fps, np.uint64).view(np.int64), pa.int64())], ["doc_id", "fp"]
            )

    return docs.select(F.col(id_col).cast("long"), F.col(text_col)).mapInArrow(run, "doc_id long, fp long")


def neighbours(parts: int = PARTS, radius: int = RADIUS) -> list[tuple[int, ...]]:
    """Differences of count vectors that are ``radius`` at most in sum, one of each pair of signs, zero first."""
    steps = product(range(-radius, radius + 1), repeat=parts) if parts <= 4 else _sparse(parts, radius)
    return sorted(d for d in steps if sum(map(abs, d)) <= radius and next((x for x in d if x), 1) > 0)


def _sparse(parts: int, radius: int) -> Iterator[tuple[int, ...]]:
    if not parts:
        yield ()
        return
    for x in range(-radius, radius + 1):
        for rest in _sparse(parts - 1, radius - abs(x)):
            yield (x, *rest)


def tiled(fps: DataFrame, banded: bool = False, parts: int = PARTS, tile_rows: int = TILE_ROWS, radius: int = RADIUS) -> DataFrame:
    """``band, tile, block, fps``: distinct fingerprints by their population counts, in blocks."""
    whole = F.col("fp")
    if not banded:
        rows = fps.select("fp", F.lit(0).alias("band"), whole.alias("bits"))
        width = 64 // parts
    else:
        bands = []
        for q in range(4):
            own = F.shiftrightunsigned(whole, 16 * q).bitwiseAND(0xFFFF).cast("int")
            low = whole.bitwiseAND((1 << (16 * q)) - 1)
            high = F.shiftleft(F.shiftrightunsigned(whole, 16 * (q + 1)), 16 * q) if q < 3 else F.lit(0)
            bands.append(F.struct((F.lit(q << 16).bitwiseOR(own)).alias("band"), high.bitwiseOR(low).alias("bits")))
        rows = fps.select("fp", F.explode(F.array(*bands)).alias("b")).select("fp", "b.band", "b.bits")
        width = 48 // parts
    base = width + 2 * radius + 1  # digits of neighbours never meet those of another tile
    code = F.lit(0).cast("long")
    for i in range(parts):
        ones = F.bit_count(F.shiftrightunsigned("bits", width * i).bitwiseAND((1 << width) - 1))
        code = code + ones.cast("long") * F.lit(base**i)
    rows = rows.select("band", code.alias("tile"), "fp")
    many = rows.groupBy("band", "tile").agg(F.count("*").alias("n")).where(F.col("n") > tile_rows)
    rows = rows.join(many, ["band", "tile"], "left")
    fan = F.coalesce(F.ceil(2 * F.col("n") / tile_rows), F.lit(1))
    rows = rows.select("band", "tile", F.pmod(F.xxhash64("fp"), fan).alias("block"), "fp")
    return rows.groupBy("band", "tile", "block").agg(F.collect_list("fp").alias("fps"))


def tile_pairs(tiles: DataFrame, banded: bool = False, parts: int = PARTS, radius: int = RADIUS) -> DataFrame:
    """``own, other, same``: the pairs of blocks whose population counts allow a link, each once."""
    base = (48 if banded else 64) // parts + 2 * radius + 1
    steps = [sum(x * base**i for i, x in enumerate(d)) for d in neighbours(parts, radius)]
    spark = tiles.sparkSession
    tasks = int(spark.conf.get("spark.sql.shuffle.partitions"))
    home = tiles.select("band", F.col("tile").alias("home"), F.col("block").alias("at"), F.col("fps").alias("own"))
    guest = tiles.select("band", "tile", "block", F.col("fps").alias("other"), F.explode(F.lit(steps)).alias("step"))
    guest = guest.select("band", (F.col("tile") - F.col("step")).alias("home"), "block", "other", (F.col("step") == 0).alias("near"))
    # comparing costs more than its bytes tell, so the number of tasks is not left to these
    met = home.repartition(tasks, "band", "home").join(guest.repartition(tasks, "band", "home"), ["band", "home"])
    met = met.where(~F.col("near") | (F.col("at") <= F.col("block")))
    return met.select("own", "other", (F.col("near") & (F.col("at") == F.col("block"))).alias("same"))


def near_links(own: np.ndarray, other: np.ndarray, same: bool, radius: int = RADIUS) -> np.ndarray:
    """A spanning forest, as rows (position, root), of the links between two blocks laid end to end."""
    left, right = np.nonzero(np.bitwise_count(own[:, None] ^ other[None, :]) <= radius)
    right = right + (0 if same else len(own))
    keep = left < right
    left, right = left[keep], right[keep]
    if len(left) < 2:
        return np.stack([left, right], axis=1)
    up = np.arange(len(own) + len(other))
    while len(left):
        while not np.array_equal(upper := up[up], up):
            up = upper
        apart = up[left] != up[right]
        left, right = left[apart], right[apart]
        np.minimum.at(up, np.maximum(up[left], up[right]), np.minimum(up[left], up[right]))
    while not np.array_equal(upper := up[up], up):
        up = upper
    low = np.flatnonzero(up != np.arange(len(up)))
    return np.stack([low, up[low]], axis=1)


def _small_links(own, own_at, other, other_at, rows, radius: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Links of many small pairs of blocks, ``_AT_ONCE`` pairs of rows at a time."""
    n, m = np.diff(own_at)[rows], np.diff(other_at)[rows]
    ends = np.cumsum(n * m)
    for cut in np.split(np.arange(len(rows)), np.searchsorted(ends, np.arange(_AT_ONCE, ends[-1] if len(ends) else 0, _AT_ONCE))):
        if not len(cut):
            continue
        a = np.repeat(own_at[rows[cut]] - np.cumsum(n[cut]) + n[cut], n[cut]) + np.arange(n[cut].sum())
        reps = np.repeat(m[cut], n[cut])
        b = np.repeat(np.repeat(other_at[rows[cut]], n[cut]) - np.cumsum(reps) + reps, reps) + np.arange(reps.sum())
        x, y = np.repeat(own[a], reps), other[b]
        hit = np.bitwise_count(x ^ y) <= radius
        yield x[hit], y[hit]


def compare_tiles(pairs: DataFrame, radius: int = RADIUS) -> DataFrame:
    """``a, b``: links that connect, within every pair of blocks, what lies within ``radius`` bits."""

    def flat(column) -> tuple[np.ndarray, np.ndarray]:
        column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
        ends = column.offsets.to_numpy()
        return column.values.to_numpy(zero_copy_only=False).view(np.uint64), ends.astype(np.int64)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            own, own_at = flat(batch.column(0))
            other, other_at = flat(batch.column(1))
            same = batch.column(2).to_numpy(zero_copy_only=False)
            work = np.diff(own_at) * np.diff(other_at)
            found = list(_small_links(own, own_at, other, other_at, np.flatnonzero(work <= _FEW), radius))
            for i in np.flatnonzero(work > _FEW):
                x, y = own[own_at[i] : own_at[i + 1]], other[other_at[i] : other_at[i + 1]]
                at = near_links(x, y, bool(same[i]), radius)
                if len(at):
                    both = x if same[i] else np.concatenate([x, y])
                    found.append((both[at[:, 0]], both[at[:, 1]]))
            a, b = (np.concatenate(z) for z in zip(*found)) if found else (np.empty(0, np.uint64), np.empty(0, np.uint64))
            keep = a != b
            a, b = a[keep].view(np.int64), b[keep].view(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])

    return pairs.mapInArrow(run, "a long, b long").distinct()


def links(
    fps: DataFrame, banded: bool, parts: int = PARTS, tile_rows: int = TILE_ROWS, radius: int = RADIUS
) -> DataFrame:
    """``a, b``: links that connect all distinct ``fp`` that can reach each other within ``radius`` bits a step."""
    tiles = materialize(tiled(fps, banded, parts, tile_rows, radius), "tiles")
    return compare_tiles(tile_pairs(tiles, banded, parts, radius), radius)


def near_duplicates(
    docs: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    shingle: int = SHINGLE,
    radius: int = RADIUS,
    tile_rows: int = TILE_ROWS,
    banded_from: int = BANDED_FROM,
) -> DataFrame:
    """``doc_id, fingerprint, component_id`` of every document, by whole texts.

    ``fingerprint`` is 16 lower-case hex digits, ``component_id`` the smallest id that can be
    reached over links of at most ``radius`` differing bits.
    """
    rows = materialize(fingerprints(docs, id_col, text_col, shingle), "fingerprints")
    distinct = materialize(rows.groupBy("fp").agg(F.min("doc_id").alias("low_id")), "distinct-fingerprints")
    banded = radius <= RADIUS and distinct.count() >= banded_from  # four bands are exact up to three bits
    roots = connected_components(links(distinct.select("fp"), banded, PARTS, tile_rows, radius), "a", "b")
    placed = distinct.join(roots, distinct["fp"] == roots["node"], "left").select(
        "fp", "low_id", F.coalesce("root", "fp").alias("root")
    )
    lows = placed.groupBy("root").agg(F.min("low_id").alias("component_id"))
    by_fp = placed.join(lows, "root").select("fp", "component_id")
    return rows.join(by_fp, "fp").select(
        "doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id"
    )


def drop_near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` with one document of each component, the one with the smallest id.

    Rows that share an id are one document; rows without an id stay.
    """
    found = near_duplicates(docs, id_col, text_col)
    kept = found.where("doc_id = component_id").select(F.col("doc_id").alias("keep")).distinct()
    rows = docs.select(F.struct(*(docs[f"`{c}`"] for c in docs.columns)).alias("row"), docs[id_col].cast("long").alias("id"))
    named, loose = rows.where("id IS NOT NULL"), rows.where("id IS NULL")
    once = named.join(kept, named["id"] == kept["keep"], "left_semi").dropDuplicates(["id"])
    return once.unionByName(loose).select(*(F.col(f"row.`{c}`").alias(c) for c in docs.columns))
