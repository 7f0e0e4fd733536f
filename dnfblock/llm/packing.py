"""Best-fit packing of token sequences, in bulk-synchronous rounds.

Documents become token ids (the library's, word by word from a cache, which its pre-tokenizer's
split at blanks allows) and are cut into pieces of at most ``capacity`` tokens. Pieces are packed
band by band, the longest first (``BANDS``). A round range-sorts the pieces of its band and the gaps
that sequences have left, both as tables of rows; sweeps from long to short over the counts of equal
sizes and finds for each piece its successor, the smallest gap that is not shorter, opening a
sequence only where there is none; where many pieces want the same size of gap, their ranks decide
which gets which one; a join on size and rank then gives every piece its sequence, gaps are less by
what they took, and the next band repeats this. The result has as many sequences as best-fit decreasing
one by one would have.

Ranks come from the range-sorted order, so pieces of one size spread over as many tasks as they
need. What the driver holds is a count per size of piece and of gap (each at most ``capacity``) and
per sorted partition.

Defined cases: null is the empty text, which has just the end id; special tokens inside texts are
as the library has them by default; ids may be null; rows may repeat, and each is packed; an empty
table gives an empty result; further columns are not read.
"""

from __future__ import annotations

import json
import os
import re
import zlib
from array import array
from bisect import bisect_left, insort
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dnfblock.storage import materialize

CAPACITY = 2048
END_ID = 0
#: A round packs the pieces of up to one of these parts of the capacity that are longer than the next.
BANDS = (2, 4, 8)
NEW = -1
_CACHE_WORDS = 400_000
_BLANKS = " \t\n\x0b\f\r"
#: Words of printable ASCII and Latin letters: these have one normal form and lower-case by character.
_PLAIN = re.compile("[!-~\u00a1-\u024f]+").fullmatch
_SPECIAL = "<|"
_words: dict[str, "_Words"] = {}


def _byte_letters() -> dict[int, str]:
    """The printable stand-in of every byte in byte-level vocabularies: itself, or from 256 upwards."""
    own = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in own]
    return {b: chr(b) for b in own} | {b: chr(256 + i) for i, b in enumerate(rest)}


class _Words(dict):
    """Ids, as little-endian 32-bit words, of what stands between blanks; bounded, filled on demand.

    Plain words are split by the tokenizer's own pattern and each part goes to its model once; all
    other words go through the whole library.
    """

    def __init__(self, name: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        import public_tokenizers
        import regex
        from tokenizers import Tokenizer

        path = public_tokenizers.path(name)
        self.library = Tokenizer.from_file(path)
        with open(path, encoding="utf-8") as f:
            steps = json.load(f)
        split = steps["pre_tokenizer"]["pretokenizers"][0]["pattern"]["Regex"]
        kinds = [x["type"] for x in steps["normalizer"]["normalizers"]]
        if kinds != ["NFC", "Replace", "Lowercase"]:
            raise ValueError(f"{name} has another normalizer: {kinds}")
        self.parts = regex.compile(split).findall
        self.letters = _byte_letters()

    def part(self, word: str) -> bytes:
        shown = word if word.isascii() else "".join(map(self.letters.__getitem__, word.encode()))
        return array("I", [t.id for t in self.library.model.tokenize(shown)]).tobytes()

    def __missing__(self, word: str) -> bytes:
        if len(self) >= _CACHE_WORDS:
            self.clear()
        if not word:
            out = b""
        elif _PLAIN(word) and _SPECIAL not in word:
            parts = self.parts(word.lower())
            if parts == [word]:
                out = self.part(word)
            else:
                out = b"".join([self[p] if p != word else self.part(p) for p in parts])
        else:
            out = array("I", self.library.encode(word, add_special_tokens=False).ids).tobytes()
        if len(word) <= 64:
            self[word] = out
        return out


def encode_ids(name: str, text: str) -> bytes:
    """Token ids of ``text`` as little-endian 32-bit words, without added special tokens."""
    if name not in _words:
        _words[name] = _Words(name)
    for blank in _BLANKS[1:]:
        if blank in text:
            text = text.replace(blank, " ")
    return b"".join(map(_words[name].__getitem__, text.split(" ")))


def pieces(
    docs: DataFrame,
    name: str = "word_bpe_49k.json",
    id_col: str = "doc_id",
    text_col: str = "text",
    capacity: int = CAPACITY,
    end_id: int = END_ID,
    keep_ids: bool = False,
) -> DataFrame:
    """``row_id, doc_id, piece, start, length, ids_crc32`` and, if wanted, the ``ids``."""
    end = np.array([end_id], "<u4").tobytes()
    step = 4 * capacity

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows, doc_ids = [], batch.column(1).to_pylist()
            for row, doc, text in zip(batch.column(0).to_pylist(), doc_ids, batch.column(2)):
                data = encode_ids(name, text.as_py() or "") + end
                for k, at in enumerate(range(0, len(data), step)):
                    part = data[at : at + step]
                    made = (row, doc, k, at // 4, len(part) // 4, zlib.crc32(part))
                    rows.append((*made, np.frombuffer(part, "<u4").astype(np.int32)) if keep_ids else made)
            yield pa.RecordBatch.from_arrays(
                [pa.array([r[i] for r in rows], t) for i, t in enumerate(types)], names
            )

    names = ["row_id", "doc_id", "piece", "start", "length", "ids_crc32", *["ids"] * keep_ids]
    types = [pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), *[pa.list_(pa.int32())] * keep_ids]
    schema = "row_id long, doc_id long, piece int, start long, length long, ids_crc32 long" + ", ids array<int>" * keep_ids
    rows = docs.select(F.monotonically_increasing_id(), F.col(id_col).cast("long"), F.col(text_col))
    return rows.mapInArrow(run, schema)


def sweep(
    runs: dict[int, int], gaps: dict[int, int], opened: int = 0, capacity: int = CAPACITY
) -> tuple[list[tuple[int, int, int, int, int, int, int]], int]:
    """Places for runs {size: count} in gaps {gap: count}, and how many sequences are open then.

    Rows are ``(size, rank, rank_end, gap, first, each, offset)``: the piece of rank r goes to the gap of rank
    ``first + (r - rank) // each`` among those of size ``gap`` (``NEW``: to the sequence of that number), as
    the ``(r - rank) % each``-th behind ``offset``.
    """
    places: list[tuple[int, int, int, int, int, int, int]] = []
    free: dict[int, list[tuple[int, int, int]]] = {}  # what is left: (gap at first, first rank, how many)
    sizes: list[int] = []  # the keys of free, sorted

    def put(left: int, gap: int, first: int, many: int) -> None:
        if left and many:
            if left not in free:
                free[left] = []
                insort(sizes, left)
            free[left].append((gap, first, many))

    for gap, many in gaps.items():
        put(gap, gap, 0, many)
    for size in sorted(runs, reverse=True):
        rank, waiting = 0, runs[size]
        while waiting:
            at = bisect_left(sizes, size)
            if at < len(sizes):
                left = sizes[at]
                gap, first, many = free[left].pop()
                if not free[left]:
                    del free[left], sizes[at]
            else:
                left, gap, first, many = capacity, NEW, opened, -(-waiting // (capacity // size))
                opened += many
            each = left // size
            taken = min(waiting, many * each)
            full, rest = divmod(taken, each)
            places.append((size, rank, rank + taken, gap, first, each, capacity - left))
            put(left - each * size, gap, first, full)
            put(left - rest * size, gap, first + full, int(rest > 0))
            put(left, gap, first + full + (rest > 0), many - full - (rest > 0))
            rank, waiting = rank + taken, waiting - taken
    return places, opened


def ranked(rows: DataFrame, size: str, *ids: str) -> tuple[DataFrame, dict[int, int]]:
    """``rows``, range-sorted by ``size``, with their ``rank`` (from 0) among equal sizes; and {size: count}."""
    spark = rows.sparkSession
    order = [F.col(size), F.xxhash64(*ids), *(F.col(c) for c in ids)]
    rows = rows.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("__at", F.monotonically_increasing_id())
    rows = materialize(rows, "range-sorted")
    part = F.shiftrightunsigned("__at", 33)  # the sorted partition, by the layout of these numbers
    heads = rows.groupBy(part.alias("part"), F.col(size).alias("key")).agg(F.min("__at").alias("head"), F.count("*").alias("n")).toPandas()
    heads = heads.sort_values(["key", "part"], kind="stable")
    heads["shift"] = heads.groupby("key")["n"].cumsum() - heads["n"] - heads["head"]
    table = pa.Table.from_pandas(heads[["part", "key", "shift"]].astype("int64"), preserve_index=False)
    shifts = spark.createDataFrame(table)
    out = rows.join(F.broadcast(shifts), (part == shifts["part"]) & (F.col(size) == shifts["key"]))
    out = out.withColumn("rank", F.col("__at") + F.col("shift")).drop("__at", "part", "key", "shift")
    return out, {int(k): int(n) for k, n in heads.groupby("key")["n"].sum().items()}


def best_fit(items: DataFrame, capacity: int = CAPACITY, bands: tuple[int, ...] = BANDS) -> DataFrame:
    """``row_id, piece, sequence_id, offset`` of every row of ``items`` (``row_id, piece, length``).

    Call it on a written table: ``row_id`` must not change between reads.
    """
    spark = items.sparkSession
    waiting, counts = ranked(items.select("row_id", "piece", "length"), "length", "row_id", "piece")
    names = ["size", "from", "to", "gap", "first", "each", "offset"]
    gaps, opened, done = spark.createDataFrame([], "sequence_id long, gap long"), 0, []
    edges = [capacity, *(capacity // b for b in bands), 0]
    for high, low in zip(edges, edges[1:]):
        runs = {s: n for s, n in counts.items() if low < s <= high}
        if not runs:
            continue
        before = opened
        open_, left = ranked(gaps, "gap", "sequence_id") if before else (gaps.withColumn("rank", F.lit(0)), {})
        places, opened = sweep(runs, left, opened, capacity)
        table = spark.createDataFrame(pa.table([pa.array(c, pa.int64()) for c in zip(*places)], names))
        nth = F.col("rank") - F.col("from")
        wanted = waiting.where(F.col("length").between(low + 1, high)).join(
            F.broadcast(table), (F.col("length") == F.col("size")) & (F.col("rank") >= F.col("from")) & (F.col("rank") < F.col("to"))
        )
        wanted = wanted.select(
            "row_id", "piece", "length", "gap",
            (F.col("first") + F.floor(nth / F.col("each"))).alias("rank"),
            (F.col("offset") + nth % F.col("each") * F.col("length")).alias("offset"),
        )
        new = wanted.where(F.col("gap") == NEW).withColumn("sequence_id", F.col("rank")).drop("gap", "rank")
        found = wanted.where(F.col("gap") != NEW).join(open_, ["gap", "rank"]).drop("gap", "rank")
        placed = materialize(new.unionByName(found), "placed")
        done.append(placed.select("row_id", "piece", "sequence_id", "offset"))
        if low:
            used = placed.groupBy("sequence_id").agg(F.sum("length").alias("used"))
            room = gaps.unionByName(spark.range(before, opened).select(F.col("id").alias("sequence_id"), F.lit(capacity).cast("long").alias("gap")))
            rest = room.join(used, "sequence_id", "left").select("sequence_id", (F.col("gap") - F.coalesce("used", F.lit(0))).alias("gap"))
            gaps = materialize(rest.where("gap > 0"), "gaps")
    if not done:
        return items.limit(0).select("row_id", "piece", F.lit(0).cast("long").alias("sequence_id"), F.lit(0).cast("long").alias("offset"))
    return reduce(DataFrame.unionByName, done)


def pack(
    docs: DataFrame, name: str = "word_bpe_49k.json", id_col: str = "doc_id", text_col: str = "text",
    capacity: int = CAPACITY, keep_ids: bool = False, bands: tuple[int, ...] = BANDS,
) -> DataFrame:
    """``doc_id, piece, start, length, ids_crc32, sequence_id, offset`` of every piece of ``docs``."""
    cut = materialize(pieces(docs, name, id_col, text_col, capacity, keep_ids=keep_ids), "pieces")
    columns = ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset", *["ids"] * keep_ids]
    return cut.join(best_fit(cut, capacity, bands), ["row_id", "piece"]).select(*columns)
