"""Token counts of whole texts: pieces are counted once per distinct pre-token.

The vocabulary has no piece that crosses from a word into the following word mark, so a text is
cut exactly at those marks: its pre-tokens are runs of marks with the characters that follow. One
pass lists the distinct pre-tokens with their corpus counts; each is segmented once; a second pass
turns every document into its pre-token frequencies, which are joined to the piece counts and
summed. Ids are never kept.

The most frequent pre-tokens (at most ``head`` of them, a fixed bound) are held by every task, which
sums them in place; what is left has no frequent key, so the join on pre-tokens has no hot key and
carries a small share of all words. Pre-tokens of more than ``long_word`` characters are counted in
place as well, so no key is long.

Defined cases: null is the empty text with 0 tokens; strings of special tokens are ordinary text, as
the library has it; ids may be null and rows may repeat; an empty table gives an empty result; further columns are not
read.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dnfblock.storage import materialize

HEAD = 1 << 18
LONG_WORD = 48
LIMIT = 4096
_models: dict[str, object] = {}


def model(name: str):
    """The processor for a model file of the public tokenizers, loaded once per process."""
    if name not in _models:
        import public_tokenizers
        import sentencepiece

        _models[name] = sentencepiece.SentencePieceProcessor(model_file=public_tokenizers.path(name))
    return _models[name]


def pre_tokens(text: str) -> list[str]:
    """Pre-tokens of ``text``, each without the first of its word marks.

    A literal word mark counts as a space, and a text is read as if one space stood before it. A
    single space that ends the text gives the empty pre-token.
    """
    if not text:
        return []
    spaced = text.replace("▁", " ")
    if "  " in spaced or spaced[0] == " " or spaced[-1] == " ":
        return [x[1:] for x in re.findall(" +[^ ]*", " " + spaced)]
    return spaced.split(" ")


def count_pieces(name: str, words: list[str]) -> list[int]:
    """Pieces of every pre-token; the empty one is a lone word mark."""
    return [len(ids) if word else 1 for word, ids in zip(words, model(name).encode(words, num_threads=1))]


def vocabulary(docs: DataFrame, name: str, text_col: str = "text", long_word: int = LONG_WORD) -> DataFrame:
    """``word, n, pieces``: every distinct pre-token of up to ``long_word`` characters."""

    def listed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found: Counter = Counter()

        def flush():
            short = {w: n for w, n in found.items() if len(w) <= long_word}
            found.clear()
            return pa.RecordBatch.from_arrays(
                [pa.array(list(short), pa.string()), pa.array(list(short.values()), pa.int64())], ["word", "n"]
            )

        for batch in batches:
            for text in batch.column(0):
                found.update(pre_tokens(text.as_py() or ""))
                if len(found) > 400_000:
                    yield flush()
        yield flush()

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            pieces = count_pieces(name, batch.column(0).to_pylist())
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(pieces, pa.int64())], ["word", "n", "pieces"])

    words = docs.select(F.col(text_col)).mapInArrow(listed, "word string, n long")
    words = words.groupBy("word").agg(F.sum("n").alias("n"))
    return words.mapInArrow(counted, "word string, n long, pieces long")


def head_threshold(words: DataFrame, head: int) -> int:
    """The smallest count c for which at most ``head`` pre-tokens occur c times or more."""
    by_count = words.groupBy(F.least("n", F.lit(1 << 16)).alias("n")).agg(F.count("*").alias("words")).collect()
    left, least = head, (1 << 16) + 1
    for n, many in sorted(((r["n"], r["words"]) for r in by_count), reverse=True):
        left -= many
        if left < 0:
            break
        least = n
    return least


def token_counts(
    docs: DataFrame,
    name: str = "piece_bpe_32k.model",
    id_col: str = "doc_id",
    text_col: str = "text",
    limit: int = LIMIT,
    head: int = HEAD,
    long_word: int = LONG_WORD,
) -> DataFrame:
    """``doc_id, n_bytes, n_tokens, over_limit`` for every row of ``docs``."""
    spark = docs.sparkSession
    words = materialize(vocabulary(docs, name, text_col, long_word), "pre-tokens")
    least = head_threshold(words, head)
    top = words.where(F.col("n") >= least).select("word", "pieces").toPandas()
    shared = spark.sparkContext.broadcast(dict(zip(top["word"].tolist(), top["pieces"].tolist())))

    def frequencies(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = shared.value.get
        for batch in batches:
            rows, tail_words, tail_counts, sizes = [], [], [], [0]
            for text in batch.column(2):
                text = text.as_py() or ""
                sure, rest = 0, Counter()
                for word in pre_tokens(text):
                    pieces = known(word)
                    if pieces is None:
                        rest[word] += 1
                    else:
                        sure += pieces
                for word in [w for w in rest if len(w) > long_word]:
                    sure += rest.pop(word) * count_pieces(name, [word])[0]
                rows.append((len(text.encode()), sure))
                tail_words += rest
                tail_counts += rest.values()
                sizes.append(len(tail_words))
            tail = pa.ListArray.from_arrays(
                pa.array(sizes, pa.int32()),
                pa.StructArray.from_arrays(
                    [pa.array(tail_words, pa.string()), pa.array(tail_counts, pa.int64())], ["word", "n"]
                ),
            )
            yield pa.RecordBatch.from_arrays(
                [
                    batch.column(0),
                    batch.column(1),
                    pa.array([r[0] for r in rows], pa.int64()),
                    pa.array([r[1] for r in rows], pa.int64()),
                    tail,
                ],
                ["row_id", "doc_id", "n_bytes", "sure", "tail"],
            )

    rows = docs.select(F.monotonically_increasing_id(), F.col(id_col).cast("long"), F.col(text_col)).mapInArrow(
        frequencies, "row_id long, doc_id long, n_bytes long, sure long, tail array<struct<word:string,n:long>>"
    )
    # what a task has summed rides along under a key of its own, which no pre-token can be
    own = F.struct(F.concat(F.lit(" ▁"), "row_id").alias("word"), F.col("sure").alias("n"))
    rows = rows.select("row_id", "doc_id", "n_bytes", F.explode(F.concat(F.array(own), "tail")).alias("x"))
    rows = rows.select("row_id", "doc_id", "n_bytes", "x.word", "x.n")
    rest = words.where(F.col("n") < least).select("word", "pieces")
    total = F.sum(F.col("n") * F.coalesce("pieces", F.lit(1)))
    counts = rows.join(rest, "word", "left").groupBy("row_id", "doc_id", "n_bytes").agg(total.alias("n_tokens"))
    return counts.select("doc_id", "n_bytes", "n_tokens", (F.col("n_tokens") > limit).alias("over_limit"))
