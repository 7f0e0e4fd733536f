"""What the classifiers share: fold by crc32, a bounded labelled sample, fits in numpy."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Most labelled rows that a fit uses; scoring always covers every row.
SAMPLE_ROWS = 20_000


def fold(id_col: str, parts: int) -> F.Column:
    """crc32 of the id as text, modulo ``parts``; an id that is null falls in part 0."""
    return F.coalesce(F.pmod(F.crc32(F.col(id_col).cast("string").cast("binary")), F.lit(parts)), F.lit(0))


def labelled_sample(
    docs: DataFrame, labels: DataFrame, label_col: str, parts: int, held_out: int,
    id_col: str = "doc_id", text_col: str = "text", rows: int = SAMPLE_ROWS, seed: int = 5,
) -> DataFrame:
    """``id, text, label`` of documents that are labelled and not held out; at most ``rows`` ids.

    Ids are taken in hash order. The chosen labels are at most ``rows`` pairs, so they are broadcast.
    """
    known = labels.where(F.col(label_col).isNotNull() & (fold(id_col, parts) != held_out))
    known = known.groupBy(F.col(id_col).cast("long").alias("known")).agg(F.max(F.col(label_col).cast("int")).alias("label"))
    known = known.where("known IS NOT NULL").orderBy(F.xxhash64("known", F.lit(seed)), "known").limit(rows)
    own = docs.select(docs[id_col].cast("long").alias("id"), docs[text_col].alias("text"))
    return own.join(F.broadcast(known), own["id"] == known["known"]).drop("known")


def sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -40, 40)))
