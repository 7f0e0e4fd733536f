"""Exact duplicates: 128-bit content hash, smallest stable id, byte comparison inside groups.

Two texts are copies when they are equal after every character of ``[\\x20\\x09-\\x0D]`` has been
deleted. Rows are grouped by the MD5 of that normal form. Members of a group with more than one
row are then compared as bytes: their normal forms are themselves grouping keys, and a hash that
stands for two different byte strings is split by its SHA-256. Only hashes, lengths and ids travel
for rows without a copy, once Spark plans its Bloom filter in front of the semi-join (by default
from 10 GB up).

A group of more than one in ``HOT`` of all rows is dealt over ``SALTS`` tasks wherever its rows are joined
or compared; there are fewer than ``HOT`` such groups, so the table of them is broadcast.

Defined cases: a null text is the empty text, so null, empty and all-blank texts form one group; a
null id sorts last; of fully equal rows one stays; an empty table gives an empty result; further
columns are never touched and may have any name.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from dnfblock.storage import materialize

#: The six characters that the normal form deletes.
BLANKS = " \t\n\x0b\f\r"
HOT = 2048
SALTS = 32


def normal_form(text: Column) -> Column:
    """``text`` without the six blank characters; null becomes empty."""
    out = F.coalesce(text, F.lit(""))
    for blank in BLANKS:
        out = F.replace(out, F.lit(blank), F.lit(""))
    return out


def content_keys(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One narrow row per document: ``row_id, id, digest, text_sha256, n_points``."""
    text = docs[text_col]
    return docs.select(
        F.monotonically_increasing_id().alias("row_id"),
        docs[id_col].alias("id"),
        F.unhex(F.md5(normal_form(text))).alias("digest"),
        F.sha2(normal_form(text), 256).alias("text_sha256"),
        F.length(F.coalesce(text, F.lit(""))).alias("n_points"),
    )


def salted(rows: DataFrame, hot: DataFrame) -> DataFrame:
    """``rows`` (with ``digest``) and ``hot, salt``; rows of hot groups are spread over all salts."""
    out = rows.join(F.broadcast(hot.select("digest", F.lit(True).alias("hot"))), "digest", "left")
    spread = F.pmod(F.monotonically_increasing_id(), F.lit(SALTS))
    out = out.withColumn("hot", F.coalesce("hot", F.lit(False)))
    return out.withColumn("salt", F.when(F.col("hot"), spread).otherwise(F.lit(0)).cast("int"))


def every_salt(groups: DataFrame, hot: DataFrame) -> DataFrame:
    """``groups`` (with ``digest``) and ``salt``; a hot group has a row for each salt."""
    out = groups.join(F.broadcast(hot.select("digest", F.lit(True).alias("hot"))), "digest", "left")
    salts = F.sequence(F.lit(0), F.when(F.col("hot"), F.lit(SALTS - 1)).otherwise(F.lit(0)))
    return out.withColumn("salt", F.explode(salts)).drop("hot")


def collided_digests(docs: DataFrame, shared: DataFrame, hot: DataFrame, text_col: str = "text") -> DataFrame:
    """Digests of ``shared`` that stand for more than one byte string; none in practice.

    Equality of the grouped text is decided on its bytes.
    """
    forms = docs.select(normal_form(docs[text_col]).alias("form"))
    forms = salted(forms.select(F.unhex(F.md5("form")).alias("digest"), "form"), hot)
    once = forms.join(every_salt(shared.select("digest"), hot), ["digest", "salt"], "left_semi")
    once = once.groupBy("digest", "salt", "hot", "form").agg(F.count("*").alias("n"))
    variants = once.where("NOT hot").groupBy("digest", "salt").agg(F.count("*").alias("n")).select("digest", "n")
    many = once.where("hot").select("digest", "form").distinct().groupBy("digest").agg(F.count("*").alias("n"))
    return variants.unionByName(many).where("n > 1").select("digest")


def group_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Every document with its group: ``doc_id, keep_id, group_size, kept, text_sha256``.

    Of copies, the row with the most code points in its original text stays, then the one with the
    smallest id.
    """
    keys = materialize(content_keys(docs, id_col, text_col), "content-keys")
    shared = keys.groupBy("digest").agg(F.count("*").alias("n")).where("n > 1")
    shared = materialize(shared, "shared-digests")
    hot = shared.where(F.col("n") > keys.count() / HOT)
    collided = materialize(collided_digests(docs, shared, hot, text_col), "collided-digests")
    if collided.isEmpty():
        keys = keys.withColumn("variant", F.lit(""))
    else:
        keys = keys.join(collided.withColumn("collided", F.lit(True)), "digest", "left")
        keys = keys.withColumn("variant", F.when(F.col("collided"), F.col("text_sha256")).otherwise(F.lit("")))
    order = F.struct((-F.col("n_points")).alias("o"), F.col("id").isNull().alias("z"), "id", "row_id")
    groups = keys.groupBy("digest", "variant").agg(F.min(order).alias("first"), F.count("*").alias("group_size"))
    return salted(keys, hot).join(every_salt(groups, hot), ["digest", "variant", "salt"]).select(
        F.col("id").alias("doc_id"),
        F.col("first.id").alias("keep_id"),
        "group_size",
        (F.col("row_id") == F.col("first.row_id")).alias("kept"),
        "text_sha256",
        "digest",
        "n_points",
    )


def drop_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` with one row of each group of copies, all columns as they were."""
    kept = group_copies(docs, id_col, text_col).where("kept").select("doc_id", "digest", "n_points")
    text = docs[text_col]
    tagged = docs.select(
        F.struct(*(docs[f"`{c}`"] for c in docs.columns)).alias("row"),  # no column can clash inside
        docs[id_col].alias("id"),
        F.unhex(F.sha2(F.coalesce(text, F.lit("")), 256)).alias("own_text"),
        F.unhex(F.md5(normal_form(text))).alias("own_digest"),
        F.length(F.coalesce(text, F.lit(""))).alias("own_points"),
    )
    same = (
        tagged["id"].eqNullSafe(kept["doc_id"]) & (tagged["own_digest"] == kept["digest"]) & (tagged["own_points"] == kept["n_points"])
    )
    once = tagged.join(kept, same, "left_semi").dropDuplicates(["id", "own_text"])
    return once.select(*(F.col(f"row.`{c}`").alias(c) for c in docs.columns))
