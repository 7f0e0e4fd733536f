"""The logical property table of a set of triples: a schema found at run time, set-valued fields."""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

MOST_PROPERTIES = 10_000


def property_schema(triples: DataFrame, most: int = MOST_PROPERTIES) -> list[str]:
    """The distinct properties, sorted. A graph with more than ``most`` is refused: use the map form."""
    found = [r[0] for r in triples.select("p").distinct().limit(most + 1).collect()]
    if len(found) > most:
        raise ValueError(f"more than {most} properties; use to_property_map")
    return sorted(found)


def to_property_table(triples: DataFrame, schema: list[str] | None = None, multi: str = "array", delimiter: str = ";") -> DataFrame:
    """One row per subject, a column per property: sorted value sets, null where there is none.

    One shuffle by subject; properties outside ``schema`` are dropped before it.
    """
    schema = property_schema(triples) if schema is None else schema
    rows = triples.where(F.col("p").isin(schema)).groupBy("s").pivot("p", schema).agg(F.array_sort(F.collect_set("o")))
    cells = []
    for p in schema:
        value = F.when(F.size(F.col(f"`{p}`")) > 0, F.col(f"`{p}`"))
        cells.append((encode_multi(value, delimiter) if multi == "delimited" else value).alias(p))
    return rows.select(F.col("s").alias("subject"), *cells)


def to_triples(table: DataFrame, fields: list[str] | None = None) -> DataFrame:
    """The inverse, narrow. A subject without any value has no triple, before as after."""
    fields = fields or [c for c in table.columns if c != "subject"]
    cells = F.array(*(F.struct(F.lit(f).alias("p"), F.col(f"`{f}`").alias("o")) for f in fields))
    rows = table.select(F.col("subject").alias("s"), F.explode(cells).alias("x"))
    return rows.select("s", "x.p", F.explode("x.o").alias("o"))


def encode_multi(values: Column, delimiter: str = ";", escape: str = "\\") -> Column:
    """A value set as one string; delimiter and escape inside values are escaped."""
    safe = F.transform(
        values,
        lambda v: F.replace(F.replace(v, F.lit(escape), F.lit(escape * 2)), F.lit(delimiter), F.lit(escape + delimiter)),
    )
    return F.array_join(safe, delimiter)


def decode_multi(text: Column, delimiter: str = ";", escape: str = "\\") -> Column:
    """The inverse of :func:`encode_multi`."""
    d, e = re.escape(delimiter), re.escape(escape)
    cells = f"(?s)([^{d}{e}]*+(?:{e}.[^{d}{e}]*+)*+){d}"  # an escape always takes the character after it along
    parts = F.regexp_extract_all(F.concat(text, F.lit(delimiter)), F.lit(cells), F.lit(1))
    return F.transform(parts, lambda v: F.regexp_replace(v, f"(?s){e}(.)", "$1"))


def to_property_map(triples: DataFrame) -> DataFrame:
    """``subject, values: map<property, set>``: the form for graphs of very many properties."""
    cells = triples.groupBy("s", "p").agg(F.array_sort(F.collect_set("o")).alias("values"))
    pairs = F.array_sort(F.collect_list(F.struct("p", "values")))
    return cells.groupBy(F.col("s").alias("subject")).agg(F.map_from_entries(pairs).alias("values"))


def to_entities(df: DataFrame, id_col: str, fields: list[str], side: int = 0) -> DataFrame:
    """The long relation ``side, rid, field, values`` of a table or property table; narrow."""
    cells = F.array(*(F.struct(F.lit(f).alias("field"), _as_set(df, f).alias("values")) for f in fields))
    rows = df.select(F.lit(side).cast("byte").alias("side"), F.col(id_col).cast("string").alias("rid"), F.explode(cells).alias("x"))
    return rows.select("side", "rid", "x.field", "x.values").where(F.size("values") > 0)


def _as_set(df: DataFrame, field: str) -> Column:
    kind = dict(df.dtypes)[field]
    if kind in ("binary",) or kind.startswith("interval"):
        raise TypeError(f"{field}: {kind} has no string form")
    c = F.col(f"`{field}`")
    if kind.startswith("array"):
        return F.filter(F.coalesce(c.cast("array<string>"), F.array().cast("array<string>")), lambda x: x.isNotNull())
    if kind in ("double", "float"):
        c = F.format_string("%.6f", c)
    return F.when(c.isNotNull(), F.array(c.cast("string"))).otherwise(F.array().cast("array<string>"))


def profile_property_table(triples: DataFrame) -> DataFrame:
    """``property, fill_rate, max_fanout, distinct_values``: how sparse and how broad the table is."""
    subjects = triples.select("s").distinct().count()
    cells = triples.groupBy("p", "s").agg(F.count_distinct("o").alias("fanout"))
    wide = cells.groupBy("p").agg(F.count("*").alias("filled"), F.max("fanout").alias("max_fanout"))
    values = triples.groupBy("p").agg(F.count_distinct("o").alias("distinct_values"))
    return wide.join(values, "p").select(
        F.col("p").alias("property"), F.round(F.col("filled") / F.lit(max(subjects, 1)), 6).alias("fill_rate"), "max_fanout", "distinct_values"
    )


def star_select(table: DataFrame, properties: list[str]) -> DataFrame:
    """Several properties of a subject in one read of the table; subjects that have them all."""
    rows = table.select("subject", *properties)
    for p in properties:
        rows = rows.where(F.col(p).isNotNull()).withColumn(p, F.explode(p))
    return rows


def star_by_selfjoin(triples: DataFrame, properties: list[str]) -> DataFrame:
    """The same by one self-join of the triples per further property."""
    out = None
    for p in properties:
        part = triples.where(F.col("p") == p).select(F.col("s").alias("subject"), F.col("o").alias(p)).distinct()
        out = part if out is None else out.join(part, "subject")
    return out
