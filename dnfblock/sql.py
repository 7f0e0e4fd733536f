"""SQL surface: key functions inlined by Catalyst, and table functions for keys of a saved scheme and for property tables."""

from __future__ import annotations

import re
from collections.abc import Callable, Iterator
from itertools import product

from pyspark.sql import Row, SparkSession
from pyspark.sql.functions import udtf
from pyspark.sql.types import IntegerType, StringType, StructType
from pyspark.sql.udtf import AnalyzeArgument, AnalyzeResult

from dnfblock.operators.scheme import SEPARATOR, Scheme

_NORM = "trim(regexp_replace(lower(x), '[^a-z0-9]+', ' '))"
_ALL = f"filter(split({_NORM}, ' '), t -> t <> '')"
_NONE = "cast(array() AS ARRAY<STRING>)"
_SHORT = "filter(bkv_common_int(x), d -> length(d) <= 18)"


def _cut(side: str, n: int) -> str:
    return f"CASE WHEN length({_NORM}) >= {n} THEN array({side}({_NORM}, {n})) ELSE {_NONE} END"


def _runs(many: str, n: int, part: str) -> str:
    return f"CASE WHEN {many} >= {n} THEN array_distinct(transform(sequence(1, {many} - {n - 1}), i -> {part})) ELSE {_NONE} END"


#: Bodies of the SQL functions; each is one expression over ``x``. The phonetic codes but Soundex have none.
KEY_FUNCTIONS = {
    "bkv_token": f"array_distinct({_ALL})",
    "bkv_raw_token": r"array_distinct(filter(split(x, '\\s+'), t -> t <> ''))",
    "bkv_exact": f"filter(array({_NORM}), t -> t <> '')",
    "bkv_common_int": "array_distinct(transform(regexp_extract_all(x, '[0-9]+', 0), d -> regexp_replace(d, '^0+(?=[0-9])', '')))",
    "bkv_int_pm1": f"array_distinct(flatten(transform({_SHORT}, d -> array(cast(cast(d AS BIGINT) AS STRING), cast(cast(d AS BIGINT) + 1 AS STRING)))))",
    "bkv_round10": f"array_distinct(transform({_SHORT}, d -> cast(cast(d AS BIGINT) div 10 AS STRING)))",
    "bkv_first_digit": f"CASE WHEN x rlike '^[0-9]' THEN array(left(x, 1)) ELSE {_NONE} END",
    "bkv_first_sig_digits2": "array_distinct(transform(bkv_common_int(x), d -> left(d, 2)))",
    "bkv_token_prefix3": "array_distinct(transform(bkv_token(x), t -> left(t, 3)))",
    "bkv_token_sorted": f"filter(array(array_join(array_sort({_ALL}), '')), t -> t <> '')",
    "bkv_soundex": "array_distinct(transform(filter(bkv_token(x), t -> t rlike '^[a-z]+$'), t -> soundex(t)))",
    "bkv_last3": _cut("right", 3),
    **{f"bkv_first{n}": _cut("left", n) for n in (1, 3, 5, 7)},
    **{f"bkv_qgram{q}": _runs(f"length({_NORM})", q, f"substring({_NORM}, i, {q})") for q in (2, 3, 4)},
    **{f"bkv_token_ng{n}": _runs(f"size({_ALL})", n, f"array_join(slice({_ALL}, i, {n}), ' ')") for n in (2, 4, 6)},
}


def _norm(x: str) -> str:
    return re.sub("[^a-z0-9]+", " ", x.lower()).strip(" ")


def _first(n: int) -> Callable[[str], list[str]]:
    return lambda x: [_norm(x)[:n]] if len(_norm(x)) >= n else []


def _grams(q: int) -> Callable[[str], list[str]]:
    return lambda x: [_norm(x)[i : i + q] for i in range(len(_norm(x)) - q + 1)]


def _ngrams(n: int) -> Callable[[str], list[str]]:
    def keys(x: str) -> list[str]:
        w = _norm(x).split()
        return [" ".join(w[i : i + n]) for i in range(len(w) - n + 1)]

    return keys


def _ints(x: str) -> list[str]:
    return [d.lstrip("0") or "0" for d in re.findall("[0-9]+", x)]


#: Key functions of a Python form, for the table function; each gives the keys of ``REGISTRY``.
PYTHON_KEYS: dict[str, Callable[[str], list[str]]] = {
    "token": lambda x: _norm(x).split(),
    "exact": lambda x: [_norm(x)] if _norm(x) else [],
    "common_int": _ints,
    "first_digit": lambda x: re.findall("^[0-9]", x),
    "first_sig_digits2": lambda x: [d[:2] for d in _ints(x)],
    "token_prefix3": lambda x: [w[:3] for w in _norm(x).split()],
    "token_sorted": lambda x: ["".join(sorted(_norm(x).split()))] if _norm(x) else [],
    "last3": lambda x: [_norm(x)[-3:]] if len(_norm(x)) >= 3 else [],
    **{f"first{n}": _first(n) for n in (1, 3, 5, 7)},
    **{f"qgram{q}": _grams(q) for q in (2, 3, 4)},
    **{f"token_ng{n}": _ngrams(n) for n in (2, 4, 6)},
}


def register(spark: SparkSession) -> None:
    """Temporary functions ``bkv_<name>(x)`` and ``gbp_<name>(a, b)``, and the table functions ``block_keys`` and ``property_table``."""
    for name, body in KEY_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}(x STRING) RETURNS ARRAY<STRING> RETURN {body}")
        gbp = name.replace("bkv_", "gbp_")
        spark.sql(
            f"CREATE OR REPLACE TEMPORARY FUNCTION {gbp}(a STRING, b STRING) RETURNS BOOLEAN "
            f"RETURN coalesce(arrays_overlap({name}(a), {name}(b)), false)"
        )
    spark.udtf.register("block_keys", BlockKeys)
    spark.udtf.register("property_table", PropertyTable)


def _values(cell) -> list[str]:
    """A cell as a list of its values: a set-valued field as it is, a single value as one, null as none."""
    many = cell if isinstance(cell, list) else [cell]
    return [str(v) for v in many if v is not None]


@udtf
class BlockKeys:
    """``SELECT * FROM block_keys(TABLE(t), scheme, side)``: the keys of a scheme's terms, a row a record, term and key.

    ``scheme`` is a scheme as JSON, ``side`` 0 or 1; ``t`` has ``rid`` and the scheme's fields, of text or sets of
    texts. Key functions with a plain-Python form are known (``PYTHON_KEYS``), others are refused when the query
    is analysed. For SQL users; ``blocking.index`` gives the same rows and is optimised by Spark.
    """

    @staticmethod
    def analyze(row: AnalyzeArgument, scheme: AnalyzeArgument, side: AnalyzeArgument) -> AnalyzeResult:
        wanted = Scheme.from_json(scheme.value)
        unknown = {a.gbp for t in wanted.terms for a in t} - set(PYTHON_KEYS)
        missing = {"rid", *wanted.fields(side.value)} - set(row.dataType.fieldNames())
        if unknown or missing:
            raise ValueError(f"no key function {sorted(unknown)}, no column {sorted(missing)}")
        return AnalyzeResult(StructType().add("term_id", IntegerType()).add("key", StringType()).add("rid", StringType()))

    def eval(self, row: Row, scheme: str, side: int) -> Iterator[tuple[int, str, str]]:
        if not hasattr(self, "scheme"):
            self.scheme = Scheme.from_json(scheme)
        for i, term in enumerate(self.scheme.terms):
            sets = [{k for f in a.fields(side) for v in _values(row[f]) for k in PYTHON_KEYS[a.gbp](v)} for a in term]
            for key in sorted(map(SEPARATOR.join, product(*sets))):
                yield i, key, str(row["rid"])


@udtf(returnType="subject string, field string, `values` array<string>")
class PropertyTable:
    """``SELECT * FROM property_table(TABLE(t) PARTITION BY s)``: the set of values of every subject and property.

    ``t`` has ``s, p, o``. A table function cannot find columns in its rows, so the result is the long form of the
    property table; a ``PIVOT`` of it has a column a property.
    """

    def __init__(self):
        self.subject, self.sets = None, {}

    def eval(self, row: Row) -> None:
        self.subject = row["s"]
        self.sets.setdefault(row["p"], set()).add(row["o"])

    def terminate(self) -> Iterator[tuple[str, str, list[str]]]:
        for field in sorted(self.sets):
            values = sorted(o for o in self.sets[field] if o is not None)
            if values:
                yield self.subject, field, values
