"""Indexing functions: a field value gives a set of blocking key values, as Catalyst expressions.

A general blocking predicate holds for two values when their key sets share a key. ``G_CLASSIC`` has
token, numeric and character functions; ``G_FULL`` adds phonetic codes per token. The two metaphones
run as Arrow functions over all values of a field at once; the other functions are built-in expressions.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

from dnfblock.functions import phonetic


@dataclass(frozen=True)
class IndexingFunction:
    """``keys`` takes a string column and returns an array of keys without nulls."""

    name: str
    family: str  # "token", "numeric", "character", "phonetic"
    keys: Callable[[Column], Column]
    joined: bool = False  # keys of all values come from one string of them, as Arrow functions can't stand in lambdas

    def of_values(self, values: Column) -> Column:
        """Keys of a set-valued field: the union over its values."""
        if self.joined:
            return self.keys(F.array_join(F.coalesce(values, F.array().cast("array<string>")), " "))
        return F.array_distinct(F.flatten(F.transform(F.coalesce(values, F.array().cast("array<string>")), self.keys)))


def normalized(x: Column) -> Column:
    """Lower case, runs of anything but a-z and 0-9 as one space, trimmed."""
    return F.trim(F.regexp_replace(F.lower(x), "[^a-z0-9]+", " "))


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` of a value that is computed once; inside lambdas Spark would compute it at every use."""
    return F.flatten(F.transform(F.array(value), body))


def _none() -> Column:
    return F.array().cast("array<string>")


def _some(x: Column) -> Column:
    """{x}, or nothing for an empty string."""
    return F.filter(F.array(x), lambda v: v != "")


def tokens(x: Column) -> Column:
    return F.array_distinct(F.filter(F.split(normalized(x), " "), lambda t: t != ""))


def raw_tokens(x: Column) -> Column:
    """Tokens between white space with case and punctuation kept."""
    return F.array_distinct(F.filter(F.split(x, r"\s+"), lambda t: t != ""))


def _all_tokens(x: Column) -> Column:
    return F.filter(F.split(normalized(x), " "), lambda t: t != "")


def _prefix(n: int) -> Callable[[Column], Column]:
    return lambda x: let(normalized(x), lambda t: F.when(F.length(t) >= n, F.array(F.substring(t, 1, n))).otherwise(_none()))


def _qgrams(q: int) -> Callable[[Column], Column]:
    def grams(t: Column) -> Column:
        n = F.length(t) - (q - 1)
        every = F.transform(F.sequence(F.lit(1), F.greatest(n, F.lit(1))), lambda i: F.substring(t, i, F.lit(q)))
        return F.when(n >= 1, F.array_distinct(every)).otherwise(_none())

    return lambda x: let(normalized(x), grams)


def _token_ngrams(n: int) -> Callable[[Column], Column]:
    def grams(t: Column) -> Column:
        many = F.size(t) - (n - 1)
        every = F.transform(F.sequence(F.lit(1), F.greatest(many, F.lit(1))), lambda i: F.array_join(F.slice(t, i, F.lit(n)), " "))
        return F.when(many >= 1, F.array_distinct(every)).otherwise(_none())

    return lambda x: let(_all_tokens(x), grams)


def integers(x: Column) -> Column:
    """Runs of digits without leading zeros; at most 18 digits are compared as numbers."""
    found = F.regexp_extract_all(x, F.lit("[0-9]+"), F.lit(0))
    return F.array_distinct(F.transform(found, lambda d: F.regexp_replace(d, "^0+(?=[0-9])", "")))


def _within_one(x: Column) -> Column:
    short = F.filter(integers(x), lambda d: F.length(d) <= 18)
    both = F.transform(short, lambda d: F.array(d.cast("long").cast("string"), (d.cast("long") + 1).cast("string")))
    return F.array_distinct(F.flatten(both))


def _round10(x: Column) -> Column:
    short = F.filter(integers(x), lambda d: F.length(d) <= 18)
    return F.array_distinct(F.transform(short, lambda d: F.call_function("div", d.cast("long"), F.lit(10)).cast("string")))


def _per_token(code: Callable[[Column], Column]) -> Callable[[Column], Column]:
    """Codes of the tokens that are letters only."""

    def keys(x: Column) -> Column:
        words = F.filter(tokens(x), lambda t: t.rlike("^[a-z]+$"))
        return F.array_distinct(F.filter(F.transform(words, code), lambda c: c != ""))

    return keys


_LIST = (
    IndexingFunction("exact", "character", lambda x: _some(normalized(x))),
    IndexingFunction("first1", "character", _prefix(1)),
    IndexingFunction("first_digit", "numeric", lambda x: F.when(x.rlike("^[0-9]"), F.array(F.substring(x, 1, 1))).otherwise(_none())),
    IndexingFunction("first3", "character", _prefix(3)),
    IndexingFunction("first5", "character", _prefix(5)),
    IndexingFunction("first7", "character", _prefix(7)),
    IndexingFunction("last3", "character", lambda x: let(normalized(x), lambda t: F.when(F.length(t) >= 3, F.array(F.right(t, F.lit(3)))).otherwise(_none()))),
    IndexingFunction("qgram2", "character", _qgrams(2)),
    IndexingFunction("qgram3", "character", _qgrams(3)),
    IndexingFunction("qgram4", "character", _qgrams(4)),
    IndexingFunction("token", "token", tokens),
    IndexingFunction("token_ng2", "token", _token_ngrams(2)),
    IndexingFunction("token_ng4", "token", _token_ngrams(4)),
    IndexingFunction("token_ng6", "token", _token_ngrams(6)),
    IndexingFunction("token_prefix3", "token", lambda x: F.array_distinct(F.transform(tokens(x), lambda t: F.substring(t, 1, 3)))),
    IndexingFunction("token_sorted", "token", lambda x: _some(F.array_join(F.array_sort(_all_tokens(x)), ""))),
    IndexingFunction("common_int", "numeric", integers),
    IndexingFunction("int_pm1", "numeric", _within_one),
    IndexingFunction("round10", "numeric", _round10),
    IndexingFunction("first_sig_digits2", "numeric", lambda x: F.array_distinct(F.transform(integers(x), lambda d: F.substring(d, 1, 2)))),
    IndexingFunction("soundex", "phonetic", _per_token(F.soundex)),
    IndexingFunction("refined_soundex", "phonetic", _per_token(phonetic.refined_soundex)),
    IndexingFunction("nysiis", "phonetic", _per_token(phonetic.nysiis)),
    IndexingFunction("caverphone1", "phonetic", _per_token(phonetic.caverphone1)),
    IndexingFunction("caverphone2", "phonetic", _per_token(phonetic.caverphone2)),
    IndexingFunction("match_rating", "phonetic", _per_token(phonetic.match_rating)),
    IndexingFunction("cologne", "phonetic", _per_token(phonetic.cologne)),
    IndexingFunction("metaphone", "phonetic", phonetic.metaphone_keys, True),
    IndexingFunction("double_metaphone", "phonetic", phonetic.double_metaphone_keys, True),
)
REGISTRY = {f.name: f for f in _LIST}
#: Not part of G: a key of one character names a block of a constant share of all records, whatever their number.
_ASIDE = {"first_digit", "first1"}
G_CLASSIC = tuple(f.name for f in _LIST if f.family != "phonetic" and f.name not in _ASIDE)
G_FULL = tuple(f.name for f in _LIST if f.name not in _ASIDE)
REGISTRY["raw_token"] = IndexingFunction("raw_token", "token", raw_tokens)


def predicate(name: str, left: Column, right: Column) -> Column:
    """Whether the key sets of two set-valued fields share a key."""
    f = REGISTRY[name]
    return F.coalesce(F.arrays_overlap(f.of_values(left), f.of_values(right)), F.lit(False))
