r"""Secret scans in Spark expressions only: base detectors, and entropy over sliding windows.

Every kind is a pattern that cuts a text into (gap, match) pairs, so positions are running sums of
lengths; these run over one row per match, so a text with very many matches stays linear. The
entropy detector takes runs of 20 or more key characters as candidates, drops those of the
allow-list, and slides a window of 20 characters over each: counts per character, and the sum of
count times its logarithm, change by the character that leaves and the one that enters. A candidate
is reported where its lowest sum, that is its highest entropy, reaches the bound of its character
class. Candidates that overlap a base span add nothing and are left out.

Defined cases: null is the empty text; offsets count code points and ends are exclusive; a text
without matches has empty spans and the SHA-256 of the empty string; ids may be null; repeated rows are scanned each;
an empty table gives an empty result; further columns are not read.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

#: The base patterns and least lengths (of the value for assignments).
ASSIGN = r"""(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]+"
HEX = r"[0-9a-f]+"
LEAST = {"assign": 6, "access": 20, "hex": 24}
WINDOW = 20
CANDIDATE = r"[A-Za-z0-9+/_-]{20,}={0,2}"
#: Bits per character that the best window must reach, by character class.
BITS = {"hex": 3.0, "alnum": 3.6, "base64": 3.8}
#: Candidates of these shapes are no secrets.
ALLOWED = (
    r"^[A-Za-z+/_=-]*$",
    r"^[0-9+/_=-]*$",
    r"^[0-9a-fA-F]{8}(?:-[0-9a-fA-F]{4}){3}-[0-9a-fA-F]{12}$",
    r"(?i)example|sample|dummy|placeholder|changeme|your_|xxxx|0123456789|123456789|abcdefgh",
    r"^(?:[a-z]+[/_-])+[a-z]+[0-9]{0,4}$",
)
KINDS = ("assign", "access", "hex", "entropy")


def _matches(text: Column, kind: int, pattern: str, ok) -> Column:
    """(kind, nth, gap, n, ok) of every match of ``pattern``; the rest of the text is a match of length 0."""
    cut = F.lit(rf"([\s\S]*?)(?:({pattern})|\z)")
    part = lambda i: F.regexp_extract_all(text, cut, F.lit(i))
    value = part(3) if pattern == ASSIGN else part(2)
    rows = F.arrays_zip(part(1).alias("gap"), part(2).alias("match"), value.alias("value"))
    return F.transform(
        rows,
        lambda r, i: F.struct(
            F.lit(kind).alias("kind"),
            i.alias("nth"),
            F.length(r["gap"]).alias("gap"),
            F.length(r["match"]).alias("n"),
            (F.length(r["match"]) > 0) & ok(r["match"], r["value"]),
        ),
    ).cast("array<struct<kind:int,nth:int,gap:int,n:int,ok:boolean>>")


def bind(value: Column, body) -> Column:
    """``body`` of a value that is computed once; inside lambdas Spark would compute it at every use."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def lowest_sum(word: Column) -> Column:
    """The lowest sum of count * log2(count) over windows of ``word``, updated step by step."""
    term = F.array(*(F.lit(c * math.log2(c) if c else 0.0) for c in range(WINDOW + 1)))
    g = lambda c: F.element_at(term, c + 1)

    def slide(codes: Column, first: Column) -> Column:
        whole = F.aggregate(first, F.lit(0.0), lambda a, c: a + g(c))
        steps = F.when(F.size(codes) > WINDOW, F.sequence(F.lit(WINDOW + 1), F.size(codes))).otherwise(F.array().cast("array<int>"))

        def step(state: Column, i: Column) -> Column:
            gone, new = F.element_at(codes, i - WINDOW), F.element_at(codes, i)
            less, more = F.element_at(state["counts"], gone), F.element_at(state["counts"], new)
            moved = state["now"] - g(less) + g(less - 1) - g(more) + g(more + 1)
            now = F.when(gone == new, state["now"]).otherwise(moved)
            counts = F.transform(state["counts"], lambda c, j: c - (j + 1 == gone).cast("int") + (j + 1 == new).cast("int"))
            return F.struct(counts.alias("counts"), now.alias("now"), F.least(state["low"], now).alias("low"))

        start = F.struct(first.alias("counts"), whole.alias("now"), whole.alias("low"))
        return F.aggregate(steps, start, step, lambda s: s["low"])

    def counted(known: Column, codes: Column) -> Column:
        first = F.transform(F.sequence(F.lit(1), F.size(known)), lambda j: F.size(F.filter(F.slice(codes, 1, WINDOW), lambda x: x == j)))
        return bind(first, lambda f: slide(codes, f))

    def coded(letters: Column, known: Column) -> Column:
        codes = F.transform(letters, lambda c: F.array_position(known, c).cast("int"))
        return bind(codes, lambda k: counted(known, k))

    return bind(F.split(word, ""), lambda letters: bind(F.array_distinct(letters), lambda known: coded(letters, known)))


def entropy_hit(word: Column) -> Column:
    """Whether a candidate is outside the allow-list and reaches the bound of its character class."""
    allowed = F.lit(False)
    for shape in ALLOWED:
        allowed = allowed | word.rlike(shape)
    bits = (
        F.when(word.rlike("^[0-9a-fA-F]*$"), F.lit(BITS["hex"]))
        .when(word.rlike("^[A-Za-z0-9]*$"), F.lit(BITS["alnum"]))
        .otherwise(F.lit(BITS["base64"]))
    )
    best = F.lit(math.log2(WINDOW)) - lowest_sum(word) / WINDOW
    return F.when((F.length(word) < WINDOW) | allowed, F.lit(False)).otherwise(best >= bits)


def found(text: Column) -> Column:
    """All matches of all kinds; patterns run in full only where a text has a match at all."""
    none = F.array().cast("array<struct<kind:int,nth:int,gap:int,n:int,ok:boolean>>")
    at_least = lambda n: lambda match, value: F.length(value) >= n
    parts = [
        F.when(text.rlike(ASSIGN), _matches(text, 0, ASSIGN, at_least(LEAST["assign"]))),
        F.when(F.contains(text, F.lit("AKIA")), _matches(text, 1, ACCESS, at_least(LEAST["access"]))),
        F.when(text.rlike(r"[0-9a-f]{24}"), _matches(text, 2, r"[0-9a-f]{24,}", at_least(LEAST["hex"]))),
        F.when(text.rlike(r"[A-Za-z0-9+/_-]{20}"), _matches(text, 3, CANDIDATE, lambda match, value: entropy_hit(match))),
    ]
    return F.concat(*(F.coalesce(p, none) for p in parts))


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, n_assign, n_access, n_hex, base_sha256, spans, n_entropy`` of every row of ``docs``."""
    text = F.coalesce(docs[text_col], F.lit(""))
    rows = docs.select(F.monotonically_increasing_id().alias("row_id"), docs[id_col].cast("long").alias("doc_id"), text.alias("t"))
    rows = rows.select("row_id", "doc_id", F.explode_outer(found(F.col("t"))).alias("x")).select("row_id", "doc_id", "x.*")
    rows = rows.repartition("row_id")
    run = Window.partitionBy("row_id", "kind").orderBy("nth")
    rows = rows.withColumn("end", F.sum(F.col("gap") + F.col("n")).over(run)).withColumn("start", F.col("end") - F.col("n"))
    rows = rows.withColumn("ok", F.coalesce("ok", F.lit(False)))
    base = F.col("ok") & (F.col("kind") < 3)
    order = Window.partitionBy("row_id").orderBy("start", "kind")
    before = F.max(F.when(base, F.col("end"))).over(order.rowsBetween(Window.unboundedPreceding, Window.currentRow))
    after = F.min(F.when(base, F.col("start"))).over(order.rowsBetween(Window.currentRow, Window.unboundedFollowing))
    rows = rows.withColumns({"before": before, "after": after})
    covered = (F.coalesce(F.col("before") > F.col("start"), F.lit(False))) | (F.coalesce(F.col("after") < F.col("end"), F.lit(False)))
    rows = rows.withColumn("ok", F.col("ok") & ((F.col("kind") < 3) | ~covered))
    many = lambda k: F.sum(((F.col("kind") == k) & F.col("ok")).cast("long"))
    span = F.struct("start", "kind", "end")
    rows = rows.groupBy("row_id", "doc_id").agg(
        *(F.coalesce(many(k), F.lit(0)).alias(f"n_{name}") for k, name in enumerate(KINDS)),
        F.array_sort(F.collect_list(F.when(F.col("ok"), span))).alias("all"),
    )
    names = F.array(*map(F.lit, KINDS))
    told = lambda spans: F.array_join(
        F.transform(spans, lambda s: F.concat_ws(":", F.element_at(names, s["kind"] + 1), s["start"], s["end"])), ","
    )
    return rows.select(
        "doc_id", "n_assign", "n_access", "n_hex",
        F.sha2(told(F.filter("all", lambda s: s["kind"] < 3)), 256).alias("base_sha256"),
        told(F.col("all")).alias("spans"),
        "n_entropy",
    )
