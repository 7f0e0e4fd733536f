"""Queries on the matcher: weights, ranked duplicates, precision and recall, mappings."""

from __future__ import annotations

from pyspark.sql import functions as F

from dnfblock.operators import blocking, decision, matcher, metrics, top_pairs
from dnfblock.operators.scheme import Atom, Scheme
from dnfblock.plans.experiments import Bench
from dnfblock.queries import twins
from dnfblock.queries.catalogue import query
from dnfblock.sources import datasets
from dnfblock.sources.datasets import P1, P5, P6, PAIRS
from dnfblock.storage import materialize

KS = (1, 5, 10, 25, 50, 100, 200, 500, 1_000, 2_000, 5_000, 10_000, 20_000, 50_000)


def _bag(side: datasets.Side, table: str) -> str:
    parts = [f"flatten(list_transform(\"{f}\", lambda v: list_filter(string_split({twins.norm('v')}, ' '), lambda t: t <> '')))" for f in side.fields]
    return f"SELECT rid, unnest({' || '.join(parts)}) AS token FROM {table}"


def weight_ctes(pair: datasets.Pair) -> str:
    return f"""WITH {twins.sides(pair)}, b AS (SELECT 0 AS side, * FROM ({_bag(pair.left, 'l')}) UNION ALL SELECT 1, * FROM ({_bag(pair.right, 'r')})),
    n AS (SELECT (SELECT count(*) FROM l) + (SELECT count(*) FROM r) AS n), tf AS (SELECT side, rid, token, count(*) AS tf FROM b GROUP BY ALL),
    df AS (SELECT token, count(*) AS df FROM tf GROUP BY token), w0 AS (SELECT side, rid, token, df, ln(1 + tf) * ln(n / df) AS w FROM tf JOIN df USING (token), n),
    w AS (SELECT side, rid, token, df, CASE WHEN sqrt(sum(w * w) OVER (PARTITION BY side, rid)) > 0 THEN w / sqrt(sum(w * w) OVER (PARTITION BY side, rid)) ELSE 0 END AS w FROM w0)"""


def ranked_ctes(pair: datasets.Pair, t: int) -> str:
    return f"""{weight_ctes(pair)}, s AS (SELECT a.rid AS l_rid, b.rid AS r_rid, round(sum(a.w * b.w), 9) AS score FROM w a JOIN w b USING (token)
    WHERE a.side = 0 AND b.side = 1 GROUP BY ALL HAVING sum(a.w * b.w) > 0), k AS (SELECT row_number() OVER (ORDER BY score DESC, l_rid, r_rid) AS rank, * FROM s QUALIFY rank <= {t})"""


def _weights(spark, d, pair):
    left, right, truth = datasets.load(spark, d, pair)
    return matcher.weights(left, right, left.columns[1:], right.columns[1:]), truth


@query("tfidf_weights_part", f"{weight_ctes(P5)} SELECT rid, token, round(w, 6) AS weight FROM w")
def tfidf_weights_part(spark, d):
    return _weights(spark, d, P5)[0].select("rid", "token", F.round("w", 6).alias("weight"))


def _top(name: str, pair: datasets.Pair, t: int, strategy: str) -> None:
    @query(name, f"{ranked_ctes(pair, t)} SELECT rank, l_rid, r_rid, round(score, 6) AS score FROM k")
    def run(spark, d):
        if strategy == "classes":
            left, right, _ = datasets.load(spark, d, pair)
            fields = left.columns[1:], right.columns[1:]
            top = top_pairs.top_pairs(top_pairs.vectors(left, right, *fields), left, right, *fields, t)
        else:
            top = matcher.top_duplicates(_weights(spark, d, pair)[0], t, strategy)
        return top.select("rank", "l_rid", "r_rid", F.round("score", 6).alias("score"))


_top("dup_topt_p1", P1, 50, "classes")
_top("dup_prefix_pruned_p1", P1, 50, "prefix")
_top("dup_topt_p5", P5, 50, "classes")


def _precision(name: str, pair: datasets.Pair) -> None:
    sql = f"""{ranked_ctes(pair, max(KS))}, h AS (SELECT rank, CASE WHEN t.l_rid IS NULL THEN 0 ELSE 1 END AS hit FROM k LEFT JOIN truth t USING (l_rid, r_rid)),
    p AS (SELECT rank AS k, sum(hit) OVER (ORDER BY rank) AS hits FROM h)
    SELECT k, round(hits / k, 6) AS precision, round(hits / (SELECT count(*) FROM truth), 6) AS recall FROM p WHERE k IN {KS}"""

    @query(name, sql)
    def run(spark, d):
        w, truth = _weights(spark, d, pair)
        rows = metrics.precision_recall_at(matcher.top_duplicates(w, max(KS)), truth)
        return rows.where(F.col("k").isin(*KS)).select("k", F.round("precision", 6).alias("precision"), F.round("recall", 6).alias("recall"))


for _p in (P1, P5, P6):
    _precision(f"prec_recall_at_k_{_p.name}", _p)


_USED = lambda side, table, name: " UNION ".join(f"SELECT '{f}' AS {name} FROM {table} WHERE len(\"{f}\") > 0" for f in side.fields)


@query("exhaustive_mappings_p1", f"WITH {twins.sides(P1)} SELECT * FROM ({_USED(P1.left, 'l', 'l')}) AS a, ({_USED(P1.right, 'r', 'r')}) AS b")
def exhaustive_mappings_p1(spark, d):
    """Mappings of the fields that have a value in some record."""
    left, right, _ = datasets.load(spark, d, P1)

    def used(df):
        names = F.array_compact(F.array(*(F.when(F.size(f) > 0, F.lit(f)) for f in df.columns[1:])))
        there = {r[0] for r in df.select(F.explode(names)).distinct().collect()}
        return [f for f in df.columns[1:] if f in there]

    found = matcher.exhaustive_simple(used(left), used(right))
    return spark.createDataFrame([(a[0], b[0]) for a, b in found], "l string, r string")


def _similarity_sql(t: int) -> str:
    """Field similarities at a threshold of 1: cosine over equal tokens, within the fields' own vectors."""
    cells = []
    for f in P1.left.fields:
        for g in P1.right.fields:
            cells.append(f"SELECT '{f}' AS f1, '{g}' AS f2, l_rid, r_rid, l.\"{f}\" AS a, r.\"{g}\" AS b FROM k JOIN l ON l.rid = l_rid JOIN r ON r.rid = r_rid")
    bag = lambda c, n: f"SELECT f1, f2, l_rid, r_rid, token, count(*) AS tf FROM (SELECT f1, f2, l_rid, r_rid, unnest(flatten(list_transform({c}, lambda v: list_filter(string_split({twins.norm('v')}, ' '), lambda t: t <> '')))) AS token FROM cells) GROUP BY ALL"
    vec = lambda n: f"SELECT {n}.*, ln(1 + tf) * ln((SELECT n FROM n) / df) AS x FROM {n} JOIN df USING (token)"
    unit = lambda n: f"SELECT *, x / nullif(sqrt(sum(x * x) OVER (PARTITION BY f1, f2, l_rid, r_rid)), 0) AS u FROM ({vec(n)})"
    return f"""{ranked_ctes(P1, t)}, cells AS ({' UNION ALL '.join(cells)}), ba AS ({bag('a', 'ba')}), bb AS ({bag('b', 'bb')}), va AS ({unit('ba')}), vb AS ({unit('bb')}),
    s2 AS (SELECT va.f1, va.f2, va.l_rid, va.r_rid, sum(va.u * vb.u) AS s FROM va JOIN vb ON va.f1 = vb.f1 AND va.f2 = vb.f2 AND va.l_rid = vb.l_rid AND va.r_rid = vb.r_rid AND va.token = vb.token GROUP BY ALL)
    SELECT f1, f2, round(avg(coalesce(s, 0)), 6) AS sim FROM cells LEFT JOIN s2 USING (f1, f2, l_rid, r_rid) GROUP BY f1, f2"""


def _similarities(spark, d, theta, t=50):
    left, right, _ = datasets.load(spark, d, P1)
    fields = left.columns[1:], right.columns[1:]
    v = top_pairs.vectors(left, right, *fields)
    pairs = materialize(top_pairs.top_pairs(v, left, right, *fields, t), "ranked")
    return matcher.similarity_matrix(pairs, v, left, right, *fields, theta)


@query("field_similarity_p1_theta1", _similarity_sql(50))
def field_similarity_p1_theta1(spark, d):
    return _similarities(spark, d, 1.0).select("f1", "f2", F.round("sim", 6).alias("sim"))


@query("field_similarity_p1")
def field_similarity_p1(spark, d):
    return _similarities(spark, d, 0.5).select("f1", "f2", F.round("sim", 6).alias("sim"))


def _mapping_rows(spark, rows):
    return spark.createDataFrame(rows, "pair string, t int, theta double, n_found int, precision double, recall double, hit_share double")


def _quality(bench: Bench, t: int, theta: float) -> tuple:
    q = bench.mappings(t, theta)
    return (bench.pair.name, t, theta, len(q), *metrics.mapping_quality(q, bench.pair.mappings))


def _schema_map(name: str) -> None:
    @query(f"schema_map_{name}")
    def run(spark, d):
        q = Bench(spark, d, name).q
        return spark.createDataFrame([(a[0], b[0]) for a, b in q], "l string, r string")


for _n in PAIRS:
    _schema_map(_n)


@query("mapping_quality_all")
def mapping_quality_all(spark, d):
    return _mapping_rows(spark, [_quality(Bench(spark, d, n), 50, 0.5) for n in PAIRS])


@query("mapping_sweep_t_theta")
def mapping_sweep_t_theta(spark, d):
    """t at the default theta, theta at the default t; pairs of one, of n:m and of text fields."""
    rows = []
    for name in ("p1", "p2", "p5", "p7"):
        bench = Bench(spark, d, name, retrieve=10_000)
        grid = [(t, 0.5) for t in (10, 50, 100, 1_000, 10_000)] + [(50, theta) for theta in (0.0, 0.3, 0.7, 0.9)]
        rows += [_quality(bench, t, theta) for t, theta in grid]
    return _mapping_rows(spark, rows)


@query("classify_p1")
def classify_p1(spark, d):
    """Decisions on the candidates of a scheme over the fields that the matcher mapped, against the truth."""
    bench = Bench(spark, d, "p1")
    scheme = Scheme.of(*(Atom.complex("exact", a, b) for a, b in P1.mappings if "fullName" in a or "balance" in a))
    pairs = blocking.candidates(bench.left, bench.right, scheme)
    made = decision.classify(pairs, bench.weights, bench.left, bench.right, bench.q)
    hits = bench.truth.select("l_rid", "r_rid", F.lit(1).alias("hit"))
    rows = made.join(hits, ["l_rid", "r_rid"], "left").groupBy("decision")
    return rows.agg(F.count("*").alias("n_pairs"), F.coalesce(F.sum("hit"), F.lit(0)).alias("n_true"), F.round(F.avg("score"), 6).alias("mean_score"))
