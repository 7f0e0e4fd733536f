"""Queries on triples and property tables."""

from __future__ import annotations

from pyspark.sql import functions as F

from dnfblock.operators import property_table as pt
from dnfblock.queries.catalogue import query, table
from dnfblock.sources import datasets, triples as tr

KINDS = ("click", "error", "purchase", "signup", "view")
CENTS = "cast(cast(round(value * 100) as bigint) as string)"


def _event_triples(spark, d):
    e = table(spark, d, "events")
    return e.select(F.col("user_id").cast("string").alias("s"), F.col("event_type").alias("p"), F.expr(CENTS).alias("o"))


def _joined(columns):
    return [F.coalesce(F.array_join(F.col(c), "|"), F.lit("")).alias(c) for c in columns]


@query(
    "pt_build_events",
    "SELECT CAST(user_id AS VARCHAR) AS subject, "
    + ", ".join(f"coalesce(array_to_string(list_sort(list_distinct(list({CENTS}) FILTER (event_type = '{k}'))), '|'), '') AS {k}" for k in KINDS)
    + " FROM events GROUP BY user_id",
)
def pt_build_events(spark, d):
    t = pt.to_property_table(_event_triples(spark, d), list(KINDS))
    return t.select("subject", *_joined(KINDS))


@query(
    "pt_build_conversations",
    """SELECT CAST(conv_id AS VARCHAR) AS subject, role AS property, CAST(count(DISTINCT text) AS BIGINT) AS n_values,
    md5(array_to_string(list_sort(list_distinct(list(text))), '|')) AS digest
    FROM conversations WHERE text IS NOT NULL AND role IS NOT NULL GROUP BY ALL""",
)
def pt_build_conversations(spark, d):
    c = table(spark, d, "conversations").where("text IS NOT NULL AND role IS NOT NULL")
    rows = c.select(F.col("conv_id").cast("string").alias("s"), F.col("role").alias("p"), F.col("text").alias("o"))
    m = pt.to_property_map(rows).select("subject", F.explode("values").alias("property", "v"))
    return m.select("subject", "property", F.size("v").cast("long").alias("n_values"), F.md5(F.array_join("v", "|")).alias("digest"))


P1_RIGHT_TRIPLES = (
    f"WITH r AS ({datasets.duck_side(datasets.P1.right)}) "
    + " UNION ALL ".join(f"SELECT rid AS s, '{f}' AS p, unnest(\"{f}\") AS o FROM r" for f in datasets.P1.right.fields)
)


def _p1_right_triples(spark, d):
    side = datasets.side(spark, d, datasets.P1.right)
    return pt.to_triples(side.withColumnRenamed("rid", "subject"))


@query("pt_roundtrip_customer", P1_RIGHT_TRIPLES)
def pt_roundtrip_customer(spark, d):
    return pt.to_triples(pt.to_property_table(_p1_right_triples(spark, d)))


PAGE_TRIPLES = """
WITH t AS (
  SELECT CAST(page_id AS VARCHAR) AS s, 'lang' AS p, regexp_extract(html, '<html lang="([^"]*)"', 1) AS o FROM pages
  UNION SELECT CAST(page_id AS VARCHAR), 'title', regexp_extract(html, '<title>([^<]*)</title>', 1) FROM pages
  UNION SELECT CAST(page_id AS VARCHAR), 'heading', regexp_extract(html, '<h1>([^<]*)</h1>', 1) FROM pages
  UNION SELECT CAST(page_id AS VARCHAR), 'link', unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) FROM pages
), u AS (SELECT * FROM t WHERE o <> '')
"""


@query("pt_schema_pages", PAGE_TRIPLES + "SELECT p AS property, CAST(count(DISTINCT s) AS BIGINT) AS subjects, CAST(count(*) AS BIGINT) AS triples FROM u GROUP BY p")
def pt_schema_pages(spark, d):
    t = tr.html_triples(table(spark, d, "pages"))
    known = spark.createDataFrame([(p,) for p in pt.property_schema(t)], "property string")
    sizes = t.groupBy(F.col("p").alias("property")).agg(F.count_distinct("s").alias("subjects"), F.count("*").alias("triples"))
    return known.join(sizes, "property")


def _profile_sql(rows: str) -> str:
    return rows + """, n AS (SELECT count(DISTINCT s) AS n FROM u), f AS (SELECT p, s, count(DISTINCT o) AS k FROM u GROUP BY p, s)
    SELECT f.p AS property, round(count(*) / any_value(n.n), 6) AS fill_rate, CAST(max(k) AS BIGINT) AS max_fanout,
    CAST((SELECT count(DISTINCT o) FROM u WHERE u.p = f.p) AS BIGINT) AS distinct_values FROM f, n GROUP BY f.p"""


@query("pt_profile_pages", _profile_sql(PAGE_TRIPLES))
def pt_profile_pages(spark, d):
    return pt.profile_property_table(tr.html_triples(table(spark, d, "pages")))


@query(
    "pt_profile_documents",
    _profile_sql(
        """WITH u AS (
    SELECT CAST(doc_id AS VARCHAR) AS s, 'lang' AS p, lang AS o FROM documents WHERE lang IS NOT NULL
    UNION ALL SELECT CAST(doc_id AS VARCHAR), 'source', source FROM documents WHERE source IS NOT NULL
    UNION ALL SELECT CAST(d.doc_id AS VARCHAR), 'quality', CAST(quality AS VARCHAR) FROM documents d JOIN labels USING (doc_id) WHERE quality IS NOT NULL
    UNION ALL SELECT CAST(d.doc_id AS VARCHAR), 'toxic', CAST(toxic AS VARCHAR) FROM documents d JOIN labels USING (doc_id) WHERE toxic IS NOT NULL)"""
    ),
)
def pt_profile_documents(spark, d):
    docs = table(spark, d, "documents").select("doc_id", "lang", "source").join(table(spark, d, "labels"), "doc_id", "left")
    return pt.profile_property_table(tr.table_triples(docs, "doc_id", ["lang", "source", "quality", "toxic"]))


@query(
    "pt_map_form_events",
    f"""SELECT CAST(user_id AS VARCHAR) AS subject, CAST(count(DISTINCT event_type) AS BIGINT) AS n_props,
    CAST(count(DISTINCT event_type || '|' || {CENTS}) AS BIGINT) AS n_values FROM events GROUP BY user_id""",
)
def pt_map_form_events(spark, d):
    m = pt.to_property_map(_event_triples(spark, d))
    many = F.aggregate(F.map_values("values"), F.lit(0).cast("long"), lambda a, v: a + F.size(v))
    return m.select("subject", F.size("values").cast("long").alias("n_props"), many.alias("n_values"))


@query(
    "pt_json_props",
    """SELECT CAST(event_id AS VARCHAR) AS subject, k AS property, json_extract_string(props, '$.' || k) AS value
    FROM (SELECT event_id, props, unnest(json_keys(props)) AS k FROM events) WHERE json_extract_string(props, '$.' || k) IS NOT NULL""",
)
def pt_json_props(spark, d):
    t = tr.json_triples(table(spark, d, "events"), "event_id", "props")
    return t.select(F.col("s").alias("subject"), F.col("p").alias("property"), F.col("o").alias("value"))


@query(
    "pt_delimited_codec",
    r"""SELECT p_brand AS subject, array_to_string(list_transform(vs, lambda v: replace(replace(v, '\', '\\'), ' ', '\ ')), ' ') AS encoded,
    CAST(len(vs) AS BIGINT) AS decoded_count FROM (SELECT p_brand, list_sort(list_distinct(list(p_name))) AS vs FROM part GROUP BY p_brand)""",
)
def pt_delimited_codec(spark, d):
    p = table(spark, d, "part").select(F.col("p_brand").alias("s"), F.lit("names").alias("p"), F.col("p_name").alias("o"))
    t = pt.to_property_table(p, ["names"]).select("subject", pt.encode_multi(F.col("names"), " ").alias("encoded"))
    return t.withColumn("decoded_count", F.size(pt.decode_multi(F.col("encoded"), " ")).cast("long"))


STAR = ["label", "marketArea", "funds"]
STAR_SQL = f"""WITH t AS ({P1_RIGHT_TRIPLES}) SELECT a.s AS subject, a.o AS label, b.o AS "marketArea", c.o AS funds
FROM t a JOIN t b ON a.s = b.s JOIN t c ON a.s = c.s WHERE a.p = 'label' AND b.p = 'marketArea' AND c.p = 'funds'"""


@query("star_select_p1", STAR_SQL)
def star_select_p1(spark, d):
    return pt.star_select(pt.to_property_table(_p1_right_triples(spark, d), STAR), STAR)


@query("star_vs_selfjoin", STAR_SQL)
def star_vs_selfjoin(spark, d):
    return tr_star(spark, d)


def tr_star(spark, d):
    return pt.star_by_selfjoin(_p1_right_triples(spark, d), STAR)


@query("triple_pattern_events", f"SELECT CAST(user_id AS VARCHAR) AS s, {CENTS} AS o FROM events WHERE event_type = 'purchase'")
def triple_pattern_events(spark, d):
    return tr.match(_event_triples(spark, d), p="purchase").select("s", "o")


@query(
    "triple_upsert_events",
    f"""WITH t AS (SELECT DISTINCT CAST(user_id AS VARCHAR) AS s, event_type AS p, {CENTS} AS o FROM events)
    SELECT * FROM t WHERE p <> 'error' UNION SELECT DISTINCT s, 'seen', p FROM t""",
)
def triple_upsert_events(spark, d):
    t = _event_triples(spark, d)
    return tr.upsert(t, t.select("s", F.lit("seen").alias("p"), F.col("p").alias("o")), tr.match(t, p="error"))


@query(
    "deref_nation_labels",
    """SELECT CAST(n_nationkey AS VARCHAR) AS s, 'region' AS p, r_name AS label FROM nation JOIN region ON n_regionkey = r_regionkey
    UNION ALL SELECT CAST(c_custkey AS VARCHAR), 'nation', n_name FROM customer JOIN nation ON c_nationkey = n_nationkey""",
)
def deref_nation_labels(spark, d):
    n, r, c = (table(spark, d, x) for x in ("nation", "region", "customer"))
    uri = lambda kind, key: F.concat(F.lit(f"urn:{kind}:"), F.col(key).cast("string"))
    t = n.select(F.col("n_nationkey").cast("string").alias("s"), F.lit("region").alias("p"), uri("region", "n_regionkey").alias("o"))
    t = t.unionByName(c.select(F.col("c_custkey").cast("string").alias("s"), F.lit("nation").alias("p"), uri("nation", "c_nationkey").alias("o")))
    labels = r.select(uri("region", "r_regionkey").alias("uri"), F.col("r_name").alias("label")).unionByName(
        n.select(uri("nation", "n_nationkey").alias("uri"), F.col("n_name").alias("label"))
    )
    return tr.dereference(t.withColumn("o_is_uri", F.lit(True)), labels).select("s", "p", F.col("o").alias("label"))


@query("emit_links_p1", f"SELECT l_rid AS s, '{tr.SAME_AS}' AS p, r_rid AS o FROM ({datasets.duck(datasets.P1.truth_sql)})")
def emit_links_p1(spark, d):
    return tr.emit_links(datasets.truth(spark, d, datasets.P1)).select("s", "p", "o")


@query(
    "entity_values_p5",
    f"WITH r AS ({datasets.duck_side(datasets.P5.right)}) "
    + " UNION ALL ".join(f"SELECT rid, '{f}' AS field, array_to_string(list_sort(\"{f}\"), '|') AS vals FROM r WHERE len(\"{f}\") > 0" for f in datasets.P5.right.fields),
)
def entity_values_p5(spark, d):
    e = pt.to_entities(datasets.side(spark, d, datasets.P5.right), "rid", list(datasets.P5.right.fields), 1)
    return e.select("rid", "field", F.array_join(F.array_sort("values"), "|").alias("vals"))
