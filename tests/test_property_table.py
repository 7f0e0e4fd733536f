import pytest
from pyspark.sql import functions as F

from dnfblock.operators import property_table as pt
from dnfblock.sources import triples as tr

TRIPLES = [("m", "wife", "j"), ("m", "kid", "k1"), ("m", "kid", "k2"), ("j", "wife", "m"), ("k1", "age", "7"), ("k1", "age", "7")]


@pytest.fixture(scope="module")
def graph(spark):
    return spark.createDataFrame([(*t, False) for t in TRIPLES], "s string, p string, o string, o_is_uri boolean")


def test_schema_table_and_back(graph):
    assert pt.property_schema(graph) == ["age", "kid", "wife"]
    t = pt.to_property_table(graph)
    rows = {r.subject: r for r in t.collect()}
    assert rows["m"].kid == ["k1", "k2"] and rows["m"].age is None and rows["k1"].age == ["7"] and len(rows) == 3
    assert {tuple(r) for r in pt.to_triples(t).collect()} == set(TRIPLES)
    with pytest.raises(ValueError):
        pt.property_schema(graph, most=2)
    flat = {r.subject: r for r in pt.to_property_table(graph, multi="delimited").collect()}
    assert flat["m"].kid == "k1;k2" and flat["j"].kid is None


def test_codec_escapes(spark):
    values = [["a;b", "c\\", "", "\\;"], ["x"], [";"], ["a", "b"], ["a\x01b", "\x02;\x01\\"], ["\n;", "\\\\;\n\\", "$1"], ["\\;" * 2000, "é🙂;" * 100]]
    df = spark.createDataFrame([(v,) for v in values], "v array<string>")
    assert [r[0] for r in df.select(pt.decode_multi(pt.encode_multi(F.col("v")))).collect()] == values
    assert df.select(pt.encode_multi(F.lit(None).cast("array<string>"))).first()[0] is None


def test_entities_of_mixed_types(spark):
    df = spark.sql("select 1 id, cast(1.5 as double) x, date'2020-01-02' d, array('a', null) l, true b, cast(null as string) n")
    rows = {r.field: r["values"] for r in pt.to_entities(df, "id", ["x", "d", "l", "b", "n"]).collect()}
    assert rows == {"x": ["1.500000"], "d": ["2020-01-02"], "l": ["a"], "b": ["true"]}
    with pytest.raises(TypeError):
        pt.to_entities(spark.sql("select 1 id, cast('a' as binary) v"), "id", ["v"])


@pytest.mark.parametrize("part_bytes", [1_000, 1 << 20])
def test_ntriples_round_trip(spark, tmp_path, part_bytes):
    texts = ['say "hi"\n\\', "a\\nb", "\\\\u0041", "\r\n\t\b\f", "é😀'", "", "x" * 50_000, "\\" * 5]
    rows = [(f"s{i}", "p", t, False) for i, t in enumerate(texts)] + [("s1", "q", "urn:x", True), ("_:b", "q", "_:c", True)]
    df = spark.createDataFrame(rows, "s string, p string, o string, o_is_uri boolean")
    path = f"{tmp_path}/nt"
    tr.write_ntriples(df, path)
    assert sorted(map(tuple, tr.read_ntriples(spark, path).collect())) == sorted(rows)
    spark.dataSource.register(tr.NTriplesSource)
    read = spark.read.format("ntriples").option("part_bytes", part_bytes)
    assert sorted(map(tuple, read.load(path).collect())) == sorted(rows)
    assert sorted(map(tuple, read.load(f"file://{path}").collect())) == sorted(rows)


def test_ntriples_odd_lines(spark, tmp_path):
    (tmp_path / "odd").write_text('# note\n\n<s> <p> "\\u00e9\\U0001F600\\\\u0041"@en . # end\n_:b <p> _:c.\n<s> <p> "1"^^<int> .')
    rows = [("_:b", "p", "_:c", True), ("s", "p", "1", False), ("s", "p", "é😀\\u0041", False)]
    assert sorted(map(tuple, tr.read_ntriples(spark, f"{tmp_path}/odd").collect())) == rows
    spark.dataSource.register(tr.NTriplesSource)
    for parts in (1, 3, 40, 1000):
        assert sorted(map(tuple, spark.read.format("ntriples").option("part_bytes", parts).load(f"{tmp_path}/odd").collect())) == rows
    (tmp_path / "bad").write_text("# note\n\nno triple\n")
    with pytest.raises(Exception, match="no triple"):
        tr.read_ntriples(spark, f"{tmp_path}/bad").collect()


def test_patterns_updates_links(spark, graph):
    assert {r.o for r in tr.match(graph, s="m", p="kid").collect()} == {"k1", "k2"}
    new = spark.createDataFrame([("m", "kid", "k3", False)], graph.schema)
    after = {tuple(r)[:3] for r in tr.upsert(graph, new, tr.match(graph, p="age")).collect()}
    assert after == (set(TRIPLES) | {("m", "kid", "k3")}) - {("k1", "age", "7")}
    link = tr.emit_links(spark.createDataFrame([("a", "b")], "l_rid string, r_rid string")).first()
    assert (link.s, link.o, link.p) == ("a", "b", tr.SAME_AS)
    named = tr.dereference(spark.createDataFrame([("a", "p", "http://x/y#Zed", True), ("a", "p", "lit/er", False)], graph.schema))
    assert {r.o for r in named.collect()} == {"Zed", "lit/er"}


def test_map_profile_and_star(graph):
    m = {r.subject: r["values"] for r in pt.to_property_map(graph).collect()}
    assert m["m"] == {"kid": ["k1", "k2"], "wife": ["j"]}
    p = {r.property: r for r in pt.profile_property_table(graph).collect()}
    assert p["kid"].max_fanout == 2 and p["wife"].fill_rate == pytest.approx(2 / 3, abs=1e-6)
    a = pt.star_select(pt.to_property_table(graph), ["kid", "wife"])
    assert sorted(map(tuple, a.collect())) == sorted(map(tuple, pt.star_by_selfjoin(graph, ["kid", "wife"]).collect()))


def test_index_is_kept_by_term(spark, tmp_path):
    from dnfblock.operators import blocking
    from dnfblock.operators.scheme import Atom, Scheme

    df = spark.createDataFrame([("a", ["red oak"]), ("b", ["oak"])], "rid string, v array<string>")
    s = Scheme.of(Atom.simple("token", "v"), Atom.simple("exact", "v"))
    tr.write_index(blocking.index(df, s, 0), f"{tmp_path}/ix")
    back = spark.read.parquet(f"{tmp_path}/ix")
    assert back.where("term_id = 0").count() == 3 and back.where("term_id = 1").count() == 2


def test_saved_indices_meet_without_a_shuffle(spark):
    from dnfblock.operators import blocking
    from dnfblock.operators.scheme import Atom, Scheme

    df = spark.createDataFrame([("a", ["red oak"]), ("b", ["oak"]), ("c", ["elm"])], "rid string, v array<string>")
    rows = blocking.index(df, Scheme.of(Atom.simple("token", "v")), 0)
    spark.sql("DROP TABLE IF EXISTS ix_l"), spark.sql("DROP TABLE IF EXISTS ix_r")
    a, b = tr.save_index(rows, "ix_l", 4), tr.save_index(rows, "ix_r", 4)
    met = a.hint("merge").join(b.withColumnRenamed("rid", "other"), ["term_id", "key"])
    plan = met._jdf.queryExecution().executedPlan().toString()
    pairs = sorted((r.rid, r.other) for r in met.collect())
    spark.sql("DROP TABLE ix_l"), spark.sql("DROP TABLE ix_r")
    assert "SortMergeJoin" in plan and "Exchange" not in plan
    assert pairs == [("a", "a"), ("a", "a"), ("a", "b"), ("b", "a"), ("b", "b"), ("c", "c")]
