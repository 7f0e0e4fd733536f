import datetime as dt
import json

import pandas as pd
import pytest
from pyspark.sql import functions as F

from dnfblock.operators import blocking
from dnfblock.operators.scheme import Atom, Scheme
from dnfblock.streaming import streams


def _write(folder, name, rows):
    folder.mkdir(exist_ok=True)
    (folder / name).write_text("\n".join(json.dumps(r, default=str) for r in rows))


def _run(spark, df, tmp_path, name, mode="append"):
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", f"{tmp_path}/cp-{name}").trigger(availableNow=True).start()
    q.awaitTermination(120)
    assert q.exception() is None
    return spark.table(name).collect()


def test_static_index_equals_batch(spark, tmp_path):
    s = Scheme.of(Atom.simple("token", "v"))
    left = [{"rid": f"l{i}", "v": [f"w{i % 4} x{i}"]} for i in range(12)]
    for i in range(3):
        _write(tmp_path / "in", f"{i}.json", left[i * 4 : i * 4 + 4])
    right = spark.createDataFrame([(f"r{i}", [f"w{i}"]) for i in range(6)], "rid string, v array<string>")
    stream = spark.readStream.schema("rid string, v array<string>").option("maxFilesPerTrigger", 1).json(str(tmp_path / "in"))
    got = {(r.l_rid, r.r_rid) for r in _run(spark, streams.stream_candidates_static(stream, right, s), tmp_path, "static_pairs")}
    batch = blocking.candidates(spark.createDataFrame([(r["rid"], r["v"]) for r in left], right.schema), right, s)
    assert got == {tuple(r) for r in batch.collect()}


def test_two_streams_meet_within_the_wait(spark, tmp_path):
    at = lambda m: str(dt.datetime(2024, 1, 1, 10) + dt.timedelta(minutes=m))
    _write(tmp_path / "a", "0.json", [{"rid": "a1", "k": "x", "ts": at(0)}, {"rid": "a2", "k": "y", "ts": at(5)}])
    _write(tmp_path / "b", "0.json", [{"rid": "b1", "k": "x", "ts": at(30)}, {"rid": "b2", "k": "x", "ts": at(200)}, {"rid": "b3", "k": "y", "ts": at(5)}])
    read = lambda n: spark.readStream.schema("rid string, k string, ts timestamp").json(str(tmp_path / n))
    rows = _run(spark, streams.stream_stream_candidates(read("a"), read("b"), "k", "ts"), tmp_path, "two_streams")
    assert {(r.l_rid, r.r_rid) for r in rows} == {("a1", "b1"), ("a2", "b3")}


def test_redelivered_records_are_dropped(spark, tmp_path):
    rows = [{"rid": "a", "ts": "2024-01-01 10:00:00"}, {"rid": "b", "ts": "2024-01-01 10:01:00"}]
    for i in range(2):
        _write(tmp_path / "in", f"{i}.json", rows)
    stream = spark.readStream.schema("rid string, ts timestamp").option("maxFilesPerTrigger", 1).json(str(tmp_path / "in"))
    assert sorted(r.rid for r in _run(spark, streams.without_redelivery(stream), tmp_path, "once")) == ["a", "b"]


def test_stateful_index_emits_each_pair_once(spark, tmp_path):
    batches = [
        [{"key": "k", "side": 0, "rid": "l1"}, {"key": "k", "side": 1, "rid": "r1"}],
        [{"key": "k", "side": 1, "rid": "r2"}, {"key": "j", "side": 0, "rid": "l1"}, {"key": "k", "side": 0, "rid": "l1"}],
        [{"key": "k", "side": 0, "rid": "l2"}],
    ]
    for i, b in enumerate(batches):
        _write(tmp_path / "in", f"{i}.json", b)
    stream = spark.readStream.schema("key string, side int, rid string").option("maxFilesPerTrigger", 1).json(str(tmp_path / "in"))
    rows = [(r.l_rid, r.r_rid) for r in _run(spark, streams.stateful_candidates(stream), tmp_path, "stateful")]
    assert sorted(rows) == [("l1", "r1"), ("l1", "r2"), ("l2", "r1"), ("l2", "r2")]


class _List:
    def __init__(self):
        self.rows = []

    def get(self):
        return iter(self.rows)

    def put(self, rows):
        self.rows = list(rows)


class _Handle:
    def getListState(self, *_, **__):
        return _List()


def test_stateful_index_forgets_no_record_of_a_hot_key():
    """More than 1,000 records of one key over several batches, the first ones delivered again."""
    index, got = streams.PairingIndex(), []
    index.init(_Handle())
    left = [(0, f"l{i}") for i in range(1500)]
    for batch in (left[:800], left[800:], [(1, "r")], [*left[:5], (1, "q")]):
        frame = pd.DataFrame(batch, columns=["side", "rid"])
        for out in index.handleInputRows(("k",), iter([frame]), None):
            got += list(out.itertuples(index=False, name=None))
    assert sorted(got) == sorted((f"l{i}", r) for i in range(1500) for r in "rq")


def test_property_table_grows(spark):
    old = spark.createDataFrame([("a", "p", ["1"])], "s string, p string, values array<string>")
    new = spark.createDataFrame([("a", "p", "2"), ("a", "p", "1"), ("b", "q", "3")], "s string, p string, o string")
    rows = {(r.s, r.p): r["values"] for r in streams.merge_property_table(old, new).collect()}
    assert rows == {("a", "p"): ["1", "2"], ("b", "q"): ["3"]}


def test_sql_surface(spark):
    from dnfblock import sql

    sql.register(spark)
    assert spark.sql("SELECT gbp_token('Red oak', 'oak tree') a, gbp_token('x', 'y') b, gbp_soundex('Robert', 'rupert') c, gbp_common_int('no 07', '7') e").first()[:] == (True, False, True, True)


def test_table_functions(spark):
    from dnfblock import sql
    from dnfblock.operators import blocking
    from dnfblock.operators.scheme import Atom, Scheme

    sql.register(spark)
    rows = [("r1", ["Red oak 007", "OAK-tree"], "12 b"), ("r2", [], None), ("r3", None, "x 7 é"), ("r4", ["", "a b c d e f g"], "07")]
    df = spark.createDataFrame(rows, "rid string, v array<string>, w string")
    df.createOrReplaceTempView("udtf_in")
    as_sets = df.withColumn("w", F.filter(F.array("w"), lambda x: x.isNotNull()))
    for gbp in sql.PYTHON_KEYS:
        scheme = Scheme.of(Atom.simple(gbp, "v"), (Atom.complex(gbp, ("v", "w"), ("w",)), Atom.simple("token", "w")))
        for side in (0, 1) if gbp == "token" else (0,):
            made = spark.sql("SELECT * FROM block_keys(TABLE(udtf_in), '" + scheme.to_json() + f"', {side})")
            wanted = blocking.index(as_sets, scheme, side).select("term_id", "key", "rid")
            assert sorted(map(tuple, made.collect())) == sorted(map(tuple, wanted.collect())), gbp
    with pytest.raises(Exception, match="no key function"):
        spark.sql("SELECT * FROM block_keys(TABLE(udtf_in), '" + Scheme.of(Atom.simple("soundex", "v")).to_json() + "', 0)").collect()


def test_property_table_function(spark):
    from dnfblock import sql

    sql.register(spark)
    rows = [("a", "p", "2"), ("a", "p", "1"), ("a", "q", "x"), ("a", "p", "1"), ("b", "q", None), ("c", "q", "z")]
    spark.createDataFrame(rows, "s string, p string, o string").createOrReplaceTempView("udtf_triples")
    got = spark.sql("SELECT * FROM property_table(TABLE(udtf_triples) PARTITION BY s)").collect()
    assert sorted(map(tuple, got)) == [("a", "p", ["1", "2"]), ("a", "q", ["x"]), ("c", "q", ["z"])]
