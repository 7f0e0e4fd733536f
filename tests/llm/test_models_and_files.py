"""Classifiers by held-out accuracy, media and archives by round trips, the pipeline by its parts."""

import gzip
import hashlib
import os
import random
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from dnfblock import storage
from dnfblock.llm import media, queries, quality, toxicity, warc

SF = "/root/testdata/sf0.01"


@pytest.fixture(scope="module")
def labelled(spark):
    return spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/labels.parquet")


def held_out(rows, labels, column):
    known = {r.doc_id: r[column] for r in labels.collect()}
    return [(known[r.doc_id], r.predicted, r.score) for r in rows if r.held_out and r.doc_id in known]


def test_toxicity_held_out(labelled):
    docs, labels = labelled
    rows = toxicity.toxicity(docs, labels).collect()
    assert len(rows) == docs.count() and all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 3 == 1) for r in rows)
    pairs = held_out(rows, labels, "toxic")
    hit = [p for p in pairs if p[1]]
    assert sum(t for t, _, _ in hit) >= 0.9 * len(hit) and sum(t for t, _, _ in hit) >= 0.6 * sum(t for t, _, _ in pairs)
    assert all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.7) for r in rows)


def test_labels_of_held_out_rows_change_nothing(labelled):
    docs, labels = labelled
    small = docs.limit(300)
    spoiled = labels.withColumn("toxic", F.when(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 3 == 1, 1 - F.col("toxic")).otherwise(F.col("toxic")))
    a = {r.doc_id: r.score for r in toxicity.toxicity(small, labels).collect()}
    assert a == {r.doc_id: r.score for r in toxicity.toxicity(small, spoiled).collect()}


def test_counterfactual_term_evens_group_names():
    """Texts that name one group are labelled toxic more often; the term takes that back."""
    names = ["idiot", "muslim", "christian", "sky"]
    own = [[0, 1]] * 30 + [[0]] * 30 + [[1]] * 30 + [[2]] * 30 + [[3]] * 30
    label = np.array([1] * 60 + [1] * 10 + [0] * 20 + [0] * 60)
    swapped = [[[3, -2]] if 1 in r else [[2, -3]] if 2 in r else [] for r in own]
    none = [[] for _ in own]
    plain, _, _ = toxicity.fit_weights(label, own, swapped, none, len(names), fair=0.0)
    fair, _, pairs = toxicity.fit_weights(label, own, swapped, none, len(names), fair=5.0)
    assert plain[1] - plain[2] > 1 and abs(fair[1] - fair[2]) < 0.3 * (plain[1] - plain[2]) and fair[0] > 1 and pairs == 90


def objective(w, bias, label, own, swapped, inserted, l2, fair):
    """What the fit minimises, text by text."""
    logit = lambda row: bias + sum(w[p] for p in row)
    score = lambda z: 1 / (1 + np.exp(-z))
    changed = lambda row, c: (set(row) | {p - 1 for p in c if p > 0}) - {-p - 1 for p in c if p < 0}
    texts, pairs = list(zip(own, label)), []
    for row, y, swaps, puts in zip(own, label, swapped, inserted):
        pairs += [(logit(row), logit(changed(row, c))) for c in swaps]
        if puts:
            texts.append((changed(row, puts[0]), y))
            pairs += [(logit(texts[-1][0]), logit(row)), (logit(texts[-1][0]), logit(changed(row, puts[1])))]
    n = {y: sum(v == y for _, v in texts) for y in (0, 1)}
    loss = sum(-np.log(score(logit(r) if y else -logit(r))) * 0.5 / n[y] for r, y in texts)
    return loss + l2 / 2 * sum(w * w) + fair * sum((score(p) - score(q)) ** 2 + 0.1 * (p - q) ** 2 for p, q in pairs) / max(len(pairs), 1)


@pytest.mark.parametrize("fair", [0.0, 1.0])
def test_fit_minimises_loss_and_score_changes(fair):
    rng = random.Random(2)
    own = [sorted(rng.sample(range(8), rng.randint(0, 4))) for _ in range(60)]
    label = np.array([int(0 in r or rng.random() < 0.3) for r in own])
    swapped = [[[8, -7]] if 6 in r and 7 not in r else [] for r in own]
    inserted = [[[p + 1] if p not in r else [] for p in rng.sample((6, 7), 2)] if not {6, 7} & set(r) else [] for r in own]
    w, bias, pairs = toxicity.fit_weights(label, own, swapped, inserted, 8, l2=1e-2, fair=fair, steps=3000)
    assert pairs > 40
    f = lambda x: objective(x[:8], x[8], label, own, swapped, inserted, 1e-2, fair)
    best = np.append(w, bias)
    slopes = [(f(best + e) - f(best - e)) / 2e-4 for e in 1e-4 * np.eye(9)]
    assert max(map(abs, slopes)) < 2e-3
    if fair:
        without = toxicity.fit_weights(label, own, swapped, inserted, 8, l2=1e-2, fair=0.0, steps=3000)
        assert abs(w[6]) + abs(w[7]) < 0.5 * (abs(without[0][6]) + abs(without[0][7]))


def test_counterfactual_pairs_enter_the_fit(labelled):
    """On the tables, whose texts name no group: pairs come from mentions put in, and the term changes weights and scores."""
    docs, labels = labelled
    fair, plain = toxicity.fit(docs, labels), toxicity.fit(docs, labels, fair=0.0)
    known = [(r.text, r.toxic) for r in docs.join(labels.where("toxic IS NOT NULL"), "doc_id").collect()]
    assert fair.pairs >= 300 and fair.weights != plain.weights
    named = lambda m: sum(abs(m.weights.get(n, 0.0)) for n in toxicity.NAMES)
    assert named(fair) < 0.5 * named(plain)
    clean = [t for t, y in known if not y]
    with_, without = toxicity.mention_effect(fair, clean), toxicity.mention_effect(plain, clean)
    assert with_["rejected_with_mention"] <= without["rejected_with_mention"] and with_["mean_change"] < without["mean_change"]
    assert with_["rejected_with_mention"] <= with_["rejected"] + 0.001


def test_names_that_share_letters_with_insults_stay_neutral(spark):
    """An insult's leading characters are those of a group's name: the term halves what these lend to the name."""
    rng = random.Random(3)
    rows = []
    for i in range(900):
        words = [f"w{rng.randrange(300)}" for _ in range(30)]
        bad = i % 4 == 0
        rows.append((i, " ".join(words + [f"muslim{rng.choice('abcdefgh')}x"] * bad), int(bad)))
    df = spark.createDataFrame(rows, "doc_id long, text string, toxic int")
    texts = [f"w1 w2 w{i}" for i in range(50)]
    models = {fair: toxicity.fit(df.select("doc_id", "text"), df.select("doc_id", "toxic"), fair=fair) for fair in (0.0, 20.0)}
    rise = {f: (m.score([t + " muslim" for t in texts], {}) - m.score(texts, {})).mean() for f, m in models.items()}
    assert rise[0.0] > 0.01 and abs(rise[20.0]) < 0.5 * rise[0.0]


def test_scores_equal_brute_force(labelled):
    docs, labels = labelled
    model = toxicity.fit(docs, labels)
    rows = {r.doc_id: r for r in toxicity.scores(docs, model).collect()}
    import re

    for r in docs.limit(200).collect():
        words = set(re.findall(r"[^\W\d_]+", (r.text or "").lower()))
        found = words | {w[:n] + "*" for w in words for n in (4, 5, 6) if len(w) > n}
        z = model.bias + sum(w for f, w in model.weights.items() if f in found)
        assert abs(rows[r.doc_id].score - 1 / (1 + np.exp(-z))) < 1e-9 and rows[r.doc_id].predicted == int(rows[r.doc_id].score >= 0.7)


def test_model_edges(spark, labelled):
    docs, labels = labelled
    odd = spark.createDataFrame([(1, None, 1), (2, "", 2), (1, "idiot " * 50_000, 3), (None, "x", 4)], "doc_id long, text string, __label int")
    none = labels.limit(0)
    for run in (toxicity.toxicity, quality.quality):
        rows = run(odd, none).collect()
        assert len(rows) == 4 and all(r.score < 1e-6 and r.predicted == 0 for r in rows)
        assert run(odd.limit(0), labels).count() == 0
    kept = toxicity.drop_toxic(odd, none)
    assert kept.columns == odd.columns and kept.count() == 4
    ones = labels.select("doc_id", F.lit(1).alias("quality"))
    assert all(r.predicted == 1 for r in quality.quality(docs.limit(20), ones).collect())


def test_quality_held_out_and_native_scores(labelled):
    docs, labels = labelled
    model = quality.fit(docs, labels)
    assert 0 < len(model.rules) < 60
    df = quality.quality(docs, labels)
    pairs = held_out(df.collect(), labels, "quality")
    assert np.mean([t == p for t, p, _ in pairs]) >= 0.9
    assert "Python" not in df._jdf.queryExecution().executedPlan().toString()


def test_rules_as_columns_equal_rules_in_numpy(spark, labelled):
    docs, labels = labelled
    model = quality.fit(docs, labels)
    stats = quality.statistics(docs["text"])
    rows = docs.select(*(c.alias(n) for n, c in stats.items()), model.column(stats).alias("__score")).toPandas()
    table = {n: rows[n].to_numpy(float) for n in stats}
    z = model.bias + sum(w * r.holds(table) for r, w in model.rules)
    assert np.allclose(1 / (1 + np.exp(-z)), rows["__score"])


def test_media_round_trip():
    rng = random.Random(0)
    texts = ["", None, "a", "x" * 64, "x" * 65, "é🙂" * 100, "\x00\x7f" * 70] + ["".join(rng.choices("abc XYZ\n\xff", k=rng.randrange(3000))) for _ in range(40)]
    payloads = [media.payload(t)[1] for t in texts] + [os.urandom(64 * 33), bytes([255, 0]) * 320, os.urandom(64 * 8200)]
    assert all(len(p) % 64 == 0 and p for p in payloads)
    files = media.encode(payloads)
    back = [b"".join(t.tobytes() for _, t in frames) for frames in media.thumbnails(files)]
    assert back == payloads
    assert media.encode(payloads[:1]) == files[:1] and all(f[:2] == b"\xff\xd8" and f[-2:] == b"\xff\xd9" for f in files)
    assert len(media.thumbnails(files[-1:])[0]) == 2
    with pytest.raises(ValueError):
        media.Frame(b"\xff\xd8\xff\xc2\x00\x0b\x08\x00\x08\x00\x08\x01\x01\x11\x00", 0)


def test_reader_handles_other_baseline_files():
    """A file with AC terms, another Huffman table and no restart markers: DC terms still come out."""
    dc, ac = {0: 2, 1: 2, 2: 3, 3: 3, 4: 3, 5: 4, 6: 5, 7: 6}, {0x00: 2, 0x01: 2, 0xF0: 3, 0x11: 3}
    codes, bits = media.canonical(dc), ""
    acs = media.canonical(ac)
    word = lambda c: format(c[0], f"0{c[1]}b")
    levels, last = [5, -3, 40, 40, 0, 7], 0
    for i, v in enumerate(levels):
        d, last = v - last, v
        n = abs(d).bit_length()
        bits += word(codes[n]) + (format(d if d > 0 else d + (1 << n) - 1, f"0{n}b") if n else "")
        if i % 2:
            bits += word(acs[0xF0]) + word(acs[0x11]) + "1" + word(acs[0x01]) + "0"
        bits += word(acs[0x00])
    bits += "1" * (-len(bits) % 8)
    scan = bytes(int(bits[i : i + 8], 2) for i in range(0, len(bits), 8)).replace(b"\xff", b"\xff\x00")
    import struct

    head = b"\xff\xd8" + media._segment(0xDB, bytes([0, 16, *[3] * 63])) + media._segment(0xC0, struct.pack(">BHHB", 8, 16, 20, 1) + b"\1\x11\0")
    head += media._huffman_segment(0x00, dc) + media._huffman_segment(0x10, ac) + media._segment(0xDA, b"\1\1\0\0\x3f\0")
    ((_, thumb),) = media.thumbnails([head + scan + b"\xff\xd9"])[0]
    assert thumb.tolist() == [[138, 122, 208], [208, 128, 142]]


def coded(levels, last, dc, ac, high):
    """Bits of one block with some AC terms."""
    d, out = levels - last, ""
    word = lambda c: format(c[0], f"0{c[1]}b")
    n = abs(d).bit_length()
    out += word(dc[n]) + (format(d if d > 0 else d + (1 << n) - 1, f"0{n}b") if n else "")
    return out + (word(ac[0x31]) + "1" if high else "") + word(ac[0x00])


@pytest.mark.parametrize("factors", [((2, 2), (1, 1), (1, 1)), ((2, 1), (1, 1), (1, 1)), ((1, 1), (1, 1), (1, 1)), ((1, 2), (1, 1), (1, 2)), ((2, 2),)])
@pytest.mark.parametrize("apart, interval", [(False, 0), (False, 3), (True, 0)])
def test_reader_takes_luminance_of_colour_files(factors, apart, interval):
    """Interleaved and separate scans, subsampled colour, odd sizes, restart intervals, one table per kind of component."""
    import struct

    rng = random.Random(str(factors) + str(interval))
    width, height = 53, 37
    dcs = [{0: 2, 1: 2, 2: 3, 3: 3, 4: 3, 5: 4, 6: 5, 7: 6, 8: 6}, {k: 4 for k in range(9)}]
    acs = [{0x00: 1, 0x31: 2}, {0x00: 3, 0x31: 1}]
    dc, ac = [media.canonical(x) for x in dcs], [media.canonical(x) for x in acs]
    most = [max(f[k] for f in factors) for k in (0, 1)]
    units = (-(-height // (8 * most[1])), -(-width // (8 * most[0])))
    planes = [np.array([[rng.randint(-60, 60) for _ in range(units[1] * f[0])] for _ in range(units[0] * f[1])]) for f in factors]
    covered = [(-(-(-(-height * f[1] // most[1])) // 8), -(-(-(-width * f[0] // most[0])) // 8)) for f in factors]

    def scan(members):
        bits, out, last = "", b"", [0] * len(factors)
        if len(members) == 1:
            c = members[0]
            order = [[(c, y, x)] for y in range(covered[c][0]) for x in range(covered[c][1])]
        else:
            order = [[(c, my * factors[c][1] + y, mx * factors[c][0] + x) for c in members for y in range(factors[c][1]) for x in range(factors[c][0])] for my in range(units[0]) for mx in range(units[1])]
        for i, unit in enumerate(order):
            for c, y, x in unit:
                bits += coded(int(planes[c][y, x]), last[c], dc[c > 0], ac[c > 0], rng.random() < 0.5)
                last[c] = int(planes[c][y, x])
            if i == len(order) - 1 or (interval and i % interval == interval - 1):
                bits += "1" * (-len(bits) % 8)
                out += bytes(int(bits[k : k + 8], 2) for k in range(0, len(bits), 8)).replace(b"\xff", b"\xff\x00")
                bits, last = "", [0] * len(factors)
                if i < len(order) - 1:
                    out += bytes([0xFF, 0xD0 + i // interval % 8])
        head = bytes([len(members)]) + b"".join(bytes([c + 1, 0x11 * (c > 0)]) for c in members)
        return media._segment(0xDA, head + b"\0\x3f\0") + out

    data = b"\xff\xd8" + media._segment(0xE0, b"JFIF\0") + media._segment(0xDB, bytes([0, 8, *[3] * 63, 1, 5, *[3] * 63]))
    data += media._segment(0xC0, struct.pack(">BHHB", 8, height, width, len(factors)) + b"".join(bytes([c + 1, f[0] << 4 | f[1], c > 0]) for c, f in enumerate(factors)))
    for k in (0, 1):
        data += media._huffman_segment(k, dcs[k]) + media._huffman_segment(0x10 | k, acs[k])
    if interval:
        data += media._segment(0xDD, struct.pack(">H", interval))
    groups = [[c] for c in reversed(range(len(factors)))] if apart else [list(range(len(factors)))]
    data += b"".join(map(scan, groups)) + b"\xff\xd9"
    ((frame, thumb),) = media.thumbnails([data])[0]
    assert (frame.width, frame.height) == (width, height)
    assert (thumb.astype(int) - 128).tolist() == planes[0][: covered[0][0], : covered[0][1]].tolist()


def test_media_columns(spark):
    texts = ["", None, "abc", "abc", "é" * 5000]
    df = spark.createDataFrame([(i, t, b"") for i, t in enumerate(texts)], "doc_id long, text string, media binary")
    rows = {r.doc_id: r for r in media.media_columns(df, keep_media=True, step=100).collect()}
    for i, t in enumerate(texts):
        n, p = media.payload(t)
        r = rows[i]
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (n, len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-64:]))
        assert (r.media_bytes, r.media_sha256) == (len(r.media), hashlib.sha256(bytes(r.media)).hexdigest())
    assert rows[2][1:] == rows[3][1:] and rows[0][1:] == rows[1][1:]
    assert media.media_columns(df.limit(0)).count() == 0


PAGES = [
    (1, "http://a.b/c?d#e", "x" * 999), (2, "https://a.b", "x" * 999), (3, "u\r\nrl", "y" * 1000), (9, None, "y" * 1000), (4, "", "y" * 1000), (5, "http://q", None), (6, "http://q", ""),
    (7, "http://é.x/ü", "WARC/1.1\r\n\r\nContent-Length: 5\r\n\r\n" + "é\r\n\r\n" * 300), (8, "http://z", "WARC/1.1\r\n\r\nContent-Length: 5\r\n\r\n" + "é\r\n\r\n" * 300), (10, "http://big", "b" * 300_000),
]


def test_captures(spark):
    df = spark.createDataFrame([(*p, "k", 1) for p in PAGES], "page_id long, url string, html string, capture string, row int")
    rows = {r.page_id: r for r in warc.captures(df).collect()}
    assert len(rows) == len(PAGES)
    for i, _, html in PAGES:
        data = (html or "").encode()
        same = [j for j, _, h in PAGES if (h or "").encode() == data]
        revisit = len(data) >= 1000 and max(same) != i
        r = rows[i]
        assert (r.payload_bytes, r.payload_digest) == (len(data), hashlib.sha1(data).hexdigest())
        assert (r.record_type, r.refers_to) == (("revisit", max(same)) if revisit else ("response", None))
    assert warc.captures(df.limit(0)).count() == 0
    repeated = warc.captures(df.unionByName(df)).groupBy("record_type").count().collect()
    assert sum(r["count"] for r in repeated) == 2 * len(PAGES)


@pytest.mark.parametrize("hot", [0, 2, 10**9])
def test_hot_payloads_find_the_same_holders(spark, hot):
    df = spark.createDataFrame([(*p, "k") for p in PAGES], "page_id long, url string, html string, extra string")
    held = warc.holders(df, "page_id", "html")
    rows = df.select(F.col("page_id").alias("id"), F.coalesce("html", F.lit("")).alias("body"), F.monotonically_increasing_id().alias("row"))
    rows = rows.withColumns({"digest": F.sha1("body"), "n": F.octet_length("body")})
    got = warc.with_holders(rows, held, hot)
    assert got.columns[:5] == ["id", "body", "row", "digest", "n"]
    assert sorted((r.id, r.h_id) for r in got.where("h_digest IS NOT NULL").collect()) == [(3, 9), (4, 9), (7, 8), (8, 8), (9, 9)]
    assert got.count() == len(PAGES)


def test_assembled_rows_are_nested(spark):
    df = spark.createDataFrame(PAGES, "page_id long, url string, html string")
    path = storage.new_path(spark, "warc-test")
    warc.write_archives(df, path)
    rows = warc.assemble(warc.read_records(spark, path, payloads=True)).collect()
    assert len(rows) == len(PAGES) and all(r.request and r.response and r.metadata for r in rows)
    by = {int(r.metadata.fields["pageId"]): r for r in rows}
    assert bytes(by[7].response.payload) == b"" or by[7].response.type == "response"
    assert bytes(by[8].response.payload).decode() == PAGES[8][2] and by[7].response.refers_to == by[8].response.record_id
    assert all(r.response.digest == r.response.payload_digest for r in rows if r.response.type == "response")


def test_archive_parser():
    record = b"WARC/1.0\r\nWARC-Type: resource\r\ncontent-length: 7\r\n\r\na\r\n\r\nbc\r\n\r\n"
    data = gzip.compress(record) + gzip.compress(record * 3)
    got = list(warc.parse(warc.inflated(memoryview(data), 10)))
    assert len(got) == 4 and all(b == b"a\r\n\r\nbc" and h["warc-type"] == "resource" for h, b in got)
    with pytest.raises(ValueError):
        list(warc.parse(iter([record[:-9]])))
    with pytest.raises(ValueError):
        list(warc.parse(iter([b"HTTP/1.1 200\r\n\r\n"])))


def test_pipeline_equals_its_stages(spark):
    sf = SF
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    sizes = [docs.count()]
    for name, stage in corpus_pipeline.STAGES[:-1]:
        columns = docs.columns
        docs = storage.materialize(stage(spark, docs, sf), name)
        assert docs.columns == columns
        sizes.append(docs.count())
    assert sizes[0] > sizes[1] > sizes[2] >= sizes[3] > 0
    last = corpus_pipeline.STAGES[-1][1](spark, docs, sf)
    key = lambda df: sorted((r.doc_id, r.piece, r.length, r.ids_crc32) for r in df.collect())
    assert key(last) == key(corpus_pipeline.run(spark, sf))


def test_pipeline_stages_on_odd_and_empty_rows(spark):
    sf = "/root/testdata/sf0.001"
    rows = [(1, None, "en", "a", 0), (2, "", None, None, 0), (2, "", None, None, 0), (3, "same words here again", "en", "a", 5), (4, "same  words here again", "en", "b", None), (5, "w" * 100_000, "en", "a", 1)]
    odd = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, odd.limit(0), sf).count() == 0
        assert stage(spark, odd, sf).count() > 0


@pytest.mark.parametrize("name", sorted(queries.oracle_sql()))
def test_query_equals_sql(spark, duck, name):
    import sys

    sys.path.insert(0, os.path.dirname(os.path.dirname(__file__)))
    from compare import duck_rows, spark_rows

    assert spark_rows(queries.queries()[name](spark, "/root/testdata/sf0.001")) == duck_rows(duck, queries.oracle_sql()[name])


def test_feature_sees_all_frames(spark):
    """Texts that differ only past the first frame have different features."""
    from dnfblock.llm import media

    start = "ab" * (media.WIDTH * media.MOST_ROWS // 2)
    docs = spark.createDataFrame([(1, start + "z" * 300_000), (2, start + "!" * 300_000)], "doc_id long, text string")
    found = {r.doc_id: r.feature for r in media.media_columns(docs).collect()}
    assert found[1] != found[2] and all(f.endswith(":2") for f in found.values())
