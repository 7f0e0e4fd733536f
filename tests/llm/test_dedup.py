"""Exact copies and near copies against brute force; odd rows."""

import hashlib
import random
import re

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from dnfblock.llm import components, exact_dedup, shingles, simhash

BLANK = re.compile(r"[\x20\x09-\x0D]")
SCHEMA = "doc_id long, text string, digest string, n_points int, fp long, __rank int"
ODD = [
    (1, "a b", "x", 1, 1, 1), (2, "ab", "y", 2, 2, 2), (3, "a  b", None, 3, 3, 3), (4, None, "z", 4, 4, 4), (5, "", "", 5, 5, 5), (6, " \t\n\x0b\f\r", "", 6, 6, 6),
    (7, "AB", "", 7, 7, 7), (8, "a b", "", 8, 8, 8), (9, "x" * 200_000, "", 9, 9, 9), (10, "x" * 200_000 + " ", "", 1, 1, 1), (11, "ab ", "", 1, 1, 1), (None, "ab", "", 1, 1, 1),
]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame(ODD, SCHEMA)


def brute(rows):
    groups = {}
    for doc, text in rows:
        groups.setdefault(BLANK.sub("", text or ""), []).append((-len(text or ""), doc is None, doc or 0))
    return {k: (min(v)[2], len(v)) for k, v in groups.items()}


def test_groups_equal_brute_force(odd):
    known = brute([(r[0], r[1]) for r in ODD])
    rows = exact_dedup.group_copies(odd).collect()
    assert len(rows) == len(ODD) and sum(r.kept for r in rows) == len(known)
    text = {r[0]: r[1] for r in ODD}
    for r in rows:
        form = BLANK.sub("", text[r.doc_id] or "")
        assert (r.keep_id, r.group_size) == known[form]
        assert r.text_sha256 == hashlib.sha256(form.encode()).hexdigest()
        assert r.kept == (r.doc_id == r.keep_id)


def test_drop_keeps_columns_and_one_of_each(odd):
    out = exact_dedup.drop_copies(odd)
    assert out.columns == odd.columns
    assert {r.doc_id for r in out.collect()} == {3, 6, 7, 8, 10}


def test_repeated_rows_and_empty_table(spark, odd):
    twice = odd.unionByName(odd)
    assert sum(r.kept for r in exact_dedup.group_copies(twice).collect()) == 5
    assert exact_dedup.drop_copies(twice).count() == 5
    assert exact_dedup.group_copies(odd.limit(0)).count() == 0 and exact_dedup.drop_copies(odd.limit(0)).count() == 0


def test_collisions_are_split(spark, odd, monkeypatch):
    """With a hash that collides for all, the byte comparison still tells texts apart."""
    md5 = F.md5
    monkeypatch.setattr(exact_dedup.F, "md5", lambda c: md5(F.lit("same")))
    rows = exact_dedup.group_copies(odd).collect()
    assert sum(r.kept for r in rows) == 5


@pytest.mark.parametrize("collide", [False, True])
def test_hot_groups_are_spread(spark, monkeypatch, collide):
    """A third of all rows are copies of one text: same groups, and no task of the join has them all."""
    if collide:
        md5 = F.md5
        monkeypatch.setattr(exact_dedup.F, "md5", lambda c: md5(F.substring(c, 1, 1)))
    monkeypatch.setattr(exact_dedup, "HOT", 20)
    rows = [(i, "hot text" if i % 3 == 0 else f"h{i // 2}" if i % 2 else f"t {i // 4}") for i in range(900)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(6)
    known = brute(rows)
    for r in exact_dedup.group_copies(df).collect():
        assert (r.keep_id, r.group_size) == known[BLANK.sub("", rows[r.doc_id][1])]
    keys = exact_dedup.content_keys(df)
    hot = keys.groupBy("digest").count().where("count > 100")
    spread = exact_dedup.salted(keys, hot).where("hot").groupBy("digest", "salt").count()
    assert spread.agg(F.max("count")).first()[0] < 100 and exact_dedup.every_salt(hot, hot).count() == exact_dedup.SALTS * hot.count()


def fingerprint(text):
    words = (text or "").encode().lower().split()
    if not words:
        return 0
    grams = [b" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))]
    h = [xxhash.xxh64_intdigest(g, 42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def classes(fps, radius=3):
    up = list(range(len(fps)))

    def find(i):
        while up[i] != i:
            i = up[i]
        return i

    for i in range(len(fps)):
        for j in range(i):
            if (fps[i] ^ fps[j]).bit_count() <= radius:
                a, b = find(i), find(j)
                up[max(a, b)] = min(a, b)
    return [find(i) for i in range(len(fps))]


def test_fingerprints(spark, odd):
    texts = ["", None, "One", "one two", "A b C d e f", "É é x y z", "a b c d", " ".join(map(str, range(5000))), "x " * 70_000]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r.doc_id: r.fp & (2**64 - 1) for r in simhash.fingerprints(df).collect()}
    assert got == {i: fingerprint(t) for i, t in enumerate(texts)}
    # the hash is Spark's own xxhash64 of the shingle
    assert spark.range(1).select(F.xxhash64(F.lit("one"))).first()[0] & (2**64 - 1) == xxhash.xxh64_intdigest(b"one", 42)


def test_components_equal_brute_force(spark):
    rng = random.Random(1)
    base = [" ".join(rng.choices([f"w{i}" for i in range(300)], k=120)) for _ in range(25)]
    texts = []
    for b in base:
        texts.append(b)
        for _ in range(rng.randrange(6)):
            words = b.split()
            words[rng.randrange(len(words))] = "other"
            texts.append(" ".join(words))
    texts += ["", None, "  ", "lone"]
    ids = rng.sample(range(1000), len(texts))
    rows = simhash.near_duplicates(spark.createDataFrame(list(zip(ids, texts)), "doc_id long, text string")).collect()
    fps = [fingerprint(t) for t in texts]
    root = classes(fps)
    low = {r: min(i for i, x in zip(ids, root) if x == r) for r in set(root)}
    assert {r.doc_id: (r.fingerprint, r.component_id) for r in rows} == {i: (f"{f:016x}", low[x]) for i, f, x in zip(ids, fps, root)}


def planted_fingerprints(seed):
    """Random fingerprints, chains of neighbours at 0 to 4 bits, and a ball of them."""
    rng = random.Random(seed)
    fps = [0, 2**64 - 1, 7]
    for _ in range(60):
        f = rng.getrandbits(64)
        fps.append(f)
        for _ in range(4):
            g = f
            for b in rng.sample(range(64), rng.randrange(5)):
                g ^= 1 << b
            fps.append(g)
            f = g
    center = rng.getrandbits(64)
    fps += [center ^ (1 << a) ^ (1 << b) for a in range(12) for b in range(a, 12)]
    return list(dict.fromkeys(fps))


def roots_of(fps, links):
    at = {int(np.uint64(f).astype(np.int64)): i for i, f in enumerate(fps)}
    up = list(range(len(fps)))

    def find(i):
        while up[i] != i:
            i = up[i]
        return i

    for r in links:
        a, b = find(at[r.a]), find(at[r.b])
        up[max(a, b)] = min(a, b)
    return [find(i) for i in range(len(fps))]


def as_table(spark, fps):
    return spark.createDataFrame([(int(np.uint64(f).astype(np.int64)),) for f in fps], "fp long")


@pytest.mark.parametrize("tile_rows", [2, 512])
@pytest.mark.parametrize("banded, parts, radius", [(False, 4, 3), (True, 4, 3), (False, 8, 3), (True, 3, 2), (False, 2, 5)])
def test_tiles_miss_no_link(spark, monkeypatch, tile_rows, banded, parts, radius):
    monkeypatch.setattr(simhash, "_FEW", 8 if tile_rows == 512 else 512)
    fps = planted_fingerprints(2)
    links = simhash.links(as_table(spark, fps), banded, parts, tile_rows, radius).collect()
    assert roots_of(fps, links) == classes(fps, radius)


def test_tiles_are_skipped_by_population_counts(spark, monkeypatch):
    """Most pairs are never compared; the pairs of tiles that are, are needed: without neighbours links are lost."""
    rng = random.Random(4)
    fps = planted_fingerprints(5) + [rng.getrandbits(64) for _ in range(3000)]
    counts = lambda f: [(f >> s & 0xFFFF).bit_count() for s in range(0, 64, 16)]
    tiles = simhash.tiled(as_table(spark, fps)).persist()
    compared = 0
    for r in simhash.tile_pairs(tiles).collect():
        a, b = counts(r.own[0] & (2**64 - 1)), counts(r.other[0] & (2**64 - 1))
        assert sum(abs(x - y) for x, y in zip(a, b)) <= 3
        compared += len(r.own) * (len(r.own) - 1) // 2 if r.same else len(r.own) * len(r.other)
    assert 0 < compared < 0.1 * len(fps) ** 2 / 2
    monkeypatch.setattr(simhash, "neighbours", lambda parts, radius: [(0,) * parts])
    assert roots_of(fps, simhash.compare_tiles(simhash.tile_pairs(tiles)).collect()) != classes(fps)
    tiles.unpersist()


def test_bands_and_null_ids(spark):
    fps = ["a b c d e", "a b c d e", "", None, "x y z"]
    df = spark.createDataFrame([(None, t) for t in fps] + [(i, t) for i, t in enumerate(fps)], "doc_id long, text string")
    plain = sorted(map(repr, simhash.near_duplicates(df).collect()))
    assert plain == sorted(map(repr, simhash.near_duplicates(df, banded_from=0).collect()))
    assert all(r.component_id is not None for r in simhash.near_duplicates(df).collect())


def test_near_drop_on_odd_rows(odd):
    out = simhash.drop_near_duplicates(odd)
    assert out.columns == odd.columns
    kept = [r.doc_id for r in out.collect()]
    assert len(kept) == len(set(kept)) and {4, None} <= set(kept) and not {5, 6} & set(kept)
    assert simhash.near_duplicates(odd.limit(0)).count() == 0 and simhash.drop_near_duplicates(odd.limit(0)).count() == 0
    twice = simhash.near_duplicates(odd.unionByName(odd))
    assert twice.count() == 2 * len(ODD)


def test_chain_components(spark):
    n = 200
    links = spark.createDataFrame([(i, i + 1) for i in range(n)] + [(500, 400), (7, 7)], "a long, b long")
    roots = {r.node: r.root for r in components.connected_components(links, "a", "b").collect()}
    assert all(roots[i] == 0 for i in range(n + 1)) and roots[400] == roots[500] == 400 and len(roots) == n + 3
    assert components.connected_components(links.limit(0), "a", "b").count() == 0


def grams(text):
    words = text.split()
    return {tuple(words[i : i + 5]) for i in range(max(1, len(words) - 4))}


@pytest.mark.parametrize("pairs, few, tile", [(0, shingles.FEW, 128), (100, 2, 4), (100, 1, 128), (100, 10_000, 128)])
def test_stage_leaves_no_near_copies(spark, monkeypatch, pairs, few, tile):
    """No two texts at a five-word Jaccard of 0.8 or more stay, and each that goes was near another."""
    from corpus_pipeline import drop_near_copies

    monkeypatch.setattr(shingles, "PAIRS_A_ROW", pairs)
    monkeypatch.setattr(shingles, "FEW", few)
    monkeypatch.setattr(shingles, "TILE_ROWS", tile)
    monkeypatch.setattr(shingles, "COLUMNS", 64)
    rng = random.Random(3)
    texts = []
    for _ in range(12):
        words = [f"w{rng.randrange(5000)}" for _ in range(200)]
        for n in (0, 1, 2, 3, 4, 20, *([2] * 20 if len(texts) < 7 else [])):
            new = list(words)
            for at in rng.sample(range(200), n):
                new[at] = f"x{rng.randrange(5000)}"
            texts.append(" ".join(new))
    texts += ["", "short", "short one"]
    near = lambda a, b: 5 * len(grams(a) & grams(b)) >= 4 * len(grams(a) | grams(b))
    out = drop_near_copies(spark, spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string"), "")
    kept = {r.doc_id for r in out.collect()}
    assert out.columns == ["doc_id", "text"] and not [(a, b) for a in kept for b in kept if a < b and near(texts[a], texts[b])]
    fps = [fingerprint(t) for t in texts]
    linked = lambda a, b: near(texts[a], texts[b]) or (fps[a] ^ fps[b]).bit_count() <= 3
    assert all(any(linked(a, b) for b in range(len(texts)) if a != b) for a in range(len(texts)) if a not in kept)
    assert drop_near_copies(spark, out.limit(0), "").count() == 0


def test_near_copies_do_not_depend_on_other_texts(spark):
    """A chain of near texts loses the same ones alone and beside a large group of copies."""
    words = [f"w{i}" for i in range(200)]
    step = lambda ws, at: [f"x{i}" if i in at else w for i, w in enumerate(ws)]
    b = step(words, (20, 60, 100, 140))
    chain = [words, b, step(b, (40, 80, 120, 160))]
    group = [step([f"g{i}" for i in range(200)], (k,)) for k in range(0, 200, 10)]
    make = lambda texts: spark.createDataFrame([(i, " ".join(t)) for i, t in enumerate(texts)], "id long, text string")
    gone = lambda texts: {r.id for r in shingles.near_copies(make(texts)).collect() if r.id < 3}
    assert gone(chain) == gone(chain + group) == {1}
