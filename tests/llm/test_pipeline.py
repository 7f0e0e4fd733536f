"""The pipeline against plain Python, stage by stage, on documents whose right decisions are known."""

import random
import re

import public_tokenizers
import pytest
from tokenizers import Tokenizer

import corpus_pipeline
from dnfblock import storage

INSULTS = ["idiot", "moron", "scum", "trash"]


def planted(seed=1):
    """Documents, labels, and the ids of toxic texts, groups of exact copies and groups of near copies."""
    rng = random.Random(seed)
    words = [f"w{chr(97 + i % 26)}{i}" for i in range(4000)]
    docs, toxic, exact, near = [], set(), [], []

    def add(text):
        docs.append((len(docs), text, "en", f"s{rng.randrange(3)}", len(text)))
        return docs[-1][0]

    for i in range(420):
        body = rng.choices(words, k=rng.randint(60, 160))
        if i % 6 == 0:
            for w in rng.sample(INSULTS, 2):
                body.insert(rng.randrange(len(body)), w)
            toxic.add(add(" ".join(body)))
        elif i % 25 == 1:
            text = " ".join(body)
            exact.append({add(text), add(text.replace(" ", "  ", 3)), add(text + "\n")})
        elif i % 25 == 2:
            body = rng.choices(words, k=200)
            group = {add(" ".join(body))}
            for _ in range(3):
                other = list(body)
                other[rng.randrange(200)] = "changed"
                group.add(add(" ".join(other)))
            near.append(group)
        else:
            add(" ".join(body))
    labels = [(d[0], 1, int(d[0] in toxic)) for d in docs if d[0] % 10 < 8]
    return docs, labels, toxic, exact, near


def grams(text):
    w = text.lower().split()
    return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))}


@pytest.fixture(scope="module")
def stages(spark, tmp_path_factory):
    """What goes into and comes out of each stage."""
    docs, labels, toxic, exact, near = planted()
    sf = f"file://{tmp_path_factory.mktemp('sf')}"
    spark.createDataFrame(docs, "doc_id long, text string, lang string, source string, n_chars long").repartition(3).write.parquet(f"{sf}/documents.parquet")
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{sf}/labels.parquet")
    frame, out = spark.read.parquet(f"{sf}/documents.parquet"), {"documents": docs}
    for name, stage in corpus_pipeline.STAGES:
        frame = storage.materialize(stage(spark, frame, sf), name)
        out[name] = [tuple(r) for r in frame.collect()]
    final = sorted(map(tuple, corpus_pipeline.run(spark, sf).select("doc_id", "piece", "length", "ids_crc32").collect()))
    return out, toxic, exact, near, final


def test_toxic_documents_go_and_clean_ones_stay(stages):
    out, toxic, *_ = stages
    assert {r[0] for r in out["toxicity"]} == {r[0] for r in out["documents"]} - toxic


def test_one_of_each_group_of_copies_stays(stages):
    out, _, exact, _, _ = stages
    best = {}
    for i, text, *_ in out["toxicity"]:
        form = re.sub(r"[\x20\x09-\x0D]", "", text)
        best[form] = min(best.get(form, (0, 0)), (-len(text), i)) if form in best else (-len(text), i)
    kept = {r[0] for r in out["exact_dedup"]}
    assert kept == {i for _, i in best.values()} and all(len(kept & g) == 1 for g in exact)


def test_one_of_each_group_of_near_copies_stays(stages):
    out, _, _, near, _ = stages
    before, kept = {r[0]: grams(r[1]) for r in out["exact_dedup"]}, {r[0] for r in out["simhash_near_dedup"]}
    alike = lambda a, b: 5 * len(before[a] & before[b]) >= 4 * len(before[a] | before[b])
    assert all(len(kept & g) == 1 for g in near)
    assert kept == before.keys() - set().union(*near) | {i for g in near for i in kept & g}
    assert all(any(alike(a, b) for b in before if a != b) for a in before.keys() - kept)


def test_sources_are_mixed_to_their_weights(stages):
    out = stages[0]
    size = lambda rows, s: sum(len(r[1].split()) for r in rows if r[3] == s)
    own = [size(out["simhash_near_dedup"], f"s{i}") for i in range(3)]
    assert all(sum(own) * (i + 1) / 6 < 3 * own[i] for i in range(3))
    texts = {r[0]: r for r in out["simhash_near_dedup"]}
    times = {}
    for r in out["mix_sources"]:
        assert texts[r[0]] == r
        times[r[0]] = times.get(r[0], 0) + 1
    assert max(times.values()) <= 3
    for i in range(3):
        assert 0 <= sum(own) * (i + 1) / 6 - size(out["mix_sources"], f"s{i}") < 160


def test_sequences_hold_every_token_once(stages):
    from test_text_ops import best_fit_decreasing

    out, *_, final = stages
    library = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    want = sorted((r[0], len(library.encode(r[1], add_special_tokens=False).ids) + 1) for r in out["mix_sources"])
    got = sorted((r[0], r[3]) for r in out["best_fit_packing"])
    assert got == want and all(n <= 2048 for _, n in got)
    by = {}
    for doc, piece, start, length, crc, sequence, offset in out["best_fit_packing"]:
        by.setdefault(sequence, []).append((offset, length))
    for parts in by.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= 2048
    assert len(by) == best_fit_decreasing([n for _, n in got], 2048)
    assert final == sorted((r[0], r[1], r[3], r[4]) for r in out["best_fit_packing"])
