"""Toxicity: a logistic classifier with counterfactual regularisation.

Features are the words of a text and their leading characters (presence, not counts). The fit
minimises logistic loss, an L2 term, and a counterfactual term over pairs of texts that differ in a
group's name only: squared differences of the two scores, and of their logits, are penalised. A
labelled text that names a group is paired with its copies in which the name is swapped for others of
its kind. A text that names none gets a neutral mention: one name, chosen by a hash of the text,
is put into it; that sentence keeps its label, joins the loss, and is paired with the text as it was and
with the same sentence about another group. A text that merely names a group then scores as it would
without the name. Scoring reads whole texts; it holds the chosen features (at most ``features``) and
nothing of the corpus.

Defined cases: null and empty texts get the score of a text without features; a table without
usable labels, or with one class only, gives every row the class share (0 without labels); repeated
rows get equal scores; a null id falls in fold 0; an empty table gives an empty result; no column but
the text and, for the fold, the id is read.
"""

from __future__ import annotations

import math
import re
import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from dnfblock.llm.training import fold, labelled_sample, sigmoid
from dnfblock.storage import materialize

PARTS, HELD_OUT = 3, 1
THRESHOLD = 0.7
FEATURES = 4096
PREFIXES = (4, 5, 6)
LEAST_GAIN = 10.0
#: Weight of the counterfactual term against the loss.
FAIR = 5.0
#: Names of groups in four languages, by kind; a swap stays inside its kind.
GROUPS = (
    ("women", "men", "girls", "boys"),
    ("woman", "man", "girl", "boy"),
    ("muslim", "christian", "jewish", "hindu", "buddhist", "atheist"),
    ("muslims", "christians", "jews", "hindus", "buddhists", "atheists"),
    ("black", "white", "asian", "latino", "african", "european"),
    ("gay", "lesbian", "straight", "bisexual", "transgender"),
    ("immigrants", "refugees", "citizens", "foreigners"),
    ("old", "young", "disabled", "deaf", "blind"),
    ("frauen", "männer", "mädchen", "jungen"),
    ("muslime", "christen", "juden", "hindus", "buddhisten", "atheisten"),
    ("schwule", "lesben", "heteros", "bisexuelle"),
    ("einwanderer", "flüchtlinge", "bürger", "ausländer"),
    ("femmes", "hommes", "filles", "garçons"),
    ("musulmans", "chrétiens", "juifs", "hindous", "bouddhistes", "athées"),
    ("homosexuels", "lesbiennes", "hétérosexuels", "bisexuels"),
    ("immigrés", "réfugiés", "citoyens", "étrangers"),
    ("mujeres", "hombres", "chicas", "chicos"),
    ("musulmanes", "cristianos", "judíos", "hindúes", "budistas", "ateos"),
    ("homosexuales", "lesbianas", "heterosexuales", "bisexuales"),
    ("inmigrantes", "refugiados", "ciudadanos", "extranjeros"),
)
NAMES = sorted({name for kind in GROUPS for name in kind})
_KIND = {name: kind for kind in reversed(GROUPS) for name in kind}
_WORD = re.compile(r"[^\W\d_]+")


def words_of(text: str | None) -> set[str]:
    return set(_WORD.findall((text or "").lower()))


def features_of(word: str) -> list[str]:
    """A word and its leading characters."""
    return [word, *(f"{word[:n]}*" for n in PREFIXES if len(word) > n)]


@dataclass
class Model:
    """Weights by feature, the score without any, and how many counterfactual pairs the fit had."""

    weights: dict[str, float]
    bias: float
    pairs: int = 0

    def score(self, texts: list[str | None], cache: dict[str, float]) -> np.ndarray:
        """Scores of ``texts``; prefixes of several words of a text count once."""
        out = np.empty(len(texts))
        known = self.weights
        for i, text in enumerate(texts):
            found: set[str] = set()
            for word in words_of(text):
                hit = cache.get(word)
                if hit is None:
                    if len(cache) > 100_000:
                        cache.clear()
                    hit = cache[word] = tuple(f for f in features_of(word) if f in known)
                if hit:
                    found.update(hit)
            out[i] = self.bias + math.fsum(known[f] for f in found)
        return sigmoid(out)


def feature_counts(sample: DataFrame) -> DataFrame:
    """``feature, pos, all``: texts of the sample that have a feature."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pos, every = Counter(), Counter()

        def flush():
            out = pa.RecordBatch.from_arrays(
                [pa.array(list(every), pa.string()), pa.array([pos[f] for f in every], pa.int64()), pa.array(list(every.values()), pa.int64())],
                ["feature", "pos", "all"],
            )
            pos.clear()
            every.clear()
            return out

        for batch in batches:
            for text, label in zip(batch.column(0), batch.column(1).to_pylist()):
                found = {f for w in words_of(text.as_py()) for f in features_of(w)}
                every.update(found)
                if label:
                    pos.update(found)
                if len(every) > 300_000:
                    yield flush()
        yield flush()

    found = sample.select("text", "label").mapInArrow(run, "feature string, pos long, all long")
    return found.groupBy("feature").agg(F.sum("pos").alias("pos"), F.sum("all").alias("all"))


def chosen_features(counts: DataFrame, n_pos: int, n_all: int, most: int, least_gain: float = LEAST_GAIN) -> list[str]:
    """Features whose label share differs from the overall one by more than chance allows.

    The measure is the log-likelihood ratio of the two shares, in nats; at ``least_gain`` a feature
    without any relation to the label passes about once in twenty thousand. Names of groups are
    always among the features.
    """
    share, p = n_pos / n_all, F.col("pos") / F.col("all")
    term = lambda x, y: F.when(x > 0, x * F.ln(x / y)).otherwise(0.0)
    gain = F.col("all") * (term(p, F.lit(share)) + term(1 - p, F.lit(1 - share)))
    top = counts.where((gain >= least_gain) & ~F.col("feature").isin(NAMES))
    top = top.orderBy(F.round(gain, 9).desc(), "feature").limit(most - len(NAMES)).select("feature")
    return [r[0] for r in top.collect()] + NAMES


def mentions(text: str | None) -> tuple[str, str]:
    """Two names of one kind, chosen by a hash of the text."""
    pick = zlib.crc32((text or "").encode())
    kind = GROUPS[pick % len(GROUPS)]
    first, step = pick // len(GROUPS) % len(kind), 1 + pick // 997 % (len(kind) - 1)
    return kind[first], kind[(first + step) % len(kind)]


def counterfactuals(words: set[str], text: str | None) -> tuple[list[set[str]], list[set[str]]]:
    """The words of a text with a name swapped, for each name in it; if it has none, with two names put in, one each."""
    named = sorted(words & _KIND.keys())
    if named:
        return [words - {w} | {other} for w in named for other in _KIND[w] if other != w], []
    return [], [words | {w} for w in mentions(text)]


def design(sample: DataFrame, features: list[str]):
    """Label, feature positions, swapped and inserted texts of each sampled text, in order of id.

    The latter two are rows of what changes: p + 1 where position p is new, -(p + 1) where it goes.
    """
    at = {f: i for i, f in enumerate(features)}

    def positions(words: set[str]) -> set[int]:
        return {at[f] for w in words for f in features_of(w) if f in at}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for text in batch.column(1):
                words = words_of(text.as_py())
                own = positions(words)
                change = lambda other: [p + 1 for p in sorted(other - own)] + [-p - 1 for p in sorted(own - other)]  # noqa: B023, E731
                made = counterfactuals(words, text.as_py())
                rows.append((sorted(own), *([change(positions(w)) for w in x] for x in made)))
            own, swapped, inserted = zip(*rows) if rows else ((), (), ())
            kinds = [pa.list_(pa.int32()), *[pa.list_(pa.list_(pa.int32()))] * 2]
            columns = [pa.array(list(c), k) for c, k in zip((own, swapped, inserted), kinds)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), *columns], ["id", "label", "own", "swapped", "inserted"])

    rows = sample.select("id", "text", "label").mapInArrow(
        run, "id long, label int, own array<int>, swapped array<array<int>>, inserted array<array<int>>"
    )
    made = rows.toPandas()
    made["size"] = made["own"].map(len)
    made = made.sort_values(["id", "label", "size"], kind="stable")
    return made["label"].to_numpy(), *(list(made[c]) for c in ("own", "swapped", "inserted"))


class _Rows:
    """Rows of zeros and ones by position."""

    def __init__(self, rows: list, width: int):
        self.row = np.repeat(np.arange(len(rows)), [len(r) for r in rows])
        self.col = np.concatenate([np.asarray(r, np.int64) for r in rows]) if rows else np.empty(0, np.int64)
        self.n, self.width = len(rows), width

    def dot(self, w: np.ndarray) -> np.ndarray:
        return np.bincount(self.row, w[self.col], self.n)

    def back(self, g: np.ndarray) -> np.ndarray:
        return np.bincount(self.col, g[self.row], self.width)


class _Changed:
    """Texts that differ from rows of a :class:`_Rows` by signed positions."""

    def __init__(self, base: list[int], changes: list, width: int):
        self.base, self.n, self.width = np.asarray(base, np.int64), len(base), width
        self.row = np.repeat(np.arange(self.n), [len(c) for c in changes])
        signed = np.concatenate([np.asarray(c, np.int64) for c in changes]) if len(self.row) else np.empty(0, np.int64)
        self.col, self.sign = np.abs(signed) - 1, np.sign(signed)

    def logits(self, own: np.ndarray, w: np.ndarray) -> np.ndarray:
        return own[self.base] + np.bincount(self.row, self.sign * w[self.col], self.n)

    def back(self, g: np.ndarray) -> np.ndarray:
        return np.bincount(self.col, self.sign * g[self.row], self.width)


def fit_weights(
    label: np.ndarray, own: list, swapped: list, inserted: list, width: int, l2: float = 2e-5, fair: float = FAIR, steps: int = 400
) -> tuple[np.ndarray, float, int]:
    """Weights, bias and the number of pairs, by full-batch accelerated descent; classes weigh equally in the loss."""
    x = _Rows(own, width)
    put = [(i, rows[0]) for i, rows in enumerate(inserted) if len(rows)]
    pairs = [(i, (), row) for i, rows in enumerate(swapped) for row in rows]
    pairs += [(i, rows[0], other) for i, rows in enumerate(inserted) if len(rows) for other in ((), rows[1])]
    more = _Changed([i for i, _ in put], [c for _, c in put], width)
    a, b = (_Changed([p[0] for p in pairs], [p[k] for p in pairs], width) for k in (1, 2))
    y = label.astype(float)
    y_more = y[more.base]
    n_pos, n_neg = y.sum() + y_more.sum(), (1 - y).sum() + (1 - y_more).sum()
    weigh = lambda y: np.where(y > 0, 0.5 / max(n_pos, 1), 0.5 / max(n_neg, 1))
    weight, weight_more = weigh(y), weigh(y_more)
    w, bias, m, mb = np.zeros(width), 0.0, np.zeros(width), 0.0
    v, vb = np.zeros(width), 0.0
    for t in range(1, steps + 1):
        z = x.dot(w) + bias
        g = weight * (sigmoid(z) - y)
        more_g = weight_more * (sigmoid(more.logits(z, w)) - y_more)
        g += np.bincount(more.base, more_g, x.n)
        gw = more.back(more_g) + l2 * w
        if pairs and fair:
            za, zb = a.logits(z, w), b.logits(z, w)
            p, q = sigmoid(za), sigmoid(zb)
            d = 2 * fair * (p - q) / len(pairs)
            apart = 0.2 * fair * (za - zb) / len(pairs)  # where scores saturate, logits still differ
            ga, gb_ = d * p * (1 - p) + apart, -d * q * (1 - q) - apart
            gw += a.back(ga) + b.back(gb_)
            g += np.bincount(a.base, ga + gb_, x.n)
        gw, gb = gw + x.back(g), g.sum()
        m, mb = 0.9 * m + 0.1 * gw, 0.9 * mb + 0.1 * gb
        v, vb = 0.999 * v + 0.001 * gw * gw, 0.999 * vb + 0.001 * gb * gb
        c1, c2 = 1 - 0.9**t, 1 - 0.999**t
        rate = 0.05 * (1 - t / (steps + 1)) + 0.002
        w = w - rate * (m / c1) / (np.sqrt(v / c2) + 1e-8)
        bias = bias - rate * (mb / c1) / (math.sqrt(vb / c2) + 1e-8)
    return w, bias, len(pairs)


def fit(
    docs: DataFrame, labels: DataFrame, label_col: str = "toxic", id_col: str = "doc_id", text_col: str = "text",
    features: int = FEATURES, fair: float = FAIR,
) -> Model:
    """Fit on a bounded sample of the labelled rows that are not held out."""
    sample = materialize(labelled_sample(docs, labels, label_col, PARTS, HELD_OUT, id_col, text_col), "toxicity-sample")
    n_pos, n_all = sample.agg(F.coalesce(F.sum("label"), F.lit(0)), F.count("*")).first()
    if not 0 < n_pos < n_all:
        share = n_pos / n_all if n_all else 0.0
        return Model({}, 40.0 if share else -40.0)
    names = chosen_features(feature_counts(sample), n_pos, n_all, features)
    w, bias, pairs = fit_weights(*design(sample, names), len(names), fair=fair)
    return Model({f: float(x) for f, x in zip(names, w) if abs(x) > 1e-6}, float(bias), pairs)


def mention_effect(model: Model, texts: list[str | None]) -> dict[str, float]:
    """What neutral mentions do to texts: share rejected without and with one, over all names, and the mean and largest change of score."""
    before = model.score(texts, {})
    after = np.stack([model.score([f"{t or ''} {name}" for t in texts], {}) for name in NAMES])
    change = np.abs(after - before)
    return {
        "rejected": float((before >= THRESHOLD).mean()), "rejected_with_mention": float((after >= THRESHOLD).mean()),
        "mean_change": float(change.mean()), "largest_change": float(change.max()),
    }


def scores(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, held_out, score, predicted`` of every row."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache: dict = {}
        for batch in batches:
            found = shared.value.score(batch.column(1).to_pylist(), cache)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(found)], ["doc_id", "score"])

    made = docs.select(F.col(id_col).cast("long"), F.col(text_col)).mapInArrow(run, "doc_id long, score double")
    return made.select(
        "doc_id", (fold("doc_id", PARTS) == HELD_OUT).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted")
    )


def toxicity(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Fit, then score every row of ``docs``."""
    return scores(docs, fit(docs, labels, id_col=id_col, text_col=text_col), id_col, text_col)


def score_column(model: Model, text: Column, spark) -> Column:
    """The score as a column, for filters that keep all columns of a table."""
    shared = spark.sparkContext.broadcast(model)

    @F.pandas_udf("double")
    def score(texts: pd.Series) -> pd.Series:
        return pd.Series(shared.value.score([t if isinstance(t, str) else None for t in texts], {}))

    return score(text)


def drop_toxic(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows of ``docs`` that the classifier doesn't reject, all columns as they were."""
    model = fit(docs, labels, id_col=id_col, text_col=text_col)
    return docs.where(score_column(model, docs[text_col], docs.sparkSession) < THRESHOLD)
