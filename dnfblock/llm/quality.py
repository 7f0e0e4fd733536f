"""Quality: a sparse rule ensemble over text statistics, compiled to column expressions.

Statistics of whole texts are Spark columns. Small boosted trees over a bounded labelled sample
give paths; every node's path is a conjunction of thresholds, a rule. A lasso logistic fit over the
rules leaves a few with a weight, and these become one column expression, so that scoring runs in
the JVM, row by row, without Python.

Defined cases: null and empty texts have statistics of zero and get the score of those; a table
without usable labels, or with one class only, gives every row the class share (0 without labels);
repeated rows get equal scores; an empty table gives an empty result; no column but the text and,
for the fold, the id is read.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from dnfblock.llm.training import fold, labelled_sample, sigmoid

PARTS, HELD_OUT = 4, 2
THRESHOLD = 0.7
#: Frequent short words of four languages.
COMMON = "the|of|and|to|in|is|that|it|for|was|der|die|und|das|den|von|zu|mit|de|la|le|et|les|des|que|en|el|los|las|un"


def statistics(text: Column) -> dict[str, Column]:
    """Statistics by name; the arguments of rules."""
    t = F.coalesce(text, F.lit(""))
    count = lambda pattern: F.regexp_count(t, F.lit(pattern)).cast("double")
    chars = F.length(t).cast("double")
    words = count(r"[^\x20\x09-\x0D]+")
    lines = count(r"[^\n]+")
    per_char, per_word = F.greatest(chars, F.lit(1.0)), F.greatest(words, F.lit(1.0))
    letters = count(r"\p{L}+")
    parts = F.split(t, r"[\x20\x09-\x0D]+")
    return {
        "chars": chars,
        "words": words,
        "word_length": chars / per_word,
        "line_words": words / F.greatest(lines, F.lit(1.0)),
        "capitals": count(r"\p{Lu}") / per_char,
        "capital_words": count(r"\p{Lu}{2}") / per_word,
        "digits": count(r"[0-9]") / per_char,
        "pipes": count(r"\|") / per_word,
        "symbols": count(r"[#$%&*@^~<>=+{}\[\]\\]") / per_char,
        "marks": count(r"[!?]") / per_word,
        "stops": count(r"[.]") / per_word,
        "commas": count(r",") / per_word,
        "common": count(rf"\b(?:{COMMON})\b") / per_word,
        "pieces": letters / per_word,
        "distinct": F.size(F.array_distinct(parts)).cast("double") / F.greatest(F.size(parts), F.lit(1)),
    }


@dataclass(frozen=True)
class Rule:
    """A conjunction: every statistic of ``above`` is over its bound, of ``below`` at most at it."""

    above: tuple[tuple[str, float], ...] = ()
    below: tuple[tuple[str, float], ...] = ()

    def holds(self, table: dict[str, np.ndarray]) -> np.ndarray:
        out = np.ones(len(next(iter(table.values()))), bool)
        for name, bound in self.above:
            out &= table[name] > bound
        for name, bound in self.below:
            out &= table[name] <= bound
        return out

    def column(self, columns: dict[str, Column]) -> Column:
        out = None
        for name, bound in self.above:
            part = columns[name] > bound
            out = part if out is None else out & part
        for name, bound in self.below:
            part = columns[name] <= bound
            out = part if out is None else out & part
        return out


@dataclass
class RuleModel:
    bias: float
    rules: list[tuple[Rule, float]] = field(default_factory=list)

    def column(self, columns: dict[str, Column]) -> Column:
        z = F.lit(self.bias)
        for rule, weight in self.rules:
            z = z + F.when(rule.column(columns), F.lit(weight)).otherwise(F.lit(0.0))
        return 1 / (1 + F.exp(-z))

    def used(self) -> set[str]:
        return {n for r, _ in self.rules for n, _ in (*r.above, *r.below)}


def _tighter(rule: Rule, name: str, bound: float, above: bool) -> Rule:
    """``rule`` and one more condition; of two on the same side of a statistic the tighter stays."""
    up, down = dict(rule.above), dict(rule.below)
    if above:
        up[name] = max(bound, up.get(name, bound))
    else:
        down[name] = min(bound, down.get(name, bound))
    return Rule(tuple(sorted(up.items())), tuple(sorted(down.items())))


def tree_rules(table: dict[str, np.ndarray], label: np.ndarray, trees: int = 30, depth: int = 3, rate: float = 0.3, bins: int = 32) -> list[Rule]:
    """The path of every node of ``trees`` boosted trees over binned statistics, without repeats."""
    names = list(table)
    edges = [np.unique(np.quantile(table[n], np.linspace(0, 1, bins + 1)[1:-1])) for n in names]
    binned = np.stack([np.searchsorted(e, table[n], side="left") for n, e in zip(names, edges)])
    y, z = label.astype(float), np.zeros(len(label))
    rules: dict[Rule, None] = {}
    for _ in range(trees):
        p = sigmoid(z)
        g, h = y - p, p * (1 - p)
        nodes = [(Rule(), np.arange(len(y)))]
        for level in range(depth):
            below = []
            for rule, at in nodes:
                best = (1e-6, None)
                whole = g[at].sum() ** 2 / (h[at].sum() + 1)
                for f in range(len(names)):
                    if not len(edges[f]):
                        continue
                    gs = np.bincount(binned[f, at], g[at], len(edges[f]) + 1).cumsum()[:-1]
                    hs = np.bincount(binned[f, at], h[at], len(edges[f]) + 1).cumsum()[:-1]
                    ns = np.bincount(binned[f, at], minlength=len(edges[f]) + 1).cumsum()[:-1]
                    gain = gs**2 / (hs + 1) + (g[at].sum() - gs) ** 2 / (h[at].sum() - hs + 1) - whole
                    gain[(ns < 5) | (ns > len(at) - 5)] = 0
                    k = int(gain.argmax())
                    if gain[k] > best[0]:
                        best = (gain[k], (f, k))
                if best[1] is None:
                    z[at] += rate * g[at].sum() / (h[at].sum() + 1)
                    continue
                f, k = best[1]
                low = binned[f, at] <= k
                bound = float(edges[f][k])
                for part, above in ((at[low], False), (at[~low], True)):
                    child = _tighter(rule, names[f], bound, above)
                    rules[child] = None
                    below.append((child, part))
            nodes = below
        for _, at in nodes:
            z[at] += rate * g[at].sum() / (h[at].sum() + 1)
    return list(rules)


def lasso(x: np.ndarray, label: np.ndarray, l1: float, steps: int = 600) -> tuple[np.ndarray, float]:
    """L1 logistic weights by accelerated proximal steps; the intercept is not penalised."""
    n, y = len(label), label.astype(float)
    size = 0.25 * (np.linalg.norm(x, 2) ** 2 / n + 1) if x.size else 1.0
    w, b = np.zeros(x.shape[1]), float(np.log((y.mean() + 1e-6) / (1 - y.mean() + 1e-6)))
    v, vb, t = w.copy(), b, 1.0
    for _ in range(steps):
        r = sigmoid(x @ v + vb) - y
        nw = v - x.T @ r / n / size
        nw = np.sign(nw) * np.maximum(np.abs(nw) - l1 / size, 0)
        nb = vb - r.mean() / size
        nt = (1 + (1 + 4 * t * t) ** 0.5) / 2
        v, vb = nw + (t - 1) / nt * (nw - w), nb + (t - 1) / nt * (nb - b)
        w, b, t = nw, nb, nt
    return w, b


def fit(docs: DataFrame, labels: DataFrame, label_col: str = "quality", id_col: str = "doc_id", text_col: str = "text", l1: float = 5e-4) -> RuleModel:
    """Fit on a bounded sample of the labelled rows that are not held out."""
    sample = labelled_sample(docs, labels, label_col, PARTS, HELD_OUT, id_col, text_col)
    names = list(statistics(F.lit("")))
    rows = sample.select("id", "label", *(c.alias(n) for n, c in statistics(sample["text"]).items()))
    rows = rows.toPandas().sort_values(["id", "label", *names], kind="stable")
    label = rows["label"].to_numpy()
    if not len(label) or label.min() == label.max():
        return RuleModel(40.0 if len(label) and label[0] else -40.0)
    table = {n: rows[n].to_numpy(float) for n in names}
    rules = tree_rules(table, label)
    x = np.stack([r.holds(table) for r in rules], axis=1).astype(float)
    w, b = lasso(x, label, l1)
    return RuleModel(float(b), [(r, float(c)) for r, c in zip(rules, w) if abs(c) > 1e-3])


def quality(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, held_out, score, predicted`` of every row."""
    model = fit(docs, labels, id_col=id_col, text_col=text_col)
    stats, used = statistics(docs[text_col]), model.used()
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), *(c.alias(n) for n, c in stats.items() if n in used))
    score = model.column({n: F.col(n) for n in used})
    return rows.select(
        "doc_id", (fold("doc_id", PARTS) == HELD_OUT).alias("held_out"), score.alias("score"), (score >= THRESHOLD).cast("int").alias("predicted")
    )
