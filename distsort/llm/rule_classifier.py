"""Quality classifier: a sparse ensemble of rules over text statistics.

Shallow trees, boosted on the labels, give paths; each path is a conjunction of bounds on statistics.  A lasso logistic
regression weighs the conjunctions and most get no weight.  What is left is compiled into one Spark expression, so that scoring is a
column of the same scan that makes the statistics.

Trees and weights are fitted on the driver, in numpy, on at most `sample` labelled documents: those with the least hashes of their ids.
Labels come only from rows whose crc32(doc_id as text) mod 5 is not 0.  Statistics of all documents are computed over their whole texts.

Defined results: a null or empty text has statistics of 0 and a score as any other; a null doc_id is scored and is not held out;
labels that repeat a doc_id count as one, the larger; null labels are left out; without labels of both kinds the score is their mean, or
0.5 without any; repeated rows are scored each; an empty table gives an empty result; only doc_id and text, and doc_id and quality
of the labels, are read.
"""

from __future__ import annotations

import math
from dataclasses import dataclass
from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import words

SAMPLE = 6000
THRESHOLD = 0.3
FEATURES = ("n_words", "word_length", "symbols", "bangs", "digits", "uppers", "bars", "distinct", "adjacent", "repeated_lines", "lines_a_word")


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0, F.lit(False))


def statistics(docs: DataFrame) -> DataFrame:
    """doc_id and FEATURES, from whole texts."""
    text = F.coalesce(F.col("text"), F.lit(""))
    a = docs.select("doc_id", text.alias("text"), words("text").alias("w"))
    n = F.greatest(F.size("w"), F.lit(1))
    without = lambda chars: F.length("text") - F.length(F.regexp_replace("text", f"[{chars}]", ""))
    lines = F.split("text", "\n")
    chars = F.greatest(F.length("text"), F.lit(1))
    share = lambda x, of: F.round(x / of, 6)
    return a.select(
        "doc_id",
        F.size("w").cast("double").alias("n_words"),
        share(F.length(F.array_join("w", "")), n).alias("word_length"),
        share(without("#*$%&<>@^~=+{}\\\\\\[\\]"), n).alias("symbols"),
        share(without("!?"), n).alias("bangs"),
        share(without("0-9"), chars).alias("digits"),
        share(without("A-Z\\u00C0-\\u00DE"), chars).alias("uppers"),
        share(without("|"), n).alias("bars"),
        share(F.size(F.array_distinct("w")), n).alias("distinct"),
        share(F.size(F.filter("w", lambda x, i: x == F.get("w", i - 1))), n).alias("adjacent"),
        share(F.size(lines) - F.size(F.array_distinct(lines)), F.size(lines)).alias("repeated_lines"),
        share(F.size(lines), n).alias("lines_a_word"),
    )


@dataclass(frozen=True)
class Rule:
    """Bounds (feature, above, at most); all must hold."""

    bounds: tuple[tuple[int, float, float], ...]

    def holds(self, x: np.ndarray) -> np.ndarray:
        return reduce(np.logical_and, [(x[:, f] > low) & (x[:, f] <= high) for f, low, high in self.bounds])

    def column(self) -> Column:
        out = []
        for f, low, high in self.bounds:
            if low > -math.inf:
                out.append(F.col(FEATURES[f]) > float(low))
            if high < math.inf:
                out.append(F.col(FEATURES[f]) <= float(high))
        return reduce(Column.__and__, out)


@dataclass(frozen=True)
class RuleEnsemble:
    intercept: float
    rules: tuple[tuple[Rule, float], ...]

    def score(self, x: np.ndarray) -> np.ndarray:
        z = self.intercept + sum((w * r.holds(x) for r, w in self.rules), np.zeros(len(x)))
        return 1 / (1 + np.exp(-z))

    def column(self) -> Column:
        """The score as an expression over FEATURES."""
        z = reduce(Column.__add__, [F.when(r.column(), float(w)).otherwise(0.0) for r, w in self.rules], F.lit(float(self.intercept)))
        return 1 / (1 + F.exp(-z))


def _tree(x: np.ndarray, cuts: list[np.ndarray], codes: np.ndarray, g: np.ndarray, h: np.ndarray, depth: int, least: int) -> tuple[list[Rule], np.ndarray]:
    """A tree on gradients: the rules of all its nodes but the root, and its step for each row."""
    rules, step = [], np.zeros(len(x))

    def grow(rows, bounds, left):
        best = (1e-6, None, None)
        total_g, total_h = g[rows].sum(), h[rows].sum()
        if left and len(rows) >= 2 * least:
            for f in range(x.shape[1]):
                k = len(cuts[f])
                if not k:
                    continue
                sg = np.bincount(codes[rows, f], g[rows], k + 1).cumsum()[:-1]
                sh = np.bincount(codes[rows, f], h[rows], k + 1).cumsum()[:-1]
                n = np.bincount(codes[rows, f], minlength=k + 1).cumsum()[:-1]
                gain = sg**2 / (sh + 1) + (total_g - sg) ** 2 / (total_h - sh + 1) - total_g**2 / (total_h + 1)
                gain[(n < least) | (len(rows) - n < least)] = 0
                i = int(gain.argmax())
                if gain[i] > best[0]:
                    best = (gain[i], f, i)
        if best[1] is None:
            step[rows] = -total_g / (total_h + 1)
            return
        f, i = best[1:]
        low, high = bounds.get(f, (-math.inf, math.inf))
        cut = float(cuts[f][i])
        for side, span in ((codes[rows, f] <= i, (low, cut)), (codes[rows, f] > i, (cut, high))):
            own = bounds | {f: span}
            rules.append(Rule(tuple((k, *v) for k, v in sorted(own.items()))))
            grow(rows[side], own, left - 1)

    grow(np.arange(len(x)), {}, depth)
    return rules, step


def extracted_rules(x: np.ndarray, y: np.ndarray, trees: int = 25, depth: int = 3, bins: int = 32, rate: float = 0.3, seed: int = 3) -> list[Rule]:
    """Paths of boosted trees, each grown on half of the rows."""
    rng = np.random.default_rng(seed)
    cuts = [np.unique(np.quantile(x[:, f], np.linspace(0, 1, bins + 1)[1:-1])) for f in range(x.shape[1])]
    cuts = [c[c < x[:, f].max()] for f, c in enumerate(cuts)]
    codes = np.stack([np.searchsorted(c, x[:, f], side="left") for f, c in enumerate(cuts)], axis=1)
    z, seen = np.full(len(x), math.log((y.mean() + 1e-6) / (1 - y.mean() + 1e-6))), {}
    for _ in range(trees):
        p = 1 / (1 + np.exp(-z))
        half = rng.permutation(len(x))[: max(1, len(x) // 2)]
        g, h = np.zeros(len(x)), np.zeros(len(x))
        g[half], h[half] = (p - y)[half], (p * (1 - p))[half]
        rules, step = _tree(x, cuts, codes, g, h, depth, max(5, len(x) // 400))
        seen |= dict.fromkeys(rules)
        z += rate * step
    return list(seen)


def lasso_weights(a: np.ndarray, y: np.ndarray, penalty: float, steps: int = 400) -> tuple[float, np.ndarray]:
    """Logistic weights with an L1 penalty by accelerated proximal gradient steps; the intercept is free."""
    n, m = a.shape
    a1 = np.concatenate([np.ones((n, 1)), a], axis=1)
    rate = 4 * n / (np.linalg.norm(a1, 2) ** 2)
    w = np.zeros(m + 1)
    w[0] = math.log((y.mean() + 1e-6) / (1 - y.mean() + 1e-6))
    ahead, t = w.copy(), 1.0
    for _ in range(steps):
        p = 1 / (1 + np.exp(-(a1 @ ahead)))
        new = ahead - rate * (a1.T @ (p - y)) / n
        new[1:] = np.sign(new[1:]) * np.maximum(np.abs(new[1:]) - rate * penalty, 0)
        t2 = (1 + math.sqrt(1 + 4 * t * t)) / 2
        ahead, w, t = new + (t - 1) / t2 * (new - w), new, t2
    return float(w[0]), w[1:]


def fitted(x: np.ndarray, y: np.ndarray, seed: int = 3) -> RuleEnsemble:
    """The ensemble with the penalty that a quarter of the rows, kept apart, favours; fitted again on all of them."""
    if not len(y) or y.min() == y.max():
        mean = float(y.mean()) if len(y) else 0.5
        return RuleEnsemble(math.log((mean + 1e-3) / (1 - mean + 1e-3)), ())
    rules = extracted_rules(x, y)
    a = np.stack([r.holds(x) for r in rules], axis=1).astype(float) if rules else np.zeros((len(x), 0))
    use = a.std(axis=0) > 0
    rules, a = [r for r, k in zip(rules, use) if k], a[:, use]
    scale = a.std(axis=0)
    apart = np.random.default_rng(seed).permutation(len(x))
    kept, test = apart[len(x) // 4 :], apart[: len(x) // 4]

    def loss(penalty):
        b, w = lasso_weights((a / scale)[kept], y[kept], penalty)
        p = np.clip(1 / (1 + np.exp(-(b + (a / scale)[test] @ w))), 1e-6, 1 - 1e-6)
        return -(y[test] * np.log(p) + (1 - y[test]) * np.log(1 - p)).mean()

    penalty = min((0.03, 0.01, 0.003, 0.001), key=loss)
    b, w = lasso_weights(a / scale, y, penalty)
    return RuleEnsemble(b, tuple((r, float(k)) for r, k in zip(rules, w / scale) if abs(k) > 1e-6))


def learned(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> RuleEnsemble:
    known = labels.where(F.col("doc_id").isNotNull() & F.col("quality").isNotNull() & ~held_out(F.col("doc_id")))
    known = known.groupBy("doc_id").agg(F.max("quality").cast("double").alias("quality"))
    chosen = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample).select(F.col("doc_id").alias("id"), "quality")
    rows = statistics(docs.select("doc_id", "text").join(F.broadcast(chosen.select("id")), F.col("doc_id") == F.col("id"), "left_semi")).join(F.broadcast(chosen), F.col("doc_id") == F.col("id"))
    # one row for each id, of those that repeat it always the same
    got = rows.groupBy("id", "quality").agg(F.min(F.struct(*FEATURES)).alias("x")).select("id", "quality", "x.*").toArrow()  # `sample` rows at most
    order = np.argsort(got.column("id").to_numpy(), kind="stable")
    x = np.stack([got.column(f).to_numpy() for f in FEATURES], axis=1)[order]
    return fitted(x, got.column("quality").to_numpy()[order])


def classify(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> DataFrame:
    """doc_id, held_out, score, predicted, for every document."""
    model = learned(docs, labels, sample)
    scored = statistics(docs.select("doc_id", "text")).withColumn("score", model.column())
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", F.when(F.col("score") >= THRESHOLD, 1).otherwise(0).alias("predicted"))
