"""Quality classification by a sparse ensemble of rules over text statistics.

Shallow regression trees are boosted on a labelled sample; every path from a root to a node is a
conjunctive rule.  A lasso-penalised logistic regression keeps the few rules that matter, and the
result is compiled into one Spark column expression, so that scoring runs inside the JVM.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import WORD, apart

#: Bound of the labelled sample, and the shape of the ensemble.
SAMPLE, TREES, DEPTH, BINS, LASSO = 20_000, 40, 3, 48, 0.002


def statistics(text: Column) -> dict[str, Column]:
    """Statistics of a whole text; null counts as empty, shares of nothing are 0."""
    t = F.coalesce(text, F.lit(""))
    n = F.char_length(t).cast("double")
    words = F.regexp_count(t, F.lit(WORD)).cast("double")
    each = F.greatest(words, F.lit(1.0))
    count = lambda pattern: F.regexp_count(t, F.lit(pattern)) / each
    pieces = F.split(t, " ")
    return {
        "words": words,
        "word_length": n / each,
        "capitals": count(r"[A-ZÀ-Þ]{2,}"),
        "bars": (n - F.char_length(F.replace(t, F.lit("|"), F.lit("")))) / each,
        "symbols": count(r"[#$%&*=~^<>_]{2,}"),
        "exclamations": count(r"!{2,}"),
        "repeats": count(r"(?<!\S)(\S++)\s\1(?!\S)"),
        "distinct": F.size(F.array_distinct(pieces)) / F.size(pieces).cast("double"),
        "numbers": count(r"[0-9]++"),
        "lines": (n - F.char_length(F.replace(t, F.lit("\n"), F.lit("")))) / each,
        "stops": count(r"[.?](?!\S)"),
    }


@dataclass(frozen=True)
class RuleEnsemble:
    """``bias + sum of weight where all conditions hold``; a condition is (statistic, above?, threshold)."""

    bias: float
    rules: list[tuple[float, tuple[tuple[str, bool, float], ...]]]

    def column(self, stats: dict[str, Column]) -> Column:
        total = F.lit(self.bias)
        for weight, terms in self.rules:
            test = None
            for name, above, cut in terms:
                one = stats[name] > cut if above else stats[name] <= cut
                test = one if test is None else test & one
            total = total + F.when(test, F.lit(weight)).otherwise(F.lit(0.0))
        return 1.0 / (1.0 + F.exp(-total))


def _tree(codes: np.ndarray, grad: np.ndarray, depth: int, path: tuple, out: list[tuple]) -> np.ndarray:
    """Grow one tree on binned features; collects the paths of all nodes; the fitted values."""
    fit = np.full(len(grad), grad.mean() if len(grad) else 0.0)
    if depth == 0 or len(grad) < 40:
        return fit
    best = (1e-6, -1, -1)
    for j in range(codes.shape[1]):
        n = np.bincount(codes[:, j], minlength=BINS).cumsum()[:-1]
        s = np.bincount(codes[:, j], weights=grad, minlength=BINS).cumsum()[:-1]
        ok = (n >= 10) & (n <= len(grad) - 10)
        rest = len(grad) - n
        gain = np.where(ok, s**2 / np.maximum(n, 1) + (grad.sum() - s) ** 2 / np.maximum(rest, 1), 0) - grad.sum() ** 2 / len(grad)
        gain = np.where(ok, gain, -1)
        k = int(gain.argmax())
        if gain[k] > best[0]:
            best = (float(gain[k]), j, k)
    if best[1] < 0:
        return fit
    _, j, k = best
    low = codes[:, j] <= k
    for side, above in ((low, False), (~low, True)):
        out.append(branch := path + ((j, above, k),))
        fit[side] = _tree(codes[side], grad[side], depth - 1, branch, out)
    return fit


def fit(x: np.ndarray, y: np.ndarray, names: list[str], seed: int = 7) -> RuleEnsemble:
    """Rules for the chance of label 1.  No rows give 0.5, a single class a constant near it."""
    if len(y) == 0 or len(set(y.tolist())) < 2:
        share = (y.sum() + 0.5) / (len(y) + 1)
        return RuleEnsemble(float(np.log(share / (1 - share))), [])
    cuts = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, BINS)[1:-1])) for j in range(x.shape[1])]
    codes = np.stack([np.searchsorted(c, x[:, j], side="left") for j, c in enumerate(cuts)], axis=1)
    rng, f, paths = np.random.default_rng(seed), np.zeros(len(y)), []
    for _ in range(TREES):
        rows = rng.permutation(len(y))[: max(200, len(y) // 2)]
        cols = rng.permutation(x.shape[1])[: max(3, x.shape[1] * 2 // 3)]
        p, grown = 1 / (1 + np.exp(-f)), []
        _tree(codes[np.ix_(rows, cols)], (y - p)[rows], DEPTH, (), grown)
        grown = [tuple((int(cols[j]), above, k) for j, above, k in path) for path in grown]
        paths += grown
        leaves = [g for g in grown if not any(h[: len(g)] == g and len(h) > len(g) for h in grown)]
        for leaf in leaves:
            hit = _holds(codes, leaf)
            if hit.any():
                f[hit] += 0.5 * (y - p)[hit].sum() / max(1e-3, (p * (1 - p))[hit].sum())
        f = np.clip(f, -6, 6)
    tidy: dict[tuple, None] = {}
    for path in paths:
        last = {(j, above): k for j, above, k in path}  # a later test on the same side is the sharper one
        tidy[tuple(sorted((j, above, k) for (j, above), k in last.items()))] = None
    rules = list(tidy)
    r = np.stack([_holds(codes, rule) for rule in rules], axis=1).astype(np.float64)
    bias, w = _lasso(r, y.astype(np.float64))
    named = lambda rule: tuple((names[j], above, float(cuts[j][min(k, len(cuts[j]) - 1)])) for j, above, k in rule)
    return RuleEnsemble(bias, [(float(v), named(rule)) for v, rule in zip(w, rules, strict=True) if abs(v) > 1e-4])


def _holds(codes: np.ndarray, rule: tuple) -> np.ndarray:
    hit = np.ones(len(codes), bool)
    for j, above, k in rule:
        hit &= (codes[:, j] > k) if above else (codes[:, j] <= k)
    return hit


def _lasso(r: np.ndarray, y: np.ndarray, steps: int = 400) -> tuple[float, np.ndarray]:
    """Accelerated proximal gradient for the logistic loss with an L1 penalty; the bias is free."""
    centre = r.mean(0)
    r = r - centre
    step = 4 / max(1e-9, np.linalg.norm(r.T @ r / len(y), 2) + 1)
    w, v, b, t = np.zeros(r.shape[1]), np.zeros(r.shape[1]), float(np.log((y.mean() + 1e-6) / (1 - y.mean() + 1e-6))), 1.0
    for _ in range(steps):
        e = 1 / (1 + np.exp(-np.clip(r @ v + b, -30, 30))) - y
        u = v - step * (r.T @ e) / len(y)
        new = np.sign(u) * np.maximum(np.abs(u) - step * LASSO, 0)
        b -= step * e.mean()
        t2 = (1 + np.sqrt(1 + 4 * t * t)) / 2
        v, w, t = new + (t - 1) / t2 * (new - w), new, t2
    return float(b - centre @ w), w


def train(docs: DataFrame, labels: DataFrame, text: str = "text", doc_id: str = "doc_id", label: str = "quality") -> RuleEnsemble:
    """Fit on at most SAMPLE labelled rows, chosen by a hash of the id; rows without a label take no part.

    The sample's ids are bounded by SAMPLE and are broadcast; only its rows have their statistics computed.  Of documents
    that share an id and a label, the mean of each statistic counts, so that what is collected is bounded too.
    """
    chosen = labels.select(F.col(f"`{doc_id}`").alias("i"), F.col(f"`{label}`").cast("double").alias("y")).where("y IS NOT NULL")
    chosen = chosen.orderBy(F.xxhash64(F.lit(7), "i"), "i", "y").limit(SAMPLE)
    rows = docs.select(F.col(f"`{doc_id}`").alias("i"), F.col(f"`{text}`").alias("t")).join(F.broadcast(chosen), "i")
    stats = statistics(F.col("t"))
    each = rows.select("i", "y", *[c.alias(n) for n, c in stats.items()]).groupBy("i", "y").agg(*[F.avg(n).alias(n) for n in stats])
    got = sorted(tuple(r) for r in each.collect())
    x = np.array([r[2:] for r in got], np.float64).reshape(len(got), len(stats))
    return fit(x, np.array([r[1] for r in got], np.float64), list(stats))


def score(docs: DataFrame, model: RuleEnsemble, text: str = "text") -> DataFrame:
    """All rows and columns of ``docs`` with ``quality_score`` from 0 to 1, null and empty texts too.

    Each statistic is computed once a row, in the JVM; no shuffle.  A column called ``quality_score`` is replaced.
    """
    docs = docs.drop("quality_score")
    used = sorted({name for _, terms in model.rules for name, _, _ in terms})
    stats = statistics(F.col(f"`{text}`"))
    # Columns that many rules read and that aren't cheap: Spark keeps them in a projection of their own.
    own = dict(zip(used, apart(docs, *used), strict=True))
    found = docs.withColumns({own[n]: stats[n] for n in used}) if used else docs
    return found.withColumn("quality_score", model.column({n: F.col(own[n]) for n in used})).drop(*own.values())
