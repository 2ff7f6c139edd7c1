"""Sparse rule ensemble for document quality, compiled to column expressions (op 5)."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from slotlens.llm.common import crc_remainder

#: Labelled rows used for fitting at most, those of least hash: a documented bound on the training sample only.
MAX_FIT_ROWS = 20_000
TREES, DEPTH, LEAST_LEAF, LASSO, STEP = 60, 3, 12, 2e-3, 0.25
#: Fixed threshold of the query's contract.
ACCEPT_AT = 0.3


def statistics(text: Column) -> dict[str, Column]:
    """Per-text figures from built-in functions; every share is safe on the empty text."""
    words, lines = F.split(text, " ", -1), F.split(text, "\n", -1)
    chars, n_words, n_lines = F.length(text), F.size(words), F.size(lines)

    def per(x: Column, n: Column) -> Column:
        return (x / F.greatest(n, F.lit(1))).cast("double")

    def count(pattern: str) -> Column:
        return F.regexp_count(text, F.lit(pattern))

    return {
        "chars": chars.cast("double"),
        "words": n_words.cast("double"),
        "chars_per_word": per(chars, n_words),
        "distinct_words": per(F.size(F.array_distinct(words)), n_words),
        "lines_per_word": per(n_lines, n_words),
        "distinct_lines": per(F.size(F.array_distinct(lines)), n_lines),
        "capitals": per(count(r"\p{Lu}"), chars),
        "digits": per(count(r"[0-9]+"), n_words),
        "exclamations": per(count(r"!"), n_words),
        "symbol_runs": per(count(r"[&*$%#@^~=<>{}\[\]\\]{2,}"), n_words),
        "bars": per(count(r"\|"), n_words),
        "stops": per(count(r"[.?](?:\s|$)"), n_words),
        "commas": per(count(r","), n_words),
        "links": per(count(r"://|www\.|@"), n_words),
    }


@dataclass(frozen=True)
class Rule:
    """A conjunction of (statistic, above, cut): above means value > cut, else value <= cut."""

    tests: tuple[tuple[str, bool, float], ...]

    def holds(self, x: np.ndarray, names: list[str]) -> np.ndarray:
        out = np.ones(len(x), bool)
        for name, above, cut in self.tests:
            v = x[:, names.index(name)]
            out &= v > cut if above else v <= cut
        return out

    def column(self, figures: Column) -> Column:
        out = None
        for name, above, cut in self.tests:
            test = figures[name] > F.lit(cut) if above else figures[name] <= F.lit(cut)
            out = test if out is None else out & test
        return out

    def simplified(self) -> Rule:
        """Only the tightest cut of each statistic and direction, in a fixed order."""
        tight: dict[tuple[str, bool], float] = {}
        for name, above, cut in self.tests:
            held = tight.get((name, above), cut)
            tight[name, above] = max(held, cut) if above else min(held, cut)
        return Rule(tuple(sorted((n, a, c) for (n, a), c in tight.items())))


@dataclass(frozen=True)
class RuleModel:
    intercept: float
    rules: tuple[Rule, ...]
    weights: tuple[float, ...]

    def score(self, text: Column) -> Column:
        """Probability of the good class.

        The statistics are bound once, as the one element that a lambda sees: no pushed-down filter or merged
        projection can then copy their expressions into every rule.
        """

        def ensemble(figures: Column) -> Column:
            z = F.lit(self.intercept)
            for rule, weight in zip(self.rules, self.weights, strict=True):
                z = z + F.when(rule.column(figures), F.lit(weight)).otherwise(F.lit(0.0))
            return F.lit(1.0) / (F.lit(1.0) + F.exp(-z))

        used = {name for rule in self.rules for name, _, _ in rule.tests}
        if not used:
            return ensemble(text)
        bound = F.array(F.struct(*(c.alias(n) for n, c in statistics(text).items() if n in used)))
        return F.get(F.transform(bound, ensemble), F.lit(0))


def _grow(x, gradient, hessian, cuts, names, rng) -> tuple[list[Rule], np.ndarray]:
    """One regression tree on the gradient; returns the rules of its nodes and its step on each row."""
    rules, step = [], np.zeros(len(x))

    def split(rows: np.ndarray, tests: tuple, depth: int) -> None:
        g, h = gradient[rows].sum(), hessian[rows].sum()
        if tests:
            rules.append(Rule(tests).simplified())
        best = None
        if depth < DEPTH and len(rows) >= 2 * LEAST_LEAF:
            for j in rng.permutation(len(names))[: max(4, len(names) // 2)]:
                if not len(cuts[j]):
                    continue
                at = np.searchsorted(cuts[j], x[rows, j], side="left")
                gs = np.bincount(at, gradient[rows], len(cuts[j]) + 1).cumsum()[:-1]
                hs = np.bincount(at, hessian[rows], len(cuts[j]) + 1).cumsum()[:-1]
                ns = np.bincount(at, minlength=len(cuts[j]) + 1).cumsum()[:-1]
                ok = (ns >= LEAST_LEAF) & (len(rows) - ns >= LEAST_LEAF)
                gain = np.where(ok, gs**2 / (hs + 1) + (g - gs) ** 2 / (h - hs + 1) - g**2 / (h + 1), 0)
                k = int(gain.argmax())
                if gain[k] > 1e-6 and (best is None or gain[k] > best[0]):
                    best = gain[k], j, float(cuts[j][k])
        if best is None:
            step[rows] = g / (h + 1)
            return
        _, j, cut = best
        left = x[rows, j] <= cut
        split(rows[left], (*tests, (names[j], False, cut)), depth + 1)
        split(rows[~left], (*tests, (names[j], True, cut)), depth + 1)

    split(np.arange(len(x)), (), 0)
    return rules, step


def _lasso(z: np.ndarray, y: np.ndarray, penalty: float, rounds: int = 600) -> tuple[float, np.ndarray]:
    """Logistic weights under an L1 penalty by accelerated proximal steps; columns scaled to unit deviation."""
    scale = np.maximum(z.std(axis=0), 1e-3)
    z, n = (z - z.mean(axis=0)) / scale, len(y)
    length = 4.0 / max(1e-9, np.linalg.eigvalsh(z.T @ z / n)[-1] + 1)
    share = np.clip(y.mean(), 1e-3, 1 - 1e-3)
    w = v = np.zeros(z.shape[1])
    b = c = float(np.log(share / (1 - share)))
    t = 1.0
    for _ in range(rounds):
        miss = 1 / (1 + np.exp(-(z @ v + c))) - y
        u = v - length * (z.T @ miss) / n
        new = np.sign(u) * np.maximum(np.abs(u) - length * penalty, 0)
        nb = c - length * miss.mean()
        nt = (1 + (1 + 4 * t * t) ** 0.5) / 2
        v, c = new + (t - 1) / nt * (new - w), nb + (t - 1) / nt * (nb - b)
        w, b, t = new, nb, nt
    return b, w / scale


def fit_rules(x: np.ndarray, y: np.ndarray, names: list[str], seed: int = 7) -> RuleModel:
    """Boosted shallow trees give the rules, the lasso picks and weighs them. One class only: its smoothed share."""
    share = (y.sum() + 1) / (len(y) + 2)
    prior = float(np.log(share / (1 - share)))
    if len(y) < 2 * LEAST_LEAF or y.min() == y.max():
        return RuleModel(prior, (), ())
    rng = np.random.default_rng(seed)
    cuts = [np.unique(np.quantile(x[:, j], np.linspace(0.01, 0.99, 48))) for j in range(x.shape[1])]
    z, found = np.full(len(y), prior), {}
    for _ in range(TREES):
        p = 1 / (1 + np.exp(-z))
        rows = rng.random(len(y)) < 0.7
        rules, step = _grow(x[rows], (y - p)[rows], (p * (1 - p))[rows], cuts, names, rng)
        found |= dict.fromkeys(rules)
        # the tree's step on the rows it has not seen follows from its leaves' rules
        leaf = {r: r.holds(x, names) for r in rules}
        full = np.zeros(len(y))
        for r, mask in leaf.items():
            seen = mask[rows]
            if seen.any():
                full[mask] = np.median(step[seen])
        z += STEP * full
    rules = list(found)
    held = np.stack([r.holds(x, names) for r in rules], axis=1)
    _, first = np.unique(held, axis=1, return_index=True)
    keep = [k for k in sorted(first) if 0 < held[:, k].mean() < 1]
    rules, held = [rules[k] for k in keep], held[:, keep].astype(float)
    b, w = _lasso(held, y.astype(float), LASSO)
    b -= float(held.mean(axis=0) @ w)
    used = np.flatnonzero(np.abs(w) > 1e-4)
    return RuleModel(float(b), tuple(rules[k] for k in used), tuple(float(w[k]) for k in used))


def with_statistics(docs: DataFrame, text: str = "text", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    body = docs.select(*keep, F.coalesce(F.col(text), F.lit("")).alias("_text"))
    return body.select(*keep, *(c.alias(n) for n, c in statistics(F.col("_text")).items()))


def fit(docs: DataFrame, labels: DataFrame, label: str = "quality", limit: int = MAX_FIT_ROWS) -> RuleModel:
    """Fits on labelled rows whose crc32(doc_id) mod 5 is not 0, at most ``limit`` of them, those of least hash.

    Rows without a label, or whose id is null, take no part; a repeated label row counts again.
    """
    marked = labels.where(F.col(label).isNotNull() & F.col("doc_id").isNotNull() & (crc_remainder() != 0))
    marked = marked.select(F.col("doc_id").alias("_id"), F.col(label).cast("double").alias("_y"))
    # A sample of ids first (no texts move), then the texts of that sample alone: its size is bounded.
    chosen = marked.orderBy(F.xxhash64("_id"), "_id", "_y").limit(limit)
    body = docs.select("doc_id", "text").join(F.broadcast(chosen), F.col("doc_id") == F.col("_id"))
    names = list(statistics(F.lit("")))
    table = with_statistics(body, keep=("doc_id", "_y")).toPandas().sort_values(["doc_id", "_y", *names])
    return fit_rules(table[names].to_numpy(float), table["_y"].to_numpy(float), names)


def score(docs: DataFrame, model: RuleModel, threshold: float = ACCEPT_AT) -> DataFrame:
    """doc_id, held_out, score, predicted of every row; null text scores as the empty text. No shuffle, no Python."""
    body = F.coalesce(F.col("text"), F.lit(""))
    scored = docs.select("doc_id", (crc_remainder() == 0).alias("held_out"), model.score(body).alias("score"))
    return scored.withColumn("predicted", F.when(F.col("score") >= threshold, 1).otherwise(0))


def accepted(docs: DataFrame, model: RuleModel, threshold: float = ACCEPT_AT) -> DataFrame:
    """The rows of ``docs`` whose score reaches the threshold, columns as they were."""
    return docs.where(model.score(F.coalesce(F.col("text"), F.lit(""))) >= threshold)
