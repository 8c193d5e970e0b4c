"""Quality classifier: a sparse rule ensemble over statistics of the text, compiled into Spark columns.

Small boosted trees are grown on a bounded sample of labelled rows (`sample`, 20,000 by default). Every path from a root to a node is a
conjunction of thresholds, a rule. Logistic regression with a lasso penalty gives most rules weight zero; the others become one
Spark expression, so scoring needs no Python. The statistics are DataFrame functions too and cover whole texts.

Defined results: null and empty texts have statistics of zero and get a score like any other; rows without label only get a score;
without any usable label the score is 0.5 for all; with one class only it is near that class for all. Rows without doc_id are scored, never held
out and train nothing. Repeated rows get a row each but train once; ties of score don't matter. Very long texts are treated whole. Empty input
gives an empty result. Other columns of the documents don't matter, whatever their names, and are kept by `accepted`.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphsplit.llm.common import cut, held_out, labelled, let, unused, words

ACCEPT = 0.3


def statistics(text: Column) -> Column:
    """A struct of numbers that describe a text; shares are of words unless named otherwise."""
    whole = F.coalesce(text, F.lit(""))
    count = lambda pattern: F.regexp_count(whole, F.lit(pattern)).cast("double")

    def of(ws: Column) -> Column:
        n, least = F.size(ws).cast("double"), F.greatest(F.size(ws), F.lit(1)).cast("double")
        chars = F.length(F.array_join(ws, "")).cast("double")
        lines = F.filter(F.split(whole, "\n"), lambda x: F.length(x) > 0)
        return F.struct(
            F.log1p(n).alias("log_words"),
            (chars / least).alias("word_length"),
            (F.size(F.array_distinct(ws)) / least).alias("distinct_words"),
            (count("[A-Z]") / F.greatest(chars, F.lit(1.0))).alias("upper_of_chars"),
            (count("[#*$%&|<>]") / least).alias("symbols"),
            (count("[!?]") / least).alias("exclaims"),
            (count("[.,;:]") / least).alias("stops"),
            (count("[0-9]") / F.greatest(chars, F.lit(1.0))).alias("digits_of_chars"),
            let(lines, lambda a: (F.size(F.array_distinct(a)) / F.greatest(F.size(a), F.lit(1))).cast("double")).alias("distinct_lines"),
            let(lines, lambda a: n / F.greatest(F.size(a), F.lit(1))).alias("words_per_line"),
        )

    return let(words(text), of)


NAMES = ["log_words", "word_length", "distinct_words", "upper_of_chars", "symbols", "exclaims", "stops", "digits_of_chars", "distinct_lines", "words_per_line"]


@dataclass
class RuleModel:
    """Rules are tuples of (statistic, is_above, threshold)."""

    rules: list[tuple[tuple[str, bool, float], ...]] = field(default_factory=list)
    weights: list[float] = field(default_factory=list)
    bias: float = 0.0

    def score(self, stats: str) -> Column:
        total = F.lit(float(self.bias))
        for rule, w in zip(self.rules, self.weights, strict=True):
            met = F.lit(True)
            for name, above, t in rule:
                met = met & ((F.col(f"{stats}.{name}") > t) if above else (F.col(f"{stats}.{name}") <= t))
            total = total + F.when(met, F.lit(float(w))).otherwise(F.lit(0.0))
        return F.lit(1.0) / (F.lit(1.0) + F.exp(-total))


def grow(x: np.ndarray, residual: np.ndarray, hessian: np.ndarray, rows: np.ndarray, cuts: list[np.ndarray], depth: int, least: int, path: tuple, out: list, step: np.ndarray, rate: float) -> None:
    """Splits `rows` where the second-order gain is largest; adds each path to `out`, and the leaves' values to `step`."""
    g, h = residual[rows].sum(), hessian[rows].sum()
    best = (1e-6, None)
    if depth:
        for j, c in enumerate(cuts):
            if not len(c):
                continue
            bins = np.searchsorted(c, x[rows, j], side="left")
            gs, hs, ns = (np.bincount(bins, weights=w, minlength=len(c) + 1).cumsum()[:-1] for w in (residual[rows], hessian[rows], np.ones(len(rows))))
            ok = (ns >= least) & (len(rows) - ns >= least)
            gain = np.where(ok, gs**2 / (hs + 1) + (g - gs) ** 2 / (h - hs + 1) - g**2 / (h + 1), 0.0)
            k = int(gain.argmax())
            if gain[k] > best[0]:
                best = (gain[k], (j, float(c[k])))
    if best[1] is None:
        step[rows] += rate * g / (h + 1)
        return
    j, t = best[1]
    for above in (False, True):
        side = rows[(x[rows, j] > t) == above]
        out.append((*path, (j, above, t)))
        grow(x, residual, hessian, side, cuts, depth - 1, least, out[-1], out, step, rate)


def sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -40, 40)))


def lasso_logistic(a: np.ndarray, y: np.ndarray, penalty: float, rounds: int = 500) -> tuple[np.ndarray, float]:
    """Weights and bias that minimise mean logistic loss plus penalty times the weights' absolute sum (accelerated proximal gradient)."""
    n, m = a.shape
    v = np.ones(m)
    for _ in range(20):
        v = a.T @ (a @ v)
        v /= max(np.linalg.norm(v), 1e-12)
    rate = 1 / (0.25 * (np.linalg.norm(a @ v) ** 2 / n + 1))
    w, b, z, zb, t = np.zeros(m), float(np.log((y.mean() + 1e-6) / (1 - y.mean() + 1e-6))), np.zeros(m), 0.0, 1.0
    zb = b
    for _ in range(rounds):
        r = sigmoid(a @ z + zb) - y
        new = z - rate * (a.T @ r) / n
        new = np.sign(new) * np.maximum(0, np.abs(new) - rate * penalty)
        nb = zb - rate * r.mean()
        t2 = (1 + (1 + 4 * t * t) ** 0.5) / 2
        z, zb = new + (t - 1) / t2 * (new - w), nb + (t - 1) / t2 * (nb - b)
        w, b, t = new, nb, t2
    return w, b


def learn(x: np.ndarray, y: np.ndarray, trees: int = 30, depth: int = 3, penalty: float = 0.001, names: list[str] = NAMES) -> RuleModel:
    if not len(y) or y.min() == y.max():
        return RuleModel(bias=0.0 if not len(y) else (4.0 if y[0] else -4.0))
    cuts = [np.unique(np.quantile(x[:, j], np.linspace(0.01, 0.99, 65))) for j in range(x.shape[1])]
    margin, found = np.full(len(y), np.log(y.mean() / (1 - y.mean()))), []
    least = max(5, len(y) // 400)
    for _ in range(trees):
        p = sigmoid(margin)
        step = np.zeros(len(y))
        grow(x, y - p, p * (1 - p), np.arange(len(y)), cuts, depth, least, (), found, step, 0.3)
        margin += step
    unique = list(dict.fromkeys(tuple(sorted(r)) for r in found))
    if not unique:  # too few rows to split
        return RuleModel(bias=float(np.log(y.mean() / (1 - y.mean()))))
    a = np.stack([np.logical_and.reduce([(x[:, j] > t) == above for j, above, t in r]) for r in unique], axis=1).astype(float)
    w, b = lasso_logistic(a, y.astype(float), penalty)
    some = np.flatnonzero(np.abs(w) > 1e-6)
    return RuleModel([tuple((names[j], above, t) for j, above, t in unique[k]) for k in some], [float(w[k]) for k in some], float(b))


def not_for_training(doc_id: Column) -> Column:
    return held_out(doc_id, 5, 0)


def train(stats: DataFrame, labels: DataFrame, sample: int = 20_000, label: str = "quality", held=not_for_training) -> RuleModel:
    """A model from a table doc_id, stats (its repeated rows count once) and labels."""
    chosen = labelled(labels, label, held, sample, "rules")
    rows = stats.join(F.broadcast(chosen), "doc_id").groupBy("doc_id", "y").agg(F.min("stats").alias("stats"))  # `sample` rows at most, about
    got = rows.select("doc_id", "y", *[F.col(f"stats.{c}").alias(c) for c in NAMES]).toPandas().sort_values("doc_id")
    return learn(got[NAMES].to_numpy(float), got["y"].to_numpy())


def with_statistics(docs: DataFrame) -> DataFrame:
    return cut(docs.select(F.col("doc_id"), statistics(F.col("text")).alias("stats")))


def scores(docs: DataFrame, labels: DataFrame, sample: int = 20_000, accept: float = ACCEPT) -> DataFrame:
    """doc_id, held_out, score, predicted of every row of docs."""
    stats = with_statistics(docs)
    model = train(stats, labels, sample)
    out = stats.select("doc_id", not_for_training(F.col("doc_id")).alias("held_out"), model.score("stats").alias("score"))
    return out.withColumn("predicted", (F.col("score") >= accept).cast("int"))


def accepted(docs: DataFrame, labels: DataFrame, sample: int = 20_000, accept: float = ACCEPT) -> DataFrame:
    """The rows of docs that the model accepts; texts are read once for the labelled rows and once for all, and are never shuffled."""
    chosen = labelled(labels, "quality", not_for_training, sample, "rules")
    stats = docs.join(F.broadcast(chosen.select("doc_id")), "doc_id", "left_semi").select("doc_id", statistics(F.col("text")).alias("stats"))
    model = train(stats, labels, sample)
    name = unused(docs, "_stats")
    return docs.withColumn(name, statistics(F.col("text"))).filter(model.score(name) >= accept).drop(name)
