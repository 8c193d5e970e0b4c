"""Toxicity by multiple-instance learning: only documents are labelled, sentences are scored.

A sentence's chance of being toxic is logistic in its words; a document's is the noisy-or of its sentences. Both follow from the
documents' labels alone by gradient descent on the likelihood, over the words that tell the labels apart best. Sentences over one half
are the offending ones.

Words are chosen from counts over a bounded sample of labelled rows (`sample`, 12,000 by default), on which the weights are fitted too;
every whole text is scored.

Defined results: null and empty texts have one empty sentence. Without usable labels the score is 0. Repeated rows get a row each but
train once. Empty input gives an empty result. Other columns don't matter.
"""

from __future__ import annotations

import math
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphsplit.llm.common import cut, held_out, labelled, map_texts

ACCEPT = 0.3
#: Log odds that a sentence without telling words is toxic, before fitting.
BIAS = -8.0
SENTENCE = re.compile(r"[^.!?\n]+")
TOKEN = re.compile(r"[^\W\d_]+")


#: Lengths of the beginnings of a word that count as its stems.
STEMS = (4, 5, 6, 7)


def features(word: str) -> list[str]:
    """The word itself, and its longer beginnings, which inflected and compound forms share."""
    return [word, *[word[:k] + "*" for k in STEMS if len(word) > k]]


class Known(dict):
    """Weight of each word: the sum of its features'. Remembers up to 500,000 words."""

    def __init__(self, weights: dict[str, float]):
        super().__init__()
        self.weights = weights

    def __missing__(self, word: str) -> float:
        x = sum(self.weights.get(f, 0.0) for f in features(word))
        if len(self) > 500_000:
            self.clear()
        self[word] = x
        return x


class SentenceModel:
    def __init__(self, names: list[str], weights: np.ndarray, bias: float):
        self.weights, self.bias = {w: float(x) for w, x in zip(names, weights, strict=True) if x}, float(bias)

    def judge(self, text: str | None, known: Known) -> tuple[float, list[tuple[int, int]]]:
        """Score of a document; bounds (code points, end exclusive) of its offending sentences."""
        if not self.weights:
            return 0.0, []
        text = text or ""
        low = text.lower()
        if len(low) != len(text):  # a letter whose lower case is longer: keep places
            low = "".join(c.lower() if len(c.lower()) == 1 else c for c in text)
        clean, found = float(-np.logaddexp(0, self.bias)), []  # log of the chance that a sentence without known words is clean
        total, weight = 0.0, known.__getitem__
        for s in SENTENCE.finditer(low):
            z = sum(map(weight, TOKEN.findall(s.group())))
            if not z:
                total += clean
                continue
            total -= float(np.logaddexp(0, z + self.bias))
            if z + self.bias > 0:
                found.append(s.span())
        return 1 - math.exp(total or clean), found


def fit_noisy_or(bags: list[list[list[int]]], lone: np.ndarray, y: np.ndarray, begin: np.ndarray, bias: float, rounds: int = 300, ridge: float = 1e-3) -> tuple[np.ndarray, float]:
    """Word weights and bias, from the first guess `begin` on, to which a ridge penalty ties them.

    bags: for each document its sentences with known words, as word numbers; lone: how many sentences have none.
    """
    size = len(begin)
    doc = np.asarray([d for d, b in enumerate(bags) for _ in b], dtype=np.int64)
    sentence = [s for b in bags for s in b]
    at = np.repeat(np.arange(len(sentence)), [len(s) for s in sentence])
    word = np.asarray([w for s in sentence for w in s], dtype=np.int64)
    w, b, n = begin.copy(), bias, len(y)
    m1, m2, k1, k2 = np.zeros(size + 1), np.zeros(size + 1), 0.9, 0.999
    for r in range(1, rounds + 1):
        z = b + np.bincount(at, weights=w[word], minlength=len(sentence))
        p, p0 = 1 / (1 + np.exp(-np.clip(z, -30, 30))), 1 / (1 + np.exp(-b))
        log_clean = np.bincount(doc, weights=-np.logaddexp(0, z), minlength=n) - lone * np.logaddexp(0, b)
        toxic = np.clip(1 - np.exp(log_clean), 1e-9, 1)
        # d loss / d log_clean: -1 for clean documents, clean / toxic for toxic ones
        back = np.where(y > 0, np.exp(log_clean) / toxic, -1.0)
        gz = -back[doc] * p  # times d log_clean / dz = -p
        g = np.append(np.bincount(word, weights=gz[at], minlength=size), gz.sum() + (-back * lone * p0).sum()) / n
        g[:-1] += ridge * (w - begin) / n
        m1, m2 = k1 * m1 + (1 - k1) * g, k2 * m2 + (1 - k2) * g * g
        step = 0.05 * (m1 / (1 - k1**r)) / (np.sqrt(m2 / (1 - k2**r)) + 1e-8)
        w, b = w - step[:-1], float(np.clip(b - step[-1], -14, -4))
    w[np.abs(w) < 0.2] = 0
    return w, b


def not_for_training(doc_id: Column) -> Column:
    return held_out(doc_id, 4, 2)


def train(docs: DataFrame, labels: DataFrame, sample: int = 12_000, vocabulary: int = 2000, least: int = 4, held=not_for_training) -> SentenceModel:
    chosen = labelled(labels, "toxic", held, sample, "toxicity")
    texts = docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id")  # `sample` rows of labels at most, about

    def start():
        def work(texts: list) -> list[list]:
            cut_up = [[m.group().lower() for m in SENTENCE.finditer(x or "")] for x in texts]
            return [[sorted({f for s in ss for w in set(TOKEN.findall(s)) for f in features(w)}) for ss in cut_up], cut_up]

        return work

    columns = [("words", "array<string>", pa.list_(pa.string())), ("sentences", "array<string>", pa.list_(pa.string()))]
    known = map_texts(texts, ["doc_id", "y"], start, columns)
    once = cut(known.groupBy("doc_id", "y").agg(F.min(F.struct(F.size("words"), "words", "sentences")).alias("_x")).select("doc_id", "y", "_x.words", "_x.sentences"))
    n = {r["y"]: r["n"] for r in once.groupBy("y").agg(F.count("*").alias("n")).collect()}
    if len(n) < 2:
        return SentenceModel([], np.zeros(0), BIAS)
    seen = once.select("y", F.explode("words").alias("word")).groupBy("word").agg(F.sum("y").alias("t"), F.count("*").alias("c")).filter(F.col("c") >= least)
    share = n[1] / (n[0] + n[1])
    z = (F.col("t") - F.col("c") * share) / F.sqrt(F.col("c") * share * (1 - share))
    best = seen.withColumn("z", z).filter("z > 4").orderBy(F.desc("z"), F.length("word"), "word").limit(vocabulary).collect()
    number: dict[str, int] = {}
    begin = []
    for r in best:
        stem = r["word"].rstrip("*")
        if any(stem.startswith(x.rstrip("*")) or x.rstrip("*").startswith(stem) for x in number):
            continue  # a feature that tells more covers the same words
        number[r["word"]] = len(number)
        pure = (r["t"] + 4 * share) / (r["c"] + 4)
        excess = min(0.98, max(0.02, (pure - share) / (1 - share)))
        begin.append(math.log(excess / (1 - excess)) - BIAS)
    if not number:
        return SentenceModel([], np.zeros(0), BIAS)
    shared = docs.sparkSession.sparkContext.broadcast(number)

    def bag(batches):
        number = shared.value
        for b in batches:
            ids, ys, bags, lone = [], [], [], []
            for doc_id, y, sentences in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2), strict=True):
                found = [[number[f] for w in TOKEN.findall(s) for f in features(w) if f in number] for s in sentences.as_py()]
                bags.append([s for s in found if s])
                lone.append(len(found) - len(bags[-1]))
                ids.append(doc_id)
                ys.append(y)
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(ys, pa.int32()), pa.array(bags, pa.list_(pa.list_(pa.int32()))), pa.array(lone, pa.int64())], names=["doc_id", "y", "bags", "lone"])

    rows = once.select(F.col("doc_id").cast("long"), "y", "sentences").mapInArrow(bag, "doc_id long, y int, bags array<array<int>>, lone long").toArrow().sort_by("doc_id")
    bags, lone, y = rows.column("bags").to_pylist(), np.asarray(rows.column("lone")), np.asarray(rows.column("y"))
    w, b = fit_noisy_or(bags, lone, y, np.asarray(begin), BIAS)
    return SentenceModel(list(number), w, b)


def judge(docs: DataFrame, model: SentenceModel) -> DataFrame:
    """doc_id, score, spans of every row of docs; spans are the offending sentences, as start:end, joined by commas."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def start():
        model = shared.value
        known = Known(model.weights)

        def work(texts: list) -> list[list]:
            found = [model.judge(x, known) for x in texts]
            return [[s for s, _ in found], [",".join(f"{a}:{b}" for a, b in spans) for _, spans in found]]

        return work

    return map_texts(docs, ["doc_id"], start, [("score", "double", pa.float64()), ("spans", "string", pa.string())])


def scores(docs: DataFrame, labels: DataFrame, sample: int = 12_000, accept: float = ACCEPT) -> DataFrame:
    out = judge(docs, train(docs, labels, sample))
    return out.withColumn("held_out", not_for_training(F.col("doc_id"))).withColumn("predicted", (F.col("score") >= accept).cast("int"))
