"""Language identification by error-correcting output codes.

Each language has a codeword; a binary classifier for each bit looks at hashed byte trigrams of the lower-cased text. A text goes to the
language whose codeword has the least loss: the logistic loss of each bit's margin, summed. If the runner-up's loss is near, the
prediction is flagged as ambiguous. With up to 6 languages the code is exhaustive (every way to halve them), beyond that random.

The classifiers learn from a bounded sample: of each language the `sample` (3,000 by default) over the number of languages documents that come
first by a hash of their id, LEAST at least, all if there are fewer. No language is left out; the driver holds a row for each, and its codeword.
Random codewords are drawn until all differ in at least a quarter of their bits. Scoring covers whole texts.

Defined results: null texts and texts without a letter are `und` with score 0; without any learned language all are. One language alone is
always predicted. Equal losses go to the language that comes first by code point, flagged as ambiguous. Rows without doc_id get a prediction
and train nothing. Repeated rows get a row each but train once. Very long texts are treated whole. Empty input gives an empty result. Other
columns don't matter, whatever their names.
"""

from __future__ import annotations

from itertools import product

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from graphsplit.llm.common import cut, held_out, join_small, map_texts, unit_hash

DIMENSIONS = 4096
#: Documents of a language that are learned from however many languages there are.
LEAST = 20


def codewords(k: int, seed: int = 7) -> np.ndarray:
    """k rows of +1 and -1."""
    if k <= 6:
        rows = [bits for bits in product((1, -1), repeat=k) if bits[0] == 1 and -1 in bits]
        return np.asarray(rows, dtype=float).T.reshape(k, -1)
    r, bits = np.random.default_rng(seed), int(np.ceil(15 * np.log2(k)))
    while True:
        out = r.choice([-1.0, 1.0], size=(k, bits))
        apart = (bits - out @ out.T) / 2
        if (apart + bits * np.eye(k)).min() >= bits / 4 and (np.abs(out.sum(axis=0)) < k).all():
            return out
        bits += 1  # a little longer until it works out


def trigrams(text: str, dimensions: int = DIMENSIONS) -> np.ndarray:
    """Square roots of the counts of hashed byte trigrams, of length one."""
    b = np.frombuffer(text.lower().encode("utf-8", "replace"), dtype=np.uint8).astype(np.uint32)
    if len(b) < 3:
        b = np.concatenate([b, np.full(3 - len(b), 32, np.uint32)])
    h = (b[:-2] * np.uint32(0x9E3779B1) + b[1:-1] * np.uint32(0x85EBCA77) + b[2:] * np.uint32(0xC2B2AE3D)) >> np.uint32(32 - int(dimensions).bit_length() + 1)
    v = np.sqrt(np.bincount(h, minlength=dimensions)).astype(np.float32)
    return v / max(float(np.linalg.norm(v)), 1e-9)


def fit_bits(x: np.ndarray, bits: np.ndarray, rounds: int = 150, ridge: float = 1e-5) -> tuple[np.ndarray, np.ndarray]:
    """Weights (dimensions x bits) and biases of a logistic classifier for each column of bits (+1, -1)."""
    n, t = len(x), 1.0
    w = z = np.zeros((x.shape[1], bits.shape[1]), np.float32)
    b = zb = np.zeros(bits.shape[1], np.float32)
    rate = np.float32(1 / (0.25 * 2))  # rows have length one, and the bias
    for _ in range(rounds):
        g = (-bits / (1 + np.exp(np.clip(bits * (x @ z + zb), -30, 30)))).astype(np.float32)
        new, nb = z - rate * (x.T @ g / n + np.float32(ridge) * z), zb - rate * g.mean(axis=0)
        t2 = (1 + (1 + 4 * t * t) ** 0.5) / 2
        z, zb, w, b, t = new + np.float32((t - 1) / t2) * (new - w), nb + np.float32((t - 1) / t2) * (nb - b), new, nb, t2
    return w, b


class Decoder:
    def __init__(self, languages: list[str], x: np.ndarray, y: np.ndarray):
        self.languages, self.codes = languages, codewords(len(languages))
        self.w, self.b = fit_bits(x, self.codes[y]) if len(languages) > 1 else (np.zeros((DIMENSIONS, 0), np.float32), np.zeros(0, np.float32))
        # margins grow with the training rounds; their scale turns losses into confidence
        self.scale = 2.0 / max(1e-6, float(np.abs(x @ self.w + self.b).mean())) if len(languages) > 1 else 1.0

    def decode(self, v: np.ndarray) -> tuple[str, float, bool]:
        margin = (v @ self.w + self.b) * self.scale
        loss = np.logaddexp(0, -self.codes * margin).sum(axis=1)
        p = np.exp(loss.min() - loss)
        p /= p.sum()
        first = int(loss.argmin())
        return self.languages[first], float(p[first]), len(p) > 1 and float(p[first] - np.sort(p)[-2]) < 0.2


def not_for_training(doc_id: Column) -> Column:
    return held_out(doc_id, 4, 2)


def train(docs: DataFrame, sample: int = 3000, held=not_for_training) -> Decoder | None:
    usable = docs.filter(F.col("lang").isNotNull() & F.col("text").isNotNull() & F.col("doc_id").isNotNull() & ~held(F.col("doc_id")))
    counts = cut(usable.groupBy("lang").agg(F.count("*").alias("n")))
    n = counts.count()
    if not n:
        return None
    each = max(LEAST, sample // n)
    # four times as many as needed by the hash, of every language alike; then the first of them
    u = unit_hash("language", F.col("doc_id"))
    drawn = join_small(usable.select("lang", "doc_id"), counts, ["lang"], n).filter(u * F.col("n") < 4.0 * each)
    first = F.dense_rank().over(Window.partitionBy("lang").orderBy(u, "doc_id"))  # repeated rows rank alike
    chosen = cut(drawn.select("lang", "doc_id").withColumn("_r", first).filter(F.col("_r") <= each).select("lang", "doc_id").distinct())
    some = join_small(usable.select("doc_id", "lang", "text"), chosen, ["lang", "doc_id"], each * n)

    def start():
        return lambda texts: [[trigrams(x).tobytes() for x in texts]]

    vectors = map_texts(some, ["doc_id", "lang"], start, [("v", "binary", pa.binary())]).groupBy("doc_id", "lang").agg(F.min("v").alias("v"))
    rows = sorted((r["lang"], r["doc_id"], bytes(r["v"])) for r in vectors.collect())  # `each` rows a language
    languages = sorted({r[0] for r in rows})
    return Decoder(languages, np.frombuffer(b"".join(r[2] for r in rows), np.float32).reshape(len(rows), -1), np.asarray([languages.index(r[0]) for r in rows]))


def identify(docs: DataFrame, model: Decoder | None) -> DataFrame:
    """doc_id, lang_pred, score, ambiguous of every row of docs."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def start():
        import regex

        letter, decoder = regex.compile(r"\p{L}").search, shared.value

        def work(texts: list) -> list[list]:
            found = [decoder.decode(trigrams(x)) if decoder and x and letter(x) else ("und", 0.0, True) for x in texts]
            return [list(c) for c in zip(*found, strict=True)]

        return work

    return map_texts(docs, ["doc_id"], start, [("lang_pred", "string", pa.string()), ("score", "double", pa.float64()), ("ambiguous", "boolean", pa.bool_())])


def predictions(docs: DataFrame, sample: int = 3000) -> DataFrame:
    return identify(docs, train(docs, sample)).withColumn("held_out", not_for_training(F.col("doc_id")))
