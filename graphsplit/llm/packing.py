"""Packing documents into sequences of a fixed number of tokens, by patterns fitted with non-negative least squares.

Lengths of pieces are counted over all documents. Patterns, the sums of a few lengths that fill a sequence, get repeat counts by
non-negative least squares against the counts. Rounded down, they take what pieces there are; what stays over is packed by best fit
decreasing. All this works on counts by length, so it needs memory for the lengths (at most as many as a sequence has tokens), not for
the pieces. Its result is a list of runs: from the n-th piece of a length on, so many pieces go to consecutive sequences at one
offset. Pieces are numbered within their length by input partition, and each looks up its run.

Defined results: null and empty texts are one piece of the closing id alone; repeated rows are packed one by one. Empty input gives an
empty result. Other columns of the documents don't matter. Very long documents are cut into full pieces and a last, shorter one.
"""

from __future__ import annotations

import json
import os
import re
import zlib
from array import array
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphsplit.llm.common import cut

#: Words whose ids a worker remembers.
REMEMBERED = 500_000
PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long, chunk int, at long"
NAMES = [x.split()[0] for x in PIECES.split(", ")]
ARROW = [pa.int32() if x.endswith(" int") else pa.int64() for x in PIECES.split(", ")]


class WordIds(dict):
    """Token ids of words, as little-endian 32-bit bytes; what isn't known yet is computed.

    The tokenizer never lets a token span white space and treats each word alike wherever it stands, so the ids of words between
    spaces and line ends, joined, are those of the text. Two generations of words are remembered, the older one dropped whenever the
    younger is full. Words of Latin letters go through the same merges in a faster library: a byte that UTF-8 lacks marks the word's
    end there. All others go to the tokenizer itself.
    """

    END = b"\xff"
    OTHER = re.compile("[\x00-\x1f\x7f-\xa0\u0250-\U0010ffff]|<\\|")

    def __init__(self, path: str):
        super().__init__({"": b""})
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer, self.older, self.fast = Tokenizer.from_file(path), {}, None
        shape = json.loads(self.tokenizer.to_str())
        model, steps = shape["model"], [x["type"] for x in (shape["normalizer"] or {}).get("normalizers", [])]
        rank = {f"{a}{b}": k for k, (a, b) in enumerate(model.get("merges") or [])} if model["type"] == "BPE" else {}
        in_order = [model["vocab"].get(w) for w in rank]
        if model.get("end_of_word_suffix") == "</w>" and steps == ["NFC", "Replace", "Lowercase"] and None not in in_order and in_order == sorted(in_order):
            self.prepare(shape, rank)

    def prepare(self, shape: dict, rank: dict) -> None:
        import regex
        import tiktoken

        plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
        byte = {chr(b): b for b in plain} | {chr(256 + k): b for k, b in enumerate(b for b in range(256) if b not in plain)}
        ranks = {}
        for word, n in shape["model"]["vocab"].items():
            core = word.removesuffix("</w>")
            if all(c in byte for c in core) and (word in rank or len(core) == 1):
                ranks[bytes(byte[c] for c in core) + (self.END if word != core else b"")] = n
        self.fast = tiktoken.Encoding("words", pat_str=".", mergeable_ranks=ranks, special_tokens={})._core_bpe.encode_single_piece
        self.parts = regex.compile(next(x["pattern"]["Regex"] for x in shape["pre_tokenizer"]["pretokenizers"] if x["type"] == "Split")).findall

    def __missing__(self, word: str) -> bytes:
        ids = self.older.get(word)
        if ids is None:
            if self.fast is None or self.OTHER.search(word):
                found = self.tokenizer.encode(word, add_special_tokens=False).ids
            else:
                found = [n for part in self.parts(word.lower()) for n in self.fast(part.encode() + self.END)]
            ids = array("I", found).tobytes()
        self[word] = ids
        return ids

    def of(self, text: str) -> bytes:
        if len(self) > REMEMBERED:
            self.older = dict(self)
            self.clear()
            self[""] = b""
        return b"".join(map(self.__getitem__, text.replace("\n", " ").replace("\t", " ").replace("\r", " ").split(" ")))


def tokenizer_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def pieces(docs: DataFrame, tokenizer: str = "word_bpe_49k.json", capacity: int = 2048, closing: int = 0) -> DataFrame:
    """A row for each piece of each document, with its place among the pieces of its length in its partition (chunk, at)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, seen, chunk = WordIds(tokenizer_path(tokenizer)), defaultdict(int), TaskContext.get().partitionId()
        end = array("I", [closing]).tobytes()
        for batch in batches:
            out = tuple([] for _ in range(7))
            for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                ids = words.of(text.as_py() or "") + end
                for k in range(0, len(ids) // 4, capacity):
                    part = ids[4 * k : 4 * (k + capacity)]
                    n = len(part) // 4
                    for column, x in zip(out, (doc_id, k // capacity, k, n, zlib.crc32(part), chunk, seen[n]), strict=True):
                        column.append(x)
                    seen[n] += 1
            yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(out, ARROW, strict=True)], names=NAMES)

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, PIECES)


def patterns(counts: np.ndarray, capacity: int, triples: int = 24) -> np.ndarray:
    """Rows of up to three lengths (0: none) that fill a sequence: all pairs, and for each length the triples whose others are most frequent."""
    have = np.flatnonzero(counts[: capacity + 1])
    have = have[have > 0]
    rows = {(capacity, 0, 0)} if counts[capacity] else set()
    there = counts > 0
    for a in have[have * 2 >= capacity]:
        if (b := capacity - int(a)) and there[b]:
            rows.add((int(a), b, 0))
    for a in have:
        room = capacity - int(a)
        b = have[(have <= a) & (have * 2 >= room) & (have < room)]
        c = room - b
        fits = there[c] & (c > 0)
        b, c = b[fits], c[fits]
        for k in np.argsort(-np.minimum(counts[b], counts[c]), kind="stable")[:triples]:
            rows.add((int(a), int(b[k]), int(c[k])))
    return np.asarray(sorted(rows), dtype=np.int64).reshape(-1, 3)


def fit(made: np.ndarray, counts: np.ndarray, rounds: int = 400) -> np.ndarray:
    """Repeats x >= 0 of the patterns that minimise the squared distance of their lengths' counts from `counts` (accelerated projected gradient)."""
    if not len(made):
        return np.zeros(0)
    size = len(counts)
    weigh = lambda x: sum(np.bincount(made[:, j], weights=x, minlength=size) for j in range(made.shape[1]))
    goal = counts.astype(float)
    goal[0] = 0.0
    back = lambda r: r[made].sum(axis=1)
    v = np.ones(len(made))
    for _ in range(20):  # largest eigenvalue, for the step
        r = weigh(v)
        r[0] = 0.0
        v = back(r)
        top = np.linalg.norm(v)
        v /= top
    x = y = np.zeros(len(made))
    t = 1.0
    for _ in range(rounds):
        r = weigh(y) - goal
        r[0] = 0.0
        new = np.maximum(0.0, y - back(r) / top / 1.01)
        t2 = (1 + (1 + 4 * t * t) ** 0.5) / 2
        y = new + (t - 1) / t2 * (new - x)
        x, t = new, t2
    return x


def runs(counts: np.ndarray, capacity: int) -> list[tuple[int, int, int, int, int]]:
    """(length, first, count, sequence, offset): pieces first .. first + count - 1 of the length go to sequences from `sequence` on, at `offset`."""
    left, used, out, sequence = counts.astype(np.int64).copy(), np.zeros(len(counts), np.int64), [], 0

    def place(lengths: tuple[int, ...], n: int) -> None:
        nonlocal sequence
        offset = 0
        for length in lengths:
            out.append((length, int(used[length]), n, sequence, offset))
            used[length] += n
            offset += length
        sequence += n

    made = patterns(counts, capacity)
    repeats = fit(made, counts)
    for k in np.argsort(-repeats, kind="stable"):
        lengths = tuple(int(x) for x in made[k] if x)
        n = int(repeats[k] + 1e-6)
        for x in set(lengths):
            n = min(n, int(left[x]) // lengths.count(x))
        if n > 0:
            for x in lengths:
                left[x] -= n
            place(lengths, n)
    by_room: dict[int, dict[tuple[int, ...], int]] = defaultdict(dict)
    rooms = np.zeros(capacity + 1, bool)

    def open_(room: int, lengths: tuple[int, ...], n: int) -> None:
        by_room[room][lengths] = by_room[room].get(lengths, 0) + n
        rooms[room] = True

    for length in np.flatnonzero(left)[::-1]:
        length, n = int(length), int(left[length])
        while n:
            fits = np.flatnonzero(rooms[length:])
            if not len(fits):
                each = capacity // length
                if full := n // each:
                    open_(capacity - each * length, (length,) * each, full)
                if rest := n % each:
                    open_(capacity - rest * length, (length,) * rest, 1)
                break
            room = length + int(fits[0])
            lengths, there = by_room[room].popitem()
            take = min(n, there)
            if take < there:
                by_room[room][lengths] = there - take
            rooms[room] = bool(by_room[room])
            open_(room - length, (*lengths, length), take)
            n -= take
    for room in sorted(by_room):
        for lengths, n in by_room[room].items():
            place(lengths, n)
    return out


def pack(docs: DataFrame, tokenizer: str = "word_bpe_49k.json", capacity: int = 2048, closing: int = 0) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset of every piece."""
    spark = docs.sparkSession
    cut_up = cut(pieces(docs, tokenizer, capacity, closing))
    by_chunk = cut(cut_up.groupBy("chunk", "length").agg(F.count("*").alias("n")))
    counts = np.zeros(capacity + 1, np.int64)
    for length, n in by_chunk.groupBy("length").agg(F.sum("n")).collect():  # at most `capacity` rows
        counts[length] = n
    found = spark.createDataFrame(runs(counts, capacity) or [(-1, 0, 0, 0, 0)], "r_length long, first long, count long, sequence long, offset long")
    earlier = Window.partitionBy("length").orderBy("chunk").rowsBetween(Window.unboundedPreceding, -1)
    before = by_chunk.withColumn("before", F.coalesce(F.sum("n").over(earlier), F.lit(0))).select("chunk", "length", "before")
    numbered = cut_up.join(before, ["chunk", "length"]).withColumn("nth", F.col("before") + F.col("at"))
    inside = (F.col("length") == F.col("r_length")) & (F.col("nth") >= F.col("first")) & (F.col("nth") < F.col("first") + F.col("count"))
    placed = numbered.join(F.broadcast(found), inside)  # runs are bounded by the lengths, not by the pieces
    return placed.select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("sequence") + F.col("nth") - F.col("first")).alias("sequence_id"), "offset")
