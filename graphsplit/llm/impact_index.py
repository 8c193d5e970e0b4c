"""Exact top-k inner products with an impact-ordered index, processed a score at a time.

Vectors are cut into blocks. In a block every dimension has posting lists: the rows whose quantised component has one level are a segment. A
query takes the segments of all dimensions from one queue, by descending impact (its weight times the level), and adds each segment's score to
the accumulators of the rows in it. What a row has met bounds its score from both sides: the rounding of what was met, by the norm of the row's
rounding errors, and what was not met, by the norms of the rest of the query and of the rest of the row. A query's search of a block stops
only when that proves all but a few rows out of its k best (or when no segment is left); those few are rescored exactly. The k best of each
block are merged.

Every query meets every block once: index blocks and blocks of queries are dealt to tasks by (block, slice of the queries), a task reads its
index block and then one block of queries after the other. Nothing is broadcast.

Defined results: vectors that are null or hold null or non-finite components, and rows without id, take no part; components beyond a
shorter vector's end count as zero. Rows that share a query's id count as its own and aren't its candidates; of repeated queries one is
asked. Repeated candidates are ranked one by one. Ties go to the smaller id. Scores are 64-bit integers; larger ones aren't supported. Empty
input gives an empty result. Other columns don't matter, whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from graphsplit.llm.common import cut

BLOCK = 16384
QUERIES = 512
LEVELS = 64
#: Segments that are added at once, and how many such steps lie between checks of the bounds.
STEP = 64
CHECK = 4
#: Blocks of queries that one task takes past its index block.
SLICE = 16


def quantised(vector: Column, scale: float = 1024.0) -> Column:
    return F.transform(vector, lambda x: F.floor(F.lit(scale) * x.cast("double")))


def usable(vectors: DataFrame) -> DataFrame:
    """vec_id and v, the scaled integer components, of the rows that take part."""
    good = F.col("embedding").isNotNull() & F.forall("embedding", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf"))))
    return vectors.filter(F.col("vec_id").isNotNull() & F.coalesce(good, F.lit(False))).select(F.col("vec_id").cast("long").alias("vec_id"), quantised(F.col("embedding")).alias("v"))


def matrix(column: pa.ChunkedArray | pa.Array) -> np.ndarray:
    """Rows of a list column, shorter ones filled with zeros."""
    a = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    sizes = np.asarray(pa.compute.list_value_length(a))
    out = np.zeros((len(sizes), int(sizes.max(initial=0))), np.int64)
    out[np.arange(out.shape[1]) < sizes[:, None]] = np.asarray(a.flatten())
    return out


def blocks(rows: DataFrame, size: int, column: str) -> DataFrame:
    """Rows vec_id, v gathered as one row a block: its number, ids and components as bytes."""
    n = max(1, -(-rows.count() // size))

    def gather(table: pa.Table) -> pa.Table:
        table = table.sort_by("vec_id")
        x = matrix(table.column("v"))
        return pa.table({column: [table.column(column)[0].as_py()], "ids": [np.asarray(table.column("vec_id")).tobytes()], "dims": [x.shape[1]], "x": [x.tobytes()]}, schema=pa.schema([(column, pa.int32()), ("ids", pa.binary()), ("dims", pa.int32()), ("x", pa.binary())]))

    numbered = rows.withColumn(column, F.pmod(F.xxhash64("vec_id"), F.lit(n)).cast("int"))
    return numbered.groupBy(column).applyInArrow(gather, f"{column} int, ids binary, dims int, x binary")


class Postings:
    """The impact-ordered lists of one block: for each dimension the rows of each level, and the rows' norms."""

    def __init__(self, ids: np.ndarray, x: np.ndarray, levels: int = LEVELS):
        self.ids, self.x = ids, x
        low, high = (int(x.min()), int(x.max())) if x.size else (0, 0)
        width = (high - low) // levels + 1
        level = (x - low) // width
        least = low + np.arange(levels) * width
        self.middle = least + (width - 1) / 2
        #: least square that a component of a level can have
        self.energy = np.where((least <= 0) & (least + width > 0), 0, np.minimum(np.abs(least), np.abs(least + width - 1))).astype(float) ** 2
        self.rows = np.argsort(level, axis=0, kind="stable").T.astype(np.int32)  # of each dimension, by level
        counts = np.stack([np.bincount(c, minlength=levels) for c in level.T]) if x.shape[1] else np.zeros((0, levels), np.int64)
        ends = counts.cumsum(axis=1)
        self.dimension, self.level = np.nonzero(counts)  # the segments
        self.start, self.end = (ends - counts)[self.dimension, self.level], ends[self.dimension, self.level]
        self.rounding = np.sqrt(((x - self.middle[level]) ** 2).sum(axis=1))
        self.squares = (x.astype(float) ** 2).sum(axis=1)

    def search(self, query_id: int, q: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, int, int]:
        """Ids and scores of the k best rows for one query, how many segments were processed, and how many rows were rescored."""
        n, weight = len(self.ids), q[self.dimension].astype(float)
        score, met, known = np.zeros(n), np.zeros(n), np.zeros(n)
        gain, mass, energy = weight * self.middle[self.level], weight**2, self.energy[self.level]
        queue = np.argsort(-np.abs(gain), kind="stable")
        queue = queue[weight[queue] != 0]
        whole, own = float((q.astype(float) ** 2).sum()), self.ids == query_id
        few, done, left = max(4 * k, n // 64), 0, ~own
        for turn, at in enumerate(range(0, max(1, len(queue)), STEP), 1):
            some = queue[at : at + STEP]
            if len(some):
                rows = np.concatenate([self.rows[d, a:b] for d, a, b in zip(self.dimension[some].tolist(), self.start[some].tolist(), self.end[some].tolist(), strict=True)])
                sizes = self.end[some] - self.start[some]
                for total, part in ((score, gain), (met, mass), (known, energy)):
                    total += np.bincount(rows, weights=np.repeat(part[some], sizes), minlength=n)
            done += len(some)
            if turn % CHECK and done < len(queue):
                continue
            # a hair of room for rounding of large numbers
            room = (np.sqrt(met) * self.rounding + np.sqrt(np.maximum(0, whole - met) * np.maximum(0, self.squares - known))) * (1 + 1e-9) + 1 + np.abs(score) * 1e-9
            lower = np.where(own, -np.inf, score - room)
            limit = np.partition(lower, n - k)[n - k] if n > k else -np.inf
            left = ~own & (score + room >= limit)
            if left.sum() <= few:
                break
        rows = np.flatnonzero(left)
        exact = self.x[rows] @ q
        best = np.lexsort((self.ids[rows], -exact))[:k]
        return self.ids[rows[best]], exact[best], done, len(rows)

    def widened(self, width: int) -> Postings:
        return Postings(self.ids, np.pad(self.x, ((0, 0), (0, width - self.x.shape[1])))) if width > self.x.shape[1] else self


def search(index: DataFrame, queries: DataFrame, k: int = 10) -> DataFrame:
    """query_id, rank, vec_id, score, segments, rescored: for each row of a table of query blocks the k best of a table of index blocks.

    segments and rescored count what the row's block processed for the query.
    """
    blocks_, asked = index.agg(F.max("block")).first()[0], queries.agg(F.max("q_block")).first()[0]
    slices = (asked or 0) // SLICE + 1
    every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n)))
    here = index.select("block", every(slices - 1).alias("slice"), F.lit(0).alias("role"), "ids", "dims", "x")
    there = queries.select(every(blocks_ or 0).alias("block"), F.pmod("q_block", F.lit(slices)).alias("slice"), F.lit(1).alias("role"), "ids", "dims", "x")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, postings = None, None
        for batch in batches:
            for row in range(batch.num_rows):
                block, slice_, role, ids, dims, x = (c[row].as_py() for c in batch.columns)
                ids = np.frombuffer(ids, np.int64)
                x = np.frombuffer(x, np.int64).reshape(len(ids), dims)
                if role == 0:
                    at, postings = (block, slice_), Postings(ids, x)
                    continue
                if (block, slice_) != at:
                    continue  # an empty block
                postings = postings.widened(dims)
                out = []
                for query_id, q in zip(ids.tolist(), x, strict=True):
                    found, scores, segments, rescored = postings.search(query_id, np.pad(q, (0, postings.x.shape[1] - dims)), k)
                    out += [(query_id, i, s, segments, rescored) for i, s in zip(found.tolist(), scores.tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in (zip(*out, strict=True) if out else ([],) * 5)], names=["query_id", "vec_id", "score", "segments", "rescored"])

    # an Arrow batch holds whole rows of index blocks: few groups a partition
    parts = min(20_000, ((blocks_ or 0) + 1) * slices)
    dealt = here.union(there).repartition(parts, "block", "slice").sortWithinPartitions("block", "slice", "role")
    local = dealt.mapInArrow(run, "query_id long, vec_id long, score long, segments long, rescored long")
    ranked = local.withColumn("rank", F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")))
    return ranked.filter(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score", "segments", "rescored")


def build(vectors: DataFrame, size: int = BLOCK) -> DataFrame:
    return cut(blocks(usable(vectors), size, "block"))


def nearest(vectors: DataFrame, k: int = 10, every: int = 100) -> DataFrame:
    """The k best partners of every row whose id is divisible by `every`, among all other rows."""
    asked = usable(vectors.filter(F.col("vec_id") % every == 0)).groupBy("vec_id").agg(F.min("v").alias("v"))
    return search(build(vectors), cut(blocks(asked, QUERIES, "q_block")), k)


SQL = """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(1024 * x::DOUBLE)::BIGINT) AS v FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
q AS (SELECT * FROM v WHERE vec_id % 100 = 0),
p AS (SELECT q.vec_id AS query_id, v.vec_id, list_sum(list_transform(range(1, len(v.v) + 1), lambda i: q.v[i] * v.v[i]))::BIGINT AS score
  FROM q JOIN v ON q.vec_id <> v.vec_id),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INT AS rank FROM p)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 10
"""
