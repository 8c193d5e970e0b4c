"""Mixing sources to target weights by Pareto order sampling.

A source's target words are shared among its classes of document length (longer ones weigh slightly more), none above the most
repeats allowed. A document of a class gets the whole part of the class's mean repeats as certain copies. The rest is an inclusion
probability: documents are ranked by random odds divided by inclusion odds, and the best ranked ones are taken until the words that
the certain copies leave open are filled, to half a document. A source's rows are never gathered: ranks are cut into buckets, whose
words are summed; only the one bucket of each source in which the limit falls is sorted.

Defined results: a null text has no words; a null source is a source of its own, ordered last; empty texts are taken zero times;
repeated rows are taken or left one by one; ties of rank go to the smaller doc_id. Empty input gives an empty result. Other columns of
the documents don't matter.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from graphsplit.llm.common import cut, join_small, unit_hash, word_count

BUCKETS = 4096


def fill(df: DataFrame, group: list[str], cap: str, weight: str, total: str, out: str) -> DataFrame:
    """Shares `total` in each group in proportion to `weight`, no row above `cap`; what is cut off goes to the others.

    Rows sorted by cap over weight are full up to some row. The level, share over weight, if the first j were full, is largest at the
    true j, which makes it a maximum over the rows. One row is one source or class here, so these windows are small.
    """
    ratio = F.when(F.col(weight) > 0, F.col(cap) / F.col(weight)).otherwise(F.lit(0.0))
    whole = Window.partitionBy(*group)
    before = whole.orderBy("_ratio", *[c for c in df.columns if c not in group]).rowsBetween(Window.unboundedPreceding, -1)
    open_ = F.sum(weight).over(whole) - F.coalesce(F.sum(weight).over(before), F.lit(0))
    rest = F.col(total) - F.coalesce(F.sum(cap).over(before), F.lit(0))
    level = df.withColumn("_ratio", ratio).withColumn("_level", F.when(open_ > 0, rest / open_)).withColumn("_level", F.max("_level").over(whole))
    full = F.col("_ratio") <= F.col("_level") * F.lit(1 + 1e-12)
    return level.withColumn(out, F.when(full, F.col(cap).cast("double")).otherwise(F.col("_level") * F.col(weight))).drop("_ratio", "_level")


def length_weight(size_class: Column) -> Column:
    return size_class + F.lit(8)


def targets(sizes: DataFrame, weights: tuple[int, ...] = (1, 2, 3), share: float = 1.0, most: int = 3) -> DataFrame:
    """source, source_size, target for a table source, source_size; weights repeat over the sources in code point order, null last."""
    order = Window.orderBy(F.col("source").asc_nulls_last())
    ranked = sizes.withColumn("_at", F.row_number().over(order)).withColumn("weight", F.element_at(F.array(*[F.lit(w).cast("long") for w in weights]), (F.pmod(F.col("_at") - 1, F.lit(len(weights))) + 1).cast("int")))
    ranked = ranked.withColumn("cap", F.col("source_size") * most).withColumn("total", F.sum("source_size").over(Window.partitionBy()) * F.lit(float(share)))
    return fill(ranked.drop("_at"), [], "cap", "weight", "total", "target").select("source", "source_size", "target")


def levels(base: DataFrame, weights: tuple[int, ...], share: float, most: int) -> tuple[int, DataFrame]:
    """How many (source, size_class) there are, and for each of them source_size, target, certain, chance, open_words."""
    classes = cut(base.groupBy("source", "size_class").agg(F.sum("size").alias("class_size")))
    sources = targets(classes.groupBy("source").agg(F.sum("class_size").alias("source_size")), weights, share, most)
    n = classes.count()
    shares = join_small(classes, sources, ["source"], n)
    shares = shares.withColumn("cap", F.col("class_size") * most).withColumn("weight", F.col("class_size") * length_weight(F.col("size_class")))
    shares = fill(shares, ["source"], "cap", "weight", "target", "class_target")
    shares = shares.withColumn("mean", F.when(F.col("class_size") > 0, F.col("class_target") / F.col("class_size")).otherwise(F.lit(0.0)))
    shares = shares.withColumn("certain", F.floor("mean")).withColumn("chance", F.col("mean") - F.col("certain"))
    shares = shares.withColumn("open_words", F.col("target") - F.sum(F.col("certain") * F.col("class_size")).over(Window.partitionBy("source")))
    return n, cut(shares.select("source", "size_class", "source_size", "target", "certain", "chance", "open_words"))


def with_rank(base: DataFrame, shares: DataFrame, n: int, seed: str, buckets: int) -> DataFrame:
    """base with its class's share, its rank (null: nothing to draw) and the rank's bucket."""
    u = unit_hash(seed, F.col("doc_id"))
    odds = F.when((F.col("chance") > 0) & (F.col("size") > 0), (u / (F.lit(1.0) - u)) / (F.col("chance") / (F.lit(1.0) - F.col("chance"))))
    ranked = join_small(base, shares, ["source", "size_class"], n).withColumn("rank", odds)
    return ranked.withColumn("bucket", F.least(F.lit(buckets - 1), F.floor(F.col("rank") / (F.lit(1.0) + F.col("rank")) * buckets)))


def edges(ranked: DataFrame) -> DataFrame:
    """source, edge, before: the bucket in which the source's open words end, and the words of earlier buckets. Sources that take all have none."""
    ends = Window.partitionBy("source").orderBy("bucket")
    by_bucket = ranked.filter("rank is not null").groupBy("source", "bucket").agg(F.sum("size").alias("in_bucket"), F.first("open_words").alias("open_words"))
    edge = by_bucket.withColumn("_end", F.sum("in_bucket").over(ends)).withColumn("before", F.col("_end") - F.col("in_bucket"))
    return cut(edge.filter("before <= open_words and open_words < _end").select("source", F.col("bucket").alias("edge"), "before"))


def on_edge(placed: DataFrame) -> DataFrame:
    """The rows of the edge buckets, with extra: 1 as long as the words up to their middle fit."""
    upto = Window.partitionBy("source").orderBy("rank", "doc_id", "size").rowsBetween(Window.unboundedPreceding, 0)
    rows = placed.filter("bucket = edge").withColumn("_middle", F.col("before") + F.sum("size").over(upto) - F.col("size") / 2)
    return rows.withColumn("extra", (F.col("_middle") <= F.col("open_words")).cast("long")).drop("_middle")


def off_edge(rank: Column, bucket: Column, edge: Column) -> Column:
    return F.when(rank.isNull(), 0).when(edge.isNull() | (bucket < edge), 1).otherwise(0).cast("long")


def copies(extra: Column) -> Column:
    return F.when(F.col("size") > 0, F.col("certain") + extra).otherwise(F.lit(0)).cast("long")


def sized(docs: DataFrame, *more: Column) -> DataFrame:
    return docs.select("doc_id", "source", word_count(F.col("text")).alias("size"), *more).withColumn("size_class", F.length(F.bin("size")).cast("long"))


def plan(docs: DataFrame, weights: tuple[int, ...] = (1, 2, 3), share: float = 1.0, most: int = 3, seed: str = "mix", buckets: int = BUCKETS) -> DataFrame:
    """doc_id, size, source_size, target, taken of each row of docs."""
    base = cut(sized(docs))
    n, shares = levels(base, weights, share, most)
    ranked = with_rank(base, shares, n, seed, buckets)
    placed = join_small(ranked, edges(ranked), ["source"], n, "left")
    rest = placed.filter("edge is null or bucket is null or bucket <> edge").withColumn("extra", off_edge(F.col("rank"), F.col("bucket"), F.col("edge")))
    both = rest.unionByName(on_edge(placed))
    return both.select("doc_id", "size", "source_size", "target", (copies(F.col("extra")) * F.col("size")).alias("taken"))


def mix(docs: DataFrame, weights: tuple[int, ...] = (1, 2, 3), share: float = 1.0, most: int = 3, seed: str = "mix", buckets: int = BUCKETS) -> DataFrame:
    """The mixed corpus itself: every row of docs as often as it is taken, with its columns.

    The last rank taken of each source is a small table, so that texts are read once more and never shuffled. Rows of one doc_id and
    size have one rank and are taken together here.
    """
    base = cut(sized(docs))
    n, shares = levels(base, weights, share, most)
    ranked = with_rank(base, shares, n, seed, buckets)
    edge = edges(ranked)
    place = lambda size: F.struct("rank", F.col("doc_id").isNotNull(), "doc_id", size)
    last = on_edge(join_small(ranked, edge, ["source"], n)).filter("extra = 1").groupBy(F.col("source").alias("_s")).agg(F.max(place("size")).alias("last"))
    edge = cut(edge.join(last, F.col("source").eqNullSafe(F.col("_s")), "left").drop("_s"))
    rows = join_small(with_rank(sized(docs, F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_row")), shares, n, seed, buckets), edge, ["source"], n, "left")
    extra = F.when(F.col("bucket") == F.col("edge"), F.coalesce(place("size") <= F.col("last"), F.lit(False)).cast("long")).otherwise(off_edge(F.col("rank"), F.col("bucket"), F.col("edge")))
    taken = rows.withColumn("_copies", copies(extra)).filter("_copies > 0")
    return taken.withColumn("_copy", F.explode(F.sequence(F.lit(1), F.col("_copies").cast("int")))).select("_row.*")


SQL = r"""
WITH d AS (
  SELECT doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::BIGINT AS size FROM documents
), d2 AS (SELECT *, length(bin(size)) AS size_class FROM d),
c AS (SELECT source, size_class, sum(size)::BIGINT AS class_size FROM d2 GROUP BY ALL),
s AS (SELECT source, sum(class_size)::BIGINT AS source_size FROM c GROUP BY ALL),
s1 AS (SELECT *, 3 * source_size AS cap, 1 + (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 AS w, sum(source_size) OVER () AS total FROM s),
s2 AS (SELECT *, cap::DOUBLE / w AS ratio FROM s1),
s3 AS (SELECT *, sum(w) OVER () - coalesce(sum(w) OVER b, 0) AS open_w, total - coalesce(sum(cap) OVER b, 0) AS rest FROM s2
  WINDOW b AS (ORDER BY ratio, source NULLS FIRST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
s4 AS (SELECT *, max(rest::DOUBLE / open_w::DOUBLE) OVER () AS level FROM s3),
s5 AS (SELECT source, source_size, CASE WHEN ratio <= level * (1 + 1e-12) THEN cap::DOUBLE ELSE level * w END AS target FROM s4),
k1 AS (SELECT c.source, size_class, class_size, source_size, target, 3 * class_size AS cap, class_size * (size_class + 8) AS w,
  CASE WHEN class_size > 0 THEN (3 * class_size)::DOUBLE / (class_size * (size_class + 8)) ELSE 0 END AS ratio
  FROM c JOIN s5 ON c.source IS NOT DISTINCT FROM s5.source),
k2 AS (SELECT *, sum(w) OVER (PARTITION BY source) - coalesce(sum(w) OVER b, 0) AS open_w, target - coalesce(sum(cap) OVER b, 0)::DOUBLE AS rest FROM k1
  WINDOW b AS (PARTITION BY source ORDER BY ratio, size_class ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
k3 AS (SELECT *, max(CASE WHEN open_w > 0 THEN rest / open_w::DOUBLE END) OVER (PARTITION BY source) AS level FROM k2),
k4 AS (SELECT *, CASE WHEN class_size = 0 THEN 0 WHEN ratio <= level * (1 + 1e-12) THEN cap::DOUBLE / class_size ELSE level * w / class_size END AS mean FROM k3),
k5 AS (SELECT *, floor(mean) AS certain, mean - floor(mean) AS chance, target - sum(floor(mean) * class_size) OVER (PARTITION BY source) AS open_words FROM k4),
u AS (SELECT d2.*, source_size, target, certain, chance, open_words,
  (('0x' || substr(md5('mix:' || coalesce(doc_id::VARCHAR, 'null')), 1, 12))::BIGINT + 0.5::DOUBLE) / 281474976710656.0::DOUBLE AS u
  FROM d2 JOIN k5 ON d2.source IS NOT DISTINCT FROM k5.source AND d2.size_class = k5.size_class),
r AS (SELECT *, CASE WHEN chance > 0 AND size > 0 THEN (u / (1 - u)) / (chance / (1 - chance)) END AS rank FROM u),
m AS (SELECT *, sum(CASE WHEN rank IS NULL THEN 0 ELSE size END) OVER (PARTITION BY source ORDER BY rank NULLS LAST, doc_id, size ROWS UNBOUNDED PRECEDING) - size / 2.0 AS middle FROM r)
SELECT doc_id, size, source_size, target, (size * (certain + CASE WHEN rank IS NOT NULL AND middle <= open_words THEN 1 ELSE 0 END))::BIGINT AS taken FROM m
"""
