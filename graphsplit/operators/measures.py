"""What partitions and clusterings cost: cut, balance, feasibility, boundary, communication."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphsplit.functions.columns import l_classic, l_max
from graphsplit.model import Graph


def between(g: Graph, p: DataFrame) -> DataFrame:
    """Arcs with the blocks a and b of their ends."""
    b = p.select("vid", "block")
    return g.edges.join(b.withColumnsRenamed({"vid": "src", "block": "a"}), "src").join(b.withColumnsRenamed({"vid": "dst", "block": "b"}), "dst")


def edge_cut(g: Graph, p: DataFrame) -> DataFrame:
    return between(g, p).agg((F.coalesce(F.sum(F.when(F.col("a") != F.col("b"), F.col("w"))), F.lit(0)) / 2).cast("long").alias("cut"))


def block_matrix(g: Graph, p: DataFrame) -> DataFrame:
    """a < b, w: weight of the edges between two blocks."""
    return between(g, p).filter("a < b").groupBy("a", "b").agg(F.sum("w").alias("w"))


def block_weights(g: Graph, p: DataFrame, k: int) -> DataFrame:
    """block, weight, vertices, empty blocks included."""
    own = g.vertices.join(p, "vid").groupBy("block").agg(F.sum("c").alias("weight"), F.count("*").alias("vertices"))
    return g.vertices.sparkSession.range(k).select(F.col("id").cast("int").alias("block")).join(own, "block", "left").fillna({"weight": 0, "vertices": 0})


def imbalance(g: Graph, p: DataFrame, k: int) -> DataFrame:
    return block_weights(g, p, k).agg(F.round(F.max("weight") * k / F.lit(g.total) - 1, 9).alias("imbalance"))


def feasibility(g: Graph, p: DataFrame, k: int, eps: float) -> DataFrame:
    """One row: feasible by the relaxed and by the classic limit, overloaded blocks and their excess."""
    limit = F.lit(float(l_max(g.total, k, eps, g.heaviest)))
    return block_weights(g, p, k).agg(
        (F.max("weight") <= limit).alias("feasible"),
        (F.max("weight") <= F.lit(float(l_classic(g.total, k, eps)))).alias("classic"),
        F.count(F.when(F.col("weight") > limit, 1)).alias("overloaded"),
        F.round(F.sum(F.greatest(F.lit(0.0), F.col("weight") - limit)), 6).alias("excess"),
    )


def boundary_vertices(g: Graph, p: DataFrame) -> DataFrame:
    """block, boundary: vertices with a neighbour in another block."""
    return between(g, p).filter("a <> b").groupBy(F.col("a").alias("block")).agg(F.countDistinct("src").alias("boundary"))


def comm_volume(g: Graph, p: DataFrame) -> DataFrame:
    """block, volume: foreign blocks among the neighbours of each vertex, summed."""
    return between(g, p).filter("a <> b").select("a", "src", "b").distinct().groupBy(F.col("a").alias("block")).agg(F.count("*").alias("volume"))


def validate_partition(g: Graph, p: DataFrame, k: int) -> DataFrame:
    """One row: vertices, rows, distinct vertices with a block, rows of no vertex, labels out of range."""
    rows = p.agg(F.count("*").alias("rows"), F.countDistinct("vid").alias("distinct_vertices"), F.count(F.when((F.col("block") < 0) | (F.col("block") >= k) | F.col("block").isNull(), 1)).alias("out_of_range"))
    strange = p.join(g.vertices, "vid", "left_anti").agg(F.count("*").alias("strangers"))
    return rows.crossJoin(strange).withColumn("n", F.lit(g.n).cast("long"))


def clustering_stats(g: Graph, clustering: DataFrame, limit: float) -> DataFrame:
    """One row: clusters, heaviest, those over the limit, and the factor by which contraction shrinks."""
    w = g.vertices.join(clustering, "vid").groupBy("cluster").agg(F.sum("c").alias("c"))
    return w.agg(F.count("*").alias("clusters"), F.max("c").alias("heaviest"), F.count(F.when(F.col("c") > limit, 1)).alias("over"), F.round(F.lit(float(g.n)) / F.count("*"), 6).alias("shrink"))
