"""Order in which label propagation visits vertices: degree buckets, shuffled chunks, batches. Never a global sort."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphsplit.functions.columns import coin, degree_bucket
from graphsplit.model import Graph


def degree_buckets(g: Graph) -> DataFrame:
    """vid, deg, bucket of every vertex."""
    return g.vertices.select("vid").join(g.degrees(), "vid", "left").fillna({"deg": 0}).withColumn("bucket", degree_bucket(F.col("deg")))


def traversal(g: Graph, layout: DataFrame, chunk_size: int, seed: int, order: str = "buckets") -> DataFrame:
    """vid, pe, pos: each PE's own order. Buckets of low degree first, cut into chunks; chunks and vertices in a chunk are shuffled.

    order='degree' sorts by degree instead, order='id' keeps ids.
    """
    rows = degree_buckets(g).join(layout.select("vid", "pe"), "vid")
    if order == "buckets":
        chunk = F.floor((F.row_number().over(Window.partitionBy("pe", "bucket").orderBy("vid")) - 1) / chunk_size)
        rows = rows.withColumn("chunk", chunk).withColumn("_c", coin(seed, "chunk", F.col("pe"), F.col("bucket"), F.col("chunk"))).withColumn("_v", coin(seed, "vertex", F.col("vid")))
        by = ["bucket", "_c", "chunk", "_v", "vid"]
    else:
        by = ["deg", "vid"] if order == "degree" else ["vid"]
    return rows.select("vid", "pe", (F.row_number().over(Window.partitionBy("pe").orderBy(*by)) - 1).alias("pos"))


def batches(order: DataFrame, count: int) -> DataFrame:
    """order with batch: each PE's positions cut into `count` consecutive, nearly equal pieces."""
    return order.withColumn("batch", F.ntile(count).over(Window.partitionBy("pe").orderBy("pos")) - 1)
