"""Graphs and partitions as SQL: views, measures as SQL text, and a table function."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphsplit.functions import columns
from graphsplit.model import Graph

#: Measures over the views v_vertices, v_edges (each edge once) and v_partition. `eps` and `k` are filled in as numbers.
MEASURES = {
    "cut": "SELECT CAST(coalesce(sum(e.w), 0) AS BIGINT) AS cut FROM v_edges e JOIN v_partition a ON a.vid = e.u JOIN v_partition b ON b.vid = e.v WHERE a.block <> b.block",
    "block_weights": "SELECT CAST(t.id AS INT) AS block, coalesce(sum(x.c), 0) AS weight, count(x.vid) AS vertices FROM range({k}) t LEFT JOIN (SELECT p.block, v.vid, v.c FROM v_partition p JOIN v_vertices v ON v.vid = p.vid) x ON x.block = t.id GROUP BY t.id",
    "feasible": "SELECT max(b.weight) <= max(l_max(t.total, {k}, {eps}D, t.heaviest)) AS feasible FROM (SELECT sum(v.c) AS weight FROM v_partition p JOIN v_vertices v ON v.vid = p.vid GROUP BY p.block) b CROSS JOIN (SELECT sum(c) AS total, max(c) AS heaviest FROM v_vertices) t",
    "boundary": "SELECT a.block, count(DISTINCT a.vid) AS boundary FROM (SELECT u AS x, v AS y FROM v_edges UNION ALL SELECT v, u FROM v_edges) e JOIN v_partition a ON a.vid = e.x JOIN v_partition b ON b.vid = e.y WHERE a.block <> b.block GROUP BY a.block",
}


def create_views(g: Graph, partition: DataFrame | None = None) -> None:
    """v_vertices (vid, c), v_edges (u, v, w with u < v) and, with a partition, v_partition (vid, block) of this session, with the SQL functions."""
    spark = g.vertices.sparkSession
    columns.register(spark)
    register_spans(spark)
    g.vertices.select("vid", "c").createOrReplaceTempView("v_vertices")
    g.edges.filter("src < dst").select(F.col("src").alias("u"), F.col("dst").alias("v"), "w").createOrReplaceTempView("v_edges")
    if partition is not None:
        partition.select("vid", "block").createOrReplaceTempView("v_partition")


def measure(spark: SparkSession, name: str, k: int = 1, eps: float = 0.03) -> DataFrame:
    return spark.sql(MEASURES[name].format(k=int(k), eps=float(eps)))


class BlockSpans:
    """Rows level, block, first, span: the final blocks that each block of a level stands for, when k blocks arise by repeated halving."""

    def eval(self, k: int):
        level, spans = 0, [k] if k and k > 0 else []
        while spans:
            first = 0
            for block, span in enumerate(spans):
                yield level, block, first, span
                first += span
            if max(spans) == 1:
                return
            level, spans = level + 1, [h for s in spans for h in ((s + 1) // 2, s // 2) if h]


def register_spans(spark: SparkSession) -> None:
    """SELECT * FROM block_spans(6), and with LATERAL for a column of k."""
    spark.udtf.register("block_spans", F.udtf(BlockSpans, returnType="level int, block int, first int, span int"))
