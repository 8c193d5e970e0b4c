"""Distribution over logical processing elements (PEs), and what they would have to exchange.

A PE is a column, not a Spark task: vertices with consecutive ids share one, arcs live with their tail.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from graphsplit.model import Graph, snapshot


def pe_of(vid: Column, n: int, pes: int) -> Column:
    return F.floor(vid * F.lit(pes) / F.lit(max(n, 1))).cast("int")


def assign_pe(g: Graph, pes: int, by: str = "vertices") -> DataFrame:
    """vid, c, pe: ranges of ids with equally many vertices, or (by='edges') about equally many arcs."""
    if by == "vertices":
        return g.vertices.withColumn("pe", pe_of(F.col("vid"), g.n, pes))
    # arcs before a vertex: sums over chunks of ids, and running sums within a chunk
    degrees = g.vertices.join(g.edges.groupBy(F.col("src").alias("vid")).agg(F.count("*").alias("deg")), "vid", "left").fillna({"deg": 0})
    chunk = F.floor(F.col("vid") / 65536)
    chunks = degrees.groupBy(chunk.alias("chunk")).agg(F.sum("deg").alias("d"))
    before = chunks.select("chunk", (F.sum("d").over(Window.orderBy("chunk").rowsBetween(Window.unboundedPreceding, 0)) - F.col("d")).alias("before"))
    run = F.sum("deg").over(Window.partitionBy("chunk").orderBy("vid").rowsBetween(Window.unboundedPreceding, 0)) - F.col("deg")
    rows = degrees.withColumn("chunk", chunk).withColumn("_run", run).join(before, "chunk")
    return rows.select("vid", "c", F.least(F.lit(pes - 1), F.floor((F.col("before") + F.col("_run")) * pes / F.lit(max(g.arcs, 1)))).cast("int").alias("pe"))


def arcs_by_pe(g: Graph, layout: DataFrame) -> DataFrame:
    """Arcs with the PEs of both ends."""
    at = layout.select("vid", "pe")
    return g.edges.join(at.withColumnsRenamed({"vid": "src", "pe": "src_pe"}), "src").join(at.withColumnsRenamed({"vid": "dst", "pe": "dst_pe"}), "dst")


def interface_vertices(g: Graph, layout: DataFrame) -> DataFrame:
    return arcs_by_pe(g, layout).filter("src_pe <> dst_pe").select(F.col("src").alias("vid")).distinct()


def ghost_table(g: Graph, layout: DataFrame) -> DataFrame:
    """pe, vid: copies of foreign vertices that a PE needs."""
    return arcs_by_pe(g, layout).filter("src_pe <> dst_pe").select(F.col("src_pe").alias("pe"), F.col("dst").alias("vid")).distinct()


def ghost_updates(moved: DataFrame, ghosts: DataFrame) -> DataFrame:
    """pe, vid, label: the changed labels (vid, label) and the PEs that hold a copy."""
    return moved.select("vid", "label").join(ghosts, "vid").select("pe", "vid", "label")


def hop(src: Column, dst: Column, pes: int) -> Column:
    """Where a message stops on a grid of side ceil(sqrt(P)): in the receiver's row, in the sender's column."""
    side = math.isqrt(pes - 1) + 1 if pes > 1 else 1
    stop = F.floor(dst / side) * side + src % side
    return F.when(stop < pes, stop).otherwise(dst).cast("int")


def exchange_direct(messages: DataFrame) -> DataFrame:
    """Messages (src_pe, dst_pe, ...) brought to their receivers in one shuffle."""
    return messages.repartition("dst_pe")


def exchange_grid(messages: DataFrame, pes: int) -> DataFrame:
    """The same in two shuffles, by way of the receiver's row and the sender's column."""
    half = messages.withColumn("_via", hop(F.col("src_pe"), F.col("dst_pe"), pes)).repartition("_via")
    return snapshot(half).drop("_via").repartition("dst_pe")


def exchange_cost(messages: DataFrame, pes: int, topology: str = "direct") -> DataFrame:
    """hop, messages, rows: pairs of different PEs that talk in each hop, and rows that travel. messages: src_pe, dst_pe, a row each."""
    if topology == "direct":
        out = messages.filter("src_pe <> dst_pe").select(F.lit(1).alias("hop"), F.col("src_pe").alias("a"), F.col("dst_pe").alias("b"))
    else:
        via = messages.filter("src_pe <> dst_pe").withColumn("via", hop(F.col("src_pe"), F.col("dst_pe"), pes))
        out = via.select(F.lit(1).alias("hop"), F.col("src_pe").alias("a"), F.col("via").alias("b")).union(via.select(F.lit(2), "via", "dst_pe")).filter("a <> b")
    return out.groupBy("hop", "a", "b").agg(F.count("*").alias("n")).groupBy("hop").agg(F.count("*").alias("messages"), F.sum("n").alias("rows"))
