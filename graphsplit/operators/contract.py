"""Contraction of a clustering, placement of the coarse vertices on PEs, and projection back."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphsplit.model import Graph, dense_ids, discard, snapshot, stored
from graphsplit.operators.layout import pe_of


def coarse_vertices(g: Graph, clustering: DataFrame) -> DataFrame:
    return g.vertices.join(clustering, "vid").groupBy("cluster").agg(F.sum("c").alias("c"))


def coarse_arcs(g: Graph, clustering: DataFrame) -> DataFrame:
    """a, b, w: arcs between different clusters, merged; arcs inside vanish."""
    named = g.edges.join(clustering.withColumnsRenamed({"vid": "src", "cluster": "a"}), "src").join(clustering.withColumnsRenamed({"vid": "dst", "cluster": "b"}), "dst")
    return named.filter("a <> b").groupBy("a", "b").agg(F.sum("w").alias("w"))


def place_clusters(g: Graph, clustering: DataFrame, pes: int, delta: float = 1.1, arcs: DataFrame | None = None) -> DataFrame:
    """cluster, owner, pe: clusters stay with the owner of the vertex that names them, the largest by degree first, up to a cap; the surplus
    fills PEs from the emptiest on.

    The tables of PEs have a row each, which is what the unpartitioned windows see. Levels of equal sets of open PEs are intervals, at most two
    for each PE; the surplus finds its level and PE by arithmetic. arcs: coarse arcs a, b, if they are known.
    """
    sizes = clustering.groupBy("cluster").agg(F.count("*").alias("_n"))
    degree = (coarse_arcs(g, clustering) if arcs is None else arcs).groupBy(F.col("a").alias("cluster")).agg(F.count("*").alias("deg"))
    owned = snapshot(sizes.select("cluster", pe_of(F.col("cluster"), g.n, pes).alias("owner")).join(degree, "cluster", "left").fillna({"deg": 0}))
    n = owned.count()
    cap = max(math.floor(delta * n / pes), -(-n // pes))
    ranked = owned.withColumn("_r", F.row_number().over(Window.partitionBy("owner").orderBy(F.desc("deg"), "cluster")))
    kept = ranked.filter(F.col("_r") <= cap).select("cluster", "owner", F.col("owner").alias("pe"))
    surplus = ranked.filter(F.col("_r") > cap)
    # rank of a surplus cluster among all: its owner's offset plus its rank there
    offsets = surplus.groupBy("owner").agg(F.count("*").alias("_k"))
    offsets = offsets.select("owner", (F.sum("_k").over(Window.orderBy("owner").rowsBetween(Window.unboundedPreceding, 0)) - F.col("_k")).alias("_o"))
    moved = surplus.withColumn("_i", F.row_number().over(Window.partitionBy("owner").orderBy("cluster"))).join(F.broadcast(offsets), "owner").withColumn("_nth", F.col("_o") + F.col("_i") - 1)
    # water filling: slots go by level (how many a PE has already), then PE
    have = dict.fromkeys(range(pes), 0) | {r["pe"]: r["n"] for r in kept.groupBy("pe").agg(F.count("*").alias("n")).collect()}  # a row for each PE
    edges = sorted({x for x in have.values() if x < cap} | {cap})
    runs, nth = [], 0
    for low, high in zip(edges, edges[1:], strict=False):
        here = sorted(p for p, x in have.items() if x <= low)
        runs.append((nth, nth + (high - low) * len(here), len(here), here))
        nth += (high - low) * len(here)
    spark = kept.sparkSession
    levels = spark.createDataFrame(runs or [(0, 0, 1, [0])], "_from long, _to long, _wide int, _pes array<int>")  # at most a row for each PE
    at = moved.join(F.broadcast(levels), (F.col("_nth") >= F.col("_from")) & (F.col("_nth") < F.col("_to")))
    return kept.union(at.select("cluster", "owner", F.get("_pes", ((F.col("_nth") - F.col("_from")) % F.col("_wide")).cast("int")).alias("pe")))


def renumber(placed: DataFrame) -> DataFrame:
    """cluster, coarse_vid: consecutive ids, those of a PE together, in order of clusters."""
    sizes = placed.groupBy("pe").agg(F.count("*").alias("_k"))
    offsets = sizes.select("pe", (F.sum("_k").over(Window.orderBy("pe").rowsBetween(Window.unboundedPreceding, 0)) - F.col("_k")).alias("_o"))
    return placed.join(F.broadcast(offsets), "pe").select("cluster", (F.col("_o") + F.row_number().over(Window.partitionBy("pe").orderBy("cluster")) - 1).alias("coarse_vid"))


def contract(g: Graph, clustering: DataFrame, pes: int = 0, delta: float = 1.1) -> tuple[Graph, DataFrame]:
    """The coarse graph and the mapping vid, coarse_vid. With pes, ids follow the placement on PEs, otherwise the clusters' order.

    Arcs are merged under the clusters' names first; only what is left of them gets ids. Copies stay apart and in order.
    """
    clustering = snapshot(clustering)
    merged = stored(coarse_arcs(g, clustering))
    if pes and len(g.copies) == 1:
        names = snapshot(renumber(place_clusters(g, clustering, pes, delta, merged)))
    else:
        names = snapshot(dense_ids(clustering.select("cluster").distinct(), "cluster", "coarse_vid").select("cluster", "coarse_vid"))
    mapping = snapshot(clustering.join(names, "cluster").select("vid", "coarse_vid"))
    copy = [F.min("copy").alias("copy")] if "copy" in g.vertices.columns else []
    vertices = snapshot(g.vertices.join(mapping, "vid").groupBy(F.col("coarse_vid").alias("vid")).agg(F.sum("c").alias("c"), *copy))
    ends = lambda old, new: names.select(F.col("cluster").alias(old), F.col("coarse_vid").alias(new))
    arcs = stored(merged.join(ends("a", "src"), "a").join(ends("b", "dst"), "b").select("src", "dst", "w"))
    for table in (merged, names, clustering):  # all that was made from them is stored
        discard(table)
    return Graph.of(vertices, arcs), mapping


def project(partition: DataFrame, mapping: DataFrame) -> DataFrame:
    """vid, block of the finer level."""
    return mapping.join(partition.select(F.col("vid").alias("coarse_vid"), "block"), "coarse_vid").select("vid", "block")


def check_contraction(g: Graph, coarse: Graph, mapping: DataFrame) -> DataFrame:
    """One row: weights and arcs before and after, and what lies inside clusters."""
    m = mapping.withColumnRenamed("coarse_vid", "x")
    inside = g.edges.join(m.withColumnsRenamed({"vid": "src", "x": "_a"}), "src").join(m.withColumnsRenamed({"vid": "dst", "x": "_b"}), "dst").agg(F.sum("w").alias("fine_arcs"), F.coalesce(F.sum(F.when(F.col("_a") == F.col("_b"), F.col("w"))), F.lit(0)).alias("inside"))
    return inside.crossJoin(coarse.edges.agg(F.coalesce(F.sum("w"), F.lit(0)).alias("coarse_arcs"))).withColumn("fine_weight", F.lit(g.total).cast("long")).withColumn("coarse_weight", F.lit(coarse.total).cast("long")).withColumn("n", F.lit(coarse.n).cast("long"))
