"""Initial partitions of gathered graphs, and extension of the blocks of a distributed one."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphsplit.functions.columns import block_limit
from graphsplit.model import Graph, snapshot, stored
from graphsplit.operators import kernels
from graphsplit.operators.kernels import Csr


#: Arcs of a graph, or of a block, that one task may hold. More is an error: the scheme bounds the vertices it gathers, not their arcs.
TASK_ARCS = 50_000_000


def gather(g: Graph, vertices: int = 100_000) -> Csr:
    """The whole graph as arrays on the driver; an error if it has more vertices, or arcs, than a task may hold."""
    if g.n > vertices or g.arcs > TASK_ARCS:
        raise ValueError(f"{g.n} vertices and {g.arcs} arcs are too many for one task")
    v, e = g.vertices.select("vid", "c").toArrow().sort_by("vid"), g.edges.select("src", "dst", "w").toArrow()
    return Csr.of(np.asarray(v.column("c")), *(np.asarray(e.column(c)) for c in ("src", "dst", "w")))


def with_copy(g: Graph, rows: DataFrame, at: str) -> DataFrame:
    """rows with the copy of the vertex in column `at`."""
    if len(g.copies) == 1:
        return rows.withColumn("copy", F.lit(0))
    return rows.join(g.vertices.select(F.col("vid").alias(at), "copy"), at)


def replicate(g: Graph, copies: int) -> Graph:
    """Each copy of g `copies` times, with ids of their own: the j-th after the other, those of one copy of g together."""
    spark = g.vertices.sparkSession
    table = spark.createDataFrame([(i, j, int(off) * copies + j * int(n) - int(off)) for i, (off, n) in enumerate(g.copies) for j in range(copies)], "copy int, j int, shift long")  # a row for each group of PEs
    table = F.broadcast(table)
    vertices = with_copy(g, g.vertices.select("vid", "c"), "vid").join(table, "copy").select((F.col("vid") + F.col("shift")).alias("vid"), "c", (F.col("copy") * copies + F.col("j")).cast("int").alias("copy"))
    arcs = with_copy(g, g.edges, "src").join(table, "copy").select((F.col("src") + F.col("shift")).alias("src"), (F.col("dst") + F.col("shift")).alias("dst"), "w")
    return Graph.of(snapshot(vertices), stored(arcs))


def best_copies(g: Graph, partition: DataFrame, copies: int, blocks: int, limits: list[float], onto: Graph) -> DataFrame:
    """vid, block on `onto`, of which g is a replication: of the `copies` partitions of each of its copies the best, by excess, then cut, then number."""
    b = partition.select("vid", "block")
    arcs = g.edges.join(b.withColumnsRenamed({"vid": "src", "block": "_a"}), "src").join(b.withColumnsRenamed({"vid": "dst", "block": "_b"}), "dst")
    cuts = arcs.filter("_a <> _b").groupBy(F.floor(F.col("_a") / blocks).alias("copy")).agg(F.sum("w").alias("cut"))
    limit = F.get(F.array(*[F.lit(float(x)) for x in limits]), (F.col("block") % blocks).cast("int")) if len(limits) <= 64 else F.lit(float(max(limits)))
    over = g.vertices.select("vid", "c").join(partition, "vid").groupBy("block").agg(F.sum("c").alias("w")).withColumn("x", F.greatest(F.lit(0.0), F.col("w") - limit)).groupBy(F.floor(F.col("block") / blocks).alias("copy")).agg(F.sum("x").alias("excess"))
    rated = over.join(cuts, "copy", "left").fillna({"cut": 0})
    best = rated.groupBy(F.floor(F.col("copy") / copies).alias("home")).agg(F.min_by("copy", F.struct("excess", "cut", "copy")).alias("copy")).collect()  # a row for each group of PEs
    spark = partition.sparkSession
    table = spark.createDataFrame([(int(r["copy"]), int(r["home"]), int(onto.copies[int(r["home"])][0]) - int(g.copies[int(r["copy"])][0])) for r in best], "_copy long, _home long, _shift long")
    rows = partition.join(F.broadcast(table), F.floor(F.col("block") / blocks) == F.col("_copy"))
    return snapshot(rows.select((F.col("vid") + F.col("_shift")).alias("vid"), (F.col("_home") * blocks + F.col("block") % blocks).cast("int").alias("block")))


def trials(g: Graph, count: int, seed: int, solve) -> DataFrame:
    """copy, seed, infeasible, cut, part: `count` runs of solve(csr, seed) -> (labels, worst excess) for each copy of g, each in a task that gathers it.

    This is what the PEs of a group do with the coarsest graph: all get it, each solves it with its own seed.
    """
    if g.arcs / len(g.copies) > TASK_ARCS:
        raise RuntimeError(f"coarsening ended at {g.n} vertices and {g.arcs} arcs, more than a task may hold")

    def run(key: tuple, vertices: pa.Table, arcs: pa.Table) -> pa.Table:
        vertices = vertices.sort_by("vid")
        first, s = (vertices.column("vid")[0].as_py(), key[1].as_py())
        csr = Csr.of(np.asarray(vertices.column("c")), *(np.asarray(arcs.column(c)) - first for c in ("src", "dst")), np.asarray(arcs.column("w")))
        part, excess = solve(csr, s + 7919 * key[0].as_py())
        return pa.table({"copy": pa.array([key[0].as_py()], pa.int32()), "seed": pa.array([s], pa.int64()), "infeasible": pa.array([excess], pa.float64()), "cut": pa.array([csr.cut(part)], pa.int64()), "part": pa.array([part.astype(np.int32).tolist()], pa.list_(pa.int32()))})

    every = F.explode(F.sequence(F.lit(seed).cast("long"), F.lit(seed + count - 1).cast("long"))).alias("seed")
    spread = lambda rows: rows.select("*", every).repartition(len(g.copies) * count, "copy", "seed").groupBy("copy", "seed")
    own, arcs = with_copy(g, g.vertices.select("vid", "c"), "vid"), with_copy(g, g.edges, "src").select("copy", "src", "dst", "w")
    return snapshot(spread(own).cogroup(spread(arcs)).applyInArrow(run, "copy int, seed long, infeasible double, cut long, part array<int>"))


def select_best(found: DataFrame, g: Graph | None = None, blocks: int = 0) -> DataFrame:
    """vid, block of the best trial of each copy: feasible first, then least cut, then least seed."""
    best = found.groupBy("copy").agg(F.min_by("part", F.struct("infeasible", "cut", "seed")).alias("part"))
    rows = best.select("copy", F.posexplode("part").alias("vid", "block"))
    if g is None or len(g.copies) == 1:
        return rows.select(F.col("vid").cast("long").alias("vid"), "block")
    offsets = F.broadcast(g.vertices.sparkSession.createDataFrame([(i, int(off)) for i, (off, _) in enumerate(g.copies)], "copy int, off long"))
    return rows.join(offsets, "copy").select((F.col("vid") + F.col("off")).alias("vid"), (F.col("block") + F.col("copy") * blocks).alias("block"))


def excess_of(g: Csr, part: np.ndarray, limits: list[float]) -> float:
    return float(np.maximum(0, np.bincount(part, weights=g.c, minlength=len(limits)) - np.asarray(limits)).sum())


def initial_partition(g: Graph, spans: list[int], k: int, eps: float, count: int, seed: int, strong: bool = False) -> DataFrame:
    """The best of `count` recursive bisections into len(spans) blocks, of each copy."""

    def solve(csr: Csr, s: int) -> tuple[np.ndarray, float]:
        limits = kernels.limits_of(csr, spans, k, eps)
        part = kernels.settle(csr, kernels.split(csr, spans, limits, s, strong, eps), limits, 3, s)
        return part, excess_of(csr, part, limits)

    return snapshot(select_best(trials(g, count, seed, solve), g, len(spans)))


def induced_subgraphs(g: Graph, partition: DataFrame) -> DataFrame:
    """block, src, dst, w: the arcs inside blocks."""
    b = partition.select("vid", "block")
    arcs = g.edges.join(b.withColumnRenamed("vid", "src"), "src").join(b.withColumnsRenamed({"vid": "dst", "block": "_b"}), "dst")
    return arcs.filter("block = _b").select("block", "src", "dst", "w")


def block_graph(vertices: pa.Table, arcs: pa.Table) -> tuple[np.ndarray, Csr]:
    """Ids of a block's vertices, in order, and the graph that they induce."""
    if arcs.num_rows > TASK_ARCS:
        raise RuntimeError(f"a block of {arcs.num_rows} arcs is more than a task may hold")
    vertices = vertices.sort_by("vid")
    ids = np.asarray(vertices.column("vid"))
    src, dst = (np.searchsorted(ids, np.asarray(arcs.column(c))) for c in ("src", "dst"))
    return ids, Csr.of(np.asarray(vertices.column("c")), src, dst, np.asarray(arcs.column("w")))


def fill_empty(g: Graph, partition: DataFrame, k: int, eps: float, seed: int, strong: bool = False) -> DataFrame:
    """The partition with all k blocks in use: each empty one takes half of a heavy one. Limits only bound blocks from above."""
    while True:
        used = partition.join(g.vertices.select("vid", "c"), "vid").groupBy("block").agg(F.sum("c").alias("c"), F.count("*").alias("n")).collect()  # a row for each block
        empty = sorted(set(range(k)) - {r["block"] for r in used})
        if not empty:
            return partition
        full = [r["block"] for r in sorted(used, key=lambda r: (-r["c"], r["block"])) if r["n"] > 1]
        if not full:
            raise ValueError(f"fewer vertices than {k} blocks")
        other = dict(zip(full, empty, strict=False))

        def halve(key: tuple, vertices: pa.Table, arcs: pa.Table) -> pa.Table:
            b = key[0].as_py()
            ids, csr = block_graph(vertices, arcs)
            side = kernels.split(csr, [1, 1], [float("inf")] * 2, seed + 31 * b, strong, eps)
            if side.min() == side.max():
                side[csr.c.argmin()] = 1 - side[0]
            return pa.table({"vid": pa.array(ids), "block": pa.array(np.where(side == 0, b, other[b]).astype(np.int32))})

        shared = partition.filter(F.col("block").isin(list(other)))
        own = g.vertices.join(shared, "vid").select("block", "vid", "c").groupBy("block")
        inside = induced_subgraphs(g, shared).withColumnRenamed("block", "_block").groupBy("_block")
        halves = own.cogroup(inside).applyInArrow(halve, "vid long, block int")
        partition = snapshot(partition.filter(~F.col("block").isin(list(other))).select("vid", "block").union(halves))


def extend(g: Graph, partition: DataFrame, spans: list[int], target: int, parts: int, k: int, eps: float, seed: int, strong: bool = False) -> tuple[DataFrame, list[int]]:
    """Every block split into up to `parts`, towards `target` blocks a copy, each in a task of its own; the partition and the new spans.

    The deep scheme keeps a block of a level to a bounded number of vertices, so that one fits into a task.
    """
    children, more = kernels.widen(spans, target, parts)
    if not more:
        return partition, spans
    starts, blocks = np.cumsum([0] + [len(x) for x in children]).tolist(), len(spans)
    total, heaviest = g.total, g.heaviest

    def split_block(key: tuple, vertices: pa.Table, arcs: pa.Table) -> pa.Table:
        copy, b = divmod(key[0].as_py(), blocks)
        ids, csr = block_graph(vertices, arcs)
        limits = [block_limit(total, k, eps, heaviest, s) for s in children[b]]
        part = kernels.split(csr, children[b], limits, seed + 31 * b + 7919 * copy, strong, eps) + starts[b] + copy * starts[-1]
        return pa.table({"vid": pa.array(ids), "block": pa.array(part.astype(np.int32))})

    inside = induced_subgraphs(g, partition).withColumnRenamed("block", "_block").groupBy("_block")
    own = g.vertices.join(partition, "vid").select("block", "vid", "c").groupBy("block")
    return snapshot(own.cogroup(inside).applyInArrow(split_block, "vid long, block int")), [s for x in children for s in x]
