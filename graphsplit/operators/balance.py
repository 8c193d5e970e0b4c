"""Refinement by label propagation over blocks, and the greedy global balancer that restores the limits."""

from __future__ import annotations

import heapq

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphsplit.functions.columns import relative_gain
from graphsplit.model import Graph, snapshot
from graphsplit.operators.cluster import rate, sweeps
from graphsplit.operators.fleet import Fleet, laid_out, propagate
from graphsplit.operators.layout import assign_pe

#: Rounds that the root PE may take for a block's excess; with more ahead, moves are decided in Spark.
ROUNDS = 4
#: Tables of at most so many blocks are broadcast.
BROADCAST_BLOCKS = 1_000_000


def small(table: DataFrame, blocks: int) -> DataFrame:
    """A table with a row for each block, broadcast if its size allows it."""
    return F.broadcast(table) if blocks <= BROADCAST_BLOCKS else table


def limit_table(g: Graph, limits: list[float]) -> DataFrame:
    """block, limit: a row for each block of each copy."""
    every = [float(x) for _ in g.copies for x in limits]
    return g.vertices.sparkSession.createDataFrame(list(enumerate(every)), "block int, limit double")


def weighted(g: Graph, partition: DataFrame, limits: list[float]) -> DataFrame:
    """block, weight, limit of every block, empty ones too."""
    own = g.vertices.select("vid", "c").join(partition, "vid").groupBy("block").agg(F.sum("c").alias("weight"))
    return limit_table(g, limits).join(own, "block", "left").fillna({"weight": 0})


def lp_refine(g: Graph, partition: DataFrame, limits: list[float], iterations: int, pes: int, seed: int, limit_mode: str = "overshoot", batches: int | None = None, fleet: Fleet | None = None, trace: dict | None = None) -> DataFrame:
    """vid, block after sweeps that move vertices to better connected blocks with room; ties to the lighter block.

    Blocks may overshoot when several PEs choose the same one in a batch, as each PE only knows the others' weights from the batch's start.
    'strict' admits only what fits, in synchronous supersteps.
    """
    if limit_mode == "strict":
        state = snapshot(assign_pe(g, pes).join(partition, "vid").select("vid", "c", "pe", F.col("block").cast("long").alias("label")))
        weights = snapshot(weighted(g, partition, limits).select(F.col("block").cast("long").alias("label"), "weight", "limit"))
        state, _ = sweeps(g, state, weights, None, iterations, pes, seed, limit_mode, "lighter", batches or 2)
        return state.select("vid", F.col("label").cast("int").alias("block"))
    weights = [r["weight"] for r in sorted(weighted(g, partition, limits).collect(), key=lambda r: r["block"])]  # a row for each block
    labels = partition.select("vid", F.col("block").cast("long").alias("label"))
    found = propagate(g, pes, [x for _ in g.copies for x in limits], iterations, seed, "overshoot", labels, weights, len(limits), batches, trace=trace, fleet=fleet)
    return found.select("vid", F.col("label").cast("int").alias("block"))


def move_gains(g: Graph, partition: DataFrame, vids: DataFrame | None = None) -> DataFrame:
    """vid, block, gain: what moving a vertex to an adjacent block would cut less."""
    state = partition.select("vid", F.col("block").alias("label"))
    conn = rate(g.edges, state, vids)
    rows = conn.join(partition.withColumnRenamed("block", "own"), "vid")
    own = F.coalesce(F.sum(F.when(F.col("label") == F.col("own"), F.col("conn"))).over(Window.partitionBy("vid")), F.lit(0))
    return rows.withColumn("gain", F.col("conn") - own).filter("label <> own").select("vid", F.col("label").alias("block"), "gain")


def overloaded(weights: DataFrame) -> DataFrame:
    """block, excess of the blocks above their limits."""
    return weights.filter("weight > limit").select("block", (F.col("weight") - F.col("limit")).alias("excess"))


def connections(g: Graph, partition: DataFrame, weights: DataFrame) -> DataFrame:
    """vid, label, conn of the vertices in overloaded blocks: what a PE's queues are made from."""
    return rate(g.edges, partition.select("vid", F.col("block").alias("label")), partition.join(overloaded(weights), "block"))


def moved_connections(g: Graph, conn: DataFrame, moves: DataFrame) -> DataFrame:
    """conn after moves (vid, old, new): only the neighbours of moved vertices change, by the arcs between."""
    told = g.edges.join(moves.select(F.col("vid").alias("dst"), "old", "new"), "dst").select(F.col("src").alias("vid"), F.explode(F.array(F.struct(F.col("old").alias("label"), (-F.col("w")).alias("conn")), F.struct(F.col("new").alias("label"), F.col("w").alias("conn")))).alias("d"))
    deltas = told.join(conn.select("vid").distinct(), "vid", "left_semi").select("vid", "d.label", "d.conn")
    return conn.union(deltas).groupBy("vid", "label").agg(F.sum("conn").alias("conn")).filter("conn <> 0")


def local_candidates(g: Graph, partition: DataFrame, layout: DataFrame, weights: DataFrame, rating: str = "relative", conn: DataFrame | None = None, blocks: int | None = None) -> DataFrame:
    """pe, block, vid, c, target, gain, rel_gain: on each PE, just enough of the best vertices of each overloaded block to cover its excess.

    A target is the best connected block with room, or else the lightest block of the copy with room, adjacent or not. A row is kept while the
    weight of better ones is below the excess. conn: connections of the vertices in overloaded blocks, if known; blocks: those of a copy.
    """
    count = blocks * len(g.copies) if blocks else BROADCAST_BLOCKS + 1
    rows = partition.join(small(overloaded(weights), count), "block").join(layout.select("vid", "c", "pe"), "vid")
    if conn is None:
        conn = connections(g, partition, weights)
    own = conn.join(partition.withColumnRenamed("block", "label"), ["vid", "label"]).select("vid", F.col("conn").alias("own"))
    options = conn.select("vid", F.col("label").alias("target"), "conn")
    home = lambda b: F.floor(F.col(b) / (blocks or 2**31)).alias("home")
    lightest = weights.groupBy(home("block")).agg(F.min_by("block", F.struct("weight", "block")).alias("target"))  # a row for each copy
    options = options.union(rows.select("vid", home("block")).join(F.broadcast(lightest), "home").select("vid", "target", F.lit(0).cast("long")))
    best = options.groupBy("vid", "target").agg(F.max("conn").alias("conn")).join(small(weights.select(F.col("block").alias("target"), "weight", "limit"), count), "target")
    best = best.join(rows, "vid").filter((F.col("target") != F.col("block")) & (F.col("weight") + F.col("c") <= F.col("limit")))
    best = best.groupBy("vid", "pe", "block", "c", "excess").agg(F.max(F.struct("conn", (-F.col("weight")).alias("_w"), (-F.col("target")).alias("_t"))).alias("best"))
    best = best.join(own, "vid", "left").withColumn("gain", F.col("best.conn") - F.coalesce("own", F.lit(0))).withColumn("target", -F.col("best._t"))
    rated = best.withColumn("rel_gain", relative_gain(F.col("gain"), F.col("c")) if rating == "relative" else F.col("gain").cast("double"))
    before = F.coalesce(F.sum("c").over(Window.partitionBy("pe", "block").orderBy(F.desc("rel_gain"), "vid").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return rated.withColumn("_before", before).filter("_before < excess").select("pe", "block", "vid", "c", "target", "gain", "rel_gain")


def top_ell(candidates: DataFrame, ell: int, weights: DataFrame | None = None) -> DataFrame:
    """The best `ell` candidates of each block; limited on each side of the shuffle. With weights, sooner if a shorter prefix covers the excess."""
    best = Window.partitionBy("block").orderBy(F.desc("rel_gain"), "vid")
    top = candidates.withColumn("_r", F.row_number().over(best)).filter(F.col("_r") <= ell).drop("_r")
    if weights is None:
        return top
    before = F.coalesce(F.sum("c").over(best.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return top.join(overloaded(weights), "block").withColumn("_before", before).filter("_before < excess").drop("_before", "excess")


def decide_moves(candidates: list, weights: dict[int, tuple[int, float]], blocks: int | None = None) -> list[tuple[int, int, int]]:
    """(vid, old, target) of the candidates (block, vid, c, target, rel_gain) that are taken, one by one, best first.

    Weights change along the way: a source that is no longer overloaded keeps the rest, a full target is replaced by the lightest block of the
    copy if that has room.
    """
    load, out, heaps = {b: w for b, (w, _) in weights.items()}, [], {}
    for b, w in load.items():
        heaps.setdefault(b // (blocks or 2**31), []).append((w, b))
    for h in heaps.values():
        heapq.heapify(h)
    for block, vid, c, target, _ in sorted(candidates, key=lambda r: (-r[4], r[1])):
        if load[block] <= weights[block][1]:
            continue
        if load[target] + c > weights[target][1]:
            heap = heaps[block // (blocks or 2**31)]
            while heap[0][0] != load[heap[0][1]]:  # outdated
                heapq.heapreplace(heap, (load[heap[0][1]], heap[0][1]))
            target = heap[0][1]
            if target == block or load[target] + c > weights[target][1]:
                continue
        load[block] -= c
        load[target] += c
        heapq.heappush(heaps[block // (blocks or 2**31)], (load[block], block))
        out.append((vid, block, target))
    return out


def window_moves(candidates: DataFrame, weights: DataFrame) -> DataFrame:
    """vid, old, new: the same decision for very many blocks, without the driver: sources give no more than covers their excess, targets admit
    the best while they have room. The best candidate of a target always fits, so that every round moves something.
    """
    upto = lambda by: F.sum("c").over(Window.partitionBy(by).orderBy(F.desc("rel_gain"), "vid").rowsBetween(Window.unboundedPreceding, 0))
    room = weights.select(F.col("block").alias("target"), (F.col("limit") - F.col("weight")).alias("_room"))
    excess = weights.select("block", (F.col("weight") - F.col("limit")).alias("_excess"))
    given = candidates.join(excess, "block").withColumn("_given", upto("block") - F.col("c")).filter("_given < _excess")
    return given.join(room, "target").withColumn("_w", upto("target")).filter("_w <= _room").select("vid", F.col("block").alias("old"), F.col("target").alias("new"))


def balance_round(g: Graph, partition: DataFrame, layout: DataFrame, weights: DataFrame, ell: int, rating: str = "relative", decide: str = "driver", conn: DataFrame | None = None, blocks: int | None = None) -> tuple[DataFrame, DataFrame | None]:
    """The partition after one round, and its moves vid, old, new; none if there aren't any. decide: 'all' is 'window' for more than `ell` candidates."""
    chosen = local_candidates(g, partition, layout, weights, rating, conn, blocks).select("block", "vid", "c", "target", "rel_gain")
    if decide != "all":
        chosen = top_ell(chosen, ell, weights)
    if decide != "driver":
        moves = snapshot(window_moves(chosen, weights))
        if not moves.count():
            return partition, None
    else:
        taken = decide_moves([tuple(r) for r in chosen.collect()], {r["block"]: (r["weight"], r["limit"]) for r in weights.collect()}, blocks)  # ell rows a block; a row a block
        if not taken:
            return partition, None
        moves = g.vertices.sparkSession.createDataFrame(taken, "vid long, old int, new int")  # at most ell a block
    return snapshot(partition.join(moves.select("vid", "new"), "vid", "left").select("vid", F.coalesce("new", "block").cast("int").alias("block"))), moves


def balance(g: Graph, partition: DataFrame, limits: list[float], ell: int = 1024, pes: int = 16, rating: str = "relative", decide: str = "driver", trace: dict | None = None) -> DataFrame:
    """A partition without overloaded blocks. Every round takes weight out of an overloaded block and overloads none, so that it ends.

    decide: 'driver' is the root PE, which sees `ell` candidates a block; 'window' decides in Spark, for k too large for that. Where a block's excess
    is that of more than `ROUNDS` times `ell` mean vertices, a round of windows over all candidates comes first: else rounds would grow with the graph.
    """
    layout, conn, rounds, total = None, None, 0, 0
    while True:
        weights = snapshot(weighted(g, partition, limits))
        excess = overloaded(weights).agg(F.max("excess")).first()[0]
        if excess is None:
            if trace is not None:
                trace.update(rounds=rounds, balance_moves=total)
            return partition
        if layout is None:
            layout = snapshot(laid_out(g, pes))
            conn = snapshot(connections(g, partition, weights))
        partition, moves = balance_round(g, partition, layout, weights, ell, rating, "all" if excess * g.n > ROUNDS * ell * g.total * len(g.copies) else decide, conn, len(limits))
        if moves is None:
            raise RuntimeError("no vertex fits into any block: limits below the mean block weight plus the heaviest vertex")
        # only neighbours of moved vertices have other gains; blocks that were settled meanwhile take no part
        conn = snapshot(moved_connections(g, conn, moves))
        rounds, total = rounds + 1, total + moves.count()


def settle(g: Graph, partition: DataFrame, limits: list[float], iterations: int, pes: int, seed: int, ell: int = 1024, batches: int | None = None, limit_mode: str = "overshoot", fleet: Fleet | None = None, decide: str = "driver", trace: dict | None = None) -> DataFrame:
    """Balance, refine, balance."""
    first, last, moves = {}, {}, {}
    partition = balance(g, partition, limits, ell, pes, decide=decide, trace=first)
    partition = lp_refine(g, partition, limits, iterations, pes, seed, limit_mode, batches, fleet, moves)
    partition = balance(g, partition, limits, ell, pes, decide=decide, trace=last)
    if trace is not None:
        trace.update(moves, rounds=first["rounds"] + last["rounds"], balance_moves=first["balance_moves"] + last["balance_moves"])
    return partition
