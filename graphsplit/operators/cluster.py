"""Size-constrained label propagation in synchronous supersteps, as DataFrames; `fleet` has the PEs that scan their vertices one by one.

A state has a row (vid, c, pe, label) for each vertex. Labels are clusters (named by a vertex) or blocks. One superstep lets the vertices
of one batch choose by the weights at its start; then moves that make a label too heavy are dealt with by one of these rules:

- revert: each PE takes back moves in proportion to its share of the overweight cluster,
- strict: moves are admitted in order while there is room,
- local: each PE only looks at its own part of a cluster,
- none, or overshoot (candidates are held to the limit at the batch's start, but many may take the same room).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from graphsplit.functions.columns import coin
from graphsplit.model import Graph, snapshot
from graphsplit.operators.fleet import Fleet, propagate
from graphsplit.operators.initial import with_copy
from graphsplit.operators.layout import assign_pe
from graphsplit.operators.order import batches, traversal

MODES = ("revert", "strict", "local", "none", "overshoot")


def rate(arcs: DataFrame, state: DataFrame, active: DataFrame | None = None) -> DataFrame:
    """vid, label, conn: the connecting weight of each (active) vertex to each adjacent label."""
    if active is not None:
        arcs = arcs.join(active.select(F.col("vid").alias("src")), "src", "left_semi")
    return arcs.join(state.select(F.col("vid").alias("dst"), "label"), "dst").groupBy(F.col("src").alias("vid"), "label").agg(F.sum("w").alias("conn"))


def label_weights(state: DataFrame) -> DataFrame:
    return state.groupBy("label").agg(F.sum("c").alias("weight"))


def best_move(ratings: DataFrame, state: DataFrame, weights: DataFrame, tie: str = "coin", seed: int = 0) -> DataFrame:
    """vid, pe, c, old, new, gain of the vertices that want to move.

    weights: label, weight, limit. The best label with room wins, by connection; ties go to a coin, or with tie='lighter' to the lighter
    label and then the coin. With 'lighter', an equally connected but strictly lighter label is better than the own one.
    """
    rows = ratings.join(state.select("vid", "pe", "c", F.col("label").alias("old")), "vid").join(weights, "label")
    light = (-F.col("weight")) if tie == "lighter" else F.lit(0).cast("long")
    fits = (F.col("label") != F.col("old")) & (F.col("weight") + F.col("c") <= F.col("limit"))
    choice = F.struct("conn", light.alias("light"), coin(seed, "tie", F.col("vid"), F.col("label")).alias("coin"), "label", "weight")
    picked = rows.groupBy("vid", "pe", "c", "old").agg(F.max(F.when(fits, choice)).alias("best"), F.coalesce(F.max(F.when(F.col("label") == F.col("old"), F.col("conn"))), F.lit(0)).alias("own"))
    picked = picked.filter("best is not null").withColumn("gain", F.col("best.conn") - F.col("own"))
    if tie == "lighter":
        home = weights.select(F.col("label").alias("old"), F.col("weight").alias("_home"))
        picked = picked.join(home, "old").filter("gain > 0 or (gain = 0 and best.weight < _home - c)")
    else:
        picked = picked.filter("gain > 0")
    return picked.select("vid", "pe", "c", "old", F.col("best.label").alias("new"), "gain")


def moved(state: DataFrame, moves: DataFrame) -> DataFrame:
    return state.join(moves.select("vid", "new"), "vid", "left").select("vid", "c", "pe", F.coalesce("new", "label").alias("label"))


def apply_weight_deltas(weights: DataFrame, moves: DataFrame) -> DataFrame:
    """Label weights after moves: what goes in and out is sent to the label's owner, summed there, and added."""
    deltas = moves.select(F.col("new").alias("label"), F.col("c").alias("weight")).union(moves.select(F.col("old"), -F.col("c")))
    return weights.select("label", "weight").union(deltas).groupBy("label").agg(F.sum("weight").alias("weight")).filter("weight <> 0")


def revert_overweight(moves: DataFrame, state: DataFrame, weights: DataFrame, limit: float) -> DataFrame:
    """moves with reverted: whether a PE takes the move back because its cluster is overweight.

    state and weights are those after the moves. A PE's quota of the excess is its share of the cluster, rounded up; it reverts its moves of
    least gain until their weight reaches the quota.
    """
    heavy = weights.filter(F.col("weight") > limit).select(F.col("label").alias("new"), "weight")
    shares = state.select("pe", F.col("label").alias("new"), "c").join(heavy, "new").groupBy("pe", "new", "weight").agg(F.sum("c").alias("share"))
    quota = shares.select("pe", "new", F.ceil((F.col("weight") - F.lit(float(limit))) * F.col("share") / F.col("weight")).alias("quota"))
    before = F.coalesce(F.sum("c").over(Window.partitionBy("new", "pe").orderBy("gain", "vid").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return moves.join(quota, ["new", "pe"], "left").withColumn("reverted", F.col("quota").isNotNull() & (before < F.col("quota"))).select("vid", "pe", "c", "old", "new", "gain", "reverted")


def admit_strict(moves: DataFrame, weights: DataFrame) -> DataFrame:
    """moves with reverted: those are kept that fit while a label's moves are admitted by descending gain. weights: before the moves, with limits."""
    upto = F.sum("c").over(Window.partitionBy("new").orderBy(F.desc("gain"), "vid").rowsBetween(Window.unboundedPreceding, 0))
    room = weights.select(F.col("label").alias("new"), (F.col("limit") - F.col("weight")).alias("_room"))
    return moves.join(room, "new").withColumn("reverted", upto > F.col("_room")).drop("_room")


def admit_local(moves: DataFrame, state: DataFrame, limit: float) -> DataFrame:
    """moves with reverted, if each PE only keeps its own part of a cluster at the limit. state: before the moves."""
    own = state.groupBy("pe", F.col("label").alias("new")).agg(F.sum("c").alias("_own"))
    upto = F.sum("c").over(Window.partitionBy("new", "pe").orderBy(F.desc("gain"), "vid").rowsBetween(Window.unboundedPreceding, 0))
    return moves.join(own, ["new", "pe"], "left").withColumn("reverted", upto + F.coalesce("_own", F.lit(0)) > F.lit(float(limit))).drop("_own")


def superstep(arcs: DataFrame, state: DataFrame, weights: DataFrame, active: DataFrame, limit: float | None, limit_mode: str, tie: str, seed: int) -> tuple[DataFrame, DataFrame, int]:
    """State, weights (label, weight, limit) and number of moves after one batch."""
    wants = weights
    if limit_mode in ("none", "local"):
        wants = weights.withColumn("limit", F.lit(float("inf")))
    moves = snapshot(best_move(rate(arcs, state, active), state, wants, tie, seed))
    if limit_mode == "strict":
        judged = admit_strict(moves, weights)
    elif limit_mode == "local":
        judged = admit_local(moves, state, limit)
    elif limit_mode == "revert":
        judged = revert_overweight(moves, moved(state, moves), apply_weight_deltas(weights, moves), limit)
    else:
        judged = moves.withColumn("reverted", F.lit(False))
    kept = snapshot(judged.filter(~F.col("reverted")))
    n = kept.count()
    if not n:
        return state, weights, 0
    new = apply_weight_deltas(weights, kept)
    new = new.join(weights.select("label", "limit"), "label", "left")
    if limit is not None:
        new = new.withColumn("limit", F.lit(float(limit)))
    return snapshot(moved(state, kept)), snapshot(new), n


def sweeps(g: Graph, state: DataFrame, weights: DataFrame, limit: float | None, iterations: int, pes: int, seed: int, limit_mode: str, tie: str, count: int, arcs: DataFrame | None = None, order: str = "buckets") -> tuple[DataFrame, list[int]]:
    """`iterations` passes over all vertices in `count` batches each, or until a pass moves nothing. Returns the state and each pass's moves."""
    moves = []
    for sweep in range(iterations):
        turn = snapshot(batches(traversal(g, state, 64, seed + sweep, order), count))
        moves.append(0)
        for b in range(count):
            state, weights, n = superstep(g.edges if arcs is None else arcs, state, weights, turn.filter(F.col("batch") == b), limit, limit_mode, tie, seed + sweep)
            moves[-1] += n
        if not moves[-1]:
            break
    return state, moves


def pack_isolated(g: Graph, limit: float) -> DataFrame:
    """vid, cluster of the vertices without arcs: consecutive ones (in ranges of ids) share a cluster of at most the limit.

    Running weights are cut into bins of half the limit's room, so that no bin exceeds it; the smallest id names the bin.
    """
    alone = with_copy(g, g.vertices.select("vid", "c").join(g.edges.select(F.col("src").alias("vid")), "vid", "left_anti"), "vid")
    alone = alone.withColumn("chunk", F.struct("copy", F.floor(F.col("vid") / 65536)))
    size = max(1.0, float(limit) - g.heaviest + 1)
    run = F.sum("c").over(Window.partitionBy("chunk").orderBy("vid").rowsBetween(Window.unboundedPreceding, 0)) - F.col("c")
    binned = alone.withColumn("bin", F.floor(run / F.lit(size)))
    return binned.select("vid", F.min("vid").over(Window.partitionBy("chunk", "bin")).alias("cluster"))


def lp_cluster(g: Graph, limit: float | list[float], iterations: int, pes: int, seed: int, mode: str = "fleet", limit_mode: str = "revert", within: DataFrame | None = None, count: int = 2, order: str = "buckets", fleet: Fleet | None = None, trace: dict | None = None) -> DataFrame:
    """vid, cluster of every vertex. within: vid, block; clusters then stay inside blocks. limit: one for each copy, or for all.

    mode 'fleet': PEs that scan and exchange messages; 'bulk': supersteps. Vertices without arcs are packed together.
    """
    arcs = g.edges
    limits = limit if isinstance(limit, list) else [float(limit)] * len(g.copies)
    if within is not None:
        b = within.select("vid", "block")
        arcs = snapshot(arcs.join(b.withColumnsRenamed({"vid": "src", "block": "_a"}), "src").join(b.withColumnsRenamed({"vid": "dst", "block": "_b"}), "dst").filter("_a = _b").select("src", "dst", "w"))
    if mode == "fleet":
        clusters = propagate(g, pes, limits, iterations, seed, limit_mode, batches=count, arcs=arcs, trace=trace, fleet=fleet).withColumnRenamed("label", "cluster")
    else:
        state = snapshot(assign_pe(g, pes).withColumn("label", F.col("vid")))
        weights = state.select("label", F.col("c").alias("weight"), F.lit(min(limits)).alias("limit"))
        state, moves = sweeps(g, state, weights, min(limits), iterations, pes, seed, limit_mode, "coin", count, arcs, order)
        if trace is not None:
            trace.update(moves=moves)
        clusters = state.select("vid", F.col("label").alias("cluster"))
    if within is not None:
        return clusters
    return clusters.join(pack_isolated(g, min(limits)).withColumnRenamed("cluster", "_bin"), "vid", "left").select("vid", F.coalesce("_bin", "cluster").alias("cluster"))


def mutual_matching(g: Graph, limit: float, rounds: int, seed: int) -> DataFrame:
    """vid, cluster: heavy-edge matching by mutual best proposals, at most two vertices to a cluster."""
    free = g.vertices
    pairs = None
    for r in range(rounds):
        found = snapshot(matching_round(g.edges, free, limit, seed + r))
        pairs = found if pairs is None else pairs.union(found)
        if not found.count():
            break
        gone = found.select(F.col("a").alias("vid")).union(found.select("b"))
        free = snapshot(free.join(gone, "vid", "left_anti"))
    return g.vertices.select("vid").join(pairs.select(F.col("b").alias("vid"), F.col("a").alias("_a")), "vid", "left").select("vid", F.coalesce("_a", "vid").alias("cluster"))


def pair_leftovers(g: Graph, clusters: DataFrame, limit: float, seed: int) -> DataFrame:
    """vid, cluster: vertices that are alone in their cluster are paired if they share their heaviest neighbour, or have none.

    Leaves of a hub, which takes one partner a level, go on shrinking this way. Followers of a hub are paired in chunks of ids.
    """
    alone = clusters.join(clusters.groupBy("cluster").count().filter("count = 1"), "cluster").select("vid").join(g.vertices, "vid")
    toss: Column = coin(seed, "follow", F.least("src", "dst"), F.greatest("src", "dst"))
    favourite = g.edges.join(alone.select(F.col("vid").alias("src")), "src").groupBy(F.col("src").alias("vid")).agg(F.max_by("dst", F.struct("w", toss, "dst")).alias("hub"))
    rows = with_copy(g, alone.select("vid", "c").join(favourite, "vid", "left"), "vid").withColumn("hub", F.coalesce("hub", -1 - F.col("copy"))).withColumn("_chunk", F.floor(F.col("vid") / 65536))
    rows = rows.withColumn("_pair", F.floor((F.row_number().over(Window.partitionBy("hub", "_chunk").orderBy("c", "vid")) - 1) / 2))
    both = rows.groupBy("hub", "_chunk", "_pair").agg(F.min("vid").alias("a"), F.max("vid").alias("b"), F.sum("c").alias("c")).filter((F.col("a") < F.col("b")) & (F.col("c") <= limit))
    return clusters.join(both.select(F.col("b").alias("vid"), "a"), "vid", "left").select("vid", F.coalesce("a", "cluster").alias("cluster"))


def matching_round(arcs: DataFrame, free: DataFrame, limit: float, seed: int) -> DataFrame:
    """a, b with a < b: vertices that are each other's heaviest free neighbour; ties by a coin of the edge."""
    ends = lambda c: free.select(F.col("vid").alias(c), F.col("c").alias(f"_{c}"))
    open_: DataFrame = arcs.join(ends("src"), "src").join(ends("dst"), "dst").filter(F.col("_src") + F.col("_dst") <= limit)
    toss: Column = coin(seed, "match", F.least("src", "dst"), F.greatest("src", "dst"))
    best = open_.groupBy("src").agg(F.max_by("dst", F.struct("w", toss, "dst")).alias("dst"))
    return best.join(best.select(F.col("src").alias("dst"), F.col("dst").alias("src")), ["src", "dst"]).filter("src < dst").select(F.col("src").alias("a"), F.col("dst").alias("b"))
