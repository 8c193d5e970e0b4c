"""The methods that the deep scheme is compared with; all return a partition vid, block.

The inner workings of the three distributed baselines aren't published in full here; these are in their spirit, from the public literature.
All but `shared_deep`, which is one PE by definition, coarsen and refine on the same PEs as the deep scheme, with the baseline's own rules, at
every size.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphsplit.functions.columns import coin, l_max, max_cluster_weight, num_batches
from graphsplit.model import Graph, dense_ids, snapshot
from graphsplit.operators import kernels
from graphsplit.operators.balance import balance, lp_refine, settle
from graphsplit.operators.cluster import lp_cluster, mutual_matching, pair_leftovers
from graphsplit.operators.contract import contract, project
from graphsplit.operators.fleet import lay_out
from graphsplit.operators.initial import excess_of, gather, induced_subgraphs, select_best, trials
from graphsplit.operators.kernels import Csr
from graphsplit.plans.deep import DeepParams, limits_for


def hash_partition(g: Graph, k: int, seed: int = 0) -> DataFrame:
    return g.vertices.select("vid", F.pmod(coin(seed, "block", F.col("vid")), F.lit(k)).cast("int").alias("block"))


def range_partition(g: Graph, k: int) -> DataFrame:
    return g.vertices.select("vid", F.floor(F.col("vid") * k / F.lit(max(g.n, 1))).cast("int").alias("block"))


def multilevel_down_up(g: Graph, k: int, eps: float, c: int, sweeps: int, pes: int, seed: int, cluster, solve, balanced: bool, spans: list[int] | None = None, start: DataFrame | None = None, trace: list[dict] | None = None, stop: int = 60) -> DataFrame:
    """Coarsen with cluster(graph, limit, seed, within, fleet) to `stop` vertices a block, solve(csr, seed) there in a task, refine on the way up.

    Where a level shrinks by less than 5 %, vertices left alone that share their heaviest neighbour are paired, too; where even that stalls, what
    is left is solved, and fails with RuntimeError if a task can't hold it. spans: how many of the k final blocks each block of the result stands
    for; one each if not given. start: a partition that clusters must respect and that is refined instead of solving (a V-cycle).
    """
    levels, spans = [], spans or [1] * k
    batches = num_batches(pes)
    while g.n > stop * len(spans):
        limit, s = max_cluster_weight(g.total, g.n, k, c, eps), seed + 101 * len(levels)
        fleet = lay_out(g, pes, s, batches)
        clusters = snapshot(cluster(g, limit, s, start, None if start is not None else fleet))
        coarse, mapping = contract(g, clusters)
        if coarse.n > 0.95 * g.n and start is None:
            coarse, mapping = contract(g, pair_leftovers(g, clusters, max(limit, 2.0 * g.heaviest), s))
        if coarse.n > 0.95 * g.n:
            break
        if trace is not None:
            trace.append({"n": g.n, "after": coarse.n, "heaviest": coarse.heaviest, "limit": limit})
        levels.append((g, mapping, fleet))
        if start is not None:
            start = snapshot(start.join(mapping, "vid").groupBy(F.col("coarse_vid").alias("vid")).agg(F.min("block").alias("block")))
        g = coarse
    if start is None:
        start = snapshot(select_best(trials(g, 1, seed, lambda csr, s: (part := solve(csr, s), excess_of(csr, part, kernels.limits_of(csr, spans, k, eps))))))
    for fine, mapping, fleet in reversed(levels):
        start, limits = snapshot(project(start, mapping)), limits_for(fine, spans, k, eps)
        start = settle(fine, start, limits, sweeps, pes, seed, batches=batches, fleet=fleet) if balanced else lp_refine(fine, start, limits, sweeps, pes, seed, batches=batches, fleet=fleet)
    if not levels and balanced:
        start = balance(g, start, limits_for(g, spans, k, eps), pes=pes)
    return start


def relaxed_lp_partition(g: Graph, k: int, eps: float = 0.03, preset: str = "fast", seed: int = 1, pes: int = 16, c: int = 160, cycles: int = 1, population: int = 3, trace: list[dict] | None = None, stop: int = 60) -> DataFrame:
    """Label propagation whose cluster limit each PE keeps only for its own part, so that clusters reach P times the limit; no balancer.

    The 'eco' preset solves the coarsest graph by a population of starts and overlays of pairs of them, and adds V-cycles, which coarsen again inside
    the blocks found.
    """

    def solve(csr: Csr, s: int) -> np.ndarray:
        limits = kernels.limits_of(csr, [1] * k, k, eps)
        run = lambda s: kernels.refine(csr, kernels.split(csr, [1] * k, limits, s), limits, 3, s)
        if preset == "fast":
            return run(s)
        key = lambda p: (excess_of(csr, p, limits), csr.cut(p))
        pool = sorted((run(s + j) for j in range(population)), key=key)
        for j in range(population):
            # overlay of two parents: clusters lie inside blocks of both
            both = np.unique(pool[0] * np.int64(k) + pool[1], return_inverse=True)[1]
            small, to = kernels.contract(csr, kernels.cluster(csr, limits[0] / 4, 2, s + j, both))
            child = kernels.refine(small, pool[0][_heads(to, small.n)], limits, 5, s + j)[to]
            pool = sorted([*pool, kernels.refine(csr, child, limits, 5, s + j)], key=key)[:population]
        return pool[0]

    cluster = lambda h, limit, s, within, fleet: lp_cluster(h, limit, 3, pes, s, limit_mode="local", within=within, count=num_batches(pes), fleet=fleet)
    found = multilevel_down_up(g, k, eps, c, 3, pes, seed, cluster, solve, False, trace=trace, stop=stop)
    for j in range(cycles if preset == "eco" else 0):
        found = multilevel_down_up(g, k, eps, c, 3, pes, seed + 1000 * (j + 1), cluster, solve, False, start=found, stop=stop)
    return found


def _heads(to: np.ndarray, n: int) -> np.ndarray:
    first = np.zeros(n, dtype=np.int64)
    first[to[::-1]] = np.arange(len(to))[::-1]
    return first


def matching_partition(g: Graph, k: int, eps: float = 0.03, seed: int = 1, pes: int = 16, c: int = 160, trace: list[dict] | None = None, stop: int = 60) -> DataFrame:
    """Coarsening by heavy-edge matching, at most two vertices to a cluster; greedy refinement, no balancer."""
    solve = lambda csr, s: kernels.refine(csr, kernels.split(csr, [1] * k, limits := kernels.limits_of(csr, [1] * k, k, eps), s), limits, 3, s)
    return multilevel_down_up(g, k, eps, c, 3, pes, seed, lambda h, limit, s, within, fleet: mutual_matching(h, max(limit, 2.0 * h.heaviest), 4, s), solve, False, trace=trace, stop=stop)


def flat_lp_partition(g: Graph, k: int, eps: float = 0.03, iterations: int = 5, seed: int = 1, pes: int = 16) -> DataFrame:
    """Label propagation on the input graph alone, from a random start; no balancer."""
    return lp_refine(g, snapshot(hash_partition(g, k, seed)), limits_for(g, [1] * k, k, eps), iterations, pes, seed)


def shared_deep_partition(g: Graph, k: int, eps: float = 0.03, params: DeepParams | None = None, seed: int = 1) -> DataFrame:
    """The deep scheme of one memory: a single PE, strict limits, everything in one task; an error for graphs that no task can hold."""
    p = params or DeepParams(eps=eps)
    solve = lambda csr, s: (part := kernels.deep(csr, k, eps, p.c, p.parts, p.sweeps, s, p.strong)[0], excess_of(csr, part, kernels.limits_of(csr, [1] * k, k, eps)))
    return snapshot(select_best(trials(g, 1, seed, solve)))


def multilevel_partition(g: Graph, k: int, eps: float = 0.03, seed: int = 1, pes: int = 16, c: int = 160, stop: int = 60) -> DataFrame:
    """Plain multilevel scheme: one k-way initial partition of the coarsest graph, balanced on the way up."""

    def solve(csr: Csr, s: int) -> np.ndarray:
        limits = kernels.limits_of(csr, [1] * k, k, eps)
        return kernels.settle(csr, kernels.split(csr, [1] * k, limits, s), limits, 3, s)

    cluster = lambda h, limit, s, within, fleet: lp_cluster(h, limit, 3, pes, s, count=num_batches(pes), fleet=fleet)
    return multilevel_down_up(g, k, eps, c, 3, pes, seed, cluster, solve, True, stop=stop)


def recursive_bisection(g: Graph, k: int, eps: float = 0.03, seed: int = 1, pes: int = 16, c: int = 160) -> DataFrame:
    """Bisections of bisections, each a multilevel run of its own on the halves; the limits of all blocks are restored at the end.

    Each bisection gets its share of eps, so that those of all depths together keep to it. Parts of at most 2 * c vertices, which a bisection would
    not coarsen, are finished in one task.
    """
    share = (1 + eps) ** (1 / max(1, (k - 1).bit_length())) - 1
    return balance(g, bisections(g, k, share, seed, pes, c), limits_for(g, [1] * k, k, eps), pes=pes)


def bisections(g: Graph, k: int, eps: float, seed: int, pes: int, c: int) -> DataFrame:
    if k == 1 or not g.n:
        return g.vertices.select("vid", F.lit(0).alias("block"))
    if g.n <= 2 * c:

        def finish(csr: Csr, s: int) -> tuple[np.ndarray, float]:
            limits = kernels.limits_of(csr, [1] * k, k, eps)
            part = kernels.rebalance(csr, kernels.split(csr, [1] * k, limits, s), limits)
            return part, excess_of(csr, part, limits)

        return snapshot(select_best(trials(g, 1, seed, finish)))
    spans = [(k + 1) // 2, k // 2]
    solve = lambda csr, s: (limits := kernels.limits_of(csr, spans, k, eps), kernels.settle(csr, kernels.split(csr, spans, limits, s), limits, 3, s))[1]
    cluster = lambda h, limit, s, within, fleet: lp_cluster(h, limit, 3, pes, s, count=num_batches(pes), fleet=fleet)
    sides = multilevel_down_up(g, k, eps, c, 3, pes, seed, cluster, solve, True, spans, stop=c)
    arcs, own, out = snapshot(induced_subgraphs(g, sides)), g.vertices.join(sides, "vid"), None
    for side, span in enumerate(spans):
        half, names = induced(own.filter(F.col("block") == side), arcs.filter(F.col("block") == side))
        inner = bisections(half, span, eps, seed * 2 + side + 1, pes, c).withColumnRenamed("vid", "_new").join(names, "_new").select("vid", (F.col("block") + side * spans[0]).cast("int").alias("block"))
        out = inner if out is None else out.union(inner)
    return snapshot(out)


def induced(vertices: DataFrame, arcs: DataFrame) -> tuple[Graph, DataFrame]:
    """The graph of some vertices and the arcs between them, with dense ids, and the table vid, _new."""
    ids = snapshot(dense_ids(vertices.select("vid", "c"), "vid", "_new").select("vid", "_new", "c"))
    names = ids.select("vid", "_new")
    named = arcs.join(names.withColumnsRenamed({"vid": "src", "_new": "_s"}), "src").join(names.withColumnsRenamed({"vid": "dst", "_new": "_d"}), "dst")
    return Graph.of(ids.select(F.col("_new").alias("vid"), "c"), snapshot(named.select(F.col("_s").alias("src"), F.col("_d").alias("dst"), "w"))), names


def brute_force_partition(g: Graph, k: int, eps: float = 0.03) -> tuple[int, DataFrame]:
    cut, part = kernels.brute_force(gather(g, 14), k, l_max(g.total, k, eps, g.heaviest))
    return cut, g.vertices.sparkSession.createDataFrame([(v, int(b)) for v, b in enumerate(part)], "vid long, block int")
