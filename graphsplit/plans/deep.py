"""Deep multilevel partitioning: coarsen, split what is left, and on the way up project, balance, refine and extend the blocks.

Every level is worked on by P logical PEs. A graph too small for them, of fewer than C vertices a PE, is copied, and groups of PEs work on a
copy each with coins of their own; the best partition of the copies goes on. Coarsening ends at C * min(k, K) vertices, or when it converges.
Only then a task gathers a whole graph (a copy of it). Blocks are split in tasks of their own.
"""

from __future__ import annotations

import time
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphsplit.functions.columns import block_limit, ceil2, max_cluster_weight, num_batches, num_copies, target_blocks
from graphsplit.model import Graph, snapshot
from graphsplit.operators.balance import settle
from graphsplit.operators.cluster import lp_cluster, mutual_matching, pair_leftovers
from graphsplit.operators.contract import contract, project
from graphsplit.operators.fleet import Fleet, lay_out
from graphsplit.operators.initial import best_copies, extend, fill_empty, initial_partition, replicate
from graphsplit.operators.measures import clustering_stats, edge_cut

#: Arcs that a PE should not exceed, when their number is derived from the graph.
PE_ARCS = 4_000_000


@dataclass(frozen=True)
class DeepParams:
    """c: vertices that a PE should have at least, where coarsening ends; parts: into how many a block is split at once (K); pes: P, a power of
    two, from the graph and the cluster if 0; trials: how often a group of PEs solves the coarsest graph at most; batches: of a sweep, from P if 0;
    mode: 'fleet' (PEs that scan and exchange messages) or 'bulk' (synchronous supersteps of joins and aggregates).
    """

    eps: float = 0.03
    c: int = 2000
    parts: int = 2
    sweeps: int = 3
    strong: bool = False
    pes: int = 0
    ell: int = 1024
    trials: int = 16
    batches: int = 0
    mode: str = "fleet"
    limit_mode: str = "revert"
    refine_mode: str = "overshoot"
    coarsening: str = "lp"
    place: bool = True
    delta: float = 1.1
    decide: str = "driver"
    adaptive_eps: bool = False

    @staticmethod
    def fast(**more) -> DeepParams:
        return replace(DeepParams(), **more)

    @staticmethod
    def strong_(**more) -> DeepParams:
        return replace(DeepParams(c=5000, sweeps=5, strong=True), **more)

    def for_graph(self, g: Graph) -> int:
        """P: as many as the cluster runs tasks, and as the arcs ask for; 16 at least, so that little work still has PEs."""
        return self.pes or max(16, ceil2(g.vertices.sparkSession.sparkContext.defaultParallelism), ceil2(g.arcs / PE_ARCS))


@dataclass
class Level:
    """One step of the hierarchy: what it did to the graph ('copied' or 'coarsened'), the graph before, its PEs a copy, and what leads back."""

    kind: str
    graph: Graph
    pes: int
    fleet: Fleet | None = None
    mapping: DataFrame | None = None
    copies: int = 1
    after: Graph | None = None


@dataclass
class DeepResult:
    partition: DataFrame
    k: int
    levels: list[tuple[int, int]] = field(default_factory=list)  # vertices and blocks of each level, coarsest first
    distributed: int = 0  # levels coarsened
    copies: int = 1  # of the coarsest graph
    trace: list[dict] = field(default_factory=list)  # what each step did, and how long it took


def limits_for(g: Graph, spans: list[int], k: int, eps: float) -> list[float]:
    return [block_limit(g.total, k, eps, g.heaviest, s) for s in spans]


def coarsen_once(g: Graph, k: int, p: DeepParams, pes: int, batches: int, seed: int, fleet: Fleet | None, trace: dict) -> tuple[Graph, DataFrame]:
    """The next graph and the mapping to it. Where the clusters shrink it by less than 5 %, vertices left alone that share a neighbour are paired."""
    limit = [max_cluster_weight(g.total, n, k, p.c, p.eps) for _, n in g.copies]
    if p.coarsening == "matching":
        clusters = mutual_matching(g, max(limit), 4, seed)
    else:
        clusters = lp_cluster(g, limit, p.sweeps, pes, seed, p.mode, p.limit_mode, count=batches, fleet=fleet, trace=trace)
    clusters = snapshot(clusters)
    trace.update(limit=max(limit), **clustering_stats(g, clusters, max(limit)).first().asDict())
    if g.n < trace["clusters"] * 1.05:
        clusters = snapshot(pair_leftovers(g, clusters, max(limit), seed))
    return contract(g, clusters, pes if p.place else 0, p.delta)


def coarsen_hierarchy(g: Graph, k: int, p: DeepParams, seed: int, trace: list[dict], stop: int | None = None) -> tuple[list[Level], Graph, int]:
    """Levels, finest first, the coarsest graph and its PEs a copy: the first of at most `stop` vertices (C * min(k, K)), or where coarsening converged."""
    levels, all_pes = [], p.for_graph(g)
    pes, batches = all_pes, p.batches or num_batches(all_pes)
    stop = stop or p.c * min(k, p.parts)
    size = lambda h: max(n for _, n in h.copies)
    while size(g) > stop:
        began, step = time.monotonic(), {}
        copies = num_copies(size(g), p.c, pes)
        if copies > 1:
            more = replicate(g, copies)
            levels.append(Level("copied", g, pes, copies=copies, after=more))
            trace.append({"step": "copy", "n": size(g), "copies": copies})
            g, pes = more, pes // copies
        s = seed + 101 * len(levels)
        fleet = lay_out(g, pes, s, batches) if p.mode == "fleet" else None
        coarse, mapping = coarsen_once(g, k, p, pes, batches, s, fleet, step)
        trace.append({"step": "coarsen", "n": size(g), "after": size(coarse), "seconds": time.monotonic() - began, **step})
        if size(coarse) > 0.95 * size(g):
            break  # converged
        levels.append(Level("coarsened", g, pes, fleet, mapping))
        g = coarse
    return levels, g, pes


def split_blocks(g: Graph, partition: DataFrame, spans: list[int], target: int, k: int, p: DeepParams, pes: int, seed: int, fleet: Fleet | None, trace: list[dict], at_once: int | None = None) -> tuple[DataFrame, list[int]]:
    """Blocks split by up to K at once until there are `target`, each time balanced and refined."""
    while len(spans) < target:
        began, before = time.monotonic(), len(spans)
        eps = p.eps
        if p.adaptive_eps and max(spans) > 1:
            eps = (1 + p.eps) ** (1 / max(1, (max(spans) - 1).bit_length())) - 1
        partition, spans = extend(g, partition, spans, target, at_once or p.parts, k, eps, seed, p.strong)
        if len(spans) == before:
            break
        step = {}
        partition = settle(g, partition, limits_for(g, spans, k, p.eps), p.sweeps, pes, seed, p.ell, p.batches or None, p.refine_mode, fleet, p.decide, step)
        trace.append({"step": "extend", "n": g.n, "blocks": len(spans), "seconds": time.monotonic() - began, **step})
    return partition, spans


def deep_partition(g: Graph, k: int, params: DeepParams | None = None, seed: int = 1) -> DeepResult:
    """vid, block in 0..k-1, balanced within eps; k need not be a power of two."""
    p = params or DeepParams()
    if k < 1 or (g.n and k > g.n):
        raise ValueError(f"cannot split {g.n} vertices into {k} blocks")
    if k == 1 or not g.n:
        return DeepResult(g.vertices.select("vid", F.lit(0).alias("block")), 1, [(g.n, 1)])
    finest, trace, all_pes = g, [], p.for_graph(g)
    p = replace(p, batches=p.batches or num_batches(all_pes))
    levels, g, pes = coarsen_hierarchy(g, k, p, seed, trace)
    began = time.monotonic()
    spans = [k]
    while len(spans) < min(k, p.parts):
        spans = [x for y in spans for x in ([(y + 1) // 2, y // 2] if y > 1 else [y])]
    partition = initial_partition(g, spans, k, p.eps, min(p.trials, pes), seed, p.strong)
    found, copies = [(max(n for _, n in g.copies), len(spans))], len(g.copies)
    trace.append({"step": "initial", "n": g.n, "blocks": len(spans), "copies": copies, "seconds": time.monotonic() - began})
    fleet = None
    for level in reversed(levels):
        began, h = time.monotonic(), level.graph
        if level.kind == "copied":
            partition = best_copies(level.after, partition, level.copies, len(spans), limits_for(h, spans, k, p.eps), h)
            continue
        partition, fleet, pes, step = snapshot(project(partition, level.mapping)), level.fleet, level.pes, {}
        partition = settle(h, partition, limits_for(h, spans, k, p.eps), p.sweeps, pes, seed, p.ell, p.batches, p.refine_mode, fleet, p.decide, step)
        n = max(n for _, n in h.copies)
        trace.append({"step": "refine", "n": n, "blocks": len(spans), "seconds": time.monotonic() - began, **step})
        partition, spans = split_blocks(h, partition, spans, target_blocks(n, k, p.c), k, p, pes, seed, fleet, trace)
        found.append((n, len(spans)))
    if len(spans) < k:  # the finest graph has fewer blocks than k: its blocks are split once more, into all that is missing
        if not levels or levels[0].kind == "copied":
            fleet, pes = None, all_pes
        partition, spans = split_blocks(finest, partition, spans, k, k, p, pes, seed, fleet, trace, k)
        found.append((finest.n, len(spans)))
    elif not levels:
        partition = settle(finest, partition, limits_for(finest, spans, k, p.eps), p.sweeps, all_pes, seed, p.ell, p.batches, p.refine_mode, None, p.decide)
    partition = fill_empty(finest, partition, k, p.eps, seed, p.strong)
    return DeepResult(partition, k, found, sum(x.kind == "coarsened" for x in levels), copies, trace)


def portfolio(g: Graph, k: int, presets: list[DeepParams], seed: int = 1) -> DeepResult:
    """The best of several parameter sets, run side by side."""
    with ThreadPoolExecutor(len(presets)) as pool:
        found = list(pool.map(lambda p: deep_partition(g, k, p, seed), presets))
    return min(found, key=lambda r: edge_cut(g, r.partition).first()["cut"])
