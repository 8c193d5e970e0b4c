"""Partitioning of graphs that fit into one task, on arrays.

These run inside Arrow tasks: on the gathered coarsest graph, on the subgraph of one block, or on one processing element's share. The
level loop outside decides what is small enough; nothing here grows with the input.
"""

from __future__ import annotations

import heapq
from dataclasses import dataclass

import numpy as np

from graphsplit.functions.columns import block_limit, max_cluster_weight, target_blocks


@dataclass
class Csr:
    """Vertices 0..n-1 with weights c; arcs of v are adj[x[v]:x[v+1]] with weights w."""

    x: np.ndarray
    adj: np.ndarray
    w: np.ndarray
    c: np.ndarray

    @property
    def n(self) -> int:
        return len(self.c)

    @property
    def total(self) -> int:
        return int(self.c.sum())

    @property
    def heaviest(self) -> int:
        return int(self.c.max(initial=0))

    @staticmethod
    def of(c: np.ndarray, src: np.ndarray, dst: np.ndarray, w: np.ndarray) -> Csr:
        order = np.lexsort((dst, src))
        return Csr(np.concatenate([[0], np.bincount(src, minlength=len(c)).cumsum()]).astype(np.int64), dst[order].astype(np.int32), w[order].astype(np.int64), c.astype(np.int64))

    def tails(self) -> np.ndarray:
        return np.repeat(np.arange(self.n), np.diff(self.x))

    def cut(self, part: np.ndarray) -> int:
        return int(self.w[part[self.tails()] != part[self.adj]].sum()) // 2

    def lists(self) -> tuple[list, list, list, list]:
        return self.x.tolist(), self.adj.tolist(), self.w.tolist(), self.c.tolist()

    def induced(self, rows: np.ndarray) -> Csr:
        local = np.full(self.n, -1)
        local[rows] = np.arange(len(rows))
        t = self.tails()
        keep = (local[t] >= 0) & (local[self.adj] >= 0)
        return Csr.of(self.c[rows], local[t[keep]], local[self.adj[keep]], self.w[keep])


def by_degree(g: Csr, rng: np.random.Generator) -> np.ndarray:
    """Vertices by degree bucket, low ones first, random within."""
    d = np.diff(g.x)
    return np.lexsort((rng.random(g.n), np.where(d > 0, np.floor(np.log2(np.maximum(d, 1))), -1)))


def scan(g: Csr, label: list, weight: dict | list, limit, order, lighter: bool, rng: np.random.Generator, within: list | None = None) -> int:
    """One sweep of size-constrained label propagation; label and weight change in place. Returns the number of moves.

    limit: one number, or one for each label. Ties go to the lighter label if asked, then to a coin.
    """
    x, adj, w, c = g.lists()
    moves, coins = 0, rng.random(g.n).tolist()
    one = not isinstance(limit, (list, dict))
    for v in order.tolist() if isinstance(order, np.ndarray) else order:
        own, conn = label[v], {}
        for k in range(x[v], x[v + 1]):
            u = adj[k]
            if within is not None and within[u] != within[v]:
                continue
            t = label[u]
            conn[t] = conn.get(t, 0) + w[k]
        if not conn:
            continue
        here = conn.pop(own, 0)
        best, best_conn, best_weight, seen = own, here, weight[own] - c[v], 1
        for t, s in conn.items():
            if s < best_conn or weight[t] + c[v] > (limit if one else limit[t]):
                continue
            if s > best_conn or (lighter and weight[t] < best_weight):
                best, best_conn, best_weight, seen = t, s, weight[t], 1
            elif best != own and (not lighter or weight[t] == best_weight):
                seen += 1
                if coins[v] * seen < 1:
                    best = t
        if best != own:
            weight[own] -= c[v]
            weight[best] += c[v]
            label[v] = best
            moves += 1
    return moves


def cluster(g: Csr, limit: float, sweeps: int, seed: int, within: np.ndarray | None = None) -> np.ndarray:
    """Clusters by label propagation, none heavier than the limit; isolated vertices are packed together."""
    rng = np.random.default_rng(seed)
    label, weight = list(range(g.n)), g.c.tolist()
    for _ in range(sweeps):
        if not scan(g, label, weight, limit, by_degree(g, rng), False, rng, None if within is None else within.tolist()):
            break
    out = np.asarray(label)
    alone = np.flatnonzero(np.diff(g.x) == 0)
    groups: dict = {}
    for v in alone.tolist():
        key = -1 if within is None else int(within[v])
        head = groups.get(key)
        if head is None or weight[head] + g.c[v] > limit:
            groups[key] = v
        else:
            weight[head] += int(g.c[v])
            out[v] = head
    return out


def contract(g: Csr, label: np.ndarray) -> tuple[Csr, np.ndarray]:
    heads, to = np.unique(label, return_inverse=True)
    s, d = to[g.tails()], to[g.adj]
    keep = s != d
    key, at = np.unique(s[keep] * np.int64(len(heads)) + d[keep], return_inverse=True)
    w = np.bincount(at, weights=g.w[keep], minlength=len(key)).astype(np.int64)
    return Csr.of(np.bincount(to, weights=g.c, minlength=len(heads)).astype(np.int64), key // len(heads), key % len(heads), w), to


def refine(g: Csr, part: np.ndarray, limits: list[float], sweeps: int, seed: int) -> np.ndarray:
    rng = np.random.default_rng(seed)
    label, weight = part.tolist(), np.bincount(part, weights=g.c, minlength=len(limits)).astype(np.int64).tolist()
    for _ in range(sweeps):
        if not scan(g, label, weight, limits, by_degree(g, rng), True, rng):
            break
    return np.asarray(label, dtype=np.int64)


def rebalance(g: Csr, part: np.ndarray, limits: list[float]) -> np.ndarray:
    """Moves vertices of best relative gain out of overloaded blocks until none is left."""
    part = part.copy()
    weight = np.bincount(part, weights=g.c, minlength=len(limits)).astype(np.int64)
    for b in np.flatnonzero(weight > np.asarray(limits)).tolist():
        rows = np.flatnonzero(part == b)

        def rating(v: int, b: int = b) -> tuple:
            conn: dict = {}
            for k in range(g.x[v], g.x[v + 1]):
                t = int(part[g.adj[k]])
                conn[t] = conn.get(t, 0) + int(g.w[k])
            fits = [(s, -weight[t] / limits[t], -t) for t, s in conn.items() if t != b and weight[t] + g.c[v] <= limits[t]]
            room = np.asarray(limits) - weight
            room[b] = -1
            t = int(room.argmax())
            if not fits and room[t] < g.c[v]:
                return None
            s, t = (max(fits)[0], -max(fits)[2]) if fits else (0, t)
            gain = s - conn.get(b, 0)
            return (-(gain * g.c[v]) if gain >= 0 else -gain / g.c[v], v, t)

        heap = [r for v in rows.tolist() if (r := rating(v))]
        heapq.heapify(heap)
        while weight[b] > limits[b] and heap:
            r, v, t = heapq.heappop(heap)
            now = rating(v)
            if now is None:
                continue
            if now[0] > r + 1e-12:
                heapq.heappush(heap, now)
                continue
            t = now[2]
            part[v] = t
            weight[b] -= g.c[v]
            weight[t] += g.c[v]
    return part


def settle(g: Csr, part: np.ndarray, limits: list[float], sweeps: int, seed: int) -> np.ndarray:
    return rebalance(g, refine(g, rebalance(g, part, limits), limits, sweeps, seed), limits)


def fm(g: Csr, side: np.ndarray, limits: tuple[float, float], passes: int = 4, patience: int = 120) -> np.ndarray:
    """Two-way local search: best moves first, worse ones for a while, back to the best prefix."""
    x, adj, w, c = g.lists()
    side = side.tolist()
    weight = [sum(a for a, s in zip(c, side, strict=True) if s == b) for b in (0, 1)]
    for _ in range(passes):
        gain = [sum(w[k] if side[adj[k]] != side[v] else -w[k] for k in range(x[v], x[v + 1])) for v in range(g.n)]
        heap = [(-gain[v], v) for v in range(g.n) if any(side[adj[k]] != side[v] for k in range(x[v], x[v + 1])) or weight[side[v]] > limits[side[v]]]
        heapq.heapify(heap)
        done, moved, total, best, best_at = set(), [], 0, 0, 0
        start_bad = max(0.0, weight[0] - limits[0], weight[1] - limits[1])
        best_bad = start_bad
        while heap and len(moved) - best_at < patience:
            q, v = heapq.heappop(heap)
            if v in done or -q != gain[v]:
                continue
            a = side[v]
            if weight[1 - a] + c[v] > limits[1 - a] and weight[a] <= limits[a]:
                continue
            done.add(v)
            side[v] = 1 - a
            weight[a] -= c[v]
            weight[1 - a] += c[v]
            total += gain[v]
            moved.append(v)
            bad = max(0.0, weight[0] - limits[0], weight[1] - limits[1])
            if (bad, -total) < (best_bad, -best):
                best, best_at, best_bad = total, len(moved), bad
            for k in range(x[v], x[v + 1]):
                u = adj[k]
                if u not in done:
                    gain[u] += -2 * w[k] if side[u] == side[v] else 2 * w[k]
                    heapq.heappush(heap, (-gain[u], u))
        for v in moved[best_at:]:
            a = side[v]
            side[v] = 1 - a
            weight[a] -= c[v]
            weight[1 - a] += c[v]
        if best <= 0 and best_bad >= start_bad:
            break
    return np.asarray(side, dtype=np.int64)


def grow(g: Csr, goal: float, rng: np.random.Generator) -> np.ndarray:
    """Side 0 grows from a random vertex by the strongest connection until it weighs `goal`."""
    x, adj, w, c = g.lists()
    side, conn, heap, weight = [1] * g.n, [0] * g.n, [], 0
    order = rng.permutation(g.n).tolist()
    degree = [sum(w[x[v] : x[v + 1]]) for v in range(g.n)]
    while weight < goal:
        while heap and (side[heap[0][1]] == 0 or heap[0][0] != degree[heap[0][1]] - 2 * conn[heap[0][1]]):
            heapq.heappop(heap)
        if heap:
            v = heapq.heappop(heap)[1]
        else:
            while order and side[order[-1]] == 0:
                order.pop()
            if not order:
                break
            v = order.pop()
        if weight and weight + c[v] - goal > goal - weight:
            break
        side[v] = 0
        weight += c[v]
        for k in range(x[v], x[v + 1]):
            u = adj[k]
            if side[u]:
                conn[u] += w[k]
                heapq.heappush(heap, (degree[u] - 2 * conn[u], u))
    return np.asarray(side, dtype=np.int64)


def bisect(g: Csr, goal: float, limits: tuple[float, float], seed: int, strong: bool) -> np.ndarray:
    """Sides 0 and 1 with side 0 near `goal`: coarsened by small clusters down to a few vertices, the best of several grown starts there, local
    search on every level up.
    """
    rng = np.random.default_rng(seed)
    if g.n > 160:
        small, to = contract(g, cluster(g, max(g.heaviest, g.total / max(80, g.n // (3 if strong else 4))), 3, seed))
        if small.n < 0.9 * g.n:
            return fm(g, bisect(small, goal, limits, seed + 1, strong)[to], limits, 8 if strong else 3)
    best = None
    for _ in range(24 if strong else 8):
        side = fm(g, grow(g, goal, rng), limits, 8 if strong else 3)
        weight = np.bincount(side, weights=g.c, minlength=2)
        key = (max(0.0, weight[0] - limits[0], weight[1] - limits[1]), g.cut(side))
        if best is None or key < best[0]:
            best = (key, side)
    return best[1]


def split(g: Csr, spans: list[int], limits: list[float], seed: int, strong: bool = False, eps: float = 0.03) -> np.ndarray:
    """Parts 0..len(spans)-1 by recursive bisection; part i gets weight in proportion to its span, at most limits[i].

    A side keeps to its share of what is there within eps as well: limits alone would let a light graph go to one side as a whole.
    """
    if len(spans) == 1 or not g.n:
        return np.zeros(g.n, dtype=np.int64)
    h = (len(spans) + 1) // 2
    goal = g.total * sum(spans[:h]) / sum(spans)
    shares = (goal, g.total - goal)
    most = tuple(min(sum(x), max((1 + eps) * share, share + g.heaviest)) for x, share in zip((limits[:h], limits[h:]), shares, strict=True))
    side = bisect(g, goal, most, seed, strong)
    out = np.zeros(g.n, dtype=np.int64)
    for b, part in enumerate((slice(None, h), slice(h, None))):
        rows = np.flatnonzero(side == b)
        out[rows] = split(g.induced(rows), spans[part], limits[part], seed * 2 + b + 1, strong, eps) + (h if b else 0)
    return out


def halves(span: int, parts: int) -> list[int]:
    """Final blocks below each of up to `parts` children of a block with `span` of them."""
    spans = [span]
    while len(spans) < parts and max(spans) > 1:
        spans = [y for s in spans for y in ((s + 1) // 2, s // 2) if y]
    return spans


def widen(spans: list[int], target: int, parts: int) -> tuple[list[list[int]], bool]:
    """Children's spans of each block when `len(spans)` blocks become `target`, at most `parts` from one; whether anything is split."""
    share = min(parts, max(1, -(-target // len(spans))))
    share = max(2, share) if target > len(spans) else 1
    children = [halves(s, share) for s in spans]
    return children, any(len(x) > 1 for x in children)


def limits_of(g: Csr, spans: list[int], k: int, eps: float) -> list[float]:
    return [block_limit(g.total, k, eps, g.heaviest, s) for s in spans]


def deep(g: Csr, k: int, eps: float, c: int, parts: int, sweeps: int, seed: int, strong: bool = False, finest: bool = True, goal: int | None = None) -> tuple[np.ndarray, list[int], list[tuple[int, int]]]:
    """Deep multilevel partition of a gathered graph: labels, spans of the blocks, and (n, blocks) of each level.

    goal: blocks to reach on the given graph; k if it is the finest of all.
    """
    level = None
    if g.n > c * min(k, parts):
        small, to = contract(g, cluster(g, max_cluster_weight(g.total, g.n, k, c, eps), sweeps, seed))
        if small.n <= 0.95 * g.n:
            level = (small, to)
    if level:
        part, spans, trace = deep(level[0], k, eps, c, parts, sweeps, seed + 1, strong, False)
        part = settle(g, part[level[1]], limits_of(g, spans, k, eps), sweeps, seed)
    else:
        part, spans, trace = np.zeros(g.n, dtype=np.int64), [k], []
    target = k if finest else min(k, max(target_blocks(g.n, k, c), min(k, parts) if not level else 1))
    target = goal or target
    while len(spans) < target:
        children, more = widen(spans, target, parts)
        if not more:
            break
        new = np.zeros(g.n, dtype=np.int64)
        flat = [s for x in children for s in x]
        limits = limits_of(g, flat, k, eps)
        at = 0
        for b, x in enumerate(children):
            rows = np.flatnonzero(part == b)
            new[rows] = at + split(g.induced(rows), x, limits[at : at + len(x)], seed + 31 * b, strong, eps)
            at += len(x)
        part, spans = settle(g, new, limits, sweeps, seed), flat
    return part, spans, [*trace, (g.n, len(spans))]


def matching(g: Csr, limit: float, rounds: int, seed: int, within: np.ndarray | None = None) -> np.ndarray:
    """Heavy-edge matching by mutual best proposals: in each round unmatched vertices propose along their heaviest arc, mutual ones pair up."""
    label, free, t = np.arange(g.n), np.ones(g.n, bool), g.tails()
    rng = np.random.default_rng(seed)
    low, high = np.minimum(t, g.adj), np.maximum(t, g.adj)
    coin = np.zeros(len(t))
    key, at = np.unique(low * np.int64(g.n) + high, return_inverse=True)
    coin = rng.random(len(key))[at]
    for _ in range(max(rounds, 3)):
        ok = free[t] & free[g.adj] & (g.c[t] + g.c[g.adj] <= limit)
        if within is not None:
            ok &= within[t] == within[g.adj]
        e = np.flatnonzero(ok)
        if not len(e):
            break
        e = e[np.lexsort((coin[e], g.w[e], t[e]))]
        last = np.append(np.flatnonzero(np.diff(t[e])), len(e) - 1)
        best = np.full(g.n, -1)
        best[t[e[last]]] = g.adj[e[last]]
        v = np.flatnonzero(best >= 0)
        mutual = v[(best[best[v]] == v) & (v < best[v])]
        label[best[mutual]] = mutual
        free[mutual] = free[best[mutual]] = False
    return label


def brute_force(g: Csr, k: int, limit: float) -> tuple[int, np.ndarray]:
    """Least cut and one partition of it, for at most 14 vertices; the first vertex stays in block 0."""
    if g.n > 14:
        raise ValueError("too many vertices for an exhaustive search")
    best = None
    for code in range(k ** max(0, g.n - 1)):
        part = np.zeros(g.n, dtype=np.int64)
        for v in range(1, g.n):
            part[v], code = code % k, code // k
        if np.bincount(part, weights=g.c, minlength=k).max() <= limit and (best is None or g.cut(part) < best[0]):
            best = (g.cut(part), part)
    return best
