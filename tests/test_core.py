import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
import pytest
from pyspark.sql import functions as F

from graphsplit.functions import columns as c
from graphsplit.model import Graph
from graphsplit.operators import balance, kernels, layout, measures
from graphsplit.operators.kernels import Csr
from graphsplit.plans import baselines, report
from graphsplit.plans.deep import DeepParams, deep_partition, limits_for


def csr(n, edges, weights=None):
    s = np.array([e[0] for e in edges] + [e[1] for e in edges], dtype=np.int64)
    d = np.array([e[1] for e in edges] + [e[0] for e in edges], dtype=np.int64)
    return Csr.of(np.asarray(weights if weights is not None else [1] * n), s, d, np.ones(len(s), dtype=np.int64))


TWO = [(a, b) for h in (0, 4) for a in range(h, h + 4) for b in range(a + 1, h + 4)] + [(3, 4)]


def frame(spark, n, edges, weights=None):
    v = spark.createDataFrame([(k, (weights or [1] * n)[k]) for k in range(n)], "vid long, c long")
    e = spark.createDataFrame([x for a, b in edges for x in ((a, b, 1), (b, a, 1))], "src long, dst long, w long")
    return Graph.of(v, e)


@pytest.mark.parametrize("x,y", [(0.3, 1), (1, 1), (3, 4), (4, 4), (5, 8), (44.6, 64)])
def test_power(x, y):
    assert c.ceil2(x) == y


def test_limits():
    assert [c.num_batches(p) for p in (1, 4, 16, 64, 8192)] == [128, 32, 8, 8, 8]
    assert [c.num_copies(n, 2000, 16) for n in (8000, 5000, 1000, 32000)] == [4, 4, 16, 1]
    assert (c.target_blocks(89158, 16, 2000), c.target_blocks(89158, 128, 2000), c.target_blocks(10000, 16, 2000)) == (16, 64, 8)
    assert c.l_max(89158, 16, 0.03, 1) == pytest.approx(5739.54625)
    assert c.l_max(200, 16, 0.03, 1) == 13.5 and c.l_max(8, 2, 0.03, 1) == 5 and c.l_max(100, 4, 0.03, 10) == 35
    assert c.max_cluster_weight(89158, 89158, 16, 2000, 0.03) == pytest.approx(167.17125)
    assert c.max_cluster_weight(89158, 89158, 128, 2000, 0.03) == pytest.approx(60)


def test_two_cliques_kernels():
    g = csr(8, TWO)
    assert kernels.brute_force(g, 2, 5)[0] == 1
    part, spans, _ = kernels.deep(g, 2, 0.03, 4, 2, 3, 1)
    assert g.cut(part) == 1 and spans == [1, 1]
    assert g.cut(np.arange(8) % 2) == 9
    small, to = kernels.contract(g, np.array([0] * 4 + [4] * 4))
    assert small.c.tolist() == [4, 4] and small.w.tolist() == [1, 1]


@pytest.mark.parametrize("k", [2, 3, 4, 7])
def test_deep_kernel_is_balanced_on_a_path(k):
    g = csr(64, [(a, a + 1) for a in range(63)])
    part, _, _ = kernels.deep(g, k, 0.03, 8, 2, 3, 1)
    assert set(part.tolist()) == set(range(k))
    assert np.bincount(part).max() <= kernels.limits_of(g, [1], k, 0.03)[0]
    assert g.cut(part) <= 4 * k


def test_kernel_clusters_respect_the_limit():
    rng = np.random.default_rng(3)
    g = csr(200, {tuple(sorted(x)) for x in rng.integers(0, 200, (900, 2)).tolist() if x[0] != x[1]}, rng.integers(1, 5, 200))
    label = kernels.cluster(g, 12, 3, 1)
    small, to = kernels.contract(g, label)
    assert small.heaviest <= 12 and small.total == g.total
    p = np.arange(small.n) % 2
    assert small.cut(p) == g.cut(p[to])
    pairs = np.bincount(np.unique(kernels.matching(g, 100, 4, 1), return_inverse=True)[1])
    assert pairs.max() <= 2


def test_rebalance_from_one_block():
    g = csr(40, [(a, (a + 1) % 40) for a in range(40)])
    part = kernels.rebalance(g, np.zeros(40, dtype=np.int64), kernels.limits_of(g, [1] * 4, 4, 0.03))
    assert np.bincount(part, minlength=4).max() <= 11


def test_measures_on_two_cliques(spark):
    g = frame(spark, 8, TWO)
    parity = g.vertices.select("vid", (F.col("vid") % 2).cast("int").alias("block"))
    assert measures.edge_cut(g, parity).first()["cut"] == 9
    assert {r["block"]: r["boundary"] for r in measures.boundary_vertices(g, parity).collect()} == {0: 4, 1: 4}
    assert g.validate().count() == 0
    uneven = g.vertices.select("vid", (F.col("vid") > 4).cast("int").alias("block"))
    assert measures.edge_cut(g, uneven).first()["cut"] == 3
    assert measures.feasibility(g, uneven, 2, 0.03).first()["feasible"]
    gains = {(r["vid"], r["block"]): r["gain"] for r in balance.move_gains(g, uneven).collect()}
    assert gains[(4, 1)] == 2
    cut, best = baselines.brute_force_partition(g, 2)
    assert cut == 1 == measures.edge_cut(g, best).first()["cut"]


def test_brute_force_takes_whole_graphs_only(spark):
    from itertools import product

    edges, weights = [(a, b) for a in range(10) for b in range(a) if (3 * a + 5 * b) % 4 < 2], [1, 2, 1, 3, 1, 1, 2, 1, 1, 2]
    cut, part = baselines.brute_force_partition(g := frame(spark, 10, edges, weights), 2)
    fits = [s for s in product((0, 1), repeat=10) if max(w := sum(c for c, b in zip(weights, s, strict=True) if b), 15 - w) <= 10.5]
    assert cut == min(sum(s[a] != s[b] for a, b in edges) for s in fits) == measures.edge_cut(g, part).first()["cut"]
    with pytest.raises(ValueError):
        kernels.brute_force(csr(15, []), 2, 8)


def test_validation_finds_problems(spark):
    v = spark.createDataFrame([(0, 1), (1, 0)], "vid long, c long")
    e = spark.createDataFrame([(0, 1, 1), (1, 1, 1), (0, 9, 2), (0, 1, 1)], "src long, dst long, w long")
    assert {r["problem"] for r in Graph(v, e, 2, 4, 1, 1).validate().collect()} == {"vertex weight", "loop", "repeated arc", "no reverse", "missing end"}


def test_relative_gain(spark):
    rows = spark.createDataFrame([(4, 3), (0, 5), (-4, 2), (-4, 8)], "g long, c long")
    assert [r[0] for r in rows.select(c.relative_gain(F.col("g"), F.col("c"))).collect()] == [12, 0, -2, -0.5]


def test_queue_takes_just_enough():
    weights = {0: (10, 7.333), 1: (3, 7.333), 2: (3, 7.333)}
    moves = balance.decide_moves([(0, 1, 2, 1, 3.0), (0, 2, 1, 1, 2.0), (0, 3, 2, 2, 1.0)], weights)
    assert moves == [(1, 0, 1), (2, 0, 1)]
    # a full target gives way to the lightest block, whose weight changes along the way
    assert balance.decide_moves([(0, 1, 3, 1, 3.0), (0, 2, 3, 1, 2.0)], {0: (10, 4), 1: (4, 5), 2: (0, 5), 3: (1, 5)}) == [(1, 0, 2), (2, 0, 3)]


def test_windows_move_no_more_than_the_excess(spark):
    # a path of 400 vertices, half of it in one of four blocks, on 16 PEs: the excess is 62.7 or so
    g = frame(spark, 400, [(a, a + 1) for a in range(399)])
    p = g.vertices.select("vid", F.when(F.col("vid") < 200, 0).otherwise(1 + F.col("vid") % 3).cast("int").alias("block"))
    limits = limits_for(g, [1] * 4, 4, 0.03)
    after, moves = balance.balance_round(g, p, layout.assign_pe(g, 16), balance.weighted(g, p, limits), 400, decide="window")
    left = {r["block"]: r["weight"] for r in measures.block_weights(g, after, 4).collect()}
    assert 0 < moves.count() <= 200 - limits[0] + 1 and left[0] >= limits[0] - 1 and max(left[b] for b in (1, 2, 3)) <= limits[0]
    both = [measures.feasibility(g, balance.balance(g, p, limits, decide=d), 4, 0.03).first()["feasible"] for d in ("driver", "window")]
    assert both == [True, True]


def test_connections_follow_moves(spark):
    """Gains updated by the neighbours of moved vertices against gains from scratch."""
    g = frame(spark, 60, [(a, b) for a in range(60) for b in range(a) if (a * b) % 7 == 3])
    p = g.vertices.select("vid", F.when(F.col("vid") % 5 < 3, 0).otherwise(F.col("vid") % 3).cast("int").alias("block"))
    weights = balance.weighted(g, p, [10.0, 60.0, 60.0])
    conn = balance.connections(g, p, weights)
    moves = p.filter("block = 0 and vid % 4 = 0").select("vid", F.col("block").alias("old"), F.lit(2).alias("new"))
    after = p.join(moves.select("vid", "new"), "vid", "left").select("vid", F.coalesce("new", "block").alias("block"))
    rows = lambda df: sorted(map(tuple, df.select("vid", "label", "conn").collect()))
    fresh = balance.rate(g.edges, after.select("vid", F.col("block").alias("label")), conn.select("vid").distinct())
    assert rows(balance.moved_connections(g, conn, moves)) == rows(fresh)


def test_balance_says_so_when_nothing_fits(spark):
    g = frame(spark, 6, [(0, 1)])
    with pytest.raises(RuntimeError, match="fits"):
        balance.balance(g, g.vertices.select("vid", F.lit(0).alias("block")), [2.0, 2.0])


def test_revert_quota(spark):
    from graphsplit.operators.cluster import revert_overweight

    moves = spark.createDataFrame([(1, 0, 2, 1, 9, 1), (2, 0, 2, 2, 9, 2), (3, 0, 4, 3, 9, 3), (4, 1, 2, 4, 9, 1)], "vid long, pe int, c long, old long, new long, gain long")
    state = spark.createDataFrame([(1, 2, 0, 9), (2, 2, 0, 9), (3, 4, 0, 9), (7, 7, 0, 9), (4, 2, 1, 9), (8, 3, 1, 9)], "vid long, c long, pe int, label long")
    weights = spark.createDataFrame([(9, 20)], "label long, weight long")
    assert {r["vid"]: r["reverted"] for r in revert_overweight(moves, state, weights, 14).collect()} == {1: True, 2: True, 3: True, 4: True}


@pytest.mark.parametrize("p,direct,grid", [(4, 12, 8), (16, 240, 96), (64, 4032, 896)])
def test_exchange_counts(spark, p, direct, grid):
    full = spark.range(p * p).select((F.col("id") % p).cast("int").alias("src_pe"), F.floor(F.col("id") / p).cast("int").alias("dst_pe"))
    count = lambda how: layout.exchange_cost(full, p, how).agg(F.sum("messages")).first()[0]
    assert (count("direct"), count("grid")) == (direct, grid)


def lattice(spark, side):
    at = lambda r, q: r * side + q
    return frame(spark, side * side, [(at(r, q), at(r, q + 1)) for r in range(side) for q in range(side - 1)] + [(at(r, q), at(r + 1, q)) for r in range(side - 1) for q in range(side)])


def test_deep_scheme_on_a_lattice(spark):
    g = lattice(spark, 24)
    r = deep_partition(g, 4, DeepParams.fast(c=80, sweeps=2, pes=16))
    assert r.distributed >= 1 and r.copies >= 1
    # every level has the blocks that its size asks for; the coarsest is the first at most C * K
    assert r.levels[0][0] <= 160 and [b for _, b in r.levels] == [2] + [min(4, max(2, c.ceil2(n / 80))) for n, _ in r.levels[1:]]
    assert {t["step"] for t in r.trace} >= {"coarsen", "initial", "refine"} and all(t["limit"] >= 80 * 0.03 for t in r.trace if t["step"] == "coarsen")
    assert measures.feasibility(g, r.partition, 4, 0.03).first()["feasible"]
    assert measures.validate_partition(g, r.partition, 4).first()["distinct_vertices"] == 24 * 24
    assert measures.edge_cut(g, r.partition).first()["cut"] < 96  # twice the quarters
    with pytest.raises(ValueError):
        deep_partition(g, 24 * 24 + 1)
    assert deep_partition(g, 1).partition.select("block").distinct().count() == 1


def test_nothing_is_gathered_that_is_not_coarsened(spark, monkeypatch):
    """The driver never collects the graph, and no task gets more than C * K vertices of it before it is split."""
    from graphsplit.operators import initial

    monkeypatch.setattr(initial, "gather", lambda *a: pytest.fail("gathered on the driver"))
    seen, run = [], initial.trials
    monkeypatch.setattr(initial, "trials", lambda g, *a: seen.append(max(n for _, n in g.copies)) or run(g, *a))
    deep_partition(lattice(spark, 16), 2, DeepParams.fast(c=40, eps=0.1, sweeps=1))
    assert len(seen) == 1 and seen[0] <= 80


def simulate(n, edges, weights, pes, batches_of, limit, sweeps, seed):
    """Clusters of PEs that exchange messages, written as one loop over shared arrays; nothing overweight in this fixture."""
    arcs = [[] for _ in range(n)]
    for a, b in sorted([*edges, *[(b, a) for a, b in edges]]):
        arcs[a].append(b)
    home = [v * pes // n for v in range(n)]
    start = [min(v for v in range(n) if home[v] == p) for p in range(pes)]
    label = list(range(n))
    told = {p: label[:] for p in range(pes)}  # as each PE knows it
    known = {p: {v: weights[v] for v in range(n)} for p in range(pes)}
    true = dict(enumerate(weights))
    for sweep in range(sweeps):
        moved_in_sweep = 0
        for b in range(max(x for x in batches_of if x is not None) + 1):
            news, touched = [], {p: set() for p in range(pes)}
            for p in range(pes):
                vs = sorted((v for v in range(n) if home[v] == p and batches_of[v] == b), key=lambda v: (len(arcs[v]).bit_length(), v))
                if not vs:
                    continue
                rng = np.random.default_rng([seed, sweep, b, p])
                chunk = np.arange(len(vs)) // 64
                bucket = [np.floor(np.log2(len(arcs[v]))) for v in vs]
                order = np.lexsort((rng.random(len(vs)), rng.random(len(vs) // 64 + 1)[chunk], bucket))
                coins = rng.random(len(vs))
                for i in order:
                    v, conn = vs[i], {}
                    for u in arcs[v]:
                        conn[told[p][u]] = conn.get(told[p][u], 0) + 1
                    own = told[p][v]
                    here = conn.pop(own, 0)
                    best, most, seen = own, here, 1
                    for t, s in conn.items():
                        if s < most or known[p][t] + weights[v] > limit:
                            continue
                        if s > most:
                            best, most, seen = t, s, 1
                        elif best != own:
                            seen += 1
                            if coins[i] * seen < 1:
                                best = t
                    if best != own:
                        known[p][own] -= weights[v]
                        known[p][best] += weights[v]
                        true[own] -= weights[v]
                        true[best] += weights[v]
                        touched[p] |= {own, best}
                        told[p][v] = label[v] = best
                        news.append((p, v))
                        moved_in_sweep += 1
            views = {p: dict(k) for p, k in known.items()}
            for p, v in news:  # only PEs with a ghost of v hear of it, and of its label's weight as the teller knows it
                for q in {home[u] for u in arcs[v]} - {p}:
                    told[q][v] = label[v]
                    known[q][label[v]] = views[p][label[v]]
            for p in range(pes):
                for x in touched[p]:
                    known[p][x] = true[x]
        if not moved_in_sweep:
            break
    assert start == sorted(start)
    return label


@pytest.mark.parametrize("tasks", [1, 3])
def test_pes_that_exchange_messages_against_one_loop(spark, tasks):
    import dataclasses

    from graphsplit.operators import fleet

    n = 90
    edges = sorted({(min(a, b), max(a, b)) for a in range(n) for b in ((a + 1) % n, (a * a + 7) % n, (5 * a + 3) % n) if a != b})
    g = frame(spark, n, edges)
    f = dataclasses.replace(fleet.lay_out(g, 4, 1, 3), tasks=tasks)
    trace = {}
    got = {r.vid: r.label for r in fleet.propagate(g, 4, [1000.0], 2, 5, trace=trace, fleet=f).collect()}
    batch = [None] * n
    for r in f.adjacency.collect():
        for v in fleet.unpack(r.body)[0].tolist():
            batch[v] = r.batch
    want = simulate(n, edges, [1] * n, 4, batch, 1000.0, 2, 5)
    assert [got[v] for v in range(n)] == want
    assert trace["kept"] == sum(trace["moves"]) and trace["notified"] > 0


def test_overweight_clusters_are_taken_back(spark):
    """A star whose leaves all choose the hub's cluster at once: each PE takes back its share, and what is left keeps to the limit."""
    from graphsplit.operators.cluster import lp_cluster

    g = frame(spark, 65, [(0, v) for v in range(1, 65)])
    sizes = {m: g.vertices.join(lp_cluster(g, 10, 1, 8, 1, limit_mode=m, count=1), "vid").groupBy("cluster").count().agg(F.max("count")).first()[0] for m in ("revert", "local", "none")}
    assert sizes["none"] >= 60 and sizes["revert"] <= 10 < sizes["local"] <= 80


def test_copies_get_clusters_of_their_own(spark):
    from graphsplit.operators import initial
    from graphsplit.operators.cluster import lp_cluster
    from graphsplit.operators.contract import contract

    g = lattice(spark, 12)
    many = initial.replicate(g, 4)
    assert many.copies == ((0, 144), (144, 144), (288, 144), (432, 144)) and many.total == 144 and many.validate().count() == 0
    clusters = lp_cluster(many, [8.0] * 4, 2, 4, 1, count=4)
    rows = clusters.select((F.col("vid") / 144).cast("int").alias("a"), (F.col("cluster") / 144).cast("int").alias("b"), (F.col("cluster") % 144).alias("c"), (F.col("vid") % 144).alias("v")).collect()
    assert all(r.a == r.b for r in rows)
    assert len({tuple(sorted((r.v, r.c) for r in rows if r.a == k)) for k in range(4)}) > 1  # coins of their own
    coarse, _ = contract(many, clusters)
    assert len(coarse.copies) == 4 and coarse.total == 144 and sum(n for _, n in coarse.copies) == coarse.n


def test_recursive_bisection_bisects_large_graphs_too(spark, monkeypatch):
    calls, run = [], baselines.multilevel_down_up
    monkeypatch.setattr(baselines, "multilevel_down_up", lambda g, *a, **k: calls.append(g.n) or run(g, *a, **k))
    # four cliques of 16 in a ring; ids go round robin, so that ranges of ids cut nearly everything
    edges = [(4 * a + q, 4 * b + q) for q in range(4) for a in range(16) for b in range(a + 1, 16)] + [(q, (q + 1) % 4) for q in range(4)]
    g = frame(spark, 64, edges)
    p = baselines.recursive_bisection(g, 4, c=20)
    assert calls == [64]
    assert measures.edge_cut(g, p).first()["cut"] == 4
    assert measures.feasibility(g, p, 4, 0.03).first()["feasible"]


def test_matching_goes_on_where_hubs_stall_it(spark, monkeypatch):
    # two hubs of odd and even ids with 60 leaves each: a matching takes one leaf a hub and level
    monkeypatch.setattr(baselines, "range_partition", lambda *a: pytest.fail("ranges of ids"))
    g = frame(spark, 122, [(h, v) for h in (0, 1) for v in range(h + 2, 122, 2)] + [(0, 1)])
    trace = []
    p = baselines.matching_partition(g, 2, c=8, stop=15, trace=trace)
    assert len(trace) >= 2  # levels
    assert measures.validate_partition(g, p, 2).first()["distinct_vertices"] == 122
    assert measures.edge_cut(g, p).first()["cut"] < 30


def test_what_no_task_can_hold_fails(spark, monkeypatch):
    from graphsplit.operators import initial

    monkeypatch.setattr(initial, "TASK_ARCS", 50)
    g = frame(spark, 30, [(a, b) for a in range(30) for b in range(a)])
    with pytest.raises(RuntimeError, match="more than a task"):
        initial.trials(g, 1, 1, lambda csr, s: None)
    with pytest.raises(ValueError, match="too many"):
        initial.gather(g)


def test_time_limit_ends_a_run(spark):
    import time

    from graphsplit.plans.experiments import measured

    g = frame(spark, 8, TWO)
    half = g.vertices.select("vid", (F.col("vid") > 3).cast("int").alias("block"))
    assert measured(lambda: half, g, 2, 0.03, 60)[:3] == (1, True, "ok")

    def slow():
        for _ in range(100):
            spark.range(10_000_000_000).agg(F.max(F.xxhash64("id"))).collect()

    began = time.monotonic()
    assert measured(slow, g, 2, 0.03, 1)[2] == "timeout" and time.monotonic() - began < 30


def test_balancer_moves_everything_needed(spark):
    g = frame(spark, 30, [(a, a + 1) for a in range(29)])
    trace = {}
    p = balance.balance(g, g.vertices.select("vid", F.lit(0).alias("block")), limits_for(g, [1] * 3, 3, 0.03), ell=4, trace=trace)
    assert trace["rounds"] >= 2 and trace["balance_moves"] >= 18 and measures.feasibility(g, p, 3, 0.03).first()["feasible"]


def test_profile_and_means(spark):
    runs = spark.createDataFrame([("X", "a", 2, 1, 10, True, "ok", 1.0), ("X", "b", 2, 1, 20, True, "ok", 1.0), ("X", "c", 2, 1, 5, False, "ok", 1.0), ("Y", "a", 2, 1, 12, True, "ok", 1.0), ("Y", "b", 2, 1, 18, True, "ok", 1.0), ("Y", "c", 2, 1, 30, True, "ok", 1.0)], report.RUNS)
    means = report.aggregate_seeds(runs)
    share = {(r["algorithm"], r["tau"]): r["share"] for r in report.performance_profile(means, [1.0, 1.2]).collect()}
    assert share[("X", 1.0)] == pytest.approx(1 / 3) and share[("Y", 1.0)] == pytest.approx(2 / 3)
    assert share[("X", 1.2)] == pytest.approx(2 / 3) and share[("Y", 1.2)] == pytest.approx(1)
    two = spark.createDataFrame([("z", 10), ("z", 1000)], "a string, cut long")
    assert report.geo_mean(two, "cut", ["a"]).first()["geo_cut"] == pytest.approx(100)
    assert report.common_instances(runs).select("graph").distinct().count() == 2


@pytest.mark.parametrize("arcs_a_task", [100_000, 100])
def test_moves_of_the_last_sweep_leave_out_what_the_last_take_back_takes(spark, monkeypatch, arcs_a_task):
    from graphsplit.operators import fleet
    from graphsplit.operators.cluster import lp_cluster
    from graphsplit.sources import generators

    monkeypatch.setattr(fleet, "ARCS_A_TASK", arcs_a_task)
    g, trace = generators.star(spark, 400), {}
    w = g.vertices.join(lp_cluster(g, 12, 1, 4, 1, count=1, trace=trace), "vid").groupBy("cluster").agg(F.sum("c").alias("c"))
    assert trace["reverted"] > 0 and trace["moves"] == [trace["kept"]]
    assert w.agg(F.max("c")).first()[0] <= 12


def test_shared_deep_finds_planted_groups_and_its_query_takes_given_tables(spark):
    from graphsplit import queries
    from graphsplit.sources import generators

    p = baselines.shared_deep_partition(generators.planted(spark, 16, 60, 20, 1), 16, params=DeepParams(c=160))
    assert p.groupBy("block").agg(F.countDistinct(F.floor(F.col("vid") / 60)).alias("groups"), F.count("*").alias("n")).filter("groups <> 1 or n <> 60").count() == 0
    row = queries.QUERIES["base_shared_deep"](spark, "/root/testdata/sf0.001").first()
    assert (row["n"], row["covered"], row["blocks"]) == (25, 25, 4) and row["feasible"] and row["below_reference"]


def test_rounds_of_the_balancer_do_not_grow_with_the_excess(spark):
    g = frame(spark, 3000, [(a, a + 1) for a in range(2999)])
    trace = {}
    p = balance.balance(g, g.vertices.select("vid", F.lit(0).alias("block")), limits_for(g, [1] * 4, 4, 0.03), ell=64, trace=trace)
    assert trace["rounds"] <= 8 and trace["balance_moves"] >= 2226 and measures.feasibility(g, p, 4, 0.03).first()["feasible"]


def test_large_k_is_solved_on_the_given_vectors(spark, tmp_path):
    from graphsplit.plans import experiments

    pq.write_table(pa.table({"vec_id": [5, 3, 9, 1], "embedding": [[2.0], None, [1.0], [1.0]]}), tmp_path / "embeddings.parquet")
    g = experiments.small_graph(spark, "vectors", str(tmp_path))
    assert (g.n, sorted(tuple(r) for r in g.edges.collect())) == (4, [(0, 1, 1), (1, 0, 1), (1, 2, 1), (2, 1, 1), (2, 3, 1), (3, 2, 1)])
    assert {(n, k) for _, _, n, k, _ in experiments.SMALL["e5_large_k"]} == {("vectors", 64)} and "FROM embeddings" in experiments.small_sql("e5_large_k")


def test_light_blocks_are_split_in_proportion():
    """A path below both limits: cutting nothing, all of it on one side, was the best bisection."""
    n = 100
    path = np.arange(n - 1)
    g = kernels.Csr.of(np.ones(n, np.int64), np.concatenate([path, path + 1]), np.concatenate([path + 1, path]), np.ones(2 * n - 2, np.int64))
    for seed in range(5):
        sizes = np.bincount(kernels.split(g, [1, 1], [110.0, 110.0], seed), minlength=2)
        assert sizes.max() <= 51
        assert np.bincount(kernels.split(g, [1] * 4, [110.0] * 4, seed), minlength=4).min() >= 23


def test_empty_blocks_are_filled(spark):
    from graphsplit.operators.initial import fill_empty

    g = frame(spark, 12, [(v, v + 1) for v in range(11)])
    p = spark.createDataFrame([(v, 0 if v < 2 else 3) for v in range(12)], "vid long, block int")
    found = fill_empty(g, p, 4, 0.03, 1)
    assert found.count() == found.select("vid").distinct().count() == 12
    assert {r.block: r["count"] for r in found.groupBy("block").count().collect()} == {0: 1, 1: 5, 2: 1, 3: 5}


def test_messages_take_few_bytes_and_few_arcs_one_task():
    from graphsplit.operators import fleet

    arrays = [[], [0, 127], [-128, 5, 128], [1 << 31, -1], list(range(1000))]
    body = fleet.pack(*arrays)
    found = fleet.unpack(body)
    assert [x.tolist() for x in found] == arrays and all(x.dtype == np.int64 and x.flags.writeable for x in found)
    assert len(body) < 2400  # 8 bytes for each number took 8,144
    assert [fleet.tasks_for(16, x) for x in (0, 799_999, 800_000, 10_000_000)] == [1, 1, 8, 16]


def test_weights_that_a_pe_learns():
    from graphsplit.operators import fleet

    none = np.zeros(0, np.int64)
    pe = fleet.Pe(0, [none] * 6 + [np.array([2, 5]), np.array([20, 50])] + [none] * 7)
    pe.learn(np.array([5, 9, 1, 9]), np.array([51, 90, 10, 91]))
    assert dict(zip(pe.known.tolist(), pe.weight.tolist(), strict=True)) == {1: 10, 2: 20, 5: 51, 9: 91}
    assert pe.weight_of(np.array([9, 3, 1, 100])).tolist() == [91, 0, 10, 0]


def test_connections_on_arrays_equal_a_plain_loop():
    from graphsplit.operators import fleet

    rng = np.random.default_rng(3)
    for count in (5, 40, 100_000):
        labels, w = rng.integers(0, count, 300), rng.integers(1, 4, 300)
        plain = {}
        for t, x in zip(labels.tolist(), w.tolist(), strict=True):
            plain[t] = plain.get(t, 0) + x
        for own in (int(labels[0]), count - 1):
            here = plain.get(own, 0)
            found, others = fleet.connected(labels, w, own, count)
            assert found == here
            assert list(others.items()) == [(t, s) for t, s in plain.items() if t != own and s >= here]


def test_no_more_tasks_than_run_at_once(spark, monkeypatch):
    from graphsplit.operators import fleet

    monkeypatch.setattr(fleet, "ARCS_A_TASK", 1)
    g = frame(spark, 64, [(a, a + 1) for a in range(63)])
    assert fleet.lay_out(g, 16, 1, 2).tasks == max(2, spark.sparkContext.defaultParallelism) < 16


def test_tables_that_nothing_reads_any_more_are_deleted(spark):
    import os

    from graphsplit import model
    from graphsplit.operators import fleet
    from graphsplit.operators.contract import contract

    def files():
        return {os.path.join(at, f) for at, _, fs in os.walk(model.checkpoint_folder(spark).removeprefix("file:")) for f in fs if f.startswith("part-")}

    g = frame(spark, 64, [(a, a + 1) for a in range(63)])
    f = fleet.lay_out(g, 4, 1, 2)
    before = files()
    labels = fleet.propagate(g, 4, [8.0], 2, 1, fleet=f)
    # of labels, states of PEs before and after each sweep, and totals, only the labels stay
    assert {os.path.dirname(x) for x in files() - before} == {labels._written_at.removeprefix("file:")}
    coarse, mapping = contract(g, labels.withColumnRenamed("label", "cluster"), 4)
    assert coarse.edges.count() > 0 and mapping.count() == 64
    model.discard(labels)
    assert before - files() == set() and not any(x.startswith(labels._written_at.removeprefix("file:")) for x in files())


def test_arcs_are_packed_before_they_are_shuffled(spark, monkeypatch):
    """Many pieces of a batch give the same packed arcs as one, and ghosts follow from them."""
    from graphsplit.operators import fleet

    n = 90
    edges = sorted({(min(a, b), max(a, b)) for a in range(n) for b in ((a + 1) % n, (a * a + 7) % n, (5 * a + 3) % n) if a != b})
    g = frame(spark, n, edges)
    g = Graph(g.vertices, g.edges.repartition(5), g.n, g.arcs, g.total, g.heaviest)
    found = []
    for piece in (1, 1_000_000):
        monkeypatch.setattr(fleet, "PIECE", piece)
        f = fleet.lay_out(g, 4, 1, 3)
        found.append((sorted((r.to, r.batch, bytes(r.body)) for r in f.adjacency.collect()), sorted(map(tuple, f.ghosts.collect()))))
    assert found[0] == found[1]
    arcs, pe = set(), [int(np.searchsorted(f.starts, v, side="right")) - 1 for v in range(n)]
    for to, _, body in found[0][0]:
        vids, ends, heads, w = fleet.unpack(body)
        arcs |= set(zip(np.repeat(vids, np.diff(ends, prepend=0)).tolist(), heads.tolist(), strict=True))
        assert {pe[v] for v in vids.tolist()} == {to} and set(w.tolist()) == {1}
        assert (np.diff(np.floor(np.log2(np.diff(ends, prepend=0)))) >= 0).all()
    assert arcs == {x for a, b in edges for x in ((a, b), (b, a))}
    assert found[0][1] == sorted({(pe[a], b, pe[b]) for a, b in arcs if pe[a] != pe[b]})


def test_ids_in_order_travel_as_steps():
    from graphsplit.operators import fleet

    arrays = [np.arange(1000) + (1 << 33), np.array([-(1 << 63), (1 << 63) - 1]), np.array([1 << 40]), np.array([300, 301, 0])]
    body = fleet.pack(*arrays)
    assert [x.tolist() for x in fleet.unpack(body)] == [x.tolist() for x in arrays]
    assert len(body) < 1400  # 8 bytes for each of the first took 8,000
