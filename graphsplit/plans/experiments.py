"""The experiments: which methods on which graphs, k and seeds, with the time limit, as tables of runs.

The defaults are narrower than the published ones, which take a cluster: three or five seeds, k up to 16 or 512, graphs of the given tables and of
the generators up to 2^12 vertices. All of it is a parameter. `SMALL` holds the fixed instances that the queries e1 to e10 run.
"""

from __future__ import annotations

import threading
import time
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphsplit.model import Graph
from graphsplit.operators.measures import edge_cut, feasibility
from graphsplit.plans import baselines, report
from graphsplit.plans.deep import DeepParams, DeepResult, deep_partition
from graphsplit.sources import generators
from graphsplit.sources.graphs import load_graph

QUALITY = ("copurchase", "custpart", "partsupp", "order_star", "event_chain", "user_slot", "emb_rgg2", "emb_rgg3", "doc_dup", "word", "trade", "page_sim", "link", "turns")
HIGH, LOW = ("order_star", "partsupp", "word"), ("event_chain", "emb_rgg2")


def deep_fast(g: Graph, k: int, seed: int, **more) -> DeepResult:
    return deep_partition(g, k, DeepParams.fast(**more), seed)


def deep_strong(g: Graph, k: int, seed: int, **more) -> DeepResult:
    return deep_partition(g, k, DeepParams.strong_(**more), seed)


METHODS: dict[str, Callable[[Graph, int, int], DataFrame | DeepResult]] = {
    "deep_fast": deep_fast,
    "deep_strong": deep_strong,
    "relaxed_fast": lambda g, k, s: baselines.relaxed_lp_partition(g, k, seed=s),
    "relaxed_eco": lambda g, k, s: baselines.relaxed_lp_partition(g, k, preset="eco", seed=s),
    "matching": lambda g, k, s: baselines.matching_partition(g, k, seed=s),
    "flat_lp": lambda g, k, s: baselines.flat_lp_partition(g, k, seed=s),
    "shared_deep": lambda g, k, s: baselines.shared_deep_partition(g, k, seed=s),
    "plain_multilevel": lambda g, k, s: baselines.multilevel_partition(g, k, seed=s),
    "recursive_bisection": lambda g, k, s: baselines.recursive_bisection(g, k, seed=s),
    "hash": lambda g, k, s: baselines.hash_partition(g, k, s),
    "range": lambda g, k, s: baselines.range_partition(g, k),
}


def measured(solve: Callable[[], DataFrame | DeepResult], g: Graph, k: int, eps: float, limit_seconds: float) -> tuple:
    """(cut, feasible, status, seconds). From the time limit on, jobs of the run are cancelled until it gives up."""
    sc, group, over, done = g.vertices.sparkSession.sparkContext, f"run-{uuid.uuid4().hex}", threading.Event(), threading.Event()

    def watch():
        if not done.wait(limit_seconds):
            over.set()
            while not done.wait(0.2):
                sc.cancelJobGroup(group)

    threading.Thread(target=watch, daemon=True).start()
    sc.setJobGroup(group, "a measured run", True)
    began = time.monotonic()
    try:
        p = solve()
        p = p.partition if isinstance(p, DeepResult) else p
        cut, fine = edge_cut(g, p).first()["cut"], feasibility(g, p, k, eps).first()["feasible"]
    except Exception:
        if over.is_set():
            return None, False, "timeout", time.monotonic() - began
        return None, False, "failed", time.monotonic() - began
    finally:
        done.set()
        sc.setLocalProperty("spark.jobGroup.id", None)
    seconds = time.monotonic() - began
    return cut, fine, "timeout" if over.is_set() else "ok" if fine else "infeasible", seconds


def run(spark: SparkSession, graphs: dict[str, Graph], methods: list[str], ks: list[int], seeds: list[int], eps: float = 0.03, limit_seconds: float = 3600, least: int = 8) -> DataFrame:
    rows = []
    for name, g in graphs.items():
        for k in ks:
            if g.n < least * k:
                continue
            for m in methods:
                for s in seeds:
                    rows.append((m, name, k, s, *measured(lambda m=m, g=g, k=k, s=s: METHODS[m](g, k, s), g, k, eps, limit_seconds)))
    return spark.createDataFrame(rows, report.RUNS)


def named(spark: SparkSession, sf_dir: str, names) -> dict[str, Graph]:
    return {n: load_graph(spark, sf_dir, n) for n in names}


def e1_quality(spark, sf_dir, seeds=(1, 2, 3, 4, 5), ks=(2, 4, 8, 16), names=QUALITY, limit_seconds=3600):
    """Cuts and feasibility of the fast preset against the two distributed baselines."""
    return run(spark, named(spark, sf_dir, names), ["deep_fast", "relaxed_fast", "matching"], list(ks), list(seeds), limit_seconds=limit_seconds)


def e2_strong(spark, sf_dir, seeds=(1, 2, 3, 4, 5), ks=(2, 8), names=("custpart", "event_chain", "emb_rgg2")):
    return run(spark, named(spark, sf_dir, names), ["deep_fast", "deep_strong", "relaxed_eco"], list(ks), list(seeds))


def e3_times(runs: DataFrame) -> DataFrame:
    """Geometric mean times over the instances that all methods solved."""
    return report.geo_mean(report.aggregate_seeds(report.common_instances(runs)), "seconds", ["algorithm"])


def e4_shared(spark, sf_dir, seeds=(1, 2, 3), ks=(4, 16), names=("custpart", "event_chain", "order_star")):
    return run(spark, named(spark, sf_dir, names), ["deep_fast", "shared_deep"], list(ks), list(seeds))


def e5_large_k(spark, sf_dir, seeds=(1,), ks=(256, 512), names=("event_chain", "order_star")):
    return run(spark, named(spark, sf_dir, names), ["deep_fast", "relaxed_fast", "matching", "plain_multilevel"], list(ks), list(seeds))


def _families(spark, log_n, degree):
    return {"rgg2d": generators.rgg2d(spark, log_n, degree), "rgg3d": generators.rgg3d(spark, log_n, degree), "rhg": generators.rhg(spark, log_n, degree)}


def e6_weak(spark, degrees=(8, 32), log_per_pe=10, pes=(1, 2, 4), k=16, methods=("deep_fast", "relaxed_fast", "matching")):
    """Weak scaling at fixed k: vertices grow with the PEs."""
    out = None
    for degree in degrees:
        for p in pes:
            graphs = {f"{n}_{degree}_{p}": g for n, g in _families(spark, log_per_pe + p.bit_length() - 1, degree).items()}
            found = run(spark, graphs, list(methods), [k], [1])
            out = found if out is None else out.union(found)
    return out


def e7_weak_growing_k(spark, per_block=(64, 512), log_n=(10, 11, 12), degree=8, methods=("deep_fast", "relaxed_fast", "matching")):
    """Weak scaling with as many vertices to a block."""
    out = None
    for size in per_block:
        for ln in log_n:
            graphs = {f"{n}_{size}_{ln}": g for n, g in _families(spark, ln, degree).items()}
            found = run(spark, graphs, list(methods), [max(2, (1 << ln) // size)], [1])
            out = found if out is None else out.union(found)
    return out


def e8_strong_scaling(spark, sf_dir, pes=(1, 2, 4, 8, 16), k=16, names=HIGH + LOW):
    """Cuts and times as logical PEs grow, k and graph fixed."""
    rows = []
    for n, g in named(spark, sf_dir, names).items():
        for p in pes:
            rows.append((f"deep_fast_{p}", n, k, 1, *measured(lambda g=g, p=p: deep_fast(g, k, 1, pes=p), g, k, 0.03, 900)))  # the published limit of 15 minutes
    return spark.createDataFrame(rows, report.RUNS)


def e9_flat(spark, sf_dir, seeds=(1, 2, 3), ks=(2, 8), names=QUALITY):
    return run(spark, named(spark, sf_dir, names), ["deep_fast", "flat_lp", "hash", "range"], list(ks), list(seeds))


ABLATIONS = {
    "base": {}, "local": {"limit_mode": "local"}, "unlimited": {"limit_mode": "none"}, "parts4": {"parts": 4}, "parts8": {"parts": 8}, "c400": {"c": 400},
    "batches32": {"batches": 32}, "short_queues": {"ell": 4}, "bulk": {"mode": "bulk", "batches": 2}, "matching": {"coarsening": "matching"}, "strict_refine": {"refine_mode": "strict", "batches": 2},
    "not_placed": {"place": False}, "windows": {"decide": "window"}, "adaptive_eps": {"adaptive_eps": True},
}


def e10_ablation(spark, sf_dir, names=("event_chain",), k=8, which=tuple(ABLATIONS), c=500):
    """Variants of the deep scheme."""
    rows = []
    for n, g in named(spark, sf_dir, names).items():
        for v in which:
            p = DeepParams.fast(**{"c": c, **ABLATIONS[v]})
            rows.append((v, n, k, 1, *measured(lambda g=g, p=p: deep_partition(g, k, p), g, k, 0.03, 3600)))
    return spark.createDataFrame(rows, report.RUNS)


# Small fixed instances, with what must come out: (experiment, algorithm, graph, k, most that may be cut). Cuts known by construction: four quarters
# of a lattice cut 48, eight planted blocks about 450 of 5,700 edges. A fraction is one of all edges: `vectors` are the given ones, as many as there are.
LITTLE = {"batches": 2, "sweeps": 2, "trials": 4, "pes": 16}


def small_graph(spark: SparkSession, name: str, sf_dir: str | None = None) -> Graph:
    kind, _, n = name.partition("_")
    return {"vectors": lambda: generators.ordered(spark, sf_dir, 24), "grid": lambda: generators.grid2d(spark, 24, 24), "planted": lambda: generators.planted(spark, 8, 60, 12, 1), "rgg2d": lambda: generators.rgg2d(spark, int(n), 8), "rgg3d": lambda: generators.rgg3d(spark, int(n), 8), "rhg": lambda: generators.rhg(spark, int(n), 8)}[kind]()


def _deep(**more):
    return lambda g, k, s: deep_partition(g, k, DeepParams.fast(**{**LITTLE, **more}), s)


def _strong(g, k, s):
    return deep_partition(g, k, DeepParams.strong_(**{**LITTLE, "c": 100}), s)


def _relaxed(preset):
    return lambda g, k, s: baselines.relaxed_lp_partition(g, k, preset=preset, seed=s, stop=25)


def _matching(g, k, s):
    return baselines.matching_partition(g, k, seed=s, stop=25)


SMALL: dict[str, list[tuple[str, Callable, str, int, float]]] = {
    "e1_quality": [(m, f, n, k, most) for n, k, most in (("grid", 4, 96), ("planted", 8, 900)) for m, f in (("deep_fast", _deep(c=100)), ("relaxed_fast", _relaxed("fast")), ("matching", _matching))],
    "e2_strong": [("deep_fast", _deep(c=100), "planted", 8, 900), ("deep_strong", _strong, "planted", 8, 900), ("relaxed_eco", _relaxed("eco"), "planted", 8, 900)],
    "e4_shared": [("deep_fast", _deep(c=100), "grid", 4, 96), ("shared_deep", METHODS["shared_deep"], "grid", 4, 96)],
    "e5_large_k": [("deep_fast", _deep(), "vectors", 64, 0.634), ("plain_multilevel", METHODS["plain_multilevel"], "vectors", 64, 0.634)],
    "e6_weak": [(f"deep_fast_{p}", _deep(pes=p), f"{n}_{8 + p.bit_length()}", 4, most * p) for p in (1, 2) for n, most in (("rgg2d", 250), ("rgg3d", 500), ("rhg", 400))],
    "e7_growing_k": [("deep_fast", _deep(), f"{n}_{ln}", (1 << ln) // 64, most << (ln - 8)) for ln in (8, 9) for n, most in (("rgg2d", 250), ("rgg3d", 500), ("rhg", 400))],
    "e8_strong_scaling": [(f"deep_fast_{p}", _deep(c=100, pes=p), "grid", 4, 96) for p in (2, 16)],
    "e9_flat": [("deep_fast", _deep(c=100), "grid", 4, 96), ("flat_lp", METHODS["flat_lp"], "grid", 4, 800), ("hash", METHODS["hash"], "grid", 4, 900)],
    "e10_ablation": [(v, _deep(**{"c": 100, **ABLATIONS[v], **({"batches": 2} if v != "base" else {})}), "grid", 4, 150) for v in ("base", "unlimited", "parts4", "windows")],
}


def small(spark: SparkSession, experiment: str, sf_dir: str | None = None, built: dict[str, Graph] | None = None) -> DataFrame:
    """The runs of an experiment on its small instances. built: takes the graphs."""
    rows, built = [], {} if built is None else built
    for algorithm, solve, name, k, _ in SMALL[experiment]:
        g = built.setdefault(name, None) or small_graph(spark, name, sf_dir)
        built[name] = g
        rows.append((algorithm, name, k, 1, *measured(lambda g=g, k=k, f=solve: f(g, k, 1), g, k, 0.03, 900)))
    return spark.createDataFrame(rows, report.RUNS)


def held(experiment: str, algorithm: str) -> bool:
    """Whether feasibility is promised: by the deep scheme, wherever it runs, and by what has the balancer."""
    return experiment == "e10_ablation" or algorithm.startswith(("deep", "plain", "shared"))


def verdicts(spark: SparkSession, experiment: str, sf_dir: str | None = None) -> DataFrame:
    """algorithm, graph, k, ended, feasible (null if not promised), close: whether the cut is within the instance's bound.

    Graphs of given tables: vertices and edges, too.
    """
    built: dict[str, Graph] = {}
    runs = small(spark, experiment, sf_dir, built)
    rows = [(a, n, k, int(most * built[n].m) if most < 1 else most, held(experiment, a), built[n].n, built[n].m) for a, _, n, k, most in SMALL[experiment]]
    bounds = spark.createDataFrame(rows, "algorithm string, graph string, k int, most long, promised boolean, vertices long, edges long")
    size = ["vertices", "edges"] if of_tables(experiment) else []
    return runs.join(bounds, ["algorithm", "graph", "k"]).select("algorithm", "graph", "k", *size, F.col("status").isin("ok", "infeasible").alias("ended"), F.when(F.col("promised"), F.col("feasible")).alias("feasible"), (F.col("cut") <= F.col("most")).alias("close"))


def of_tables(experiment: str) -> bool:
    return any(n == "vectors" for _, _, n, _, _ in SMALL[experiment])


def small_sql(experiment: str) -> str:
    rows = ", ".join(f"('{a}', '{n}', {k}::INT, true, {'true' if held(experiment, a) else 'NULL'}::BOOLEAN, true)" for a, _, n, k, _ in SMALL[experiment])
    values = f"(VALUES {rows}) v(algorithm, graph, k, ended, feasible, close)"
    if not of_tables(experiment):
        return f"SELECT * FROM {values}"
    return f"WITH i AS (SELECT row_number() OVER (ORDER BY embedding[1], vec_id) - 1 AS i, count(*) OVER () AS n FROM embeddings), s AS (SELECT count(*) AS vertices, count(*) FILTER (i % 24 < 23 AND i + 1 < n) + count(*) FILTER (i + 24 < n) AS edges FROM i) SELECT v.*, vertices, edges FROM {values}, s"
