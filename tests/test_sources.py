from functools import partial

import pytest
from pyspark.sql import functions as F

from graphsplit.model import Graph, RawGraph, densify
from graphsplit.operators.measures import block_weights, edge_cut, feasibility, imbalance
from graphsplit.operators.order import degree_buckets
from graphsplit.sources import generators as gen
from graphsplit.sources import graphs, io


@pytest.mark.parametrize("make,low,high", [(lambda s: gen.rgg2d(s, 9, 8), 5, 9), (lambda s: gen.rgg3d(s, 9, 8), 4, 9), (lambda s: gen.rhg(s, 9, 8), 3, 16)])
def test_random_families_have_about_the_degree_asked(spark, make, low, high):
    g = make(spark)
    assert g.validate().count() == 0
    assert low < g.arcs / g.n < high


def test_hyperbolic_edges_are_all_near_pairs(spark):
    import math

    g = gen.rhg(spark, 7, 6)
    n, alpha = 128, 1.0
    radius = 2 * math.log(2 * n * 4 / (math.pi * 6))
    p = spark.range(n).select("id", (F.acosh(F.lit(1.0) + (math.cosh(alpha * radius) - 1) * gen.uniform(1, "r", F.col("id"))) / alpha).alias("r"), (gen.uniform(1, "phi", F.col("id")) * 2 * math.pi).alias("phi")).collect()
    near = {(a.id, b.id) for a in p for b in p if a.id < b.id and math.cosh(a.r) * math.cosh(b.r) - math.sinh(a.r) * math.sinh(b.r) * math.cos(a.phi - b.phi) < math.cosh(radius)}
    assert {(r.src, r.dst) for r in g.edges.filter("src < dst").collect()} == near


def test_lattice_and_planted(spark):
    g = gen.grid2d(spark, 4, 6)
    assert (g.n, g.m) == (24, 4 * 5 + 3 * 6)
    half = g.vertices.select("vid", (F.col("vid") % 6 >= 3).cast("int").alias("block"))
    assert edge_cut(g, half).first()["cut"] == 4
    assert gen.two_cliques(spark).m == 13 and gen.path(spark, 5).m == 4 and gen.star(spark, 8).m == 8
    assert gen.planted(spark, 3, 20, 4, 1).validate().count() == 0


def test_files(spark, tmp_path):
    (tmp_path / "e.csv").write_text("1,2,3\n2,1,1\nx,y,z\n3,3,1\n2,3,\n")
    raw = io.read_edges(spark, str(tmp_path / "e.csv"), "csv")
    assert {tuple(r) for r in raw.edges.collect()} == {(1, 2, 4), (2, 3, 1)}
    assert io.malformed(spark, str(tmp_path / "e.csv")).count() == 1
    (tmp_path / "a.txt").write_text("0 5: 1 2, 2 7\n1 1: 0 2\n2 1:\nbroken\n")
    raw = io.read_adjacency_text(spark, str(tmp_path / "a.txt"))
    assert {tuple(r) for r in raw.edges.collect()} == {(0, 1, 2), (0, 2, 7)} and raw.vertices.count() == 3
    g, _ = densify(raw)
    p = g.vertices.select("vid", (F.col("vid") % 2).cast("int").alias("block"))
    io.save_model(spark, str(tmp_path / "m"), p, {"k": 2})
    back, params = io.load_model(spark, str(tmp_path / "m"))
    assert back.count() == 3 and params == {"k": 2}


def test_measures_of_vertices_make_no_arcs(spark):
    v = spark.createDataFrame([(k, 1) for k in range(6)], "key long, c long")
    g, _ = densify(RawGraph(v, spark.createDataFrame([(0, 1, 2), (1, 3, 1)], "u long, v long, w long"), closed=True))
    p = g.vertices.select("vid", (F.col("vid") % 2).cast("int").alias("block"))
    assert [tuple(r) for r in block_weights(g, p, 2).orderBy("block").collect()] == [(0, 3, 3), (1, 3, 3)]
    assert imbalance(g, p, 2).first()[0] == 0 and feasibility(g, p, 2, 0.03).first()["feasible"]
    assert {r["vid"]: r["deg"] for r in degree_buckets(g).collect()} == {0: 1, 1: 2, 2: 0, 3: 1, 4: 0, 5: 0}
    assert "edges" not in g.__dict__
    assert g.m == 2 and g.validate().count() == 0 and {r["vid"]: r["deg"] for r in g.degrees().collect()} == {0: 1, 1: 2, 3: 1}


def test_pairs_that_share_values_are_made_in_blocks_and_not_shuffled(spark, monkeypatch):
    monkeypatch.setattr(graphs, "HOLDERS", 4)
    held = {k: {f"v{x}" for x in range(5) if (k * (x + 1)) % 7 < 3} | {"all"} | ({"twins"} if k > 27 else set()) for k in range(30)}
    rows = spark.createDataFrame([(k, x) for k, xs in held.items() for x in xs] + [(None, "v0"), (3, None)], "k long, x string")
    found = graphs.sharing(rows, "k", "x")
    assert {(r["u"], r["v"]): r["w"] for r in found.collect()} == {(a, b): len(held[a] & held[b]) for a in held for b in held if a < b}
    plan = found._jdf.queryExecution().optimizedPlan().toString()
    assert plan.index("FlatMapGroupsInArrow") < plan.index("Aggregate") and "MapGroups" in plan.splitlines()[0]


def test_generators_and_spans_take_given_tables(spark, tmp_path):
    from graphsplit import queries
    from tests.compare import database, same

    vectors = [(10 * k, [0.0, 0.0, (37 * k % 101) / 2048.0, (53 * k % 97) / 2048.0, (11 * k % 89) / 2048.0]) for k in range(40)]
    spark.createDataFrame(vectors, "vec_id long, embedding array<float>").write.parquet(str(tmp_path / "embeddings.parquet"))
    spark.createDataFrame([(7 * k + 3,) for k in range(602)], "o_orderkey long").write.parquet(str(tmp_path / "orders.parquet"))
    spark.createDataFrame([(u,) for u, n in ((1, 17), (2, 16), (9, 90)) for _ in range(n)], "user_id long").write.parquet(str(tmp_path / "events.parquet"))
    con = database(str(tmp_path))
    for name in ("gen_rgg2d", "gen_rgg3d", "gen_rhg", "gen_grid2d", "block_spans"):
        same(queries.QUERIES[name](spark, str(tmp_path)), queries.SQL[name], con)
    assert queries.QUERIES["gen_grid2d"](spark, str(tmp_path)).count() == 2 * (299 + 299 + 1 + 300 + 2)
    assert {r["k"] for r in queries.QUERIES["block_spans"](spark, str(tmp_path)).collect()} == {1, 2, 6}


def test_what_goes_from_block_to_block_is_packed_and_arcs_are_stored_once(spark, monkeypatch):
    monkeypatch.setattr(graphs, "HOLDERS", 5)
    held = {3 * k + 1: {f"v{x}" for x in range(4) if (k * (x + 2)) % 5 < 2} | {"all"} for k in range(24)}
    rows = spark.createDataFrame([(k, x) for k, xs in held.items() for x in xs], "k long, x string")
    v = spark.createDataFrame([(k, 1) for k in [*held, 200]], "key long, c long")
    g, names = densify(RawGraph(v, graphs.sharing(rows, "k", "x"), True, partial(graphs.sharing, rows.union(rows), "k", "x")))
    plan = g.edges._jdf.queryExecution().optimizedPlan().toString()
    assert "Join" not in plan and "Generate" in plan
    key = {r["vid"]: r["key"] for r in names.collect()}
    assert {(key[r["src"]], key[r["dst"]]): r["w"] for r in g.edges.collect()} == {(a, b): len(held[a] & held[b]) for a in held for b in held if a != b}
    assert "body" in graphs.sharing(rows, "k", "x")._jdf.queryExecution().optimizedPlan().toString()


def test_problems_of_a_graph_take_one_grouping_of_its_arcs(spark):
    v = spark.createDataFrame([(k, 1) for k in range(5)], "vid long, c long")
    ok = [(0, 1, 2), (1, 0, 2), (1, 2, 1), (2, 1, 1)]
    found = lambda e: sorted((tuple(r) for r in Graph.of(v, spark.createDataFrame(e, "src long, dst long, w long")).validate().collect()), key=str)
    assert found(ok) == []
    assert found([*ok, (3, 4, 1), (4, 3, 2)]) == [("no reverse", 3, 4), ("no reverse", 4, 3)]
    assert found([*ok, (3, 4, 1), (3, 4, 1), (4, 3, 2), (4, 3, 2)]) == [("no reverse", 3, 4)] * 2 + [("no reverse", 4, 3)] * 2 + [("repeated arc", 3, 4), ("repeated arc", 4, 3)]
    assert found([*ok, (3, 3, 1), (4, 4, 1), (4, 4, 1), (2, 3, 0), (3, 2, 0)]) == [("edge weight", 2, 3), ("edge weight", 3, 2), ("loop", 3, 3), ("loop", 4, 4), ("loop", 4, 4), ("repeated arc", 4, 4)]
    assert found([*ok, (3, None, 1), (3, 4, None), (4, 3, None)]) == sorted([("no reverse", 3, None), ("no reverse", 3, 4), ("no reverse", 4, 3), ("missing end", None, None), ("edge weight", 3, 4), ("edge weight", 4, 3)], key=str)
    plan = Graph.of(v, spark.createDataFrame(ok, "src long, dst long, w long")).validate()._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("Join LeftAnti") == 1  # of the ends and the vertices; before, arcs were also joined with their reverse


def test_arcs_of_copies_and_coarse_graphs_are_stored_compressed(spark):
    import os

    from graphsplit.model import checkpoint_folder
    from graphsplit.operators.contract import contract
    from graphsplit.operators.initial import replicate

    folder = checkpoint_folder(spark).removeprefix("file:")
    tables = lambda: {x for x in os.listdir(folder) if x.startswith("table-")}
    g, before = gen.grid2d(spark, 6, 6), tables()
    many = replicate(g, 2)
    between = tables()
    coarse, _ = contract(g, g.vertices.select("vid", (F.col("vid") - F.col("vid") % 2).alias("cluster")))
    assert between > before and tables() > between and (many.m, coarse.m) == (2 * g.m, 2 * 6 + 3 * 5)


def test_edges_that_give_the_vertices_are_made_once(spark, monkeypatch):
    from graphsplit.sources import graphs

    kept, store = [], graphs.stored
    monkeypatch.setattr(graphs, "_loaded", {})
    monkeypatch.setattr(graphs, "stored", lambda df: kept.append(store(df)) or kept[-1])
    g = graphs.load_graph(spark, "/root/testdata/sf0.001", "word")
    raw = graphs.BUILDERS["word"](spark, "/root/testdata/sf0.001")
    assert len(kept) == 1 and g.arcs == 2 * kept[0].count() == 2 * raw.edges.count()
    assert g.n == raw.vertices.count()
