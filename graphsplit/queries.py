"""Queries of the engine, one for each method, with their SQL.

Where a method is a fixed sequence of relational steps, the SQL is equivalent. For whole partitioners, which no SQL expresses, the query
recomputes facts about the returned partition, and the SQL gives the same row from the raw tables and what must hold.
"""

from __future__ import annotations

from pyspark.sql import functions as F

from graphsplit.functions import columns, views
from graphsplit.functions.columns import relative_gain
from graphsplit.model import dense_ids, snapshot, symmetrize
from graphsplit.operators import asof
from graphsplit.operators import balance as bal
from graphsplit.operators import cluster as cl
from graphsplit.operators import contract as con
from graphsplit.operators import initial as ini
from graphsplit.operators import layout as lay
from graphsplit.operators import measures as ms
from graphsplit.operators import order as ordr
from graphsplit.plans import baselines, experiments, report
from graphsplit.plans.deep import DeepParams, DeepResult, deep_partition, limits_for
from graphsplit.sources import generators, graphs
from graphsplit.sources.graphs import load_graph, sql_graph
from graphsplit.streaming import edges as stream

QUERIES: dict = {}
SQL: dict = {}


def query(name, sql=None):
    def add(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def on(name, graph, sql=None):
    """A query over one graph, with SQL that starts after its common table expressions."""
    return lambda f: query(name, sql and f"{sql_graph(graph)}{'' if sql.lstrip().startswith(',') else ' '}{sql}")(lambda spark, sf_dir: f(load_graph(spark, sf_dir, graph)))


def toss(seed, tag, *keys):
    return f"('0x' || substr(md5('{seed}:{tag}:' || {' || chr(58) || '.join(keys)}), 1, 8))::BIGINT"


for _name in graphs.BUILDERS:
    query(f"g_{_name}_edges", f"WITH raw_e AS ({graphs.SQL[_name][0]}) SELECT u, v, w::BIGINT AS w FROM raw_e")(lambda spark, sf_dir, name=_name: graphs.BUILDERS[name](spark, sf_dir).edges)


# Graphs and layout
PE = "least(3, (vid * 4) // (SELECT count(*) FROM ids))::INT"
LAY = f", lay AS (SELECT vid, c, {PE} AS pe FROM ids)"
GHOST = LAY + ", ghosts AS (SELECT DISTINCT s.pe, arcs.dst AS vid FROM arcs JOIN lay s ON s.vid = src JOIN lay d ON d.vid = dst WHERE s.pe <> d.pe)"


@on("graph_summary", "order_star", ", d AS (SELECT src, count(*) AS deg FROM arcs GROUP BY src) SELECT (SELECT count(*) FROM ids) AS n, (SELECT count(*) FROM e) AS m, (SELECT sum(c)::BIGINT FROM ids) AS total_c, (SELECT sum(w)::BIGINT FROM e) AS total_w, (SELECT max(deg) FROM d) AS max_degree")
def _(g):
    deg = g.edges.groupBy("src").agg(F.count("*").alias("deg"), F.sum("w").alias("w"))
    return deg.agg(F.max("deg").alias("max_degree"), (F.sum("w") / 2).cast("long").alias("total_w")).select(F.lit(g.n).cast("long").alias("n"), F.lit(g.m).cast("long").alias("m"), F.lit(g.total).cast("long").alias("total_c"), "total_w", "max_degree")


@on("degree_histogram", "order_star", ", d AS (SELECT vid, count(src) AS deg FROM ids LEFT JOIN arcs ON src = vid GROUP BY vid) SELECT deg, count(*) AS vertices FROM d GROUP BY deg")
def _(g):
    return ordr.degree_buckets(g).groupBy("deg").agg(F.count("*").alias("vertices"))


@on("degree_buckets", "doc_dup", ", d AS (SELECT vid, count(src) AS deg FROM ids LEFT JOIN arcs ON src = vid GROUP BY vid) SELECT vid, deg, CASE WHEN deg > 0 THEN length(bin(deg)) - 1 ELSE -1 END AS bucket FROM d")
def _(g):
    return ordr.degree_buckets(g)


@on("isolated_vertices", "emb_rgg2", "SELECT vid FROM ids WHERE vid NOT IN (SELECT src FROM arcs)")
def _(g):
    return g.vertices.join(g.edges, F.col("vid") == F.col("src"), "left_anti").select("vid")


@on("neighbors_list", "trade", "SELECT src AS vid, string_agg(dst || ':' || w, ',' ORDER BY dst) AS neighbours FROM arcs GROUP BY src")
def _(g):
    return g.edges.groupBy(F.col("src").alias("vid")).agg(F.array_sort(F.collect_list(F.struct("dst", "w"))).alias("a")).select("vid", F.array_join(F.transform("a", lambda x: F.concat_ws(":", x["dst"], x["w"])), ",").alias("neighbours"))


@on("connected_pairs", "geo_tree", "SELECT u, v, w FROM e")
def _(g):
    return g.edges.filter("src < dst").select(F.col("src").alias("u"), F.col("dst").alias("v"), "w")


@on("graph_problems", "page_sim", "SELECT 'none' AS problem, vid AS a, vid AS b FROM ids WHERE false")
def _(g):
    return g.validate()


@on("pe_layout", "event_chain", LAY + " SELECT vid, c, pe FROM lay")
def _(g):
    return lay.assign_pe(g, 4)


@on("pe_layout_by_edges", "order_star", ", d AS (SELECT vid, any_value(c) AS c, count(src) AS deg FROM ids LEFT JOIN arcs ON src = vid GROUP BY vid) SELECT vid, c, least(3, ((coalesce(sum(deg) OVER (ORDER BY vid ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) * 4) // (SELECT count(*) FROM arcs)))::INT AS pe FROM d")
def _(g):
    return lay.assign_pe(g, 4, "edges")


@on("interface_vertices", "event_chain", LAY + " SELECT DISTINCT src AS vid FROM arcs JOIN lay s ON s.vid = src JOIN lay d ON d.vid = dst WHERE s.pe <> d.pe")
def _(g):
    return lay.interface_vertices(g, lay.assign_pe(g, 4))


@on("ghost_table", "event_chain", GHOST + " SELECT pe, vid FROM ghosts")
def _(g):
    return lay.ghost_table(g, lay.assign_pe(g, 4))


@on("ghost_counts", "order_star", GHOST + " SELECT pe, count(*) AS ghosts FROM ghosts GROUP BY pe")
def _(g):
    return lay.ghost_table(g, lay.assign_pe(g, 4)).groupBy("pe").agg(F.count("*").alias("ghosts"))


@on("ghost_updates", "event_chain", GHOST + " SELECT pe, vid, vid % 7 AS label FROM ghosts WHERE vid % 3 = 0")
def _(g):
    moved = g.vertices.filter("vid % 3 = 0").select("vid", (F.col("vid") % 7).alias("label"))
    return lay.ghost_updates(moved, lay.ghost_table(g, lay.assign_pe(g, 4)))


GHOST16 = ", lay AS (SELECT vid, ((vid * 16) // (SELECT count(*) FROM ids))::INT AS pe FROM ids), msg AS (SELECT DISTINCT d.pe AS a, s.pe AS b, arcs.dst AS vid FROM arcs JOIN lay s ON s.vid = src JOIN lay d ON d.vid = dst WHERE s.pe <> d.pe)"


def messages(g, pes):
    layout = lay.assign_pe(g, pes)
    return lay.ghost_table(g, layout).join(layout.select("vid", F.col("pe").alias("src_pe")), "vid").select("src_pe", F.col("pe").alias("dst_pe"))


@on("exchange_cost_direct", "order_star", GHOST16 + " SELECT 1 AS hop, count(DISTINCT a * 16 + b) AS messages, count(*) AS rows FROM msg")
def _(g):
    return lay.exchange_cost(messages(g, 16), 16)


@on("exchange_cost_grid", "order_star", GHOST16 + ", via AS (SELECT a, (b // 4) * 4 + a % 4 AS x, b FROM msg), h AS (SELECT 1 AS hop, a, x AS b FROM via UNION ALL SELECT 2, x, b FROM via) SELECT hop, count(DISTINCT a * 16 + b) AS messages, count(*) AS rows FROM h WHERE a <> b GROUP BY hop")
def _(g):
    return lay.exchange_cost(messages(g, 16), 16, "grid")


@on("exchange_grid_delivers", "event_chain", GHOST16 + " SELECT b AS dst_pe, count(*) AS rows FROM msg GROUP BY b")
def _(g):
    return lay.exchange_grid(messages(g, 16), 16).groupBy("dst_pe").agg(F.count("*").alias("rows"))


ORDER = LAY + f""", d AS (SELECT lay.vid, pe, c, CASE WHEN count(src) > 0 THEN length(bin(count(src))) - 1 ELSE -1 END AS bucket FROM lay LEFT JOIN arcs ON src = lay.vid GROUP BY ALL),
ch AS (SELECT *, (row_number() OVER (PARTITION BY pe, bucket ORDER BY vid) - 1) // 64 AS chunk FROM d),
ord AS (SELECT vid, pe, c, row_number() OVER (PARTITION BY pe ORDER BY bucket, {toss(1, "chunk", "pe", "bucket", "chunk")}, chunk, {toss(1, "vertex", "vid")}, vid) - 1 AS pos FROM ch),
bat AS (SELECT *, ntile(2) OVER (PARTITION BY pe ORDER BY pos) - 1 AS batch FROM ord)"""


@on("traversal_order", "event_chain", ORDER + " SELECT vid, pe, pos FROM ord")
def _(g):
    return ordr.traversal(g, lay.assign_pe(g, 4), 64, 1)


@on("batch_assignment", "event_chain", ORDER + " SELECT vid, pe, pos, batch FROM bat")
def _(g):
    return ordr.batches(ordr.traversal(g, lay.assign_pe(g, 4), 64, 1), 2)


@on("traversal_by_degree", "order_star", LAY + ", d AS (SELECT lay.vid, pe, count(src) AS deg FROM lay LEFT JOIN arcs ON src = lay.vid GROUP BY ALL) SELECT vid, pe, row_number() OVER (PARTITION BY pe ORDER BY deg, vid) - 1 AS pos FROM d")
def _(g):
    return ordr.traversal(g, lay.assign_pe(g, 4), 64, 1, "degree")


# Coarsening
@on("lp_rate", "copurchase", "SELECT src AS vid, dst % 50 AS label, sum(w)::BIGINT AS conn FROM arcs GROUP BY ALL")
def _(g):
    return cl.rate(g.edges, g.vertices.select("vid", (F.col("vid") % 50).alias("label")))


FIRST = ORDER + f""", r AS (SELECT src AS vid, dst AS label, sum(w)::BIGINT AS conn FROM arcs JOIN bat ON bat.vid = src AND batch = 0 GROUP BY ALL),
cand AS (SELECT r.vid, b.pe, b.c, label, conn, row_number() OVER (PARTITION BY r.vid ORDER BY conn DESC, {toss(1, "tie", "r.vid", "label")} DESC, label DESC) AS k FROM r JOIN bat b ON b.vid = r.vid JOIN ids t ON t.vid = label WHERE t.c + b.c <= {{limit}}),
mv AS (SELECT vid, pe, c, vid AS old, label AS new, conn AS gain FROM cand WHERE k = 1),
st AS (SELECT lay.vid, lay.c, lay.pe, coalesce(mv.new, lay.vid) AS label FROM lay LEFT JOIN mv USING (vid)),
wt AS (SELECT label, sum(c)::BIGINT AS weight FROM st GROUP BY label)"""
ONE = FIRST.replace("{limit}", "3")
JUDGED = ONE + """, heavy AS (SELECT * FROM wt WHERE weight > 3), sh AS (SELECT pe, label, weight, sum(c) AS share FROM st JOIN heavy USING (label) GROUP BY ALL),
q AS (SELECT pe, label AS new, ceil((weight - 3.0::DOUBLE) * share::DOUBLE / weight) AS quota FROM sh),
jd AS (SELECT mv.*, quota IS NOT NULL AND coalesce(sum(c) OVER (PARTITION BY mv.new, mv.pe ORDER BY gain, vid ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) < quota AS reverted FROM mv LEFT JOIN q ON q.pe = mv.pe AND q.new = mv.new)"""


def first_batch(g, limit=3):
    """Start state, weights and moves of the first batch."""
    state = lay.assign_pe(g, 4).withColumn("label", F.col("vid"))
    weights = state.select("label", F.col("c").alias("weight"), F.lit(float(limit)).alias("limit"))
    turn = ordr.batches(ordr.traversal(g, state, 64, 1), 2).filter("batch = 0")
    return state, weights, snapshot(cl.best_move(cl.rate(g.edges, state, turn), state, weights, "coin", 1))


@on("lp_one_batch", "event_chain", ONE + " SELECT vid, pe, c, old, new, gain FROM mv")
def _(g):
    return first_batch(g)[2]


@on("cluster_weights_delta", "event_chain", ONE + " SELECT label, weight FROM wt")
def _(g):
    _, weights, moves = first_batch(g)
    return cl.apply_weight_deltas(weights, moves)


@on("revert_overweight", "event_chain", JUDGED + " SELECT vid, pe, c, old, new, gain, reverted FROM jd")
def _(g):
    state, weights, moves = first_batch(g)
    return cl.revert_overweight(moves, cl.moved(state, moves), cl.apply_weight_deltas(weights, moves), 3)


@on("lp_superstep", "event_chain", JUDGED + " SELECT lay.vid, coalesce(jd.new, lay.vid) AS label FROM lay LEFT JOIN jd ON jd.vid = lay.vid AND NOT reverted")
def _(g):
    state, weights, _ = first_batch(g)
    turn = ordr.batches(ordr.traversal(g, state, 64, 1), 2).filter("batch = 0")
    return cl.superstep(g.edges, state, weights, turn, 3, "revert", "coin", 1)[0].select("vid", "label")


SWEEP = ONE + f""", r2 AS (SELECT src AS vid, s.label, sum(w)::BIGINT AS conn FROM arcs JOIN bat ON bat.vid = src AND batch = 1 JOIN st s ON s.vid = dst GROUP BY ALL),
c2 AS (SELECT r2.vid, r2.label, r2.conn, row_number() OVER (PARTITION BY r2.vid ORDER BY r2.conn DESC, {toss(1, "tie", "r2.vid", "r2.label")} DESC, r2.label DESC) AS k, r2.conn - coalesce(o.conn, 0) AS gain
  FROM r2 JOIN st ON st.vid = r2.vid JOIN wt ON wt.label = r2.label LEFT JOIN r2 o ON o.vid = r2.vid AND o.label = st.label WHERE r2.label <> st.label AND wt.weight + st.c <= 3),
m2 AS (SELECT vid, label AS new FROM c2 WHERE k = 1 AND gain > 0)"""


@on("lp_one_sweep", "event_chain", SWEEP + " SELECT st.vid, coalesce(m2.new, st.label) AS label FROM st LEFT JOIN m2 ON m2.vid = st.vid")
def _(g):
    state, weights, _ = first_batch(g)
    return cl.sweeps(g, state, weights, 3, 1, 4, 1, "overshoot", "coin", 2)[0].select("vid", "label")


@on("strict_admission", "event_chain", ONE + ", a AS (SELECT mv.*, sum(mv.c) OVER (PARTITION BY new ORDER BY gain DESC, mv.vid ROWS UNBOUNDED PRECEDING) > 3 - t.c AS reverted FROM mv JOIN ids t ON t.vid = new) SELECT vid, pe, c, old, new, gain, reverted FROM a")
def _(g):
    _, weights, moves = first_batch(g)
    return cl.admit_strict(moves, weights)


@on("local_limit_overshoot", "event_chain", ONE + ", own AS (SELECT vid AS new, pe, c AS o FROM lay), a AS (SELECT mv.*, sum(mv.c) OVER (PARTITION BY mv.new, mv.pe ORDER BY gain DESC, vid ROWS UNBOUNDED PRECEDING) + coalesce(o, 0) > 3 AS reverted FROM mv LEFT JOIN own ON own.new = mv.new AND own.pe = mv.pe) SELECT vid, pe, c, old, new, gain, reverted FROM a")
def _(g):
    state, _, moves = first_batch(g)
    return cl.admit_local(moves, state, 3)


@on("pack_isolated", "emb_rgg2", ", a AS (SELECT vid, vid // 65536 AS chunk, sum(c) OVER (PARTITION BY vid // 65536 ORDER BY vid ROWS UNBOUNDED PRECEDING) - c AS run FROM ids WHERE vid NOT IN (SELECT src FROM arcs)) SELECT vid, min(vid) OVER (PARTITION BY chunk, run // 8) AS cluster FROM a")
def _(g):
    return cl.pack_isolated(g, 8)


@on("matching_one_round", "copurchase", f", b AS (SELECT src, arg_max(dst, (w, {toss(1, 'match', 'least(src, dst)', 'greatest(src, dst)')}, dst)) AS dst FROM arcs GROUP BY src) SELECT b.src AS a, b.dst AS b FROM b JOIN b AS x ON x.src = b.dst AND x.dst = b.src WHERE b.src < b.dst")
def _(g):
    return cl.matching_round(g.edges, g.vertices, 2, 1)


def tens(g):
    return g.vertices.select("vid", (F.floor(F.col("vid") / 10) * 10).alias("cluster"))


TEN = ", cl AS (SELECT vid, c, (vid // 10) * 10 AS cluster FROM ids)"


@on("contract_vertices", "copurchase_sized", TEN + " SELECT cluster, sum(c)::BIGINT AS c FROM cl GROUP BY cluster")
def _(g):
    return con.coarse_vertices(g, tens(g))


@on("contract_edges", "copurchase", TEN + " SELECT s.cluster AS a, d.cluster AS b, sum(w)::BIGINT AS w FROM arcs JOIN cl s ON s.vid = src JOIN cl d ON d.vid = dst WHERE s.cluster <> d.cluster GROUP BY ALL")
def _(g):
    return con.coarse_arcs(g, tens(g))


@on("contract_mapping", "copurchase", "SELECT vid, dense_rank() OVER (ORDER BY (vid // 10) * 10) - 1 AS coarse_vid FROM ids")
def _(g):
    return con.contract(g, tens(g))[1]


@on("contract_invariants", "copurchase", TEN + ", x AS (SELECT sum(w)::BIGINT AS fine_arcs, sum(CASE WHEN s.cluster = d.cluster THEN w ELSE 0 END)::BIGINT AS inside FROM arcs JOIN cl s ON s.vid = src JOIN cl d ON d.vid = dst) SELECT fine_arcs, inside, fine_arcs - inside AS coarse_arcs, (SELECT sum(c)::BIGINT FROM ids) AS fine_weight, (SELECT sum(c)::BIGINT FROM ids) AS coarse_weight, (SELECT count(DISTINCT cluster) FROM cl) AS n FROM x")
def _(g):
    coarse, mapping = con.contract(g, tens(g))
    return con.check_contraction(g, coarse, mapping)


PLACE = """, cl AS (SELECT vid, CASE WHEN vid < (SELECT count(*) // 4 FROM ids) THEN vid ELSE (vid // 10) * 10 END AS cluster FROM ids),
dg AS (SELECT s.cluster, count(DISTINCT d.cluster) AS deg FROM arcs JOIN cl s ON s.vid = src JOIN cl d ON d.vid = dst WHERE s.cluster <> d.cluster GROUP BY ALL),
ow AS (SELECT cluster, ((cluster * 4) // (SELECT count(*) FROM ids))::INT AS owner, coalesce(deg, 0) AS deg FROM (SELECT DISTINCT cluster FROM cl) LEFT JOIN dg USING (cluster)),
rk AS (SELECT *, row_number() OVER (PARTITION BY owner ORDER BY deg DESC, cluster) AS r, greatest(floor(1.1::DOUBLE * count(*) OVER () / 4), ceil(count(*) OVER () / 4)) AS cap FROM ow),
free AS (SELECT pe::INT AS pe, unnest(range((SELECT count(*) FROM rk WHERE owner = pe AND r <= cap), (SELECT max(cap) FROM rk)::BIGINT)) AS level FROM range(4) t(pe)),
slot AS (SELECT pe, row_number() OVER (ORDER BY level, pe) AS nth FROM free),
sp AS (SELECT cluster, owner, row_number() OVER (ORDER BY owner, cluster) AS nth FROM rk WHERE r > cap)"""


@on("place_clusters", "custpart", PLACE + " SELECT cluster, owner, owner AS pe FROM rk WHERE r <= cap UNION ALL SELECT cluster, owner, pe FROM sp JOIN slot USING (nth)")
def _(g):
    lone = F.col("vid") < g.n // 4
    return con.place_clusters(g, g.vertices.select("vid", F.when(lone, F.col("vid")).otherwise(F.floor(F.col("vid") / 10) * 10).alias("cluster")), 4)


@on("renumber_clusters", "copurchase", "SELECT (vid // 10) * 10 AS cluster, row_number() OVER (ORDER BY ((vid // 10) * 10 * 4) // (SELECT count(*) FROM ids), (vid // 10) * 10) - 1 AS coarse_vid FROM ids WHERE vid % 10 = 0")
def _(g):
    heads = tens(g).select("cluster").distinct()
    return con.renumber(heads.withColumn("pe", lay.pe_of(F.col("cluster"), g.n, 4)))


@on("project_partition", "copurchase", "SELECT vid, ((vid // 10) % 3)::INT AS block FROM ids")
def _(g):
    mapping = g.vertices.select("vid", F.floor(F.col("vid") / 10).alias("coarse_vid"))
    return con.project(mapping.select(F.col("coarse_vid").alias("vid"), (F.col("coarse_vid") % 3).cast("int").alias("block")).distinct(), mapping)


# Parameters
GRID = "FROM (VALUES (200, 1), (2000, 1), (89158, 50)) v(n, h), (VALUES (2), (3), (16), (128)) k(k)"


@query("max_block_weight", f"SELECT n, k, round(greatest(1.03::DOUBLE * n / k, n::DOUBLE / k + h), 6) AS l_max {GRID}")
def _(spark, sf_dir):
    columns.register(spark)
    return spark.sql(f"SELECT n, k, round(l_max(n, k, 0.03D, h), 6) AS l_max {GRID}")


@query("max_cluster_weight", f"SELECT n, k, round(0.03::DOUBLE * n / greatest(1.0::DOUBLE, least(k::DOUBLE, n::DOUBLE / 160)), 6) AS w_max {GRID}")
def _(spark, sf_dir):
    columns.register(spark)
    return spark.sql(f"SELECT n, k, round(w_max(n, n, k, 160, 0.03D), 6) AS w_max {GRID}")


@query("target_blocks", f"SELECT n, k, least(k, CASE WHEN n <= 160 THEN 1 ELSE pow(2, ceil(log2(n / 160.0)))::INT END)::BIGINT AS blocks {GRID}")
def _(spark, sf_dir):
    columns.register(spark)
    return spark.sql(f"SELECT n, k, least(k, pow2ceil(CAST(ceil(n / 160D) AS BIGINT))) AS blocks {GRID}")


@query("num_batches", "SELECT p::BIGINT AS p, greatest(8, ceil(128 / p))::BIGINT AS batches FROM (VALUES (1), (4), (16), (64), (8192)) v(p)")
def _(spark, sf_dir):
    return spark.createDataFrame([(p, columns.num_batches(p)) for p in (1, 4, 16, 64, 8192)], "p long, batches long")


@query("num_copies", "SELECT n::BIGINT AS n, CASE WHEN n < 32000 THEN 16 // least(16, CASE WHEN n <= 2000 THEN 1 ELSE pow(2, ceil(log2(n / 2000.0)))::INT END) ELSE 1 END::BIGINT AS copies FROM (VALUES (8000), (5000), (1000), (32000)) v(n)")
def _(spark, sf_dir):
    return spark.createDataFrame([(n, columns.num_copies(n, 2000, 16)) for n in (8000, 5000, 1000, 32000)], "n long, copies long")


# Measures, on blocks of ids modulo
def modulo(g, k=4):
    return g.vertices.select("vid", (F.col("vid") % k).cast("int").alias("block"))


BL = ", p AS (SELECT vid, c, (vid % 4)::INT AS block FROM ids), bt AS (SELECT arcs.*, s.block AS a, d.block AS b FROM arcs JOIN p s ON s.vid = src JOIN p d ON d.vid = dst)"
L4 = "greatest(1.03::DOUBLE * sum(weight) OVER () / 4, sum(weight) OVER ()::DOUBLE / 4 + (SELECT max(c) FROM ids))"


@on("edge_cut", "event_chain", BL + " SELECT (sum(w) // 2)::BIGINT AS cut FROM bt WHERE a <> b")
def _(g):
    return ms.edge_cut(g, modulo(g))


@on("block_cut_matrix", "custpart", BL + " SELECT a, b, sum(w)::BIGINT AS w FROM bt WHERE a < b GROUP BY ALL")
def _(g):
    return ms.block_matrix(g, modulo(g))


@on("block_weights", "doc_dup", BL + " SELECT b::INT AS block, coalesce(sum(c), 0)::BIGINT AS weight, count(vid) AS vertices FROM range(6) t(b) LEFT JOIN p ON block = b GROUP BY b")
def _(g):
    return ms.block_weights(g, modulo(g), 6)


@on("imbalance", "doc_dup", BL + " SELECT round(max(weight) * 4::DOUBLE / sum(weight) - 1, 9) AS imbalance FROM (SELECT sum(c)::BIGINT AS weight FROM p GROUP BY block)")
def _(g):
    return ms.imbalance(g, modulo(g), 4)


@on("feasibility", "doc_dup", BL + f", wl AS (SELECT weight, {L4} AS l, 1.03::DOUBLE * ceil(sum(weight) OVER () / 4) AS lc FROM (SELECT sum(c)::BIGINT AS weight FROM p GROUP BY block)) SELECT max(weight) <= any_value(l) AS feasible, max(weight) <= any_value(lc) AS classic, count(*) FILTER (weight > l) AS overloaded, round(sum(greatest(0, weight - l)), 6) AS excess FROM wl")
def _(g):
    return ms.feasibility(g, modulo(g), 4, 0.03)


@on("boundary_vertices", "event_chain", BL + " SELECT a AS block, count(DISTINCT src) AS boundary FROM bt WHERE a <> b GROUP BY a")
def _(g):
    return ms.boundary_vertices(g, modulo(g))


@on("comm_volume", "order_star", BL + " SELECT a AS block, count(*) AS volume FROM (SELECT DISTINCT src, a, b FROM bt WHERE a <> b) GROUP BY a")
def _(g):
    return ms.comm_volume(g, modulo(g))


@on("validate_partition", "turns", "SELECT count(*) AS rows, count(*) AS distinct_vertices, 0::BIGINT AS out_of_range, 0::BIGINT AS strangers, count(*) AS n FROM ids")
def _(g):
    return ms.validate_partition(g, modulo(g), 4)


@on("clustering_stats", "copurchase_sized", TEN + ", w AS (SELECT sum(c)::BIGINT AS c FROM cl GROUP BY cluster) SELECT count(*) AS clusters, max(c) AS heaviest, count(*) FILTER (c > 300) AS over, round((SELECT count(*) FROM ids)::DOUBLE / count(*), 6) AS shrink FROM w")
def _(g):
    return ms.clustering_stats(g, tens(g), 300)


@on("induced_subgraph", "custpart", BL + " SELECT a AS block, src, dst, w FROM bt WHERE a = b")
def _(g):
    return ini.induced_subgraphs(g, modulo(g))


# Refinement and balancing
SKEW = ", p AS (SELECT vid, c, least(vid % 7, 3)::INT AS block FROM ids)"


def skewed(g):
    return g.vertices.select("vid", F.least(F.col("vid") % 7, F.lit(3)).cast("int").alias("block"))


GAIN = """, r AS (SELECT src AS vid, block AS label, sum(w)::BIGINT AS conn FROM arcs JOIN p ON p.vid = dst GROUP BY ALL),
mg AS (SELECT r.vid, label AS block, conn - coalesce((SELECT conn FROM r o WHERE o.vid = r.vid AND o.label = p.block), 0) AS gain FROM r JOIN p ON p.vid = r.vid WHERE label <> p.block)"""


@on("move_gains", "custpart", SKEW + GAIN + " SELECT vid, block, gain FROM mg")
def _(g):
    return bal.move_gains(g, skewed(g))


@on("relative_gain", "copurchase_sized", SKEW + GAIN + " SELECT mg.vid, mg.block, round(CASE WHEN gain >= 0 THEN (gain * c)::DOUBLE ELSE gain::DOUBLE / c END, 9) AS rel_gain FROM mg JOIN ids ON ids.vid = mg.vid")
def _(g):
    return bal.move_gains(g, skewed(g)).join(g.vertices, "vid").select("vid", "block", F.round(relative_gain(F.col("gain"), F.col("c")), 9).alias("rel_gain"))


WL = ", wl AS (SELECT block, weight, greatest(1.03::DOUBLE * t / 4, t::DOUBLE / 4 + h) AS lim FROM (SELECT block, sum(c)::BIGINT AS weight, sum(sum(c)) OVER ()::BIGINT AS t, (SELECT max(c) FROM ids) AS h FROM p GROUP BY block))"


def skew_weights(g):
    return bal.weighted(g, skewed(g), limits_for(g, [1] * 4, 4, 0.03))


@on("overloaded_blocks", "custpart", SKEW + WL + " SELECT block, round(weight - lim, 6) AS excess FROM wl WHERE weight > lim")
def _(g):
    return bal.overloaded(skew_weights(g)).withColumn("excess", F.round("excess", 6))


CAND = LAY + SKEW + WL + """, act AS (SELECT p.vid, p.block, p.c, pe, weight - lim AS excess FROM p JOIN wl USING (block) JOIN lay ON lay.vid = p.vid WHERE weight > lim),
r AS (SELECT src AS vid, p.block AS target, sum(w)::BIGINT AS conn FROM arcs JOIN act ON act.vid = src JOIN p ON p.vid = dst GROUP BY ALL),
light AS (SELECT arg_min(block, (weight, block)) AS target FROM wl),
opt AS (SELECT vid, target, max(conn) AS conn FROM (SELECT * FROM r UNION ALL SELECT vid, target, 0 FROM act, light) GROUP BY ALL),
ok AS (SELECT act.*, opt.target, conn, row_number() OVER (PARTITION BY act.vid ORDER BY conn DESC, wl.weight, opt.target) AS k FROM opt JOIN act ON act.vid = opt.vid JOIN wl ON wl.block = opt.target WHERE opt.target <> act.block AND wl.weight + act.c <= lim),
rt AS (SELECT ok.*, ok.conn - coalesce(r.conn, 0) AS gain FROM ok LEFT JOIN r ON r.vid = ok.vid AND r.target = ok.block WHERE k = 1),
rr AS (SELECT *, CASE WHEN gain >= 0 THEN (gain * c)::DOUBLE ELSE gain::DOUBLE / c END AS rel_gain FROM rt),
cd AS (SELECT * FROM (SELECT *, coalesce(sum(c) OVER (PARTITION BY pe, block ORDER BY rel_gain DESC, vid ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS bef FROM rr) WHERE bef < excess)"""


def candidates(g):
    return bal.local_candidates(g, skewed(g), lay.assign_pe(g, 4), skew_weights(g))


@on("balance_candidates", "custpart", CAND + " SELECT pe, block, vid, c, target, gain, round(rel_gain, 9) AS rel_gain FROM cd")
def _(g):
    return candidates(g).withColumn("rel_gain", F.round("rel_gain", 9))


@on("balance_top_ell", "copurchase_sized", CAND + ", tp AS (SELECT *, row_number() OVER (PARTITION BY block ORDER BY rel_gain DESC, vid) AS rk FROM cd) SELECT pe, block, vid, c, target, gain, round(rel_gain, 9) AS rel_gain FROM tp WHERE rk <= 4")
def _(g):
    return bal.top_ell(candidates(g), 4).withColumn("rel_gain", F.round("rel_gain", 9))


@on("balance_by_windows", "custpart", CAND + ", gv AS (SELECT * FROM (SELECT cd.*, sum(cd.c) OVER (PARTITION BY cd.block ORDER BY rel_gain DESC, cd.vid ROWS UNBOUNDED PRECEDING) - cd.c AS given FROM cd) WHERE given < excess), ad AS (SELECT gv.vid, gv.block AS old, gv.target, sum(gv.c) OVER (PARTITION BY gv.target ORDER BY rel_gain DESC, gv.vid ROWS UNBOUNDED PRECEDING) AS s, wl.lim - wl.weight AS room FROM gv JOIN wl ON wl.block = gv.target) SELECT vid, old, target AS new FROM ad WHERE s <= room")
def _(g):
    return bal.window_moves(candidates(g), skew_weights(g))


# the root's walk over the best candidates: weights of the four blocks change along the way
ROUND = CAND + """, tp AS (SELECT *, row_number() OVER (PARTITION BY block ORDER BY rel_gain DESC, vid) AS rk, coalesce(sum(c) OVER (PARTITION BY block ORDER BY rel_gain DESC, vid ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS pre FROM cd),
sq AS (SELECT *, row_number() OVER (ORDER BY rel_gain DESC, vid) AS i FROM tp WHERE rk <= 64 AND pre < excess),
lm AS (SELECT any_value(lim) AS lim, list(weight ORDER BY block) AS ws FROM wl),
walk AS (SELECT 0::BIGINT AS i, ws, -1::BIGINT AS vid, -1 AS old, -1 AS new FROM lm
  UNION ALL SELECT sq.i, CASE WHEN t.new >= 0 THEN list_transform(walk.ws, lambda x, j: CASE WHEN j = sq.block + 1 THEN x - sq.c WHEN j = t.new + 1 THEN x + sq.c ELSE x END) ELSE walk.ws END, sq.vid, sq.block, t.new
  FROM walk JOIN sq ON sq.i = walk.i + 1 CROSS JOIN lm, LATERAL (SELECT CASE WHEN walk.ws[sq.block + 1] <= lm.lim THEN -1 WHEN walk.ws[sq.target + 1] + sq.c <= lm.lim THEN sq.target
    WHEN list_position(walk.ws, list_min(walk.ws)) - 1 <> sq.block AND list_min(walk.ws) + sq.c <= lm.lim THEN list_position(walk.ws, list_min(walk.ws)) - 1 ELSE -1 END::INT AS new) t)"""


@on("balance_one_round", "custpart", ROUND + " SELECT p.vid, coalesce(walk.new, p.block)::INT AS block FROM p LEFT JOIN walk ON walk.vid = p.vid AND walk.new >= 0")
def _(g):
    return bal.balance_round(g, skewed(g), lay.assign_pe(g, 4), skew_weights(g), 64)[0]


RATE2 = LAY + SKEW + WL + f""", r AS (SELECT src AS vid, p.block AS label, sum(w)::BIGINT AS conn FROM arcs JOIN p ON p.vid = dst GROUP BY ALL),
own AS (SELECT p.vid, p.block AS old, p.c, pe, coalesce(conn, 0) AS oc, wl.weight AS ow FROM p JOIN lay ON lay.vid = p.vid JOIN wl ON wl.block = p.block LEFT JOIN r ON r.vid = p.vid AND label = p.block),
bm AS (SELECT own.*, r.label AS new, conn - oc AS gain, wl.weight, row_number() OVER (PARTITION BY own.vid ORDER BY conn DESC, wl.weight, {toss(3, "tie", "own.vid", "r.label")} DESC, r.label DESC) AS k FROM r JOIN own ON own.vid = r.vid JOIN wl ON wl.block = r.label WHERE r.label <> old AND wl.weight + c <= lim)"""


@on("refine_one_batch", "custpart", RATE2 + " SELECT vid, pe, c, old::BIGINT AS old, new::BIGINT AS new, gain FROM bm WHERE k = 1 AND (gain > 0 OR (gain = 0 AND weight < ow - c))")
def _(g):
    state = lay.assign_pe(g, 4).join(skewed(g), "vid").select("vid", "c", "pe", F.col("block").cast("long").alias("label"))
    weights = skew_weights(g).select(F.col("block").cast("long").alias("label"), "weight", "limit")
    return cl.best_move(cl.rate(g.edges, state), state, weights, "lighter", 3)


@on("tie_lighter_block", "user_slot", RATE2 + " SELECT vid, old::BIGINT AS old, new::BIGINT AS new FROM bm WHERE k = 1 AND gain = 0 AND weight < ow - c")
def _(g):
    state = lay.assign_pe(g, 4).join(skewed(g), "vid").select("vid", "c", "pe", F.col("block").cast("long").alias("label"))
    weights = skew_weights(g).select(F.col("block").cast("long").alias("label"), "weight", "limit")
    return cl.best_move(cl.rate(g.edges, state), state, weights, "lighter", 3).filter("gain = 0").select("vid", "old", "new")


# Whole methods. Facts about what they return on graphs of the tables; blocks and optima where these are known.
FACTS = "SELECT (SELECT count(*) FROM ids) AS n, (SELECT sum(c)::BIGINT FROM ids) AS total_c, (SELECT coalesce(sum(w), 0)::BIGINT FROM e) AS total_w, (SELECT count(*) FROM ids) AS covered, true AS in_range, (SELECT sum(c)::BIGINT FROM ids) AS block_weight, {k}::BIGINT AS k, {k}::BIGINT AS blocks"


def facts(g, p, k, reference=None, feasible=True, coarsened=False):
    """One row recomputed from the partition: coverage, range of labels, weight in blocks, blocks in use, and what the method promises."""
    deep_result = p if isinstance(p, DeepResult) else None
    p = snapshot(p.partition if deep_result else p)
    v, f = ms.validate_partition(g, p, k).first(), ms.feasibility(g, p, k, 0.03).first()
    w = ms.block_weights(g, p, k).agg(F.sum("weight"), F.count(F.when(F.col("vertices") > 0, 1))).first()
    total_w = g.edges.agg(F.coalesce(F.sum("w"), F.lit(0))).first()[0] // 2
    row = {"n": g.n, "total_c": g.total, "total_w": total_w, "covered": v["distinct_vertices"] if v["rows"] == g.n and not v["strangers"] else -1, "in_range": v["out_of_range"] == 0, "block_weight": w[0], "k": k, "blocks": w[1]}
    kinds = {"in_range": "boolean"}
    if feasible:
        row["feasible"], kinds["feasible"] = f["feasible"], "boolean"
    if reference is not None:
        row["below_reference"], kinds["below_reference"] = ms.edge_cut(g, p).first()["cut"] <= reference(g, k), "boolean"
    if coarsened:  # the graph is above C * min(k, K) vertices, so that levels were coarsened, each to fewer blocks than its size asks for
        row["coarsened"], kinds["coarsened"] = deep_result.distributed >= 1 and all(b == min(k, max(2, columns.ceil2(n / coarsened))) for n, b in deep_result.levels[1:-1]), "boolean"
    return g.vertices.sparkSession.createDataFrame([tuple(row.values())], ", ".join(f"{c} {kinds.get(c, 'long')}" for c in row))


def by_modulo(share):
    return lambda g, k: share * ms.edge_cut(g, modulo(g, k)).first()["cut"]


def by_time(share):
    """Slices of ids, which follow time in the graph of events."""
    return lambda g, k: share * ms.edge_cut(g, baselines.range_partition(g, k)).first()["cut"]


def method(name, graph, k, solve, reference=None, feasible=True, coarsened=0):
    """coarsened: the C of a run of the deep scheme, where the graph has more than C * min(k, K) vertices at every size."""
    limit = f", (SELECT count(*) FROM ids) > {2 * coarsened} AS coarsened" if coarsened else ""
    extra = (", true AS feasible" if feasible else "") + (", true AS below_reference" if reference else "") + limit
    return on(name, graph, FACTS.format(k=k) + extra)(lambda g: facts(g, solve(g, k), k, reference, feasible, coarsened))


def deep(**more):
    return lambda g, k: deep_partition(g, k, DeepParams.fast(**more))


method("deep_fast_copurchase", "copurchase", 4, deep(c=80, eps=0.05), by_modulo(0.97), False, 80)
method("deep_fast_event_chain", "event_chain", 2, deep(c=300), by_time(1.6), True, 300)
method("deep_strong_event_chain", "event_chain", 4, lambda g, k: deep_partition(g, k, DeepParams.strong_(c=400, trials=4)), by_time(1.5), True, 400)
method("deep_fast_word", "word", 2, deep(), by_modulo(0.5))
method("deep_distributed_order_star", "order_star", 4, deep(c=400, sweeps=2), by_modulo(0.95), True, 400)
method("deep_weighted_doc_dup", "doc_dup", 4, deep(), by_modulo(0.5))
method("deep_large_k", "event_chain", 128, deep(), by_modulo(0.5))
method("deep_nonpower_k", "custpart", 6, deep(), by_modulo(0.95))
method("deep_disconnected_turns", "turns", 8, deep(), by_modulo(0.3))
method("deep_wide_split", "partsupp", 16, deep(parts=4), by_modulo(0.97))
method("deep_geometric", "emb_rgg2", 4, deep(), by_modulo(0.3))
method("balance_full", "custpart", 4, lambda g, k: bal.balance(g, skewed(g), limits_for(g, [1] * k, k, 0.03)))
method("refine_full", "user_slot", 4, lambda g, k: bal.lp_refine(g, modulo(g, k), limits_for(g, [1] * k, k, 0.03), 2, 4, 1, "strict"), by_modulo(0.999))
method("settle_skewed", "page_sim", 4, lambda g, k: bal.settle(g, skewed(g), limits_for(g, [1] * k, k, 0.03), 1, 4, 1))
method("extend_blocks", "event_chain", 4, lambda g, k: bal.balance(g, ini.extend(g, baselines.range_partition(g, 2), [2, 2], 4, 2, k, 0.03, 1)[0], limits_for(g, [1] * k, k, 0.03)), by_time(1.6))
method("base_shared_deep", "trade", 4, lambda g, k: baselines.shared_deep_partition(g, k, params=DeepParams(c=4)), by_modulo(1))
method("base_flat_lp", "event_chain", 4, lambda g, k: baselines.flat_lp_partition(g, k), by_modulo(0.9), False)

# Planted blocks: sixteen groups of ids, which each method must find again (what a group is named doesn't matter)
PLANTED = "SELECT vid, (vid // 60) * 60 AS first FROM range(960) t(vid)"


def planted(spark):
    return generators.planted(spark, 16, 60, 20, 1)


def named(p):
    """vid, first: the least vertex of its block."""
    p = snapshot(p.partition if isinstance(p, DeepResult) else p)
    return p.join(p.groupBy("block").agg(F.min("vid").alias("first")), "block").select("vid", "first")


def finds(name, solve):
    query(name, PLANTED)(lambda spark, sf_dir: named(solve(planted(spark), 16)))


def nears(name, solve):
    """Without a global limit or a balancer the groups aren't found exactly: every vertex in a block, and less than a quarter of what modulo cuts."""

    def run(spark, sf_dir):
        g = planted(spark)
        p = snapshot(solve(g, 16))
        v = ms.validate_partition(g, p, 16).first()
        return spark.createDataFrame([(v["distinct_vertices"], v["out_of_range"] + v["strangers"], ms.edge_cut(g, p).first()["cut"] < 0.25 * ms.edge_cut(g, modulo(g, 16)).first()["cut"])], "covered long, wrong long, near boolean")

    query(name, "SELECT 960::BIGINT AS covered, 0::BIGINT AS wrong, true AS near")(run)


finds("deep_fast_planted", deep(c=160))
finds("deep_strong_planted", lambda g, k: deep_partition(g, k, DeepParams.strong_(c=160, trials=4)))
finds("deep_wide_planted", deep(c=100, parts=4))
finds("deep_bulk_planted", deep(c=160, mode="bulk", batches=2, sweeps=2))
finds("initial_best_of_trials", lambda g, k: ini.initial_partition(g, [1] * k, k, 0.03, 3, 1))
nears("base_relaxed_fast", lambda g, k: baselines.relaxed_lp_partition(g, k, stop=20))
nears("base_relaxed_eco", lambda g, k: baselines.relaxed_lp_partition(g, k, preset="eco", stop=20))
finds("base_matching", lambda g, k: baselines.matching_partition(g, k, stop=20))
finds("base_plain_multilevel", lambda g, k: baselines.multilevel_partition(g, k, stop=20))
finds("base_recursive_bisection", lambda g, k: baselines.recursive_bisection(g, k, c=200))

# The least cut of all bisections of the graph of regions that keep to the limit
OPTIMUM = """, m AS (SELECT code FROM range(power(2, (SELECT count(*) FROM ids))::BIGINT) t(code)),
s AS (SELECT code, sum(c) FILTER ((code >> vid) & 1 = 0) AS a, sum(c) FILTER ((code >> vid) & 1 = 1) AS b FROM m, ids GROUP BY code),
ok AS (SELECT code FROM s, (SELECT greatest(1.03::DOUBLE * sum(c) / 2, sum(c)::DOUBLE / 2 + max(c)) AS lim FROM ids) WHERE coalesce(a, 0) <= lim AND coalesce(b, 0) <= lim AND a IS NOT NULL AND b IS NOT NULL)
SELECT min(cut)::BIGINT AS cut FROM (SELECT code, coalesce(sum(w) FILTER ((code >> u) & 1 <> (code >> v) & 1), 0) AS cut FROM ok, e GROUP BY code)"""


@on("brute_force_bisection", "region_trade", OPTIMUM)
def _(g):
    return ms.edge_cut(g, baselines.brute_force_partition(g, 2)[1])


@on("deep_optimum", "region_trade", OPTIMUM)
def _(g):
    return ms.edge_cut(g, deep_partition(g, 2, DeepParams.fast()).partition)


@on("cluster_fleet", "event_chain", "SELECT (SELECT count(*) FROM ids) AS vertices, (SELECT sum(c)::BIGINT FROM ids) AS weight, 0::BIGINT AS over, true AS shrinks, true AS counted")
def _(g):
    """Clusters of PEs that exchange messages: all vertices, none over the limit after the last take-back, fewer than half as many, counters that agree."""
    trace = {}
    clusters = cl.lp_cluster(g, 12, 3, 16, 1, count=8, trace=trace)
    w = g.vertices.join(clusters, "vid").groupBy("cluster").agg(F.sum("c").alias("c"), F.count("*").alias("n"))
    row = w.agg(F.sum("n").alias("vertices"), F.sum("c").alias("weight"), F.count(F.when(F.col("c") > 12, 1)).alias("over"), F.count("*").alias("clusters"))
    counted = sum(trace["moves"]) == trace["kept"] and trace["notified"] > 0
    return row.select("vertices", "weight", "over", (F.col("clusters") * 2 < g.n).alias("shrinks"), F.lit(counted).alias("counted"))


@on("cluster_inside_components", "turns", "SELECT conv_id AS conv, count(*) AS vertices, 1::BIGINT AS clusters FROM conversations GROUP BY conv_id HAVING count(*) <= 2")
def _(g):
    """Without a limit, the turns of a short conversation become one cluster."""
    clusters = cl.lp_cluster(g, g.total + 1, 5, 4, 1, limit_mode="none", count=8)
    home = graphs.densify_keys(g).select("vid", F.floor(F.col("key") / (1 << 20)).alias("conv"))
    return home.join(clusters, "vid").groupBy("conv").agg(F.count("*").alias("vertices"), F.countDistinct("cluster").alias("clusters")).filter("vertices <= 2")


@on("relaxed_overweight", "partsupp", "SELECT true AS relaxed_over, true AS within_pes_times, true AS taken_back FROM ids LIMIT 1")
def _(g):
    """Limits that each PE only keeps for its own part let clusters grow above the limit, up to P times; taking moves back leaves less above it."""
    over = {}
    for mode in ("local", "revert"):
        w = g.vertices.join(cl.lp_cluster(g, 8, 3, 16, 1, limit_mode=mode, count=8), "vid").groupBy("cluster").agg(F.sum("c").alias("c"))
        over[mode] = w.agg(F.max("c").alias("c"), F.coalesce(F.sum(F.greatest(F.lit(0), F.col("c") - 8)), F.lit(0)).alias("over")).first()
    a, b = over["local"], over["revert"]
    return g.vertices.sparkSession.createDataFrame([(a["c"] > 8, a["c"] <= 16 * 8, b["over"] < a["over"])], "relaxed_over boolean, within_pes_times boolean, taken_back boolean")


@on("replicated_groups", "trade", "SELECT copy::INT AS copy, count(*) AS arcs, sum(w)::BIGINT AS w, min(src + copy * (SELECT count(*) FROM ids)) AS first, max(dst + copy * (SELECT count(*) FROM ids)) AS last FROM arcs, range(3) t(copy) GROUP BY copy")
def _(g):
    many = ini.replicate(g, 3)
    return many.edges.join(many.vertices.select(F.col("vid").alias("src"), "copy"), "src").groupBy("copy").agg(F.count("*").alias("arcs"), F.sum("w").alias("w"), F.min("src").alias("first"), F.max("dst").alias("last"))


@on("best_copy", "trade", ", c AS (SELECT k, (SELECT sum(w) FROM e WHERE (u + k) % (k + 2) <> (v + k) % (k + 2)) AS cut FROM range(2) t(k)) SELECT vid, ((vid + b.k) % (b.k + 2) % 4)::INT AS block FROM ids, (SELECT k FROM c ORDER BY cut, k LIMIT 1) b")
def _(g):
    """Two copies with partitions of their own: the one that cuts less goes on."""
    many = ini.replicate(g, 2)
    at = F.col("vid") - F.col("copy") * g.n
    p = many.vertices.select("vid", (F.col("copy") * 4 + (at + F.col("copy")) % (F.col("copy") + 2)).cast("int").alias("block"))
    return ini.best_copies(many, p, 2, 4, [float(g.total)] * 4, g)


@on("base_hash", "custpart", f", p AS (SELECT vid, ({toss(0, 'block', 'vid')} % 4)::INT AS block FROM ids) SELECT vid, block FROM p")
def _(g):
    return baselines.hash_partition(g, 4)


@on("base_range", "event_chain", "SELECT vid, ((vid * 4) // (SELECT count(*) FROM ids))::INT AS block FROM ids")
def _(g):
    return baselines.range_partition(g, 4)


# Experiments on small fixed instances, and generators
for _name in experiments.SMALL:
    query(_name, experiments.small_sql(_name))(lambda spark, sf_dir, name=_name: experiments.verdicts(spark, name, sf_dir))


@query("e3_times", "SELECT * FROM (VALUES ('deep_fast', true, true), ('shared_deep', true, true)) v(algorithm, timed, fast_enough)")
def _(spark, sf_dir):
    """Times of the instances that all solved, and throughput."""
    found = experiments.small(spark, "e4_shared")
    means = report.aggregate_seeds(report.common_instances(found))
    sizes = spark.createDataFrame([("grid", 1104)], "graph string, m long")
    rate = report.throughput(means, sizes).select("algorithm", (F.col("edges_per_second") > 1).alias("fast_enough"))
    return report.geo_mean(means, "seconds", ["algorithm"]).select("algorithm", (F.col("geo_seconds") > 0).alias("timed")).join(rate, "algorithm")


def part_of(k):
    """A coordinate in [0, 1) from the k-th component, as in `generators.embedded`."""
    return f"embedding[{k}]::DOUBLE * 1024 - floor(embedding[{k}]::DOUBLE * 1024)"


def gen(name, dims, degree):
    """The given vectors as points, and all pairs nearer than the radius."""
    radius = f"sqrt({degree}::DOUBLE / (pi() * n))" if dims == 2 else f"pow(3.0::DOUBLE * {degree} / (4 * pi() * n), 1.0::DOUBLE / 3)"
    apart = " + ".join(f"(a.{d} - b.{d}) * (a.{d} - b.{d})" for d in "xyz"[:dims])
    sql = f"WITH p AS (SELECT vec_id AS i, {', '.join(f'{part_of(k + 3)} AS {d}' for k, d in enumerate('xyz'[:dims]))} FROM embeddings WHERE embedding[{dims + 2}] IS NOT NULL), s AS (SELECT {radius} AS r FROM (SELECT count(*) AS n FROM p)) SELECT a.i AS src, b.i AS dst, 1::BIGINT AS w FROM p a, p b, s WHERE a.i <> b.i AND {apart} < r * r"
    query(name, sql)(lambda spark, sf_dir: symmetrize(generators.near(generators.embedded(spark, sf_dir, list("xyz"[:dims])), list("xyz"[:dims]), degree)))


gen("gen_rgg2d", 2, 8)
gen("gen_rgg3d", 3, 8)


@query("gen_rhg", f"WITH q AS (SELECT vec_id AS i, {part_of(3)} AS x, {part_of(4)} AS y FROM embeddings WHERE embedding[4] IS NOT NULL), s AS (SELECT 2 * ln(2.0::DOUBLE * n * 4 / (pi() * 8)) AS top FROM (SELECT count(*) AS n FROM q)), p AS (SELECT i, acosh(1 + (cosh(top) - 1) * x) AS r, y * 2 * pi() AS phi, cosh(top) AS far FROM q, s), t AS (SELECT i, phi, far, cosh(r) AS c, sinh(r) AS s FROM p) SELECT a.i AS src, b.i AS dst, 1::BIGINT AS w FROM t a, t b WHERE a.i <> b.i AND a.c * b.c - a.s * b.s * cos(a.phi - b.phi) < a.far")
def _(spark, sf_dir):
    return symmetrize(generators.hyperbolic(generators.embedded(spark, sf_dir, ["r", "phi"]), 8))


@query("gen_grid2d", "WITH n AS (SELECT count(*) AS n FROM orders), i AS (SELECT row_number() OVER (ORDER BY o_orderkey) - 1 AS i FROM orders), e AS (SELECT i AS u, i + 1 AS v FROM i, n WHERE i % 300 < 299 AND i + 1 < n UNION ALL SELECT i, i + 300 FROM i, n WHERE i + 300 < n) SELECT u AS src, v AS dst, 1::BIGINT AS w FROM e UNION ALL SELECT v, u, 1 FROM e")
def _(spark, sf_dir):
    """The orders, by key, in rows of 300."""
    ids = dense_ids(graphs.read(spark, sf_dir, "orders").select("o_orderkey"), "o_orderkey", "u").select("u")
    return symmetrize(generators.lattice(ids, ids.count(), 300))


# Reports over a table of runs with fixed cuts
RUNS = " UNION ALL ".join(f"SELECT 'hash' AS algorithm, {k} AS k, {s} AS seed, (SELECT (sum(w))::BIGINT FROM e WHERE {toss(s, 'block', 'u')} % {k} <> {toss(s, 'block', 'v')} % {k}) AS cut" for k in (2, 4) for s in (0, 1, 2))
RUNS += " UNION ALL " + " UNION ALL ".join(f"SELECT 'modulo', {k}, 0, (SELECT sum(w)::BIGINT FROM e WHERE u % {k} <> v % {k})" for k in (2, 4))
RUNS = f", runs AS ({RUNS}), mn AS (SELECT algorithm, k, avg(cut) AS cut FROM runs GROUP BY ALL)"


def runs(g):
    rows = []
    for k in (2, 4):
        for s in (0, 1, 2):
            rows.append(("hash", "trade", k, s, ms.edge_cut(g, baselines.hash_partition(g, k, s)).first()["cut"], True, "ok", 1.0))
        rows.append(("modulo", "trade", k, 0, ms.edge_cut(g, modulo(g, k)).first()["cut"], True, "ok", 1.0))
    return g.vertices.sparkSession.createDataFrame(rows, report.RUNS)


@on("seed_mean", "trade", RUNS + " SELECT algorithm, k, round(cut, 6) AS cut FROM mn")
def _(g):
    return report.aggregate_seeds(runs(g)).select("algorithm", "k", F.round("cut", 6).alias("cut"))


@on("perf_profile", "trade", RUNS + ", b AS (SELECT k, min(cut) AS best FROM mn GROUP BY k) SELECT algorithm, tau::DOUBLE AS tau, avg(CASE WHEN cut <= tau * best THEN 1.0::DOUBLE ELSE 0 END) AS share FROM mn JOIN b USING (k), (VALUES (1.0::DOUBLE), (1.01::DOUBLE), (1.1::DOUBLE)) t(tau) GROUP BY ALL")
def _(g):
    return report.performance_profile(report.aggregate_seeds(runs(g)), [1.0, 1.01, 1.1])


@on("geo_mean_cut", "trade", RUNS + " SELECT algorithm, round(exp(avg(ln(cut))), 4) AS geo_cut FROM mn GROUP BY algorithm")
def _(g):
    return report.geo_mean(report.aggregate_seeds(runs(g)), "cut", ["algorithm"]).withColumn("geo_cut", F.round("geo_cut", 4))


@on("cut_ratio", "trade", RUNS + " SELECT a.algorithm, a.k, round(a.cut / b.cut, 6) AS ratio FROM mn a JOIN mn b ON b.k = a.k AND b.algorithm = 'modulo'")
def _(g):
    return report.cut_ratio(report.aggregate_seeds(runs(g)), "modulo").select("algorithm", "k", F.round("ratio", 6).alias("ratio"))


@on("common_instances", "trade", RUNS + " SELECT algorithm, k, seed, cut FROM runs WHERE k = 2")
def _(g):
    table = runs(g).withColumn("feasible", (F.col("k") == 2) | (F.col("seed") > 0))
    return report.common_instances(table).select("algorithm", "k", "seed", "cut")


@on("cut_cube", "trade", RUNS + " SELECT k, algorithm, round(avg(cut), 6) AS cut, count(*) AS runs FROM runs GROUP BY CUBE (k, algorithm)")
def _(g):
    return report.cut_cube(runs(g).withColumn("graph", F.lit("trade"))).filter("graph is not null").select("k", "algorithm", F.round("cut", 6).alias("cut"), "runs")


@query("scaling_speedup", "SELECT cores::INT AS cores, round(8.0::DOUBLE / seconds, 6) AS speedup, round(8.0::DOUBLE / seconds / cores, 6) AS efficiency FROM (VALUES (1, 8.0::DOUBLE), (2, 4.4::DOUBLE), (4, 2.5::DOUBLE)) v(cores, seconds)")
def _(spark, sf_dir):
    series = spark.createDataFrame([("deep", "x", c, s) for c, s in ((1, 8.0), (2, 4.4), (4, 2.5))], "algorithm string, graph string, cores int, seconds double")
    return report.scaling_table(series).select("cores", F.round("speedup", 6).alias("speedup"), F.round("efficiency", 6).alias("efficiency"))


# Streams
@query("stream_edge_window", "SELECT time_bucket(INTERVAL 1 DAY, ts) AS day, user_id, event_type, count(*) AS w FROM events GROUP BY ALL")
def _(spark, sf_dir):
    return stream.finished(stream.edge_windows(stream.event_stream(spark, sf_dir)), "complete").select(F.col("window.start").alias("day"), "user_id", "event_type", "w")


@query("stream_degree", "SELECT user_id, count(DISTINCT event_type) AS degree, count(*) AS weight FROM events GROUP BY user_id")
def _(spark, sf_dir):
    return stream.finished(stream.degrees(stream.event_stream(spark, sf_dir)), "complete")


@query("stream_session", "WITH g AS (SELECT user_id, ts, CASE WHEN lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOUR > ts THEN 0 ELSE 1 END AS new FROM events), s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, min(ts) AS start, count(*) AS events FROM s GROUP BY user_id, k")
def _(spark, sf_dir):
    return stream.finished(stream.sessions(stream.event_stream(spark, sf_dir), "6 hours"), "complete").select("user_id", F.col("session_window.start").alias("start"), "events")


@query("stream_assign", "SELECT event_id AS vid, CASE WHEN user_id % 4 = 3 THEN 0 ELSE user_id % 4 END::INT AS block FROM events")
def _(spark, sf_dir):
    anchors = spark.range(4).select(F.col("id").alias("anchor"), F.when(F.col("id") == 3, 0).otherwise(F.col("id")).cast("int").alias("block"))
    return stream.finished(stream.assign(stream.event_stream(spark, sf_dir), F.col("user_id") % 4, anchors), "append")


@query("stream_arrivals", "WITH m AS (SELECT max(ts) - INTERVAL 2 DAY AS mark FROM events), c AS (SELECT time_bucket(INTERVAL 1 DAY, ts) AS day, user_id, length(event_type) % 3 AS block, count(*) AS w FROM events GROUP BY ALL), r AS (SELECT *, row_number() OVER (PARTITION BY day, user_id ORDER BY w DESC, block) AS k FROM c) SELECT day, user_id, block::INT AS block, w FROM r, m WHERE k = 1 AND day + INTERVAL 1 DAY <= mark")
def _(spark, sf_dir):
    """Days that the watermark has passed: two aggregations in a stream."""
    anchors = spark.range(3).select(F.col("id").cast("int").alias("anchor"), F.col("id").cast("int").alias("block"))
    placed = stream.arrivals(stream.event_stream(spark, sf_dir, "2 days"), F.length("event_type") % 3, anchors)
    return stream.finished(placed, "append").select(F.col("window.start").alias("day"), "user_id", "block", "w")


# As-of join, SQL surface
@query("asof_purchase", "WITH p AS (SELECT user_id, ts, max(event_id) AS found FROM events WHERE event_type = 'purchase' GROUP BY ALL) SELECT e.event_id, p.found FROM events e ASOF LEFT JOIN p ON e.user_id = p.user_id AND e.ts >= p.ts")
def _(spark, sf_dir):
    """Each event with its user's last purchase up to then, in slots of a day."""
    events = spark.read.parquet(f"{sf_dir}/events.parquet").select("event_id", "user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("at"))
    bought = events.filter("event_type = 'purchase'").select("user_id", "at", "event_id")
    return asof.asof(events.select("event_id", "user_id", "at"), bought, "user_id", "at", 86400e6).select("event_id", F.col("found.event_id").alias("found"))


def in_sql(name, graph, sql):
    """A measure as SQL text over the views of a graph and the partition by modulo."""

    def run(g):
        views.create_views(g, modulo(g))
        # the views are the session's: rows are taken before another query replaces them
        return snapshot(views.measure(g.vertices.sparkSession, name, 4))

    return on(f"sql_{name}", graph, sql)(run)


in_sql("cut", "custpart", "SELECT sum(w)::BIGINT AS cut FROM e WHERE u % 4 <> v % 4")
in_sql("block_weights", "custpart", "SELECT (vid % 4)::INT AS block, sum(c)::BIGINT AS weight, count(*) AS vertices FROM ids GROUP BY ALL")
in_sql("feasible", "trade", "SELECT (SELECT max(s) FROM (SELECT sum(c) AS s FROM ids GROUP BY vid % 4)) <= greatest(1.03::DOUBLE * sum(c) / 4, sum(c)::DOUBLE / 4 + max(c)) AS feasible FROM ids")
in_sql("boundary", "partsupp", "SELECT (src % 4)::INT AS block, count(DISTINCT src) AS boundary FROM arcs WHERE src % 4 <> dst % 4 GROUP BY ALL")


@query("block_spans", "WITH RECURSIVE u AS (SELECT user_id, (count(*) + 15) // 16 AS k FROM events GROUP BY user_id), t(user_id, k, level, first, span) AS (SELECT user_id, k, 0, 0::BIGINT, k FROM u UNION ALL SELECT user_id, k, level + 1, first + d * ((span + 1) // 2), CASE d WHEN 0 THEN (span + 1) // 2 ELSE span // 2 END FROM (SELECT t.*, max(span) OVER (PARTITION BY user_id, level) AS top FROM t) t, (VALUES (0), (1)) h(d) WHERE top > 1 AND (d = 0 OR span > 1)) SELECT user_id, k, level::INT AS level, (row_number() OVER (PARTITION BY user_id, level ORDER BY first) - 1)::INT AS block, first::INT AS first, span::INT AS span FROM t")
def _(spark, sf_dir):
    """Each user's events in blocks of at most 16 on average, and the blocks of every level on the way there."""
    views.register_spans(spark)
    graphs.read(spark, sf_dir, "events").groupBy("user_id").agg(F.ceil(F.count("*") / 16).alias("k")).createOrReplaceTempView("v_users")
    return spark.sql("SELECT v.user_id, v.k, s.* FROM v_users v, LATERAL block_spans(CAST(v.k AS INT)) s")


def flagship(spark, sf_dir):
    """Parts with the block that the deep scheme puts them in."""
    g, names = graphs.densify(graphs.BUILDERS["copurchase"](spark, sf_dir))
    found = deep_partition(g, 4, DeepParams.fast()).partition
    return names.join(found, "vid").select(F.col("key").alias("p_partkey"), "vid", "block")


@query("flagship_parts", f"{sql_graph('copurchase')} SELECT k::INT AS block, (SELECT count(*) FROM ids) AS parts, true AS within_limit, true AS below_modulo FROM range(4) t(k)")
def _(spark, sf_dir):
    found = snapshot(flagship(spark, sf_dir))
    g = load_graph(spark, sf_dir, "copurchase")
    p = found.select("vid", "block")
    below = ms.edge_cut(g, p).first()["cut"] < 0.97 * ms.edge_cut(g, modulo(g)).first()["cut"]
    limit = limits_for(g, [1], 4, 0.03)[0]
    return ms.block_weights(g, p, 4).select("block", F.lit(found.select("p_partkey").distinct().count()).cast("long").alias("parts"), (F.col("weight") <= limit).alias("within_limit"), F.lit(below).alias("below_modulo"))
