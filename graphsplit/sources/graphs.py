"""Graphs built from the given tables, and the SQL that gives the same vertices and edges.

Keys of graphs with several kinds of vertices are the kind times 2^40 plus the id, or strings with the kind as prefix.
"""

from __future__ import annotations

import zlib
from collections.abc import Callable
from dataclasses import replace
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from graphsplit.model import Graph, RawGraph, densify, stored

KIND = 1 << 40


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def of_kind(kind: int, x: Column | str) -> Column:
    return (F.col(x) if isinstance(x, str) else x).cast("long") + F.lit(kind * KIND)


def counted(pairs: DataFrame, weight: Column | None = None) -> DataFrame:
    """Edges u < v with summed weight from rows u, v in any order; loops and nulls go."""
    w = F.count("*") if weight is None else F.sum(weight)
    return pairs.filter("u <> v").select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v"), *[c for c in pairs.columns if c not in "uv"]).groupBy("u", "v").agg(w.cast("long").alias("w"))


def ends(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("u").alias("key")).union(edges.select("v")).distinct().withColumn("c", F.lit(1))


def keys(*parts: DataFrame) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.union(p)
    return out.filter("key is not null").distinct().withColumn("c", F.lit(1))


def build_trade(spark, sf_dir):
    nation = lambda t, key, n: read(spark, sf_dir, t).select(key, n)
    lines = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey").join(read(spark, sf_dir, "orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    lines = lines.join(nation("customer", "c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey")).join(nation("supplier", "s_suppkey", "s_nationkey"), F.col("l_suppkey") == F.col("s_suppkey"))
    pairs = lines.select(F.col("c_nationkey").cast("long").alias("u"), F.col("s_nationkey").cast("long").alias("v"))
    return RawGraph(keys(read(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("long").alias("key"))), counted(pairs))


def build_region_trade(spark, sf_dir):
    """The trade graph contracted by region."""
    home = read(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("long").alias("nation"), F.col("n_regionkey").cast("long").alias("region"))
    e = build_trade(spark, sf_dir).edges
    pairs = e.join(home.withColumnsRenamed({"nation": "u", "region": "_u"}), "u").join(home.withColumnsRenamed({"nation": "v", "region": "_v"}), "v")
    return RawGraph(home.groupBy(F.col("region").alias("key")).agg(F.count("*").alias("c")), counted(pairs.select(F.col("_u").alias("u"), F.col("_v").alias("v"), "w"), F.col("w")))


def build_geo_tree(spark, sf_dir):
    n = read(spark, sf_dir, "nation").select("n_nationkey", "n_regionkey")
    c, s = read(spark, sf_dir, "customer").select("c_custkey", "c_nationkey"), read(spark, sf_dir, "supplier").select("s_suppkey", "s_nationkey")
    r = read(spark, sf_dir, "region").select(of_kind(0, "r_regionkey").alias("key"))
    pairs = n.select(of_kind(0, "n_regionkey").alias("u"), of_kind(1, "n_nationkey").alias("v")).union(c.select(of_kind(1, "c_nationkey"), of_kind(2, "c_custkey"))).union(s.select(of_kind(1, "s_nationkey"), of_kind(3, "s_suppkey")))
    return RawGraph(keys(r, n.select(of_kind(1, "n_nationkey")), c.select(of_kind(2, "c_custkey")), s.select(of_kind(3, "s_suppkey"))), counted(pairs))


def build_copurchase(spark, sf_dir):
    lines = read(spark, sf_dir, "lineitem").select("l_orderkey", F.col("l_partkey").cast("long").alias("p"))
    a, b = lines.withColumnRenamed("p", "u"), lines.withColumnRenamed("p", "v")
    edges = a.join(b, "l_orderkey").filter("u < v").groupBy("u", "v").agg(F.count("*").alias("w"))
    return RawGraph(keys(read(spark, sf_dir, "part").select(F.col("p_partkey").cast("long").alias("key"))), edges)


def build_copurchase_sized(spark, sf_dir):
    raw = build_copurchase(spark, sf_dir)
    return RawGraph(read(spark, sf_dir, "part").select(F.col("p_partkey").cast("long").alias("key"), F.col("p_size").alias("c")), raw.edges)


def build_custpart(spark, sf_dir):
    lines = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").join(read(spark, sf_dir, "orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    edges = counted(lines.select(of_kind(0, "o_custkey").alias("u"), of_kind(1, "l_partkey").alias("v")))
    return RawGraph(keys(read(spark, sf_dir, "customer").select(of_kind(0, "c_custkey").alias("key")), read(spark, sf_dir, "part").select(of_kind(1, "p_partkey"))), edges)


def build_partsupp(spark, sf_dir):
    edges = counted(read(spark, sf_dir, "lineitem").select(of_kind(0, "l_partkey").alias("u"), of_kind(1, "l_suppkey").alias("v")))
    return RawGraph(keys(read(spark, sf_dir, "part").select(of_kind(0, "p_partkey").alias("key")), read(spark, sf_dir, "supplier").select(of_kind(1, "s_suppkey"))), edges)


def build_order_star(spark, sf_dir):
    lines = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey")
    orders = read(spark, sf_dir, "orders").select("o_orderkey", "o_custkey").join(lines, F.col("o_orderkey") == F.col("l_orderkey"), "left_semi")
    pairs = orders.select(of_kind(0, "o_orderkey").alias("u"), of_kind(1, "o_custkey").alias("v")).union(lines.select(of_kind(0, "l_orderkey"), of_kind(2, "l_suppkey")))
    every = keys(orders.select(of_kind(0, "o_orderkey").alias("key")), read(spark, sf_dir, "customer").select(of_kind(1, "c_custkey")), read(spark, sf_dir, "supplier").select(of_kind(2, "s_suppkey")))
    return RawGraph(every, counted(pairs))


def following(events: DataFrame, by: str) -> DataFrame:
    """u, v: every event and the next one of the same `by`, by time.

    Few values of `by` hold all events: each is cut into ranges of time, which are sorted in tasks of their own; the borders, a row for each value
    and range, are stitched.
    """
    cells = F.struct(F.col(by), F.date_trunc("hour", "ts"))
    own = Window.partitionBy("cell").orderBy("ts", "event_id")
    rows = events.withColumn("cell", cells).withColumn("next", F.lead("event_id").over(own))
    firsts = rows.groupBy("cell").agg(F.min_by("event_id", F.struct("ts", "event_id")).alias("first"), F.max_by("event_id", F.struct("ts", "event_id")).alias("last"))
    borders = firsts.withColumn("then", F.lead("first").over(Window.partitionBy(f"cell.{by}").orderBy("cell")))
    return rows.filter("next is not null").select(F.col("event_id").alias("u"), F.col("next").alias("v")).union(borders.filter("then is not null").select("last", "then"))


def build_event_chain(spark, sf_dir):
    e = read(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type")
    return RawGraph(keys(e.select(F.col("event_id").alias("key"))), counted(following(e, "user_id").union(following(e, "event_type"))))


def build_user_slot(spark, sf_dir):
    e = read(spark, sf_dir, "events").select(F.concat(F.lit("u:"), F.col("user_id").cast("string")).alias("u"), F.concat(F.lit("s:"), "event_type", F.lit(":"), F.date_format("ts", "yyyy-MM-dd")).alias("v"))
    edges = counted(e)
    return RawGraph(ends(edges), edges)


def build_word(spark, sf_dir):
    tokens = F.filter(F.split(F.lower("text"), " "), lambda x: x != "")
    pairs = read(spark, sf_dir, "documents").select(tokens.alias("t")).filter("size(t) > 1").select(F.explode(F.arrays_zip(F.slice("t", F.lit(1), F.size("t") - 1).alias("u"), F.slice("t", F.lit(2), F.size("t") - 1).alias("v"))).alias("p")).select("p.u", "p.v")
    edges = counted(pairs)
    return RawGraph(ends(edges), edges, from_ends=True)


HREF = 'href="([^"]*)"'


def links(spark, sf_dir) -> DataFrame:
    return read(spark, sf_dir, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit(HREF), F.lit(1))).alias("to"))


def build_link(spark, sf_dir):
    edges = counted(links(spark, sf_dir).select(F.concat(F.lit("p:"), F.col("page_id").cast("string")).alias("u"), F.concat(F.lit("t:"), "to").alias("v")))
    return RawGraph(keys(ends(edges).select("key"), read(spark, sf_dir, "pages").select(F.concat(F.lit("p:"), F.col("page_id").cast("string")).alias("key"))), edges)


#: Keys of a block; two blocks meet in one task.
HOLDERS = 4096


def sharing(rows: DataFrame, key: str, value: str, ids: DataFrame | None = None) -> DataFrame:
    """u < v, w: pairs of keys (integers) and how many values they share, or of the keys' ids (key, vid), so that no pair has to look for its own.

    Keys are dealt to blocks, and a task makes all pairs of two blocks with their counts, so that no pair is shuffled. A row goes to the blocks
    in which its value has holders, and nowhere else; what goes from a block to another is packed.
    """
    kind = rows.schema[key].dataType.simpleString() if ids is None else "bigint"
    numbers = {"bigint": np.int64, "int": np.int32}[kind]
    rows = rows.filter(F.col(key).isNotNull() & F.col(value).isNotNull()).select(F.col(key).cast("long").alias("k"), F.xxhash64(value).alias("h"), F.xxhash64(F.md5(F.col(value).cast("binary"))).alias("m")).distinct()
    if ids is not None:
        rows = rows.join(ids.select(F.col("key").cast("long").alias("k"), "vid"), "k").select(F.col("vid").alias("k"), "h", "m")
    blocks = rows.agg(F.greatest(F.lit(1), F.ceil(F.approx_count_distinct("k") / HOLDERS)).alias("blocks"))  # one row
    rows = rows.crossJoin(F.broadcast(blocks)).select("k", "h", "m", F.pmod(F.xxhash64("k"), F.col("blocks")).cast("int").alias("b"))
    homes = rows.groupBy("h", "m").agg(F.count("*").alias("n"), F.collect_set("b").alias("o")).filter("n > 1").drop("n")
    # values are numbered once, as all blocks must know the same numbers
    dealt = rows.join(stored(homes.withColumn("x", F.monotonically_increasing_id())), ["h", "m"]).select("k", "b", "x", "o")

    def packed(table: pa.Table) -> pa.Table:
        """A row i, j, b, body for each block that shares values with block b: the keys, and by value their places among the keys."""
        table = table.combine_chunks().sort_by("x")
        k, x = (np.asarray(table.column(c)).astype(np.int64) for c in ("k", "x"))
        own, lists = table.column("b")[0].as_py(), table.column("o").combine_chunks()
        other, of = np.asarray(lists.flatten()), np.repeat(np.arange(len(k)), np.asarray(lists.value_lengths()))
        order = np.argsort(other, kind="stable")
        other, of = other[order], of[order]
        out = []
        for part in np.split(np.arange(len(of)), np.flatnonzero(np.diff(other)) + 1):
            rows, there = of[part], int(other[part[0]])
            names, at = np.unique(k[rows], return_inverse=True)
            body = [np.diff(names, prepend=0), at.astype(np.int64), np.diff(x[rows], prepend=0)]
            out.append((min(own, there), max(own, there), own, zlib.compress(np.concatenate([[len(names)], *body]).astype(np.int64).tobytes(), 1)))
        return pa.table({n: pa.array(c, t) for n, c, t in zip(("i", "j", "b", "body"), zip(*out, strict=True), (pa.int32(), pa.int32(), pa.int32(), pa.binary()), strict=True)})

    def unpacked(body: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        z = np.frombuffer(zlib.decompress(body), np.int64)
        n, r = int(z[0]), (len(z) - 1 - int(z[0])) // 2
        return z[1 : n + 1].cumsum(), z[n + 1 : n + 1 + r], z[n + 1 + r :].cumsum()

    def pairs(table: pa.Table) -> pa.Table:
        found = {b: unpacked(body) for b, body in zip(table.column("b").to_pylist(), table.column("body").to_pylist(), strict=True)}
        i, j = table.column("i")[0].as_py(), table.column("j")[0].as_py()
        (left, p, x), (right, q, y) = found[i], found[j]
        shared = np.zeros((len(left), len(right)), np.int32)
        # both know the same values, in the same order
        for own, there in zip(np.split(p, np.flatnonzero(np.diff(x)) + 1), np.split(q, np.flatnonzero(np.diff(y)) + 1), strict=True):
            shared[np.ix_(own, there)] += 1
        p, q = np.nonzero(shared)
        if i == j:
            p, q = p[p < q], q[p < q]
        u, v = left[p].astype(numbers), right[q].astype(numbers)
        return pa.table({"u": np.minimum(u, v), "v": np.maximum(u, v), "w": shared[p, q].astype(np.int64)})

    shares = dealt.groupBy("b").applyInArrow(packed, "i int, j int, b int, body binary")
    return shares.groupBy("i", "j").applyInArrow(pairs, f"u {kind}, v {kind}, w long")


def build_page_sim(spark, sf_dir):
    made = partial(sharing, links(spark, sf_dir), "page_id", "to")
    return RawGraph(keys(read(spark, sf_dir, "pages").select(F.col("page_id").alias("key"))), made(), True, made)


def geometric(points: DataFrame, dims: list[str], r: float) -> DataFrame:
    """Edges between points nearer than r: points meet only those of their own and adjacent cells of a grid of width r."""
    cells = [F.floor(F.col(d) / r).alias(f"g_{d}") for d in dims]
    home = points.select("key", *dims, *cells)
    away = home
    for d in dims:
        away = away.withColumn(f"g_{d}", F.explode(F.sequence(F.col(f"g_{d}") - 1, F.col(f"g_{d}") + 1)))
    away = away.withColumnsRenamed({"key": "other", **{d: f"o_{d}" for d in dims}})
    apart = sum((F.col(d) - F.col(f"o_{d}")) * (F.col(d) - F.col(f"o_{d}")) for d in dims)
    return home.join(away, [f"g_{d}" for d in dims]).filter((F.col("key") < F.col("other")) & (apart < r * r)).select(F.col("key").alias("u"), F.col("other").alias("v"), F.lit(1).cast("long").alias("w"))


def _rgg(dims: int, r: float):
    def build(spark, sf_dir):
        names = ["x", "y", "z"][:dims]
        p = read(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("key"), *[F.get("embedding", F.lit(k)).cast("double").alias(d) for k, d in enumerate(names)])
        return RawGraph(keys(p.select("key")), geometric(p, names, r))

    return build


def knn(points: DataFrame, k: int, block: int = 2048) -> DataFrame:
    """u < v, w = 1: pairs of which one is among the k most alike of the other by cosine, ties to the smaller key. points: key, x (doubles).

    Every point is asked against all, in blocks of both that meet in a task of their own; a task keeps the k best of each point.
    """
    spark = points.sparkSession
    n = max(1, -(-points.count() // block))
    own = points.withColumn("b", F.pmod(F.xxhash64("key"), F.lit(n)).cast("int"))
    every = F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    asked = own.select("key", "x", F.col("b").alias("q"), every.alias("b"), F.lit(1).alias("role"))
    there = own.select("key", "x", every.alias("q"), "b", F.lit(0).alias("role"))

    def best(table: pa.Table) -> pa.Table:
        key, role = (np.asarray(table.column(c)) for c in ("key", "role"))
        x = np.stack([np.asarray(v) for v in table.column("x").to_pylist()])
        x = x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-300)
        a, b = np.flatnonzero(role == 1), np.flatnonzero(role == 0)
        out = [[], [], []]
        for i, row in zip(key[a].tolist(), np.round(x[a] @ x[b].T, 12), strict=True):
            top = [j for j in np.lexsort((key[b], -row))[: k + 1].tolist() if key[b][j] != i][:k]
            for o, v in zip(out, ([i] * len(top), key[b][top].tolist(), row[top].tolist()), strict=True):
                o += v
        return pa.table({"u": pa.array(out[0], pa.int64()), "v": pa.array(out[1], pa.int64()), "s": pa.array(out[2], pa.float64())})

    near = asked.union(there).repartition(min(20_000, n * n), "q", "b").groupBy("q", "b").applyInArrow(best, "u long, v long, s double")
    rank = F.row_number().over(Window.partitionBy("u").orderBy(F.desc("s"), "v"))
    kept = near.withColumn("r", rank).filter(F.col("r") <= k)
    return kept.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).distinct().withColumn("w", F.lit(1).cast("long"))


def _knn(k: int):
    def build(spark, sf_dir):
        p = read(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("long").alias("key"), F.transform("embedding", lambda x: x.cast("double")).alias("x"))
        return RawGraph(keys(p.select("key")), knn(p, k))

    return build


def build_doc_dup(spark, sf_dir):
    docs = read(spark, sf_dir, "documents").select("doc_id", "text", "n_chars")
    lines = docs.select("doc_id", F.explode(F.split("text", "\n")).alias("l")).select("doc_id", F.lower(F.trim("l")).alias("l")).filter("length(l) >= 20")
    vertices = docs.select(F.col("doc_id").alias("key"), (F.floor(F.col("n_chars") / 1000) + 1).cast("long").alias("c"))
    made = partial(sharing, lines, "doc_id", "l")
    return RawGraph(vertices, made(), True, made)


def build_bench_doc(spark, sf_dir):
    def run_of(table, key, kind):
        t = read(spark, sf_dir, table).select(of_kind(kind, key).alias("k"), F.filter(F.split("text", r"\s+"), lambda x: x != "").alias("t")).filter("size(t) >= 8")
        return t.select("k", F.explode(F.transform(F.sequence(F.lit(1), F.size("t") - 7), lambda i: F.array_join(F.slice("t", i, 8), " "))).alias("r")).distinct()

    edges = run_of("benchmark", "item_id", 0).withColumnRenamed("k", "u").join(run_of("documents", "doc_id", 1).withColumnRenamed("k", "v"), "r").groupBy("u", "v").agg(F.count("*").alias("w"))
    return RawGraph(ends(edges), edges)


def build_turns(spark, sf_dir):
    t = read(spark, sf_dir, "conversations").select("conv_id", "turn", (F.col("conv_id") * F.lit(1 << 20) + F.col("turn")).alias("key"), F.greatest(F.lit(1), F.size(F.filter(F.split(F.coalesce("text", F.lit("")), " "), lambda x: x != ""))).alias("c"))
    pairs = t.select(F.col("key").alias("u"), F.lead("key").over(Window.partitionBy("conv_id").orderBy("turn")).alias("v"))
    return RawGraph(t.select("key", "c"), counted(pairs))


BUILDERS: dict[str, Callable[[SparkSession, str], RawGraph]] = {
    "trade": build_trade, "geo_tree": build_geo_tree, "copurchase": build_copurchase, "copurchase_sized": build_copurchase_sized, "custpart": build_custpart, "partsupp": build_partsupp,
    "order_star": build_order_star, "event_chain": build_event_chain, "user_slot": build_user_slot, "word": build_word, "link": build_link, "page_sim": build_page_sim,
    "emb_rgg2": _rgg(2, 0.03), "emb_rgg3": _rgg(3, 0.06), "emb_knn": _knn(8), "region_trade": build_region_trade, "doc_dup": build_doc_dup, "bench_doc": build_bench_doc, "turns": build_turns,
}

_loaded: dict[tuple[str, str, str], tuple[Graph, DataFrame]] = {}


def load_graph(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    """The graph with dense ids; built once for a session and directory."""
    at = (spark.sparkContext.applicationId, sf_dir, name)
    if at not in _loaded:
        raw = BUILDERS[name](spark, sf_dir)
        if raw.from_ends:  # vertices and arcs would both make the edges
            edges = stored(raw.edges)
            raw = replace(raw, vertices=ends(edges), edges=edges)
        _loaded[at] = densify(raw)
    return _loaded[at][0]


def densify_keys(g: Graph) -> DataFrame:
    """vid, key of a loaded graph."""
    return next(names for graph, names in _loaded.values() if graph is g)


K = str(KIND)
_PAIR = "SELECT least(u, v) AS u, greatest(u, v) AS v, count(*) AS w FROM ({}) WHERE u <> v GROUP BY ALL"
_ENDS = "SELECT key, 1 AS c FROM (SELECT u AS key FROM raw_e UNION SELECT v FROM raw_e)"


def _sql_rgg(dims: int, r: float) -> tuple[str, str]:
    apart = " + ".join(f"(a.embedding[{d}]::DOUBLE - b.embedding[{d}]::DOUBLE) * (a.embedding[{d}]::DOUBLE - b.embedding[{d}]::DOUBLE)" for d in range(1, dims + 1))
    return f"SELECT a.vec_id AS u, b.vec_id AS v, 1 AS w FROM embeddings a, embeddings b WHERE a.vec_id < b.vec_id AND {apart} < {r}::DOUBLE * {r}::DOUBLE", "SELECT vec_id AS key, 1 AS c FROM embeddings"


_RUN = "SELECT DISTINCT k, array_to_string(t[i:i + 7], ' ') AS r FROM (SELECT k, t, unnest(range(1, len(t) - 6)) AS i FROM (SELECT {key} AS k, list_filter(regexp_split_to_array(text, '\\s+'), lambda x: x <> '') AS t FROM {table}) WHERE len(t) >= 8)"
#: Edges and vertices of each graph in DuckDB's SQL; vertices may name raw_e, the edges.
SQL: dict[str, tuple[str, str]] = {
    "trade": (_PAIR.format("SELECT c_nationkey AS u, s_nationkey AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey"), "SELECT n_nationkey::BIGINT AS key, 1 AS c FROM nation"),
    "geo_tree": (_PAIR.format(f"SELECT n_regionkey::BIGINT AS u, {K} + n_nationkey AS v FROM nation UNION ALL SELECT {K} + c_nationkey, 2 * {K} + c_custkey FROM customer UNION ALL SELECT {K} + s_nationkey, 3 * {K} + s_suppkey FROM supplier"), f"SELECT r_regionkey::BIGINT AS key, 1 AS c FROM region UNION SELECT {K} + n_nationkey, 1 FROM nation UNION SELECT 2 * {K} + c_custkey, 1 FROM customer UNION SELECT 3 * {K} + s_suppkey, 1 FROM supplier"),
    "copurchase": ("SELECT a.l_partkey AS u, b.l_partkey AS v, count(*) AS w FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey WHERE a.l_partkey < b.l_partkey GROUP BY ALL", "SELECT p_partkey AS key, 1 AS c FROM part"),
    "copurchase_sized": ("SELECT a.l_partkey AS u, b.l_partkey AS v, count(*) AS w FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey WHERE a.l_partkey < b.l_partkey GROUP BY ALL", "SELECT p_partkey AS key, p_size AS c FROM part"),
    "custpart": (_PAIR.format(f"SELECT o_custkey AS u, {K} + l_partkey AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey"), f"SELECT c_custkey AS key, 1 AS c FROM customer UNION SELECT {K} + p_partkey, 1 FROM part"),
    "partsupp": (_PAIR.format(f"SELECT l_partkey AS u, {K} + l_suppkey AS v FROM lineitem"), f"SELECT p_partkey AS key, 1 AS c FROM part UNION SELECT {K} + s_suppkey, 1 FROM supplier"),
    "order_star": (_PAIR.format(f"SELECT o_orderkey AS u, {K} + o_custkey AS v FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem) UNION ALL SELECT l_orderkey, 2 * {K} + l_suppkey FROM lineitem"), f"SELECT DISTINCT o_orderkey AS key, 1 AS c FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem) UNION SELECT {K} + c_custkey, 1 FROM customer UNION SELECT 2 * {K} + s_suppkey, 1 FROM supplier"),
    "event_chain": (_PAIR.format("SELECT event_id AS u, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS v FROM events UNION ALL SELECT event_id, lead(event_id) OVER (PARTITION BY event_type ORDER BY ts, event_id) FROM events"), "SELECT event_id AS key, 1 AS c FROM events"),
    "user_slot": (_PAIR.format("SELECT 'u:' || user_id AS u, 's:' || event_type || ':' || strftime(ts, '%Y-%m-%d') AS v FROM events"), _ENDS),
    "word": (_PAIR.format("SELECT t[i] AS u, t[i + 1] AS v FROM (SELECT t, unnest(range(1, len(t))) AS i FROM (SELECT list_filter(string_split(lower(text), ' '), lambda x: x <> '') AS t FROM documents))"), _ENDS),
    "link": (_PAIR.format("SELECT 'p:' || page_id AS u, 't:' || x AS v FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS x FROM pages)"), "SELECT key, 1 AS c FROM (SELECT u AS key FROM raw_e UNION SELECT v FROM raw_e UNION SELECT 'p:' || page_id FROM pages)"),
    "page_sim": ("WITH l AS (SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS x FROM pages) SELECT a.page_id AS u, b.page_id AS v, count(*) AS w FROM l a JOIN l b ON a.x = b.x AND a.page_id < b.page_id GROUP BY ALL", "SELECT page_id AS key, 1 AS c FROM pages"),
    "region_trade": ("SELECT least(a.n_regionkey, b.n_regionkey)::BIGINT AS u, greatest(a.n_regionkey, b.n_regionkey)::BIGINT AS v, sum(w)::BIGINT AS w FROM (" + _PAIR.format("SELECT c_nationkey AS u, s_nationkey AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey") + ") JOIN nation a ON a.n_nationkey = u JOIN nation b ON b.n_nationkey = v WHERE a.n_regionkey <> b.n_regionkey GROUP BY ALL", "SELECT n_regionkey::BIGINT AS key, count(*) AS c FROM nation GROUP BY ALL"),
    "emb_knn": ("WITH x AS (SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS x FROM embeddings), nn AS (SELECT a.vec_id AS a, b.vec_id AS b, row_number() OVER (PARTITION BY a.vec_id ORDER BY round(list_cosine_similarity(a.x, b.x), 12) DESC, b.vec_id) AS r FROM x a JOIN x b ON a.vec_id <> b.vec_id) SELECT DISTINCT least(a, b) AS u, greatest(a, b) AS v, 1 AS w FROM nn WHERE r <= 8", "SELECT vec_id AS key, 1 AS c FROM embeddings"),
    "emb_rgg2": _sql_rgg(2, 0.03),
    "emb_rgg3": _sql_rgg(3, 0.06),
    "doc_dup": ("WITH l AS (SELECT DISTINCT doc_id, lower(trim(x)) AS l FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS x FROM documents) WHERE length(trim(x)) >= 20) SELECT a.doc_id AS u, b.doc_id AS v, count(*) AS w FROM l a JOIN l b ON a.l = b.l AND a.doc_id < b.doc_id GROUP BY ALL", "SELECT doc_id AS key, 1 + n_chars // 1000 AS c FROM documents"),
    "bench_doc": (f"SELECT a.k AS u, b.k AS v, count(*) AS w FROM ({_RUN.format(key='item_id', table='benchmark')}) a JOIN ({_RUN.format(key=K + ' + doc_id', table='documents')}) b ON a.r = b.r GROUP BY ALL", _ENDS),
    "turns": (_PAIR.format("SELECT conv_id * 1048576 + turn AS u, lead(conv_id * 1048576 + turn) OVER (PARTITION BY conv_id ORDER BY turn) AS v FROM conversations"), "SELECT conv_id * 1048576 + turn AS key, greatest(1, len(list_filter(string_split(coalesce(text, ''), ' '), lambda x: x <> ''))) AS c FROM conversations"),
}


def sql_graph(name: str) -> str:
    """Common table expressions raw_e, raw_v, ids (key, vid, c), e (u, v, w by id) and arcs (src, dst, w)."""
    edges, vertices = SQL[name]
    return f"""WITH RECURSIVE raw_e AS ({edges}), raw_v AS ({vertices}),
ids AS MATERIALIZED (SELECT key, row_number() OVER (ORDER BY key) - 1 AS vid, c::BIGINT AS c FROM raw_v),
e AS MATERIALIZED (SELECT a.vid AS u, b.vid AS v, w::BIGINT AS w FROM raw_e JOIN ids a ON a.key = u JOIN ids b ON b.key = v),
arcs AS (SELECT u AS src, v AS dst, w FROM e UNION ALL SELECT v, u, w FROM e)"""
