"""Graphs as DataFrames.

A graph has vertices (vid, c) with dense ids and positive integer weights, and arcs (src, dst, w): each undirected edge is stored from both
ends, so that sums over arcs count edges twice. Raw graphs, as built from tables, have keys instead of ids and each edge once.
"""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable
from dataclasses import dataclass
from functools import cached_property

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def checkpoint_folder(spark: SparkSession) -> str:
    """The folder that the session names. Only a local master, whose tasks all see this machine, gets a temporary one without it."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        folder = sc.getConf().get("spark.checkpoint.dir")
        if not folder and not sc.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        sc.setCheckpointDir(folder or tempfile.mkdtemp(prefix="checkpoint-"))
    return sc.getCheckpointDir()


def written(df: DataFrame, by: str) -> DataFrame:
    """The same rows, written to the shared checkpoint folder as a table with a directory for each value of a column, which filters prune."""
    spark = df.sparkSession
    at = f"{checkpoint_folder(spark)}/table-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").partitionBy(by).parquet(at)
    return at_path(spark.read.schema(df.schema).parquet(at), at)


def unsized(df: DataFrame) -> DataFrame:
    """The same rows without the size estimates of the plan so far: they multiply from join to join, and planning a long loop would take ever longer."""
    session = df.sparkSession
    return DataFrame(session._jsparkSession.internalCreateDataFrame(df._jdf.queryExecution().toRdd(), df._jdf.schema(), False), session)


def snapshot(df: DataFrame) -> DataFrame:
    """The same rows, written to the shared checkpoint folder, with the lineage cut."""
    checkpoint_folder(df.sparkSession)
    cut = df.checkpoint(eager=True)
    at = cut._jdf.queryExecution().logical().rdd().getCheckpointFile()
    return at_path(unsized(cut), at.get() if at.isDefined() else None)


def stored(df: DataFrame) -> DataFrame:
    """A snapshot as a compressed table, for rows of numbers in great number: arcs take a few bytes instead of some fifty."""
    spark = df.sparkSession
    at = f"{checkpoint_folder(spark)}/table-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(at)
    return at_path(unsized(spark.read.schema(df.schema).parquet(at)), at)


def at_path(df: DataFrame, at: str | None) -> DataFrame:
    """df, knowing where its rows were written."""
    df._written_at = at
    return df


def discard(df: DataFrame) -> None:
    """Deletes the rows of a `snapshot`, `stored` or `written` table that nothing reads any more; what was made from them must be written itself."""
    at = getattr(df, "_written_at", None)
    if at:
        spark = df.sparkSession
        path = spark._jvm.org.apache.hadoop.fs.Path(at)
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


@dataclass(frozen=True)
class RawGraph:
    vertices: DataFrame  # key, c
    edges: DataFrame  # u, v, w with u < v
    closed: bool = False  # whether both ends of every edge are among the vertices
    by_id: Callable[[DataFrame], DataFrame] | None = None  # makes the edges with ids at once, from a table key, vid
    from_ends: bool = False  # whether the vertices are the ends of the edges, made from them


@dataclass(frozen=True)
class Graph:
    """total and heaviest are those of one copy: a graph may hold several copies of one, numbered in a column `copy` of its vertices.

    copies: the first id and the number of vertices of each; ids of a copy are consecutive, and no arc leads to another copy.
    """

    vertices: DataFrame
    edges: DataFrame
    n: int
    arcs: int
    total: int
    heaviest: int
    copies: tuple[tuple[int, int], ...] = ()

    def __post_init__(self):
        if not self.copies:
            object.__setattr__(self, "copies", ((0, self.n),))

    @property
    def m(self) -> int:
        return self.arcs // 2

    @staticmethod
    def of(vertices: DataFrame, edges: DataFrame) -> Graph:
        return Graph(vertices, edges, arcs=edges.count(), **sizes(vertices))

    def degrees(self) -> DataFrame:
        """vid, deg of the vertices with arcs."""
        return self.edges.groupBy(F.col("src").alias("vid")).agg(F.count("*").alias("deg"))

    def validate(self) -> DataFrame:
        """A row (problem, a, b) for each violation: weights below 1, loops, repeated arcs, arcs without their reverse or without ends."""
        e = self.edges
        ends = e.select(F.explode(F.array("src", "dst")).alias("vid")).distinct()
        # an arc and its reverse, and no more: for all other pairs their arcs are looked at
        turn = F.when(F.col("src") < F.col("dst"), 1).when(F.col("src") > F.col("dst"), -1).otherwise(0)
        pair = [F.least("src", "dst").alias("_a"), F.greatest("src", "dst").alias("_b")]
        unknown = (F.col("src").isNull() | F.col("dst").isNull() | F.col("w").isNull()).cast("int")
        counts = e.groupBy(*pair).agg(F.count("*").alias("_n"), F.sum(turn).alias("_t"), F.sum(turn * F.col("w")).alias("_w"), F.sum(unknown).alias("_u"))
        odd = snapshot(counts.filter("_u > 0 or _n <> if(_a = _b, 1, 2) or _t <> 0 or _w <> 0").select(F.col("_a").alias("_x"), F.col("_b").alias("_y")))
        every = e
        if odd.isEmpty():
            e = e.limit(0)
        else:
            e = e.select("*", *pair).join(odd, F.col("_a").eqNullSafe(F.col("_x")) & F.col("_b").eqNullSafe(F.col("_y")), "left_semi").drop("_a", "_b")
        found = [
            self.vertices.filter("c is null or c < 1").select(F.lit("vertex weight").alias("problem"), F.col("vid").alias("a"), F.col("vid").alias("b")),
            every.filter("w is null or w < 1").select(F.lit("edge weight").alias("problem"), F.col("src").alias("a"), F.col("dst").alias("b")),
            every.filter("src = dst").select(F.lit("loop").alias("problem"), F.col("src").alias("a"), F.col("dst").alias("b")),
            e.groupBy("src", "dst").count().filter("count > 1").select(F.lit("repeated arc").alias("problem"), F.col("src").alias("a"), F.col("dst").alias("b")),
            e.join(e.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w"), ["src", "dst", "w"], "left_anti").select(F.lit("no reverse").alias("problem"), F.col("src").alias("a"), F.col("dst").alias("b")),
            ends.join(self.vertices, "vid", "left_anti").select(F.lit("missing end").alias("problem"), F.col("vid").alias("a"), F.col("vid").alias("b")),
        ]
        out = found[0]
        for df in found[1:]:
            out = out.union(df)
        return out


def sizes(vertices: DataFrame) -> dict:
    """n, total, heaviest and copies of a graph with these vertices."""
    by = ["copy"] if "copy" in vertices.columns else []
    found = vertices.groupBy(*by).agg(F.min("vid").alias("off"), F.count("*").alias("n"), F.coalesce(F.sum("c"), F.lit(0)).alias("c"), F.coalesce(F.max("c"), F.lit(0)).alias("top")).collect()  # a row for each copy
    found.sort(key=lambda r: r["off"] or 0)
    if not found:
        return {"n": 0, "total": 0, "heaviest": 0}
    return {"n": sum(r["n"] for r in found), "total": found[0]["c"], "heaviest": max(r["top"] for r in found), "copies": tuple((r["off"] or 0, r["n"]) for r in found)}


class LaterArcs(Graph):
    """A graph whose arcs are made when they are first asked for. What is measured on vertices alone, or on degrees, never makes them.

    count: gives the degrees without arcs, where that is known to be the same.
    """

    def __init__(self, vertices: DataFrame, make: Callable[[], DataFrame], count: Callable[[], DataFrame] | None = None):
        for name, value in {"vertices": vertices, "copies": (), "_make": make, "_count": count, **sizes(vertices)}.items():
            object.__setattr__(self, name, value)
        self.__post_init__()

    @cached_property
    def edges(self) -> DataFrame:
        return self._make()

    @cached_property
    def arcs(self) -> int:
        return self.edges.count()

    def degrees(self) -> DataFrame:
        return super().degrees() if "edges" in self.__dict__ or self._count is None else self._count()


def dense_ids(df: DataFrame, key: str, out: str = "vid") -> DataFrame:
    """df with consecutive ids in order of a unique key: a range sort, ranks in each partition, and the partitions' offsets (a row each)."""
    ranked = snapshot(df.repartitionByRange(F.col(key)).sortWithinPartitions(key).withColumn("_m", F.monotonically_increasing_id()))
    part = F.shiftright("_m", 33)
    sizes = ranked.groupBy(part.alias("_p")).agg(F.count("*").alias("_n"))
    offsets = sizes.select(F.col("_p").alias("_part"), (F.sum("_n").over(Window.orderBy("_p").rowsBetween(Window.unboundedPreceding, 0)) - F.col("_n")).alias("_o"))
    joined = ranked.join(F.broadcast(offsets), part == F.col("_part"))
    return joined.withColumn(out, F.col("_o") + F.col("_m").bitwiseAND((1 << 33) - 1)).drop("_m", "_part", "_o")


def symmetrize(edges: DataFrame) -> DataFrame:
    """Arcs src, dst, w from edges u, v, w."""
    return edges.select(F.explode(F.array(F.struct(F.col("u").alias("src"), F.col("v").alias("dst"), "w"), F.struct(F.col("v").alias("src"), F.col("u").alias("dst"), "w"))).alias("a")).select("a.*")


def densify(raw: RawGraph) -> tuple[Graph, DataFrame]:
    """The graph with ids in order of keys, and the table vid, key. Its arcs are made when they are first asked for."""
    ids = snapshot(dense_ids(raw.vertices.select("key", F.col("c").cast("long").alias("c")), "key"))
    named = ids.select("key", "vid")

    def arcs() -> DataFrame:
        if raw.by_id:
            return symmetrize(stored(raw.by_id(named)))
        e = raw.edges.join(named.withColumnsRenamed({"key": "u", "vid": "_u"}), "u").join(named.withColumnsRenamed({"key": "v", "vid": "_v"}), "v")
        return symmetrize(stored(e.select(F.col("_u").alias("u"), F.col("_v").alias("v"), F.col("w").cast("long").alias("w"))))

    def degrees() -> DataFrame:
        return raw.edges.select(F.explode(F.array("u", "v")).alias("key")).groupBy("key").agg(F.count("*").alias("deg")).join(named, "key").select("vid", "deg")

    return LaterArcs(ids.select("vid", "c"), arcs, degrees if raw.closed else None), ids.select("vid", "key")
