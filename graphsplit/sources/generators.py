"""Synthetic graphs, deterministic by seed: geometric, hyperbolic, lattices, planted blocks, and small ones with known cuts."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphsplit.functions.columns import coin
from graphsplit.model import Graph, dense_ids, snapshot, symmetrize
from graphsplit.sources.graphs import geometric, read


def uniform(seed: int, tag: str, key) -> F.Column:
    """In (0, 1), from 32 bits of a hash."""
    return (coin(seed, tag, key) + F.lit(0.5)) / F.lit(float(2**32))


def graph_of(spark: SparkSession, n: int, edges: DataFrame) -> Graph:
    vertices = spark.range(n).select(F.col("id").alias("vid"), F.lit(1).cast("long").alias("c"))
    return Graph.of(vertices, snapshot(symmetrize(edges.select("u", "v", F.col("w").cast("long").alias("w")))))


def points(spark: SparkSession, n: int, dims: list[str], seed: int) -> DataFrame:
    return spark.range(n).select(F.col("id").alias("key"), *[uniform(seed, d, F.col("id")).alias(d) for d in dims])


def embedded(spark: SparkSession, sf_dir: str, dims: list[str], first: int = 2) -> DataFrame:
    """key and coordinates in [0, 1) of the given vectors: fractions of 1024 times their components from `first` on."""
    scaled = [F.get("embedding", F.lit(first + k)).cast("double") * 1024 for k in range(len(dims))]
    points = read(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("key"), *[(x - F.floor(x)).alias(d) for d, x in zip(dims, scaled, strict=True)])
    return points.dropna(subset=dims)


def near(points: DataFrame, dims: list[str], degree: float) -> DataFrame:
    """Edges of points in the unit square or cube, with the radius at which a point has `degree` neighbours on average (fewer at the rim)."""
    n = max(1, points.count())
    return geometric(points, dims, math.sqrt(degree / (math.pi * n)) if len(dims) == 2 else (3 * degree / (4 * math.pi * n)) ** (1 / 3))


def rgg2d(spark: SparkSession, log_n: int, degree: float, seed: int = 1) -> Graph:
    return graph_of(spark, 1 << log_n, near(points(spark, 1 << log_n, ["x", "y"], seed), ["x", "y"], degree))


def rgg3d(spark: SparkSession, log_n: int, degree: float, seed: int = 1) -> Graph:
    return graph_of(spark, 1 << log_n, near(points(spark, 1 << log_n, ["x", "y", "z"], seed), ["x", "y", "z"], degree))


def rhg(spark: SparkSession, log_n: int, degree: float, gamma: float = 3.0, seed: int = 1) -> Graph:
    return graph_of(spark, 1 << log_n, hyperbolic(points(spark, 1 << log_n, ["r", "phi"], seed), degree, gamma))


def hyperbolic(points: DataFrame, degree: float, gamma: float = 3.0) -> DataFrame:
    """Edges of a hyperbolic random graph: radii with density growing as exp(alpha r), edges below distance R, power law exponent gamma.

    points: key, r and phi in [0, 1), from which radius and angle follow. Points are laid in annuli; a point meets those of each annulus within
    the angle at which they can still be near.
    """
    n, alpha = max(1, points.count()), (gamma - 1) / 2
    xi = alpha / (alpha - 0.5)
    radius = 2 * math.log(2 * n * xi * xi / (math.pi * degree))
    p = points.select("key", (F.acosh(F.lit(1.0) + (math.cosh(alpha * radius) - 1) * F.col("r")) / alpha).alias("r"), (F.col("phi") * 2 * math.pi).alias("phi"))
    ring = snapshot(p.withColumn("ring", F.greatest(F.lit(0), F.floor(F.lit(radius) - F.col("r"))).cast("int")))
    rings = int(radius) + 1
    # rings are counted from the rim; cells of an outer ring are as narrow as the angle that its inner edge allows
    cells = [max(1, int(2 * math.pi / max(1e-9, 2 * math.exp((radius - max(0.5, radius - a - 1) * 2) / 2)))) for a in range(rings + 1)]
    count = F.element_at(F.array(*[F.lit(c) for c in cells]), F.col("ring") + 1)
    home = ring.withColumn("cell", F.floor(F.col("phi") / (2 * math.pi) * count))
    # a pair meets in the cells of the outer one's ring: the inner one visits all cells within its reach there
    other = ring.withColumnsRenamed({"key": "k2", "r": "r2", "phi": "phi2", "ring": "ring2"}).withColumn("ring", F.explode(F.sequence(F.lit(0), F.col("ring2"))))
    reach = F.acos(F.greatest(F.lit(-1.0), F.least(F.lit(1.0), (F.cosh("r2") * F.cosh(F.greatest(F.lit(0.1), F.lit(radius) - F.col("ring") - 1)) - math.cosh(radius)) / F.greatest(F.lit(1e-9), F.sinh("r2") * F.sinh(F.greatest(F.lit(0.1), F.lit(radius) - F.col("ring") - 1))))))
    other = other.withColumn("_n", count).withColumn("_a", F.floor((F.col("phi2") - reach) / (2 * math.pi) * F.col("_n"))).withColumn("_b", F.floor((F.col("phi2") + reach) / (2 * math.pi) * F.col("_n")))
    visits = other.withColumn("_b", F.least("_b", F.col("_a") + F.col("_n") - 1)).withColumn("_k", F.explode(F.sequence("_a", "_b"))).withColumn("cell", F.pmod("_k", "_n").cast("long"))
    near = F.cosh("r") * F.cosh("r2") - F.sinh("r") * F.sinh("r2") * F.cos(F.col("phi") - F.col("phi2")) < F.lit(math.cosh(radius))
    pairs = home.join(visits.select("k2", "r2", "phi2", "ring2", "ring", "cell"), ["ring", "cell"]).filter((F.col("key") != F.col("k2")) & near)
    return pairs.select(F.least("key", "k2").alias("u"), F.greatest("key", "k2").alias("v")).distinct().withColumn("w", F.lit(1).cast("long"))


def lattice(ids: DataFrame, n: int, b: int) -> DataFrame:
    """Edges of a lattice of n places in rows of b; the last row may be shorter. ids: u, the places from 0 to n - 1."""
    right = ids.filter((F.col("u") % b < b - 1) & (F.col("u") + 1 < n)).select("u", (F.col("u") + 1).alias("v"))
    down = ids.filter(F.col("u") + b < n).select("u", (F.col("u") + b).alias("v"))
    return right.union(down).withColumn("w", F.lit(1).cast("long"))


def grid2d(spark: SparkSession, a: int, b: int) -> Graph:
    return graph_of(spark, a * b, lattice(spark.range(a * b).select(F.col("id").alias("u")), a * b, b))


def ordered(spark: SparkSession, sf_dir: str, b: int) -> Graph:
    """The given vectors, in order of their first component, as places of a lattice in rows of b."""
    place = F.struct(F.get("embedding", F.lit(0)).alias("x"), "vec_id")
    ids = snapshot(dense_ids(read(spark, sf_dir, "embeddings").select(place.alias("key")), "key", "u").select("u"))
    return Graph.of(ids.select(F.col("u").alias("vid"), F.lit(1).cast("long").alias("c")), snapshot(symmetrize(lattice(ids, ids.count(), b))))


def planted(spark: SparkSession, k: int, size: int, inside: int, across: int, seed: int = 1) -> Graph:
    """k blocks of consecutive ids; every vertex draws `inside` partners in its block and `across` anywhere."""
    n = k * size
    draw = spark.range(n).select(F.col("id").alias("a"), F.explode(F.sequence(F.lit(0), F.lit(inside + across - 1))).alias("j"))
    own = F.floor(F.col("a") / size) * size + coin(seed, "own", F.col("a"), F.col("j")) % size
    b = F.when(F.col("j") < inside, own).otherwise(coin(seed, "any", F.col("a"), F.col("j")) % n)
    e = draw.withColumn("b", b).filter("a <> b").groupBy(F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v")).agg(F.count("*").alias("w"))
    return graph_of(spark, n, e)


def two_cliques(spark: SparkSession, size: int = 4) -> Graph:
    edges = [(h + a, h + b, 1) for h in (0, size) for a in range(size) for b in range(a + 1, size)] + [(size - 1, size, 1)]
    return graph_of(spark, 2 * size, spark.createDataFrame(edges, "u long, v long, w long"))


def path(spark: SparkSession, n: int) -> Graph:
    return graph_of(spark, n, spark.range(n - 1).select(F.col("id").alias("u"), (F.col("id") + 1).alias("v"), F.lit(1).alias("w")))


def star(spark: SparkSession, leaves: int) -> Graph:
    return graph_of(spark, leaves + 1, spark.range(1, leaves + 1).select(F.lit(0).cast("long").alias("u"), F.col("id").alias("v"), F.lit(1).alias("w")))
