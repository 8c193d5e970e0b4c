"""Tables over runs (algorithm, graph, k, seed, cut, feasible, status, seconds): means, profiles, ratios, scaling."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

RUNS = "algorithm string, graph string, k int, seed int, cut long, feasible boolean, status string, seconds double"
INSTANCE = ["graph", "k"]


def aggregate_seeds(runs: DataFrame) -> DataFrame:
    """Arithmetic means over seeds; a run that isn't ok and feasible spoils its instance for the algorithm."""
    good = (F.col("status") == "ok") & F.col("feasible")
    return runs.groupBy("algorithm", *INSTANCE).agg(F.avg("cut").alias("cut"), F.avg("seconds").alias("seconds"), F.bool_and(good).alias("solved"), F.count("*").alias("seeds"))


def geo_mean(df: DataFrame, column: str, keys: list[str], shift: float = 0.0) -> DataFrame:
    """Geometric mean of a column by keys; with shift=1 zeros count too."""
    x = F.col(column) + F.lit(shift)
    return df.groupBy(*keys).agg((F.exp(F.avg(F.when(x > 0, F.log(x)))) - F.lit(shift)).alias(f"geo_{column}"))


def performance_profile(means: DataFrame, taus: list[float]) -> DataFrame:
    """algorithm, tau, share: of instances on which the algorithm is within tau of the best. Unsolved ones never count."""
    best = F.min(F.when(F.col("solved"), F.col("cut"))).over(Window.partitionBy(*INSTANCE))
    grid = means.sparkSession.createDataFrame([(float(t),) for t in taus], "tau double")
    within = F.col("solved") & (F.col("cut") <= F.col("tau") * F.col("_best"))
    return means.withColumn("_best", best).crossJoin(F.broadcast(grid)).groupBy("algorithm", "tau").agg(F.avg(F.when(within, 1.0).otherwise(0.0)).alias("share"))


def best_share(means: DataFrame) -> DataFrame:
    return performance_profile(means, [1.0]).drop("tau")


def common_instances(runs: DataFrame) -> DataFrame:
    """Runs of the instances on which every run is feasible or hit the time limit; time averages are only taken over these."""
    fine = F.bool_and(((F.col("status") == "ok") & F.col("feasible")) | (F.col("status") == "timeout")).over(Window.partitionBy(*INSTANCE))
    return runs.withColumn("_all", fine).filter("_all").drop("_all")


def cut_ratio(means: DataFrame, baseline: str) -> DataFrame:
    """algorithm, graph, k, ratio: cut over the baseline's."""
    base = means.filter((F.col("algorithm") == baseline) & F.col("solved")).select(*INSTANCE, F.col("cut").alias("_base"))
    return means.filter("solved").join(base, INSTANCE).filter("_base > 0").select("algorithm", *INSTANCE, (F.col("cut") / F.col("_base")).alias("ratio"))


def throughput(means: DataFrame, sizes: DataFrame) -> DataFrame:
    """Undirected edges per second. sizes: graph, m."""
    return means.join(F.broadcast(sizes), "graph").select("algorithm", *INSTANCE, (F.col("m") / F.col("seconds")).alias("edges_per_second"))


def scaling_table(series: DataFrame) -> DataFrame:
    """series (algorithm, graph, cores, seconds) with speedup against the fewest cores, and the share of the ideal."""
    first = Window.partitionBy("algorithm", "graph").orderBy("cores")
    out = series.withColumn("speedup", F.first("seconds").over(first) / F.col("seconds")).withColumn("_c", F.first("cores").over(first))
    return out.withColumn("efficiency", F.col("speedup") * F.col("_c") / F.col("cores")).drop("_c")


def cut_cube(runs: DataFrame) -> DataFrame:
    """Mean cuts over all combinations of graph, k and algorithm, with totals."""
    return runs.cube("graph", "k", "algorithm").agg(F.avg("cut").alias("cut"), F.count("*").alias("runs"), F.grouping_id().alias("level"))
