"""Reading edge lists and adjacency text, writing partitions, saving and loading models."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphsplit.model import RawGraph

EDGES = "u long, v long, w long"


def clean(edges: DataFrame) -> DataFrame:
    """u < v with summed weights; loops, nulls and weights below 1 go; a missing weight is 1."""
    e = edges.select("u", "v", F.coalesce("w", F.lit(1)).cast("long").alias("w")).filter("u is not null and v is not null and u <> v and w >= 1")
    return e.groupBy(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).agg(F.sum("w").alias("w"))


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet", schema: str = EDGES, **options) -> RawGraph:
    """A raw graph from u, v[, w] in parquet, orc, json, csv or tsv. Malformed lines of text formats are dropped."""
    reader = spark.read.schema(schema)
    if fmt in ("csv", "tsv"):
        df = reader.options(sep="\t" if fmt == "tsv" else ",", mode="DROPMALFORMED", **options).csv(path)
    else:
        df = reader.options(**({"mode": "DROPMALFORMED"} if fmt == "json" else {}), **options).format(fmt).load(path)
    edges = clean(df if "w" in df.columns else df.withColumn("w", F.lit(1)))
    return RawGraph(edges.select(F.col("u").alias("key")).union(edges.select("v")).distinct().withColumn("c", F.lit(1)), edges)


def malformed(spark: SparkSession, path: str, schema: str = EDGES, sep: str = ",") -> DataFrame:
    """The lines of a text file that don't fit the schema."""
    line = spark.read.text(path)
    parsed = F.from_csv("value", schema + ", _bad string", {"sep": sep, "mode": "PERMISSIVE", "columnNameOfCorruptRecord": "_bad"})
    return line.select(parsed.getField("_bad").alias("_corrupt_record")).filter("_corrupt_record is not null")


def read_adjacency_text(spark: SparkSession, path: str) -> RawGraph:
    """Lines `vertex weight: neighbour weight, neighbour weight ...`; each edge may stand at one end or at both, with one weight."""
    line = spark.read.text(path).filter(F.col("value").rlike(r"^\s*[0-9]+\s+[0-9]+\s*:"))
    head = F.split(F.trim(F.substring_index("value", ":", 1)), r"\s+")
    rows = line.select(head[0].cast("long").alias("key"), head[1].cast("long").alias("c"), F.explode_outer(F.regexp_extract_all("value", F.lit(r"([0-9]+\s+[0-9]+)\s*(?:,|$)"), F.lit(1))).alias("a"))
    arcs = rows.filter("a is not null").select(F.col("key").alias("u"), F.split("a", r"\s+")[0].cast("long").alias("v"), F.split("a", r"\s+")[1].cast("long").alias("w"))
    edges = arcs.filter("u <> v").groupBy(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).agg(F.max("w").alias("w"))
    return RawGraph(rows.groupBy("key").agg(F.max("c").alias("c")), edges)


def write_partition(partition: DataFrame, path: str, layout: str = "block") -> None:
    """vid, block as parquet: a directory for each block, or sorted by vid."""
    if layout == "block":
        partition.repartition("block").write.mode("overwrite").partitionBy("block").parquet(path)
    else:
        partition.repartitionByRange("vid").sortWithinPartitions("vid").write.mode("overwrite").parquet(path)


def split_table(table: DataFrame, key: str, partition: DataFrame, path: str) -> None:
    """Any table, laid out by the block of its key. partition: key, block."""
    table.join(partition, key).repartition("block").write.mode("overwrite").partitionBy("block").parquet(path)


def save_model(spark: SparkSession, path: str, partition: DataFrame, params: dict) -> None:
    write_partition(partition, f"{path}/partition", "vid")
    spark.createDataFrame([(json.dumps(params, sort_keys=True),)], "params string").coalesce(1).write.mode("overwrite").json(f"{path}/params")


def load_model(spark: SparkSession, path: str) -> tuple[DataFrame, dict]:
    return spark.read.parquet(f"{path}/partition"), json.loads(spark.read.schema("params string").json(f"{path}/params").first()["params"])
