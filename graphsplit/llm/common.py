"""Helpers that the training-data operators share."""

from __future__ import annotations

import tempfile
from collections.abc import Callable, Iterator
from functools import reduce

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: A word is a maximal run of anything but space, tab, line feed, vertical tab, form feed and carriage return.
WORD = r"[^\x20\x09-\x0D]+"
GAP = r"[\x20\x09-\x0D]+"

#: Tables of at most so many rows may be broadcast; beyond it joins are salted.
BROADCAST_ROWS = 200_000


def unused(df: DataFrame, name: str) -> str:
    """name, with as many underscores more as it takes to clash with no column of df, in any case."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def checkpoint_folder(spark: SparkSession) -> None:
    """Takes the folder that the session names. Only a local master, whose tasks all see this machine, gets a temporary one without it."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        folder = sc.getConf().get("spark.checkpoint.dir")
        if not folder and not sc.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        sc.setCheckpointDir(folder or tempfile.mkdtemp(prefix="checkpoint-"))


def cut(df: DataFrame) -> DataFrame:
    """The same rows, written to the shared checkpoint folder of the session, so that lost executors and reruns read them there."""
    checkpoint_folder(df.sparkSession)
    saved = df.checkpoint(eager=True)
    # without the size estimates of the plan so far: they multiply from join to join, and planning a long loop would take ever longer
    session = df.sparkSession
    return DataFrame(session._jsparkSession.internalCreateDataFrame(saved._jdf.queryExecution().toRdd(), saved._jdf.schema(), False), session)


def words(text: Column) -> Column:
    """Array of the words of a text; empty for null."""
    return F.array_remove(F.split(F.coalesce(text, F.lit("")), GAP), "")


def let(value: Column, then) -> Column:
    """then(value), with value computed once for the row."""
    return F.get(F.transform(F.array(value), then), 0)


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def held_out(doc_id: Column, parts: int, part: int) -> Column:
    """Whether crc32 of the id as text falls in the given part; a null id never does."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % parts == part, F.lit(False))


def unit_hash(seed: str, key: Column) -> Column:
    """A number in (0, 1) from 48 bits of md5; DuckDB gives the same."""
    text = F.concat(F.lit(f"{seed}:"), F.coalesce(key.cast("string"), F.lit("null")))
    return (F.conv(F.substring(F.md5(text), 1, 12), 16, 10).cast("long") + F.lit(0.5)) / F.lit(float(2**48))


def join_small(big: DataFrame, small: DataFrame, keys: list[str], rows: int, how: str = "inner", salts: int = 64) -> DataFrame:
    """Null-safe join of a large table, skewed on its keys, with one of `rows` rows: broadcast up to BROADCAST_ROWS, salted beyond."""
    if rows <= BROADCAST_ROWS:
        other = small.select(*[F.col(k).alias(f"_k_{k}") for k in keys], *[c for c in small.columns if c not in keys])
        on = reduce(lambda a, b: a & b, [F.col(k).eqNullSafe(F.col(f"_k_{k}")) for k in keys])
        return big.join(F.broadcast(other), on, how).drop(*[f"_k_{k}" for k in keys])
    salted = big.withColumn("_salt", F.pmod(F.monotonically_increasing_id(), F.lit(salts)).cast("int"))
    other = small.select(*[F.col(k).alias(f"_k_{k}") for k in keys], *[c for c in small.columns if c not in keys], F.explode(F.sequence(F.lit(0), F.lit(salts - 1))).alias("_other"))
    on = reduce(lambda a, b: a & b, [F.col(k).eqNullSafe(F.col(f"_k_{k}")) for k in keys]) & (F.col("_salt") == F.col("_other"))
    # merged, as Spark may size `small` without its copies, and broadcast them all
    return salted.join(other.hint("merge"), on, how).drop("_salt", "_other", *[f"_k_{k}" for k in keys])


#: Rows whose texts are Python strings at one time.
PORTION = 256


def map_texts(df: DataFrame, keep: list[str], start: Callable[[], Callable[[list], list[list]]], added: list[tuple[str, str, pa.DataType]], text: str = "text") -> DataFrame:
    """Columns `keep` of df as they are, and those added (name, SQL type, Arrow type) that start()(texts) returns for whole texts, null ones included."""
    names = [*keep, *[n for n, _, _ in added]]
    schema = ", ".join([*[f"`{c}` {df.schema[c].dataType.simpleString()}" for c in keep], *[f"`{n}` {t}" for n, t, _ in added]])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        work = start()
        for batch in batches:
            for k in range(0, batch.num_rows, PORTION):
                part = batch.slice(k, PORTION)
                found = work(part.column(len(keep)).to_pylist())
                yield pa.RecordBatch.from_arrays([*[part.column(j) for j in range(len(keep))], *[pa.array(x, t) for x, (_, _, t) in zip(found, added, strict=True)]], names=names)

    return df.select(*[F.col(f"`{c}`") for c in keep], text).mapInArrow(run, schema)


def labelled(labels: DataFrame, label: str, held: Callable[[Column], Column], most: int, seed: str) -> DataFrame:
    """doc_id and y (0 or 1) of about `most` labelled rows that aren't held out, all of them if there are fewer; chosen by a hash of doc_id.

    A doc_id labelled more than once counts once, with its larger label.
    """
    own = labels.filter(F.col("doc_id").isNotNull() & F.col(label).isin(0, 1) & ~held(F.col("doc_id"))).groupBy("doc_id").agg(F.max(label).cast("int").alias("y"))
    own = cut(own.withColumn("_u", unit_hash(seed, F.col("doc_id"))))
    return own.filter(F.col("_u") < most / max(most, own.count())).drop("_u")
