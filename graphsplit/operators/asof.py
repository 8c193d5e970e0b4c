"""As-of join: for each row the last row of another table that isn't later."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def asof(left: DataFrame, right: DataFrame, by: str, at: str, slot: float) -> DataFrame:
    """left with a column `found`: the row of right, as a struct, with the same `by` and the greatest `at` that isn't above left's; null without one.

    `at` is a number. Of right rows at one place the greatest row counts. Null keys and places find nothing. Both tables are united and
    filled forward inside slots of the given width, so that a key with many rows is spread over its slots; what a slot starts with comes
    from the last rows of earlier slots, one row for each key and slot.
    """
    at_slot = F.floor(F.col(at) / F.lit(float(slot)))
    row = F.struct(*[F.col(f"`{c}`") for c in left.columns])
    there = right.filter(F.col(by).isNotNull() & F.col(at).isNotNull())
    kind = F.struct(*[F.col(f"`{c}`") for c in there.columns])
    ours = left.select(F.col(by).alias("_by"), F.col(at).alias("_at"), at_slot.alias("_slot"), F.lit(1).alias("_side"), row.alias("_row"), F.lit(None).cast(there.select(kind.alias("k")).schema["k"].dataType).alias("_found"))
    theirs = there.select(F.col(by).alias("_by"), F.col(at).alias("_at"), at_slot.alias("_slot"), F.lit(0).alias("_side"), F.lit(None).cast(left.select(row.alias("r")).schema["r"].dataType).alias("_row"), kind.alias("_found"))
    inside = Window.partitionBy("_by", "_slot").orderBy("_at", "_side", "_found").rowsBetween(Window.unboundedPreceding, 0)
    filled = ours.unionByName(theirs).withColumn("_found", F.last("_found", ignorenulls=True).over(inside)).filter("_side = 1")
    ends = theirs.groupBy("_by", "_slot").agg(F.max(F.struct("_at", "_found")).alias("_end"))
    # what a slot starts with: the end of the last slot before it that right has; a row for each key and slot of either table
    wanted = filled.filter("_found is null").select("_by", "_slot").distinct()
    before = Window.partitionBy("_by").orderBy("_slot").rowsBetween(Window.unboundedPreceding, -1)
    every = wanted.join(ends.select("_by", "_slot", F.col("_end._found").alias("_last")), ["_by", "_slot"], "full")
    first = every.select("_by", "_slot", F.last("_last", ignorenulls=True).over(before).alias("_carried"))
    joined = filled.join(first, ["_by", "_slot"], "left")
    return joined.select("_row.*", F.coalesce("_found", "_carried").alias("found"))
