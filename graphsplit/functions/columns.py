"""Column functions and scalars of the method."""

from __future__ import annotations

import math

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def coin(seed: int, tag: str, *keys: Column) -> Column:
    """A 32-bit number from md5 of seed, tag and keys; the same in any engine, run or retried task."""
    text = F.concat_ws(":", F.lit(str(seed)), F.lit(tag), *[k.cast("string") for k in keys])
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long")


def relative_gain(gain: Column, c: Column) -> Column:
    return F.when(gain >= 0, (gain * c).cast("double")).otherwise(gain / c)


def degree_bucket(degree: Column) -> Column:
    """i for degrees from 2^i below 2^(i+1); -1 for isolated vertices."""
    return F.when(degree > 0, F.length(F.bin(degree)) - 1).otherwise(F.lit(-1))


def power_above(x: Column) -> Column:
    """Least power of two that is at least the positive integer x."""
    return F.when(x <= 1, F.lit(1).cast("long")).otherwise(F.shiftleft(F.lit(1).cast("long"), F.length(F.bin(x - 1))))


def ceil2(x: float) -> int:
    return 1 if x <= 1 else 1 << math.ceil(math.log2(x) - 1e-12)


def l_max(total: int, k: int, eps: float, heaviest: int) -> float:
    """Most weight of a block: the relative slack, or the mean and the heaviest vertex, whichever is more."""
    return max((1 + eps) * total / k, total / k + heaviest)


def l_classic(total: int, k: int, eps: float) -> float:
    return (1 + eps) * math.ceil(total / k)


def block_limit(total: int, k: int, eps: float, heaviest: int, span: int) -> float:
    """l_max of a block that will become `span` of the k final blocks."""
    return max((1 + eps) * total * span / k, total * span / k + heaviest)


def max_cluster_weight(total: int, n: int, k: int, c: int, eps: float) -> float:
    return eps * total / max(1.0, min(k, n / c))


def target_blocks(n: int, k: int, c: int) -> int:
    return min(k, ceil2(n / c))


def num_batches(pes: int, alpha: int = 8, beta: int = 128) -> int:
    return max(alpha, -(-beta // pes))


def num_copies(n: int, c: int, pes: int) -> int:
    return pes // min(pes, ceil2(n / c)) if n < c * pes else 1


#: SQL functions: name, parameters, type, body.
SQL_FUNCTIONS = (
    ("pow2ceil", "x BIGINT", "BIGINT", "CASE WHEN x <= 1 THEN 1 ELSE shiftleft(1L, length(bin(x - 1))) END"),
    ("relative_gain", "gain BIGINT, c BIGINT", "DOUBLE", "CASE WHEN gain >= 0 THEN CAST(gain * c AS DOUBLE) ELSE CAST(gain AS DOUBLE) / c END"),
    ("l_max", "total BIGINT, k INT, eps DOUBLE, heaviest BIGINT", "DOUBLE", "greatest((1 + eps) * total / k, CAST(total AS DOUBLE) / k + heaviest)"),
    ("w_max", "total BIGINT, n BIGINT, k INT, c INT, eps DOUBLE", "DOUBLE", "eps * total / greatest(1D, least(CAST(k AS DOUBLE), CAST(n AS DOUBLE) / c))"),
)


def register(spark: SparkSession) -> None:
    """Makes the functions known to spark.sql of this session."""
    for name, parameters, kind, body in SQL_FUNCTIONS:
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({parameters}) RETURNS {kind} RETURN {body}")
