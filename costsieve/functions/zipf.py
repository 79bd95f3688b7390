"""Skewed costs: rank r weighs r to the power of minus the skew, over a seeded shuffle of the keys."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .keys import number


def order_of(seed: int, key: Column) -> Column:
    return number(F.concat(F.lit(f"z{seed}:"), key))


def ranked(df: DataFrame, seed: int, buckets: int = 256) -> DataFrame:
    """``df`` with ``rank`` from 1 in the order of the seeded hash.

    The hash is uniform over 60 bits, so its leading bits cut it into ranges of equal size; each range is ranked on its own and starts where the ranges
    before it end. No task sees more than its ranges.
    """
    bits = buckets.bit_length() - 1
    coded = df.withColumn("__o", order_of(seed, F.col("k"))).withColumn("__b", F.shiftright("__o", 60 - bits))
    sizes = coded.groupBy("__b").agg(F.count(F.lit(1)).alias("__n"))
    starts = sizes.select("__b", F.coalesce(F.sum("__n").over(Window.orderBy("__b").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("__s"))
    within = F.row_number().over(Window.partitionBy("__b").orderBy("__o", "k"))
    return coded.join(F.broadcast(starts), "__b").withColumn("rank", within + F.col("__s")).drop("__o", "__b", "__s")  # at most ``buckets`` rows


def costs(df: DataFrame, skew: float, seed: int = 1) -> DataFrame:
    """``df`` with its cost replaced; a skew of 0 gives 1 to all."""
    if not skew:
        return df.withColumn("cost", F.lit(1.0))
    return ranked(df, seed).withColumn("cost", F.pow(F.col("rank").cast("double"), F.lit(-float(skew)))).drop("rank")


def duck_rank(keys: str, seed: int) -> str:
    """SQL over a query that gives k: the same ranks."""
    return f"SELECT *, row_number() OVER (ORDER BY ('0x' || substr(md5('z{seed}:' || k), 1, 15))::BIGINT, k) AS rank FROM ({keys})"
