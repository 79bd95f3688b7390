"""Global ranks without a task that sees all rows: rows are cut into ranges of their order, ranked inside, and each range starts where those before it end."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..sources.shared import Staging


def _before(sizes: DataFrame, *sums: str) -> DataFrame:
    """(__p, and for each of ``sums`` what the ranges before hold); one row per range, as many as shuffle partitions."""
    earlier = Window.orderBy("__p").rowsBetween(Window.unboundedPreceding, -1)
    return sizes.select("__p", *[F.coalesce(F.sum(c).over(earlier), F.lit(0)).alias(f"{c}_before") for c in sums])


def placed(df: DataFrame, order: list[Column], weight: Column | None = None) -> DataFrame:
    """``df`` with ``place`` from 1 in ``order``, which must tell all rows apart, and with ``upto``, the sum of ``weight`` up to and with the row.

    The ranges are written once: sampled bounds could differ between two runs of the same plan.
    """
    weighted = df.withColumn("__w", F.lit(1) if weight is None else weight)
    ranges = Staging(df.sparkSession, "ranks").table(weighted.repartitionByRange(*order).withColumn("__p", F.spark_partition_id()), "ranges")
    sizes = ranges.groupBy("__p").agg(F.count(F.lit(1)).alias("__n"), F.sum("__w").alias("__s"))
    inside = Window.partitionBy("__p").orderBy(*order)
    running = F.sum("__w").over(inside.rowsBetween(Window.unboundedPreceding, Window.currentRow))
    joined = ranges.withColumn("__r", F.row_number().over(inside)).withColumn("__u", running).join(F.broadcast(_before(sizes, "__n", "__s")), "__p")
    out = joined.withColumn("place", (F.col("__r") + F.col("__n_before")).cast("bigint")).withColumn("upto", F.col("__u") + F.col("__s_before"))
    return out.select(*df.columns, "place", "upto")


def ranked_ties(df: DataFrame, column: str) -> DataFrame:
    """``df`` with ``dense`` and ``rank`` by a column, largest first: values are counted before they are ranked, so ties are one row."""
    values = df.groupBy(column).agg(F.count(F.lit(1)).alias("__n"))
    ranks = placed(values, [F.desc(column)], F.col("__n"))
    ranks = ranks.select(F.col(column).alias("__v"), F.col("place").cast("int").alias("dense"), (F.col("upto") - F.col("__n") + 1).alias("rank"))
    return df.join(ranks, F.col(column).eqNullSafe(F.col("__v"))).drop("__v")


def tiled(df: DataFrame, order: list[Column], tiles: int) -> DataFrame:
    """``df`` with ``tile`` from 1; the first tiles are one row larger where rows do not divide evenly."""
    rows = placed(df, order).crossJoin(F.broadcast(df.agg(F.count(F.lit(1)).alias("__n"))))  # one row
    at, small, more = F.col("place") - 1, F.expr(f"__n div {tiles}"), F.col("__n") % tiles
    wide = more * (small + 1)
    tile = F.when(at < wide, F.floor(at / (small + 1))).otherwise(more + F.floor((at - wide) / F.greatest(small, F.lit(1))))
    return rows.select(*df.columns, (tile + 1).cast("int").alias("tile"))
