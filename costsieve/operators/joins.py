"""Joins that ask a filter first. A filter's no is certain and its yes is checked by the join, so answers are exact."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .filters import FilterSet


def maybe(left: DataFrame, on: str, filt: FilterSet) -> DataFrame:
    """``left`` with ``__hit``: whether the key may be in the filter's set."""
    keyed = left.withColumn("__key", F.col(on).cast("string"))
    return filt.probe(keyed, "__key").withColumnRenamed("hit", "__hit").drop("__key", "round")


def prefiltered(left: DataFrame, right: DataFrame, left_on: str, right_on: str, filt: FilterSet, how: str = "inner") -> DataFrame:
    """inner, semi or anti join of ``left`` to ``right``, whose keys the filter holds. Only rows that may match are shuffled; in an anti join the
    others are part of the answer at once."""
    asked = maybe(left, left_on, filt)
    may = asked.where("__hit").drop("__hit")
    if how == "inner":
        return may.join(right, F.col(left_on) == F.col(right_on))
    keys = right.select(F.col(right_on).alias("__right"))
    if how == "semi":
        return may.join(keys, F.col(left_on) == F.col("__right"), "left_semi")
    if how == "anti":
        sure = asked.where("NOT __hit OR __hit IS NULL").drop("__hit")
        return sure.unionByName(may.join(keys, F.col(left_on) == F.col("__right"), "left_anti"))
    raise ValueError(f"unknown join {how}")
