"""Cost, accuracy, space, time and memory of filters. A filter is anything with ``probe(df) -> df + hit``."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import theory, zipf


def wfpr_column(hit: Column | str = "hit", cost: Column | str = "cost") -> Column:
    hit, cost = (F.col(c) if isinstance(c, str) else c for c in (hit, cost))
    return F.sum(F.when(hit, cost).otherwise(0.0)) / F.nullif(F.sum(cost), F.lit(0.0))


def weighted_fpr(probed: DataFrame, cost: str = "cost") -> float | None:
    """Cost of the passed negatives over the cost of all; null if there is none."""
    return probed.agg(wfpr_column("hit", cost).alias("r")).first()["r"]


def fpr(probed: DataFrame) -> float | None:
    return probed.agg(F.avg(F.col("hit").cast("int")).alias("r")).first()["r"]


def false_negatives(positives: DataFrame, filt) -> int:
    """Positives that the filter loses: none, for any filter here."""
    return filt.probe(positives).where("NOT hit").count()


def evaluate(filt, positives: DataFrame, negatives: DataFrame, held_out: DataFrame | None = None) -> DataFrame:
    """One row: method, bits, sizes, false negatives and rates on known negatives and, if given, on unseen ones."""
    s = filt.probe(positives).agg(F.count(F.lit(1)).alias("n"), F.sum((~F.col("hit")).cast("int")).alias("fn"))
    o = filt.probe(negatives).agg(
        F.count(F.lit(1)).alias("o"), F.sum(F.col("hit").cast("int")).alias("fp"), F.avg(F.col("hit").cast("int")).alias("fpr"), wfpr_column().alias("wfpr")
    )
    out = s.crossJoin(o)  # one row each
    if held_out is not None:
        out = out.crossJoin(filt.probe(held_out).agg(wfpr_column().alias("wfpr_unseen")))
    return out.select(F.lit(filt.method).alias("method"), F.lit(filt.total_bits).alias("total_bits"), (F.lit(filt.total_bits) / F.col("n")).alias("bits_per_key"), *out.columns)


def rates_by_round(filt, negatives: DataFrame) -> DataFrame:
    """Negatives that each round lets through, and the rest."""
    return filt.probe(negatives).groupBy("round").agg(F.count(F.lit(1)).alias("n"), F.sum("cost").alias("cost"))


def misread_rate(filt, keys: DataFrame) -> DataFrame:
    """Share of never-stored keys whose walk through the table ends well, which the table cannot tell from stored ones."""
    from ..sources.functions import trace_keys

    steps = trace_keys(filt, keys).groupBy("k").agg(F.count(F.when(F.col("fn") > 0, 1)).alias("taken"), F.max_by("ended", "step").alias("ended"))
    return steps.agg(F.count(F.lit(1)).alias("keys"), F.avg(((F.col("taken") == filt.k) & F.col("ended")).cast("int")).alias("misread"))


def load(filt) -> DataFrame:
    """(shard, bit_load, cell_load, shared_cells)."""
    ones = F.aggregate("words", F.lit(0).cast("bigint"), lambda a, w: a + F.bit_count(w).cast("bigint"))
    used = F.size(F.filter("cells", lambda c: c > 0))
    return filt.rows.select("shard", (ones / F.col("m")).alias("bit_load"), (used / F.nullif(F.col("omega"), F.lit(0))).alias("cell_load"), F.element_at("stats", "shared_cells").alias("shared_cells"))


def build_stats(filt) -> DataFrame:
    """The optimiser's counters, summed over shards."""
    return filt.rows.select(F.explode("stats").alias("stat", "value")).groupBy("stat").agg(F.sum("value").alias("value"))


def timed_build(build: Callable[[], object], keys: int) -> tuple[object, float]:
    """(what was built, wall-clock ns per key); load and cache the keys beforehand."""
    begin = time.perf_counter()
    made = build()
    return made, (time.perf_counter() - begin) * 1e9 / max(keys, 1)


def timed_probe(filt, df: DataFrame, keys: int, **options) -> float:
    begin = time.perf_counter()
    filt.probe(df, **options).write.format("noop").mode("overwrite").save()
    return (time.perf_counter() - begin) * 1e9 / max(keys, 1)


def build_memory(filt) -> DataFrame:
    """(shard, peak_mb, state_mb): the worker's peak resident memory and the kernel arrays' size by formula."""
    stat = lambda name: F.element_at("stats", name)
    state = stat("positives") * (len(filt.pool) + 1) * 8 + stat("negatives") * filt.k * 16 + F.col("m") * 12
    return filt.rows.select("shard", (stat("peak_kb") / 1024).alias("peak_mb"), (state / (1 << 20)).alias("state_mb"))


def bound_check(filt, n: int, o: int, measured: float) -> dict:
    m, omega = (filt.rows.agg(F.sum(c)).first()[0] for c in ("m", "omega"))
    bound = theory.fpr_upper(n, o, m, omega, filt.k, len(filt.pool))
    return {"measured": measured, "bound": bound, "holds": measured <= bound}


def over_shuffles(filt, negatives: DataFrame, skew: float, seeds: range = range(1, 11)) -> DataFrame:
    """Mean and spread of the weighted rate of a built, cost-blind filter over shuffles of the costs."""
    probed = filt.probe(negatives.drop("cost")).select("k", "hit")
    runs = None
    for seed in seeds:
        one = zipf.costs(probed, skew, seed).agg(F.lit(seed).alias("seed"), wfpr_column().alias("wfpr"))
        runs = one if runs is None else runs.unionByName(one)
    return runs.agg(F.avg("wfpr").alias("mean"), F.stddev_samp("wfpr").alias("sd"), F.min("wfpr").alias("least"), F.max("wfpr").alias("most"))


def relative_to(df: DataFrame, base: str, columns: list[str], by: list[str]) -> DataFrame:
    """Factors of ``columns`` over those of the method ``base`` in the same group."""
    own = Window.partitionBy(*by)
    for c in columns:
        df = df.withColumn(f"{c}_factor", F.col(c) / F.max(F.when(F.col("method") == base, F.col(c))).over(own))
    return df
