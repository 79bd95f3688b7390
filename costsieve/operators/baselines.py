"""The filters that the custom-hash filter is compared with, each under the same budget and with the same ``probe``."""

from __future__ import annotations

import math
from dataclasses import dataclass, field
from itertools import combinations, product

import numpy as np
import pyarrow as pa
from pyspark.ml import Pipeline, PipelineModel
from pyspark.ml.classification import LogisticRegression, MultilayerPerceptronClassifier
from pyspark.ml.feature import HashingTF, NGram, RegexTokenizer
from pyspark.ml.functions import vector_to_array
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.geometry import best_k, fingerprint_bits
from ..functions.hashing import ROUTER, Family
from ..sources.shared import ship
from . import bloom
from .custom import shards_for
from .filters import ARTEFACT, BROADCAST_BYTES, FilterSet, bit, matrix, route, written

MIX = 0x9E3779B97F4A7C15


def exact_probe(keys: DataFrame, positives: DataFrame, key: str = "k") -> DataFrame:
    """Ground truth: ``keys`` with an exact ``hit``. Spark picks the join."""
    known = positives.select(F.col("k").alias("__k"), F.lit(True).alias("__in")).distinct()
    return keys.join(known, F.col(key) == F.col("__k"), "left").withColumn("hit", F.coalesce("__in", F.lit(False))).drop("__k", "__in")


def _row(shard: int, m: int, words: np.ndarray, cells, stats: dict) -> pa.Table:
    words = pa.ListArray.from_arrays(pa.array([0, len(words)], pa.int32()), pa.array(words, pa.int64()))  # no Python number per word
    kinds = pa.schema(
        [
            ("shard", pa.int32()),
            ("m", pa.int64()),
            ("omega", pa.int64()),
            ("alpha", pa.int32()),
            ("words", pa.list_(pa.int64())),
            ("cells", pa.list_(pa.int32())),
            ("stats", pa.map_(pa.string(), pa.float64())),
        ]
    )
    row = {"shard": shard, "m": m, "omega": 0, "alpha": 0, "words": None, "cells": list(cells), "stats": [(k, float(v)) for k, v in stats.items()]}
    table = pa.Table.from_pylist([row], kinds)
    return table.set_column(kinds.get_field_index("words"), kinds.field("words"), words)


# Xor filter


def _slots(values: np.ndarray, third: int, seed: int) -> np.ndarray:
    salt = seed * MIX & (1 << 59) - 1
    return np.stack([(values[:, j] ^ salt) % third + j * third for j in range(3)], axis=1)


def xor_table(values: np.ndarray, bits: int, tries: int = 10) -> tuple[np.ndarray, int]:
    """(fingerprints, seed): keys that alone use a slot go first, layer by layer; slots are filled in the opposite order."""
    n = len(values)
    third = max(1, (int(1.23 * n) + 32) // 3)
    prints = values[:, 3] & (1 << bits) - 1
    for seed in range(tries):
        slots = _slots(values, third, seed)
        count = np.bincount(slots.ravel(), minlength=3 * third)
        held = np.zeros(3 * third, np.int64)
        for j in range(3):
            np.bitwise_xor.at(held, slots[:, j], np.arange(n))
        layers, left = [], n
        while left:
            alone = np.flatnonzero(count == 1)
            if not len(alone):
                break
            keys, first = np.unique(held[alone], return_index=True)
            layers.append((keys, alone[first]))
            left -= len(keys)
            for j in range(3):
                np.subtract.at(count, slots[keys, j], 1)
                np.bitwise_xor.at(held, slots[keys, j], keys)
        if not left:
            table = np.zeros(3 * third, np.int64)
            for keys, own in reversed(layers):
                table[own] = 0
                table[own] = prints[keys] ^ np.bitwise_xor.reduce(table[slots[keys]], axis=1)
            return table, seed
    raise RuntimeError("no seed peels all keys; are they distinct?")


class XorFilter(FilterSet):
    @property
    def sent_bytes(self) -> int:
        return self.total_bits * 8  # a fingerprint of one bit or more takes 8 bytes

    def _raw_ids(self) -> list[int]:
        return [1, 2, 3, 4]

    def say(self, values: np.ndarray, shard: dict) -> np.ndarray:
        table, third = shard["words"], len(shard["words"]) // 3
        bits, seed = int(shard["cells"][0]), int(shard["cells"][1])
        slots = _slots(values, third, seed)
        return (np.bitwise_xor.reduce(table[slots], axis=1) == values[:, 3] & (1 << bits) - 1).astype(int)

    def probe(self, df: DataFrame, key: str = "k", mode: str = "auto") -> DataFrame:
        if mode not in ("arrow", "cogroup"):  # there is no probe in the JVM
            mode = "arrow" if self.sent_bytes <= BROADCAST_BYTES else "cogroup"
        return super().probe(df, key, mode)


def distinct_rows(values: np.ndarray) -> np.ndarray:
    """Each row once: a key that is given twice would never be peeled."""
    order = np.lexsort(values.T)
    again = (values[order[1:]] == values[order[:-1]]).all(axis=1)
    return np.delete(values, order[1:][again], axis=0) if again.any() else values


def xor_build(positives: DataFrame, total_bits: int, family: Family = Family(), shards: int | None = None, n: int | None = None) -> XorFilter:
    """A table per shard of, by default, about 2^18 keys, since a fingerprint takes 8 bytes in a row, so that a task's row and keys stay small. A table's slack,
    which does not grow with its keys, is paid once per shard. A key may be given more than once."""
    ship(positives.sparkSession)
    n = n or positives.count()
    shards = shards or shards_for(4 * n)
    bits = fingerprint_bits(total_bits / max(n, 1), max(n // shards, 1))

    def run(table: pa.Table) -> pa.Table:
        values = distinct_rows(matrix(table.column("h"))[0])
        prints, seed = xor_table(values, bits)
        return _row(table.column("shard")[0].as_py(), len(prints) * bits, prints, [bits, seed], {"positives": len(values), "fingerprint_bits": bits})

    hashed = positives.select(route(family, F.col("k"), shards).alias("shard"), family.columns(F.col("k"), [1, 2, 3, 4]).alias("h"))
    rows = hashed.groupBy("shard").applyInArrow(run, ARTEFACT)
    return XorFilter("xor", written(rows, "xor"), family, shards, (1, 2, 3), total_bits=total_bits)


# Weighted filter


@dataclass
class WeightedFilter(FilterSet):
    """A standard filter whose costly, cached keys are tested with more functions."""

    cache: DataFrame | None = None  # (k, functions)
    most: int = 12

    def probe(self, df: DataFrame, key: str = "k", mode: str = "expr") -> DataFrame:
        cache = self.cache.select(F.col("k").alias("__ck"), F.col("functions").alias("__kk"))
        known = df.join(cache, F.col(key) == F.col("__ck"), "left")
        art = self.rows.select(F.col("shard").alias("__shard"), F.col("m").alias("__m"), F.col("words").alias("__words"))
        joined = known.withColumn("__r", route(self.family, F.col(key), self.shards)).join(F.broadcast(art) if self.sent_bytes <= BROADCAST_BYTES else art, F.col("__r") == F.col("__shard"), "left")
        count = F.coalesce("__kk", F.lit(self.k))
        spots = joined.withColumn("__p", F.array(*[F.pmod(self.family.column(F.col(key), i + 1), F.col("__m")) for i in range(self.most)])).withColumn("__n", count)
        yes = F.lit(True)
        for j in range(self.most):
            yes = yes & ((F.col("__n") <= j) | bit(F.col("__words"), F.element_at("__p", j + 1)))
        return spots.select(*df.columns, F.explode(F.array(F.coalesce(yes, F.lit(False)))).alias("hit"))


def weighted_counts(negatives: DataFrame, k: int, cache_rows: int, most: int) -> DataFrame:
    """(k, functions) of the costliest negatives: the default plus how many doublings their cost is above the mean of logarithms."""
    mean = negatives.agg(F.avg(F.log2("cost")).alias("mean"))
    top = negatives.orderBy(F.desc("cost"), "key_id").limit(cache_rows)
    count = F.round(F.lit(k) + F.log2("cost") - F.col("mean")).cast("int")
    return top.crossJoin(F.broadcast(mean)).select("k", F.least(F.greatest(count, F.lit(k)), F.lit(most)).alias("functions"))  # one row


def weighted_build(positives: DataFrame, negatives: DataFrame, total_bits: int, family: Family = Family(), cache_share: float = 0.01, most: int = 12, shards: int = 1, n: int | None = None) -> WeightedFilter:
    n = n or positives.count()
    k = min(most, best_k(total_bits / max(n, 1)))
    base = bloom.build(positives, total_bits, family, k=k, shards=shards)
    rows = max(1, int(negatives.count() * cache_share))
    cache = written(weighted_counts(negatives, k, rows, most), "weighted-cache")
    return WeightedFilter("weighted", base.rows, family, shards, base.default, total_bits=base.total_bits, cache=cache, most=most, extra={"cache_rows": rows})


# Grouped hashing


class GroupedFilter(FilterSet):
    groups: int = 0
    tries: int = 0

    def _raw_ids(self) -> list[int]:
        return [ROUTER, *range(1, self.k * self.extra["tries"] + 1)]

    def say(self, values: np.ndarray, shard: dict) -> np.ndarray:
        group = values[:, 0] % self.extra["groups"]
        chosen = shard["cells"][group]
        places = np.take_along_axis(values[:, 1:-1], chosen[:, None] * self.k + np.arange(self.k)[None, :], axis=1) % shard["m"]
        return ((shard["words"][places >> 5] >> (places & 31)) & 1).all(axis=1).astype(int)

    def probe(self, df: DataFrame, key: str = "k", mode: str = "arrow") -> DataFrame:
        return super().probe(df, key, "cogroup" if mode == "cogroup" else "arrow")


def grouped_build(positives: DataFrame, total_bits: int, family: Family = Family(), groups: int = 64, tries: int = 4, n: int | None = None) -> GroupedFilter:
    """Groups of keys choose, one after the other, the function set that sets the fewest new bits."""
    ship(positives.sparkSession)
    n = n or positives.count()
    k = min(5, best_k(total_bits / max(n, 1)))
    m = max(32, total_bits - groups * math.ceil(math.log2(tries)))
    ids = [ROUTER, *range(1, k * tries + 1)]

    def run(table: pa.Table) -> pa.Table:
        values = matrix(table.column("h"))[0]
        group, places = values[:, 0] % groups, values[:, 1:] % m
        bits, chosen = np.zeros(m, bool), np.zeros(groups, np.int64)
        for g in range(groups):
            own = places[group == g]
            new = [np.unique(own[:, t * k : (t + 1) * k][~bits[own[:, t * k : (t + 1) * k]]]).size for t in range(tries)]
            chosen[g] = int(np.argmin(new))
            bits[own[:, chosen[g] * k : (chosen[g] + 1) * k]] = True
        padded = np.zeros(-(-m // 32) * 32, np.uint8)
        padded[:m] = bits
        return _row(0, m, np.packbits(padded, bitorder="little").view("<u4").astype(np.int64), chosen.tolist(), {"ones": bits.sum(), "positives": len(values)})

    hashed = positives.select(F.lit(0).alias("shard"), family.columns(F.col("k"), ids).alias("h"))
    rows = hashed.groupBy("shard").applyInArrow(run, ARTEFACT)
    return GroupedFilter("grouped", written(rows, "grouped"), family, 1, tuple(range(1, k + 1)), total_bits=total_bits, extra={"groups": groups, "tries": tries})


# Learned filters


@dataclass
class Model:
    pipeline: PipelineModel
    bits: int
    kind: str

    def score(self, df: DataFrame, key: str = "k") -> DataFrame:
        scored = self.pipeline.transform(df.withColumn("__text", F.lower(F.col(key))))
        return scored.select(*df.columns, vector_to_array("__probability")[1].alias("score"))


def fit_model(positives: DataFrame, negatives: DataFrame, kind: str = "logistic", features: int = 512, rows: int = 200_000) -> Model:
    """A score for keys from their character trigrams. ``kind`` logistic or mlp (six layers); they stand in for recurrent and dense networks.

    At most about ``rows`` keys are learnt from.
    """
    both = positives.select("k", F.lit(1.0).alias("label")).unionByName(negatives.select("k", F.lit(0.0).alias("label")))
    size = both.count()
    if size > rows:
        both = both.where(F.pmod(F.xxhash64("k"), F.lit(1 << 30)) < int((1 << 30) * rows / size))
    width = features if kind == "logistic" else 64
    stages = [
        RegexTokenizer(inputCol="__text", outputCol="__chars", pattern="", minTokenLength=1),
        NGram(n=3, inputCol="__chars", outputCol="__grams"),
        HashingTF(inputCol="__grams", outputCol="__features", numFeatures=width),
    ]
    common = {"featuresCol": "__features", "labelCol": "label", "probabilityCol": "__probability", "rawPredictionCol": "__raw", "predictionCol": "__prediction"}
    if kind == "logistic":
        stages.append(LogisticRegression(maxIter=25, regParam=1e-4, **common))
        bits = 32 * (width + 1)
    elif kind == "mlp":
        layers = [width, 32, 16, 16, 8, 2]
        stages.append(MultilayerPerceptronClassifier(layers=layers, maxIter=60, seed=42, **common))
        bits = 32 * sum((a + 1) * b for a, b in zip(layers, layers[1:]))
    else:
        raise ValueError(f"unknown model {kind}")
    return Model(Pipeline(stages=stages).fit(both.withColumn("__text", F.lower("k"))), bits, kind)


@dataclass
class LearnedFilter:
    """Yes if an optional first filter lets a key through and either its score reaches the threshold or the backup holds it."""

    method: str
    model: Model
    threshold: float
    backup: FilterSet | None
    first: FilterSet | None
    total_bits: int
    feasible: bool = True

    def probe(self, df: DataFrame, key: str = "k", mode: str = "expr") -> DataFrame:
        now = self.model.score(df, key)
        now = now.withColumn("__said", F.col("score") >= self.threshold).drop("score")
        if self.backup is not None:
            now = self.backup.probe(now, key, mode).withColumn("__said", F.col("__said") | F.col("hit")).select(*df.columns, "__said")
        if self.first is not None:
            now = self.first.probe(now, key, mode).withColumn("__said", F.col("__said") & F.col("hit")).select(*df.columns, "__said")
        return now.select(*df.columns, F.coalesce("__said", F.lit(False)).alias("hit"))


def _quantiles(scored: DataFrame, count: int = 40) -> list[float]:
    row = scored.agg(F.percentile_approx("score", [i / count for i in range(1, count)], 10_000).alias("q")).first()
    return sorted(set(row["q"])) if row["q"] else [0.5]


def _rates(scored: DataFrame, cuts: list[float]) -> list[float]:
    row = scored.agg(*[F.avg((F.col("score") >= c).cast("double")).alias(f"r{i}") for i, c in enumerate(cuts)]).first()
    return [row[f"r{i}"] or 0.0 for i in range(len(cuts))]


ALPHA = 0.6185  # rate of a standard filter per bit and key at its best number of functions


def learned_build(positives: DataFrame, negatives: DataFrame, model: Model, total_bits: int, family: Family = Family(), sandwiched: bool = False, n: int | None = None) -> LearnedFilter:
    """The threshold, and for the sandwiched form the split of bits, that minimise the expected rate on known negatives."""
    n = n or positives.count()
    left = total_bits - model.bits
    method = "sandwiched" if sandwiched else "learned"
    if left < 64:
        return LearnedFilter(method, model, 2.0, bloom.build(positives, total_bits, family, n=n), None, total_bits, feasible=False)
    s, o = model.score(positives).select("k", "score").cache(), model.score(negatives).select("score").cache()
    cuts = _quantiles(s) + _quantiles(o) + [2.0]
    passed, kept = _rates(o, cuts), _rates(s, cuts)
    best = (math.inf, 2.0, 0)
    for cut, fp, tp in zip(cuts, passed, kept):
        missed = max(1 - tp, 1 / max(n, 1))
        for share in (x / 10 for x in range(0, 10 if sandwiched else 1)):
            first, second = left * share / n, left * (1 - share) / n
            rate = (ALPHA**first if share else 1.0) * (fp + (1 - fp) * ALPHA ** (second / missed))
            if rate < best[0]:
                best = (rate, cut, int(left * share))
    _, cut, first_bits = best
    low = s.where(F.col("score") < cut).select("k")
    held = low.count()
    backup = bloom.build(low, left - first_bits, family, k=min(22, best_k((left - first_bits) / held))) if held else None
    first = bloom.build(positives, first_bits, family, n=n) if first_bits >= 64 else None
    s.unpersist()
    o.unpersist()
    return LearnedFilter(method, model, cut, backup, first, total_bits)


@dataclass
class AdaptiveFilter:
    """Score groups test different numbers of functions in one bit array."""

    model: Model
    cuts: list[float]
    counts: list[int]
    base: FilterSet
    total_bits: int
    feasible: bool = True
    method: str = "adaptive"

    def group_functions(self) -> Column:
        count = F.lit(self.counts[0])
        for cut, k in zip(self.cuts, self.counts[1:]):
            count = F.when(F.col("score") >= cut, F.lit(k)).otherwise(count)
        return count

    def probe(self, df: DataFrame, key: str = "k", mode: str = "expr") -> DataFrame:
        most = max(*self.counts, 1)
        scored = self.model.score(df, key).withColumn("__n", self.group_functions())
        if self.base.sent_bytes > BROADCAST_BYTES:
            raise ValueError("the filter is too large to be sent to every task")
        art = self.base.rows.select(F.col("m").alias("__m"), F.col("words").alias("__words"))
        joined = scored.crossJoin(F.broadcast(art))  # one row
        joined = joined.withColumn("__p", F.array(*[F.pmod(self.base.family.column(F.col(key), i + 1), F.col("__m")) for i in range(most)]))
        yes = F.lit(True)
        for j in range(most):
            yes = yes & ((F.col("__n") <= j) | bit(F.col("__words"), F.element_at("__p", j + 1)))
        return joined.select(*df.columns, F.explode(F.array(F.coalesce(yes, F.lit(False)))).alias("hit"))


def adaptive_build(positives: DataFrame, negatives: DataFrame, model: Model, total_bits: int, family: Family = Family(), groups: int = 4, n: int | None = None) -> AdaptiveFilter:
    """Functions fall from k_max to 0 as the score rises; bounds and k_max come from a small grid over expected rates."""
    n = n or positives.count()
    m = total_bits - model.bits
    if m < 64:
        raise ValueError(f"the model's {model.bits} bits leave nothing of {total_bits}")
    s, o = model.score(positives).select("k", "score").cache(), model.score(negatives).select("score").cache()
    every = _quantiles(o, 24)
    above_o, above_s = _rates(o, every), _rates(s, every)
    best = None
    picks = sorted(set(every[len(every) // 3 :]))
    for cuts in combinations(picks[:: max(1, len(picks) // 8)] or [0.5], min(groups - 1, max(1, len(picks[:: max(1, len(picks) // 8)])))):
        share_o, share_s = ([1 - up[0], *[a - b for a, b in zip(up, up[1:])], up[-1]] for up in ([r[every.index(c)] for c in cuts] for r in (above_o, above_s)))
        for k_max, low in product(range(3, 13), (0, 1)):
            ks = [round(k_max - (k_max - low) * i / len(cuts)) for i in range(len(cuts) + 1)]
            load = 1 - math.exp(-n * sum(f * k for f, k in zip(share_s, ks)) / m)
            rate = sum(f * load**k for f, k in zip(share_o, ks))
            if best is None or rate < best[0]:
                best = (rate, list(cuts), ks)
    _, cuts, counts = best
    made = AdaptiveFilter(model, cuts, counts, None, total_bits)
    own = model.score(positives).select("k", "score").withColumn("__n", made.group_functions())
    spots = own.select(F.explode(F.slice(F.array(*[F.pmod(family.column(F.col("k"), i + 1), F.lit(m).cast("bigint")) for i in range(max(*counts, 1))]), 1, F.col("__n"))).alias("p"))
    words = spots.groupBy(F.lit(0).alias("shard"), F.shiftright("p", 5).alias("word")).agg(F.bit_or(F.expr("shiftleft(1L, cast(p & 31 as int))")).alias("bits"))
    empty = own.sparkSession.range(1).select(F.lit(0).alias("shard"), F.lit(0).cast("bigint").alias("word"), F.lit(0).cast("bigint").alias("bits"))
    words = words.unionByName(empty).groupBy("shard", "word").agg(F.bit_or("bits").alias("bits"))
    rows = bloom.packed_by_sort(words, m).withColumn("m", F.lit(m).cast("bigint"))
    made.base = FilterSet("adaptive", written(rows, "adaptive"), family, 1, (1,), total_bits=m)
    s.unpersist()
    o.unpersist()
    return made


# All subsets, for tiny inputs


def brute_optimum(pos_s: np.ndarray, pos_o: np.ndarray, cost_o: np.ndarray, k: int, m: int) -> float:
    """The least cost that any choice of k-subsets of the pool leaves, storing aside; at most a few positives."""
    n, pool = pos_s.shape
    if math.comb(pool, k) ** n > 2_000_000:
        raise ValueError("too many choices to try them all")
    options = [[sum(1 << int(p) for p in set(pos_s[e, list(c)].tolist())) for c in combinations(range(pool), k)] for e in range(n)]
    masks = [sum(1 << int(p) for p in set(row.tolist())) for row in pos_o]
    best = math.inf
    for choice in product(*options):
        bits = 0
        for c in choice:
            bits |= c
        best = min(best, sum(c for mask, c in zip(masks, cost_o) if mask & bits == mask))
    return float(best)
