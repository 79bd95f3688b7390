"""The standard filter, wholly relational: positions explode, partial aggregates set bits word by word."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.geometry import best_k, budget
from ..functions.hashing import Family
from .filters import ARTEFACT, FilterSet, route, written


def bit_words(positives: DataFrame, m: int, family: Family, ids: list[int], shards: int = 1, fast: bool = False, key: str = "k") -> DataFrame:
    """(shard, word, bits): 32 bits a word. At most m / 32 rows of a shard leave a task."""
    size = F.lit(m).cast("bigint")
    places = family.doubled(F.col(key), ids, size) if fast else F.array(*[F.pmod(family.column(F.col(key), i), size) for i in ids])
    spots = positives.select(route(family, F.col(key), shards).alias("shard"), F.explode(places).alias("p"))
    word = F.shiftright("p", 5)
    return spots.groupBy("shard", word.alias("word")).agg(F.bit_or(F.expr("shiftleft(1L, cast(p & 31 as int))")).alias("bits"))


def packed(words: DataFrame, m: int) -> DataFrame:
    """One row per shard with all its words in order, zeros included."""
    held = words.groupBy("shard").agg(F.map_from_entries(F.collect_list(F.struct("word", "bits"))).alias("held"))
    every = F.sequence(F.lit(0).cast("bigint"), F.lit((m - 1) // 32).cast("bigint"))
    return held.select("shard", F.transform(every, lambda w: F.coalesce(F.element_at("held", w), F.lit(0).cast("bigint"))).alias("words"))


def build(positives: DataFrame, total_bits: int, family: Family = Family(), k: int | None = None, shards: int = 1, fast: bool = False, n: int | None = None, method: str = "standard") -> FilterSet:
    """``k`` different functions, by default the best number for the space."""
    if k is None:
        n = n or positives.count()
        k = best_k(total_bits / max(n, 1))
    if k > 22:
        raise ValueError("the pool has 22 functions")
    ids = tuple(range(1, k + 1))
    m = max(32, total_bits // shards)
    words = bit_words(positives, m, family, list(ids), shards, fast)
    rows = packed_by_sort(words, m).select(
        "shard",
        F.lit(m).cast("bigint").alias("m"),
        F.lit(0).cast("bigint").alias("omega"),
        F.lit(0).alias("alpha"),
        "words",
        F.expr("cast(array() as array<int>)").alias("cells"),
        F.expr("cast(map() as map<string,double>)").alias("stats"),
    )
    return FilterSet(method, written(rows, method).select(*ARTEFACT.names), family, shards, ids, fast=fast, total_bits=m * shards)


def packed_by_sort(words: DataFrame, m: int) -> DataFrame:
    """As ``packed``, from a full list of words so that no map of them is built per element."""
    every = words.select("shard").distinct().select("shard", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit((m - 1) // 32).cast("bigint"))).alias("word"))
    full = every.join(words, ["shard", "word"], "left").select("shard", F.struct("word", F.coalesce("bits", F.lit(0).cast("bigint")).alias("bits")).alias("w"))
    return full.groupBy("shard").agg(F.sort_array(F.collect_list("w")).alias("w")).select("shard", F.col("w.bits").alias("words"))


def union(a: FilterSet, b: FilterSet) -> FilterSet:
    """Bits of either; both filters need the same functions and sizes."""
    if (a.family, a.shards, a.default, a.total_bits, a.fast) != (b.family, b.shards, b.default, b.total_bits, b.fast) or a.pool or b.pool:
        raise ValueError("only standard filters of equal shape can be united")
    other = b.rows.select("shard", F.col("words").alias("__w"))
    rows = a.rows.join(other, "shard", "full").withColumn(
        "words",
        F.when(F.col("words").isNull(), F.col("__w")).when(F.col("__w").isNull(), F.col("words")).otherwise(F.zip_with("words", "__w", lambda x, y: x.bitwiseOR(y))),
    )
    return FilterSet(a.method, rows.drop("__w"), a.family, a.shards, a.default, fast=a.fast, total_bits=a.total_bits)


def for_bits_per_key(positives: DataFrame, bits_per_key: float, family: Family = Family(), **options) -> FilterSet:
    n = positives.count()
    return build(positives, budget(n, bits_per_key), family, n=n, **options)
