"""The optimiser for all owners at once: rounds of independent swaps, picked and applied by joins instead of one after the other in a shard."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.geometry import Geometry, split
from ..functions.hashing import START, Family
from . import bloom
from .filters import ARTEFACT, FilterSet, written


@dataclass
class RoundsResult:
    subsets: DataFrame  # (key_id, subset array<int>) of changed positives
    cells: DataFrame  # (cell, fn, ended)
    history: list[dict]


def run(positives: DataFrame, negatives: DataFrame, geometry: Geometry, k: int = 3, family: Family = Family(), max_rounds: int = 6) -> RoundsResult:
    """Each round: every collision key names its best swap; of swaps that touch one bit, one owner or one table cell only the first stays; the rest is
    applied together. A landing bit that is set already is locked too, lest another swap of the round clears it. The state with the least cost is kept.
    """
    m, omega, pool = geometry.m, max(1, geometry.omega), geometry.pool
    size, room = F.lit(m).cast("bigint"), F.lit(omega).cast("bigint")
    every = range(1, pool + 1)
    places = lambda ids, n: F.array(*[F.pmod(family.column(F.col("k"), i), n) for i in ids])
    s = written(
        positives.select(
            "key_id", places(every, size).alias("at"), places(every, room).alias("next"), F.pmod(family.column(F.col("k"), START), room).alias("start"),
            F.array(*[F.lit(i) for i in range(1, k + 1)]).alias("subset"), F.lit(False).alias("changed"),
        ),
        "rounds-positives",
    )
    o = written(negatives.select("key_id", "cost", F.explode(F.array_distinct(places(range(1, k + 1), size))).alias("pos")), "rounds-negatives")
    cells = written(s.sparkSession.createDataFrame([], "cell bigint, fn int, ended boolean"), "rounds-cells")
    history, best = [], None
    for step in range(max_rounds + 1):
        bits = s.select("key_id", F.explode(F.transform("subset", lambda f: F.element_at("at", f))).alias("pos"))
        index = written(bits.groupBy("pos").agg(F.count(F.lit(1)).alias("hits"), F.min("key_id").alias("owner")), "rounds-bits")
        seen = written(o.join(index, "pos", "left"), "rounds-seen")
        state = seen.groupBy("key_id", "cost").agg(F.sum(F.when(F.col("hits").isNull(), 1).otherwise(0)).alias("clear"))
        state = written(state, "rounds-state")
        cost = state.where("clear = 0").agg(F.coalesce(F.sum("cost"), F.lit(0.0)).alias("c"), F.count(F.lit(1)).alias("n")).first()
        history.append({"round": step, "cost_passed": cost["c"], "collisions": cost["n"]})
        if best is None or cost["c"] < best[0]:
            best = (cost["c"], s, cells)
        if step == max_rounds or not cost["n"]:
            break
        taken = _swaps(s, seen, state, index, cells, pool, k)
        taken = written(taken, "rounds-taken")
        if taken.isEmpty():
            break
        new = taken.select(F.col("owner").alias("key_id"), F.col("subset").alias("new_subset"))
        s = written(
            s.join(new, "key_id", "left").select(
                "key_id", "at", "next", "start", F.coalesce("new_subset", "subset").alias("subset"), (F.col("changed") | F.col("new_subset").isNotNull()).alias("changed")
            ),
            "rounds-positives",
        )
        walked = taken.select(F.explode("walk").alias("w")).select("w.cell", "w.fn", "w.ended")
        both = cells.unionByName(walked)
        cells = written(both.groupBy("cell").agg(F.max("fn").alias("fn"), F.max("ended").alias("ended")), "rounds-cells")
    _, s, cells = best
    return RoundsResult(s.where("changed").select("key_id", "subset"), cells, history)


def build(positives: DataFrame, negatives: DataFrame, total_bits: int, k: int = 3, delta: float = 0.25, alpha: int = 4, family: Family = Family(), max_rounds: int = 6) -> FilterSet:
    """A filter of one shard whose subsets were chosen in rounds. Bits and cells are aggregated like those of any filter."""
    geometry = split(total_bits, delta, alpha)
    found = run(positives, negatives, geometry, k, family, max_rounds)
    default = F.array(*[F.lit(i) for i in range(1, k + 1)])
    own = positives.join(found.subsets.select("key_id", "subset"), "key_id", "left").withColumn("subset", F.coalesce("subset", default))
    places = F.array(*[F.pmod(family.column(F.col("k"), i), F.lit(geometry.m).cast("bigint")) for i in range(1, geometry.pool + 1)])
    bits = own.select(F.explode(F.transform("subset", lambda f: F.element_at(places, f))).alias("p"))
    words = bits.groupBy(F.lit(0).alias("shard"), F.shiftright("p", 5).alias("word")).agg(F.bit_or(F.expr("shiftleft(1L, cast(p & 31 as int))")).alias("bits"))
    held = found.cells.select(F.col("cell"), (F.col("fn") + F.when(F.col("ended"), F.lit(32)).otherwise(0)).alias("c"))
    every = held.sparkSession.range(max(geometry.omega, 1)).withColumnRenamed("id", "cell").join(held, "cell", "left")
    cells = every.agg(F.sort_array(F.collect_list(F.struct("cell", F.coalesce("c", F.lit(0)).alias("c")))).alias("w")).select(F.col("w.c").cast("array<int>").alias("cells"))
    rows = bloom.packed_by_sort(words, geometry.m).crossJoin(cells)  # one row each
    rows = rows.select(
        "shard", F.lit(geometry.m).cast("bigint").alias("m"), F.lit(geometry.omega).cast("bigint").alias("omega"), F.lit(alpha).alias("alpha"), "words", "cells",
        F.expr("cast(map() as map<string,double>)").alias("stats"),
    )
    return FilterSet("custom-rounds", written(rows, "rounds").select(*ARTEFACT.names), family, 1, tuple(range(1, k + 1)), tuple(range(1, geometry.pool + 1)), total_bits=geometry.total_bits)


def _swaps(s, seen, state, index, cells, pool: int, k: int) -> DataFrame:
    """Swaps of this round: (owner, subset, walk), at most one for any bit, owner and cell."""
    coll = state.where("clear = 0").select("key_id")
    owners = seen.where("hits = 1").join(coll, "key_id", "left_semi").select(F.col("key_id").alias("victim"), "cost", "pos", "owner")
    own = s.where("NOT changed").select(F.col("key_id").alias("owner"), "at", "next", "start", F.col("subset").alias("old"))
    wide = owners.join(own, "owner")
    outside = F.array_except(F.array(*[F.lit(i) for i in range(1, pool + 1)]), F.col("old"))
    wide = wide.withColumn("fn", F.explode(outside)).withColumn("landing", F.element_at("at", F.col("fn"))).where("landing <> pos")
    kept = F.filter("old", lambda f: F.element_at("at", f) != F.col("pos"))
    wide = wide.withColumn("subset", F.array_sort(F.concat(kept, F.array("fn")))).where(F.size("subset") == k)
    one = state.where("clear = 1").select("key_id")
    near = seen.where("hits IS NULL").join(one, "key_id", "left_semi").groupBy(F.col("pos").alias("landing")).agg(F.sum("cost").alias("loss"))
    hit = index.select(F.col("pos").alias("landing"), F.lit(True).alias("held"))
    graded = wide.join(hit, "landing", "left").join(near, "landing", "left")
    graded = graded.withColumn("loss", F.when(F.col("held"), F.lit(0.0)).otherwise(F.coalesce("loss", F.lit(0.0)))).where("loss < cost OR (loss = 0)")
    # the walk of the sorted subset through the table: k left joins, in step with the chain look-up
    now = graded.withColumn("cell", F.col("start")).withColumn("left_fns", F.col("subset")).withColumn("walk", F.expr("cast(array() as array<struct<cell:bigint,fn:int,ended:boolean>>)"))
    for j in range(k):
        table = cells.select(F.col("cell").alias("__cell"), F.col("fn").alias("__fn"))
        now = now.join(table, F.col("cell") == F.col("__cell"), "left")
        chosen = F.coalesce("__fn", F.element_at("left_fns", 1))
        now = now.where(F.array_contains("left_fns", chosen) & ~F.exists("walk", lambda w: w["cell"] == F.col("cell"))).withColumn("__f", chosen)
        now = (
            now.withColumn("walk", F.concat("walk", F.array(F.struct("cell", F.col("__f").alias("fn"), F.lit(j == k - 1).alias("ended")))))
            .withColumn("left_fns", F.array_remove("left_fns", F.col("__f")))
            .withColumn("cell", F.element_at("next", F.col("__f")))
            .drop("__cell", "__fn", "__f")
        )
    order = [F.desc(F.col("cost") - F.col("loss")), "owner", "fn", "pos", "victim"]
    for key in ("victim", "owner"):
        now = now.withColumn("__r", F.row_number().over(Window.partitionBy(key).orderBy(*order))).where("__r = 1").drop("__r")
    # locks: the bit left, the bit landed on and every cell walked; a swap stays if it is first at all of its locks
    locks = now.select("owner", (F.col("cost") - F.col("loss")).alias("gain"), F.explode(F.concat(F.array(F.col("pos"), F.col("landing")), F.transform("walk", lambda w: -1 - w["cell"]))).alias("lock"))
    first = locks.withColumn("__r", F.row_number().over(Window.partitionBy("lock").orderBy(F.desc("gain"), "owner")))
    lost = first.where("__r > 1").select("owner").distinct()
    return now.join(lost, "owner", "left_anti").select("owner", "subset", "walk")
