"""The optimiser's steps before the first swap, as relations: what the shard kernel keeps in arrays, here for any number of keys and for checking."""

from __future__ import annotations

from functools import cached_property

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import ranks
from ..functions.hashing import Family


class State:
    """Positives (key_id, k) and negatives (key_id, k, cost) over m bits under the default functions 1..k."""

    def __init__(self, positives: DataFrame, negatives: DataFrame, m: int, k: int = 3, pool: int = 7, family: Family = Family()):
        self.s, self.o, self.m, self.k, self.pool, self.family = positives, negatives, m, k, pool, family

    def _spots(self, df: DataFrame, ids, *keep: str) -> DataFrame:
        pairs = F.array(*[F.struct(F.lit(i).alias("fn"), F.pmod(self.family.column(F.col("k"), i), F.lit(self.m).cast("bigint")).alias("pos")) for i in ids])
        return df.select(*keep, F.explode(pairs).alias("p")).select(*keep, "p.fn", "p.pos")

    @cached_property
    def positions(self) -> DataFrame:
        return self._spots(self.s, range(1, self.k + 1), "key_id")

    @cached_property
    def owner_index(self) -> DataFrame:
        """(pos, hits, owner): mappings of each set bit; the owner counts only where hits is 1, and a key that hits a bit twice owns it not."""
        return self.positions.groupBy("pos").agg(F.count(F.lit(1)).alias("hits"), F.min("key_id").alias("owner"))

    @cached_property
    def negative_bits(self) -> DataFrame:
        """(key_id, cost, pos, hits): each negative's distinct bits; hits is null where the bit is clear."""
        spots = self._spots(self.o, range(1, self.k + 1), "key_id", "cost").drop("fn").distinct()
        return spots.join(self.owner_index, "pos", "left").select("key_id", "cost", "pos", "hits", "owner")

    @cached_property
    def classified(self) -> DataFrame:
        """(key_id, cost, clear): number of clear bits; none means that the negative passes."""
        clear = F.sum(F.when(F.col("hits").isNull(), 1).otherwise(0)).cast("bigint")
        return self.negative_bits.groupBy("key_id", "cost").agg(clear.alias("clear"))

    def queue(self) -> DataFrame:
        """(key_id, cost, place) of the collision keys, dearest first. The order is global here; a shard orders its own keys only."""
        coll = self.classified.where("clear = 0").drop("clear")
        return ranks.placed(coll, [F.desc("cost"), F.col("key_id")]).drop("upto")

    def reliance_index(self) -> DataFrame:
        """(pos, keys, cost): rejected negatives on each bit."""
        rejected = self.classified.where("clear > 0").select("key_id")
        return self.negative_bits.join(rejected, "key_id", "left_semi").groupBy("pos").agg(F.count(F.lit(1)).alias("keys"), F.sum("cost").alias("cost"))

    @cached_property
    def near_misses(self) -> DataFrame:
        """(pos, key_id, cost): negatives with one clear bit, at that bit. Setting it lets them pass: conflict detection without the reliance index."""
        one = self.classified.where("clear = 1").select("key_id")
        return self.negative_bits.where("hits IS NULL").join(one, "key_id", "left_semi").select("pos", "key_id", "cost")

    def near_miss_cost(self) -> DataFrame:
        return self.near_misses.groupBy("pos").agg(F.sum("cost").alias("cost"), F.count(F.lit(1)).alias("keys"))

    @cached_property
    def candidates(self) -> DataFrame:
        """(key_id, cost, pos, owner): the sole owners that could free a collision key."""
        coll = self.classified.where("clear = 0").select("key_id")
        return self.negative_bits.where("hits = 1").join(coll, "key_id", "left_semi").select("key_id", "cost", "pos", "owner")

    def candidate_shares(self) -> DataFrame:
        """share: of the bits that collision keys map to, how many have one owner."""
        coll = self.classified.where("clear = 0").select("key_id")
        bits = self.negative_bits.join(coll, "key_id", "left_semi")
        return bits.agg(F.avg((F.col("hits") == 1).cast("double")).alias("share"))

    def owner_prob_empirical(self) -> DataFrame:
        """(bits, estimate, measured): over the set bits, the mean lower estimate of the chance of a single owner, from how often each function really meets each bit, and the share that has one.

        Functions may spread keys unevenly. A bit that one function gives to every key has no estimate and counts with 0.
        """
        n = F.broadcast(self.s.agg(F.count(F.lit(1)).cast("double").alias("n")))  # one row
        met = self.positions.groupBy("pos", "fn").agg(F.count(F.lit(1)).alias("hits")).crossJoin(n)
        p = F.col("hits") / F.col("n")
        spread = met.groupBy("pos", "n").agg(F.sum("hits").alias("hits"), F.sum(p).alias("p"), F.min(1 - p).alias("least"), F.sum(F.when(p < 1, F.log1p(-p))).alias("log_missed"))
        chance = F.when(F.col("least") > 0, F.col("n") * F.col("p") / (F.exp(-F.col("n") * F.col("log_missed")) - 1)).otherwise(0.0)
        return spread.agg(F.count(F.lit(1)).alias("bits"), F.round(F.avg(chance), 9).alias("estimate"), F.round(F.avg((F.col("hits") == 1).cast("double")), 9).alias("measured"))

    @cached_property
    def swaps(self) -> DataFrame:
        """(key_id, cost, pos, owner, fn, landing): every function of the pool outside the owner's subset, and the bit it would set."""
        spots = self._spots(self.s, range(self.k + 1, self.pool + 1), "key_id").select(F.col("key_id").alias("owner"), "fn", F.col("pos").alias("landing"))
        return self.candidates.join(spots, "owner").where("landing <> pos").select("key_id", "cost", "pos", "owner", "fn", "landing")

    @cached_property
    def graded(self) -> DataFrame:
        """Swaps with ``loss``, the cost of negatives that would pass, and ``tier``: 0 for set bits, 1 for harmless clear ones, 2 for the rest."""
        hit = self.owner_index.select(F.col("pos").alias("landing"), F.lit(True).alias("taken"))
        at = self.near_misses.select(F.col("pos").alias("landing"), F.col("key_id").alias("victim"), F.col("cost").alias("victim_cost"))
        safe = self.negative_bits.select(F.col("key_id").alias("victim"), "pos", F.lit(True).alias("spared"))
        victims = self.swaps.select("pos", "landing").distinct().join(at, "landing").join(safe, ["victim", "pos"], "left").where("spared IS NULL")
        loss = victims.groupBy("pos", "landing").agg(F.sum("victim_cost").alias("loss"))
        joined = self.swaps.join(hit, "landing", "left").join(loss, ["pos", "landing"], "left")
        loss = F.when(F.col("taken"), F.lit(0.0)).otherwise(F.coalesce("loss", F.lit(0.0)))
        tier = F.when(F.col("taken"), 0).when(loss == 0, 1).otherwise(2)
        return joined.select("key_id", "cost", "pos", "owner", "fn", "landing", loss.alias("loss"), tier.alias("tier"))

    def valid(self) -> DataFrame:
        """Swaps that do not lose."""
        return self.graded.where("loss <= cost")

    def best(self) -> DataFrame:
        """The first swap to try for each collision key: the smallest loss, then owner, function and bit."""
        order = Window.partitionBy("key_id").orderBy("loss", "tier", "owner", "fn", "pos")
        return self.valid().withColumn("__r", F.row_number().over(order)).where("__r = 1").drop("__r")

    def given_up(self) -> DataFrame:
        """Collision keys without any valid swap."""
        return self.classified.where("clear = 0").select("key_id", "cost").join(self.valid().select("key_id"), "key_id", "left_anti")
