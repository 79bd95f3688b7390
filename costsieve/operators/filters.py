"""Filter artefacts: one row per shard that holds all a probe needs, and the ways to probe."""

from __future__ import annotations

from dataclasses import dataclass, field, replace
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.hashing import ROUTER, START, Family
from ..sources.shared import Staging, ship
from . import chain

ARTEFACT = T.StructType(
    [
        T.StructField("shard", T.IntegerType()),
        T.StructField("m", T.LongType()),
        T.StructField("omega", T.LongType()),
        T.StructField("alpha", T.IntegerType()),
        T.StructField("words", T.ArrayType(T.LongType())),
        T.StructField("cells", T.ArrayType(T.IntegerType())),
        T.StructField("stats", T.MapType(T.StringType(), T.DoubleType())),
    ]
)
#: Beyond so many bytes of words and cells a filter is not broadcast but met shard by shard.
BROADCAST_BYTES = 256 << 20


def written(df: DataFrame, name: str) -> DataFrame:
    """``df`` as a table in the shared folder: computed once, safe from lost executors."""
    return Staging(df.sparkSession, name).table(df, "rows")


def bit(words: Column, position: Column) -> Column:
    return F.getbit(F.element_at(words, (F.shiftright(position, 5) + 1).cast("int")), position.bitwiseAND(F.lit(31)).cast("int")) == 1


def route(family: Family, key: Column, shards: int) -> Column:
    return F.pmod(family.column(key, ROUTER), F.lit(shards)).cast("int") if shards > 1 else F.lit(0)


@dataclass
class FilterSet:
    """A built filter. ``rows`` has the artefact's schema; ``default`` and ``pool`` number functions of ``family``."""

    method: str
    rows: DataFrame
    family: Family
    shards: int
    default: tuple[int, ...]
    pool: tuple[int, ...] = ()
    fast: bool = False
    total_bits: int = 0
    reject_repeats: bool = False
    extra: dict = field(default_factory=dict)

    @property
    def k(self) -> int:
        return len(self.default)

    @property
    def sent_bytes(self) -> int:
        """What a probe that holds the whole filter needs at most: words hold 32 bits in 8 bytes, cells 3 bits or more in 4."""
        return self.total_bits if self.pool else self.total_bits // 4

    def save(self, path: str) -> None:
        spark = self.rows.sparkSession
        meta = (self.method, self.family.name, self.family.seed, self.shards, list(self.default), list(self.pool), self.fast, self.total_bits)
        schema = "method string, family string, seed int, shards int, default_subset array<int>, pool array<int>, fast boolean, total_bits bigint"
        self.rows.write.mode("overwrite").parquet(f"{path}/shards")
        spark.createDataFrame([meta], schema).write.mode("overwrite").parquet(f"{path}/meta")

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> "FilterSet":
        r = spark.read.parquet(f"{path}/meta").first()
        rows = spark.read.schema(ARTEFACT).parquet(f"{path}/shards")
        return cls(r["method"], rows, Family(r["family"], r["seed"]), r["shards"], tuple(r["default_subset"]), tuple(r["pool"]), r["fast"], r["total_bits"])

    def _positions(self, key: Column, ids: list[int], size: Column) -> Column:
        if self.fast:
            return self.family.doubled(key, ids, size)
        return F.array(*[F.pmod(self.family.column(key, i), size) for i in ids])

    def rounds(self, df: DataFrame, key: Column) -> DataFrame:
        """``df``, which holds __cf_words, __cf_cells, __cf_m and __cf_omega, with ``round``: 1 if the default subset says yes, 2 if a stored one does, else null.

        Step by step, so that no expression repeats another and generated code stays small. Round 2 is hashed only after a no.
        """
        now = df.withColumn("__cf_first", self._positions(key, list(self.default), F.col("__cf_m")))
        yes = reduce(lambda a, b: a & b, [bit(F.col("__cf_words"), F.element_at("__cf_first", j + 1)) for j in range(self.k)])
        now = now.withColumn("__cf_yes", F.coalesce(yes, F.lit(False)))
        if not self.pool:
            return now.withColumn("round", F.when(F.col("__cf_yes"), F.lit(1)))
        asked = ~F.col("__cf_yes") & F.col("__cf_m").isNotNull() & (F.col("__cf_omega") > 0) & key.isNotNull()
        size = F.greatest("__cf_omega", F.lit(1))
        now = now.withColumns(
            {
                "__cf_next": F.when(asked, self._positions(key, list(self.pool), size)),
                "__cf_spots": F.when(asked, self._positions(key, list(self.pool), F.col("__cf_m"))),
                "__cf_at": F.when(asked, F.pmod(self.family.column(key, START), size)),
            }
        )
        good = asked
        for j in range(self.k):
            now = now.withColumn(f"__cf_c{j}", F.element_at("__cf_cells", (F.col("__cf_at") + 1).cast("int")))
            fn = F.col(f"__cf_c{j}").bitwiseAND(F.lit(chain.FN))
            now = now.withColumn(f"__cf_f{j}", F.greatest(fn, F.lit(1)).cast("int")).withColumn("__cf_at", F.element_at("__cf_next", F.col(f"__cf_f{j}")))
            good = good & (fn > 0) & bit(F.col("__cf_words"), F.element_at("__cf_spots", F.col(f"__cf_f{j}")))
        good = good & (F.col(f"__cf_c{self.k - 1}") >= chain.END)
        if self.reject_repeats:
            good = good & (F.size(F.array_distinct(F.array(*[F.col(f"__cf_f{j}") for j in range(self.k)]))) == self.k)
        return now.withColumn("round", F.when(F.col("__cf_yes"), F.lit(1)).when(good, F.lit(2)))

    def probe(self, df: DataFrame, key: str = "k", mode: str = "auto") -> DataFrame:
        """``df`` with ``hit`` and ``round``. A null key is never in the filter."""
        if mode == "auto":
            mode = "expr" if self.sent_bytes <= BROADCAST_BYTES else "cogroup"
        found = {"expr": self._expr, "arrow": self._arrow, "cogroup": self._cogroup}[mode](df, key)
        return found.withColumn("hit", F.col("round").isNotNull())

    def _expr(self, df: DataFrame, key: str) -> DataFrame:
        art = self.rows.select(*[F.col(c).alias(f"__cf_{c}") for c in ("shard", "m", "omega", "words", "cells")])
        routed = df.withColumn("__cf_r", route(self.family, F.col(key), self.shards))
        joined = routed.join(F.broadcast(art), F.col("__cf_r") == F.col("__cf_shard"), "left")  # its size is checked by ``probe``
        # a generator of one row keeps filters on the answer from being pushed below it, which would spell out all of the probe once more
        return self.rounds(joined, F.col(key)).select(*df.columns, F.explode(F.array("round")).alias("round"))

    def hashed(self, df: DataFrame, key: str) -> DataFrame:
        """``df`` with its shard and raw hash values, computed in the JVM."""
        ids = [*self._raw_ids(), START]
        return df.withColumn("__cf_r", route(self.family, F.col(key), self.shards)).withColumn("__cf_h", F.when(F.col(key).isNotNull(), self.family.columns(F.col(key), ids)))

    def _raw_ids(self) -> list[int]:
        from ..functions.hashing import BASE_A, BASE_B

        return [BASE_A, BASE_B] if self.fast else list(dict.fromkeys([*self.default, *self.pool]))

    def say(self, values: np.ndarray, shard: dict) -> np.ndarray:
        """Round per row of raw hash values (0: no) against one shard's arrays."""
        m, omega = shard["m"], max(1, shard["omega"])
        raw = self._raw_ids()

        def spots(ids, size):
            if self.fast:
                a, b = values[:, 0] % size, values[:, 1] % size
                return np.stack([(a + i * b) % size for i in ids], axis=1)
            return np.stack([values[:, raw.index(i)] % size for i in ids], axis=1)

        def held(places):
            return ((shard["words"][places >> 5] >> (places & 31)) & 1).astype(bool)

        out = np.where(held(spots(self.default, m)).all(axis=1), 1, 0)
        if self.pool and shard["omega"]:
            rest = np.flatnonzero(out == 0)
            rest = rest[shard["cells"][values[rest, -1] % omega] & chain.FN > 0]  # an empty cell begins no walk
            if len(rest):
                values = values[rest]
                valid, fns = chain.lookup_batch(shard["cells"], values[:, -1] % omega, spots(self.pool, omega), self.k, self.reject_repeats)
                places = spots(self.pool, m)[np.arange(len(rest))[:, None], np.minimum(fns, len(self.pool) - 1)]
                out[rest[valid & held(places).all(axis=1)]] = 2
        return out

    def _arrow(self, df: DataFrame, key: str) -> DataFrame:
        if self.sent_bytes > BROADCAST_BYTES:
            raise ValueError("the filter is too large to be sent to every task; probe with mode='cogroup'")
        ship(df.sparkSession)
        shards = {r["shard"]: unpacked(r) for r in self.rows.collect()}  # at most BROADCAST_BYTES
        sent = df.sparkSession.sparkContext.broadcast(shards)
        names, say = df.columns, self.detached().say

        def run(batches):
            for batch in batches:
                values, known = matrix(batch.column("__cf_h"))
                routed = batch.column("__cf_r").to_numpy(zero_copy_only=False)
                out = np.zeros(batch.num_rows, np.int32)
                for s in np.unique(routed):
                    own = np.flatnonzero((routed == s) & known)
                    if s in sent.value and len(own):
                        out[own] = say(values[own], sent.value[s])
                yield pa.RecordBatch.from_arrays([*[batch.column(n) for n in names], pa.array(out, mask=out == 0)], [*names, "round"])

        schema = T.StructType([*df.schema.fields, T.StructField("round", T.IntegerType())])
        return self.hashed(df, key).mapInArrow(run, schema)

    def _cogroup(self, df: DataFrame, key: str) -> DataFrame:
        ship(df.sparkSession)
        names, say = df.columns, self.detached().say

        def run(left: pa.Table, right: pa.Table) -> pa.Table:
            out = np.zeros(left.num_rows, np.int32)
            if right.num_rows and left.num_rows:
                values, known = matrix(left.column("__cf_h").combine_chunks())
                own = np.flatnonzero(known)
                if len(own):
                    out[own] = say(values[own], unpacked_table(right))
            made = pa.table([*[left.column(n) for n in names], pa.array(out, mask=out == 0)], names=[*names, "round"])
            return made

        schema = T.StructType([*df.schema.fields, T.StructField("round", T.IntegerType())])
        art = self.rows.withColumnRenamed("shard", "__cf_r")
        return self.hashed(df, key).groupBy("__cf_r").cogroup(art.groupBy("__cf_r")).applyInArrow(run, schema)

    def detached(self) -> "FilterSet":
        """Without the frame, fit to be sent to workers."""
        return replace(self, rows=None)


def matrix(column) -> tuple[np.ndarray, np.ndarray]:
    """Rows of an array column of equal lengths, and which are known."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    known = ~np.asarray(column.is_null())
    flat = column.flatten().to_numpy(zero_copy_only=False)
    width = len(flat) // max(int(known.sum()), 1)
    out = np.zeros((len(column), width), np.int64)
    out[known] = flat.reshape(-1, width) if width else 0
    return out, known


def unpacked(row) -> dict:
    return {"m": row["m"], "omega": row["omega"], "words": np.array(row["words"], np.int64), "cells": np.array(row["cells"] or [0], np.int64)}


def unpacked_table(table: pa.Table) -> dict:
    """``unpacked`` of a table of one row, without a Python number per word."""
    words, cells = (table.column(c).combine_chunks().flatten().to_numpy(zero_copy_only=False).astype(np.int64) for c in ("words", "cells"))
    return {"m": table.column("m")[0].as_py(), "omega": table.column("omega")[0].as_py(), "words": words, "cells": cells if len(cells) else np.zeros(1, np.int64)}
