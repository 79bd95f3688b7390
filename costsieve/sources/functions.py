"""SQL functions over built filters: a predicate, a packed-bits aggregate and a trace of walks."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import chain
from ..operators.filters import BROADCAST_BYTES, FilterSet, matrix, unpacked
from .shared import ship


def register_filter(spark: SparkSession, filt: FilterSet, name: str = "cf_contains") -> None:
    """A SQL predicate ``name(key)``. Keys are hashed by the family's own numbers, so only families with kernels will do."""
    ship(spark)
    if filt.total_bits // 8 > BROADCAST_BYTES:
        raise ValueError("the filter is too large to be sent to every task")
    shards = {r["shard"]: unpacked(r) for r in filt.rows.collect()}  # at most BROADCAST_BYTES
    sent, own = spark.sparkContext.broadcast(shards), filt.detached()
    from ..functions.hashing import ROUTER, START

    ids = [*own._raw_ids(), START]

    @F.pandas_udf("boolean")
    def contains(keys: pd.Series) -> pd.Series:
        values = np.array([[own.family.value(k, i) for i in ids] if k is not None else [0] * len(ids) for k in keys], np.int64).reshape(len(keys), len(ids))
        routed = np.array([own.family.value(k, ROUTER) % own.shards if k is not None and own.shards > 1 else 0 for k in keys])
        out = np.zeros(len(keys), bool)
        for s, shard in sent.value.items():
            mine = np.flatnonzero(routed == s)
            if len(mine):
                out[mine] = own.say(values[mine], shard) > 0
        return pd.Series(out & keys.notna().to_numpy())

    spark.udf.register(name, contains)


@F.pandas_udf("binary")
def pack_bits(positions: pd.Series) -> bytes:
    """Aggregate: the set positions of a group as a packed bit array, least bit first."""
    if not len(positions):
        return b""
    bits = np.zeros(int(positions.max()) + 1, np.uint8)
    bits[positions.to_numpy()] = 1
    return np.packbits(bits, bitorder="little").tobytes()


def trace_keys(filt: FilterSet, df: DataFrame, key: str = "k") -> DataFrame:
    """(k, step, cell, fn, ended): every step of each key's walk through the chain table, as far as it goes."""
    ship(df.sparkSession)
    if filt.total_bits // 8 > BROADCAST_BYTES:
        raise ValueError("the filter is too large to be sent to every task")
    shards = {r["shard"]: unpacked(r) for r in filt.rows.collect()}  # at most BROADCAST_BYTES
    sent, own = df.sparkSession.sparkContext.broadcast(shards), filt.detached()

    def run(batches):
        pool, raw = np.array(own.pool), own._raw_ids()
        place = np.zeros(max(*raw, *own.pool) + 1, np.int64)  # column of each function's hash value
        place[raw] = np.arange(len(raw))
        for batch in batches:
            values, known = matrix(batch.column("__cf_h"))
            routed = batch.column("__cf_r").to_numpy(zero_copy_only=False)
            for s in np.unique(routed):
                rows = np.flatnonzero((routed == s) & known)
                shard = sent.value.get(s)
                if shard is None or not len(rows):
                    continue
                omega = max(1, shard["omega"])
                at = values[rows, -1] % omega
                for step in range(own.k):
                    content = shard["cells"][at]
                    fn = content & chain.FN
                    columns = [batch.column(key).take(pa.array(rows)), np.full(len(rows), step + 1, np.int32), at.astype(np.int64), fn.astype(np.int32), content >= chain.END]
                    yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], ["k", "step", "cell", "fn", "ended"])
                    going = fn > 0  # an empty cell ends the walk
                    rows, ids = rows[going], pool[fn[going] - 1]
                    if not len(rows):
                        break
                    if own.fast:
                        at = (values[rows, 0] % omega + ids * (values[rows, 1] % omega)) % omega
                    else:
                        at = values[rows, place[ids]] % omega

    return filt.hashed(df.select(key), key).mapInArrow(run, "k string, step int, cell bigint, fn int, ended boolean")
