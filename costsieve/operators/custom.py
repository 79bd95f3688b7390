"""The custom-hash filter: a bit array plus a chain table, built shard by shard."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.geometry import Geometry, split
from ..functions.hashing import BASE_A, BASE_B, START, Family
from ..sources.shared import ship
from . import bloom
from .filters import ARTEFACT, FilterSet, matrix, route, written
from .optimiser import OptimiserPolicy, Shard

SHARD_KEYS = 1 << 20  # a shard holds about so many keys, negatives included


def shards_for(n: int, size: int = SHARD_KEYS) -> int:
    return max(1, -(-n // size))


def build(
    positives: DataFrame,
    negatives: DataFrame,
    total_bits: int,
    k: int = 3,
    delta: float = 0.25,
    alpha: int = 4,
    family: Family = Family(),
    fast: bool = False,
    policy: OptimiserPolicy = OptimiserPolicy(),
    shards: int | None = None,
    allow_degenerate: bool = False,
) -> FilterSet:
    """Build from positives (key_id, k) and known negatives (key_id, k, cost). One shuffle brings each shard's keys together; raw hash values are computed
    before it in the JVM, so that the strings stay behind. With ``delta=0`` it is the standard filter: one bit array, however many keys there are, unless ``shards`` asks for more."""
    if shards is None:
        shards = shards_for(positives.count() + negatives.count()) if delta else 1
    geometry = split(total_bits // shards, delta, alpha)
    if geometry.pool <= k and not allow_degenerate and delta:
        raise ValueError(f"{geometry.pool} functions leave nothing to swap in for k={k}")
    k = min(k, geometry.pool) if delta else k
    pool = tuple(range(1, geometry.pool + 1)) if delta else ()
    default = tuple(range(1, k + 1))
    method = "custom-fast" if fast else "custom"
    if not delta:
        made = bloom.build(positives, total_bits, family, k=k, shards=shards, fast=fast)
        made.method = method
        return made
    ship(positives.sparkSession)
    ids = [BASE_A, BASE_B] if fast else list(pool)
    raw = [*ids, START]

    def hashed(df: DataFrame, positive: bool) -> DataFrame:
        # a negative needs only the default functions
        own = raw if positive or fast else raw[:k]
        return df.select(
            route(family, F.col("k"), shards).alias("shard"),
            F.lit(positive).alias("positive"),
            "key_id",
            (F.lit(0.0) if positive else F.col("cost").cast("double")).alias("cost"),
            family.columns(F.col("k"), own).alias("h"),
        )

    both = hashed(positives, True).unionByName(hashed(negatives, False)).where(F.col("h").isNotNull())
    rows = both.groupBy("shard").applyInArrow(_kernel(geometry, default, pool, fast, policy), ARTEFACT)
    return FilterSet(method, written(rows, method), family, shards, default, pool, fast, geometry.total_bits * shards)


def _kernel(geometry: Geometry, default: tuple[int, ...], pool: tuple[int, ...], fast: bool, policy: OptimiserPolicy):
    def spots(values: np.ndarray, ids, size: int) -> np.ndarray:
        if not fast:
            return values[:, [i - 1 for i in ids]] % size
        a, b = values[:, 0] % size, values[:, 1] % size
        return np.stack([(a + i * b) % size for i in ids], axis=1)

    def run(table: pa.Table) -> pa.Table:
        import resource
        import time

        begin = time.perf_counter()
        chosen = np.asarray(table.column("positive"))
        key_id, cost = (table.column(c).to_numpy() for c in ("key_id", "cost"))
        yes, no = table.filter(pa.array(chosen)), table.filter(pa.array(~chosen))
        s, o = matrix(yes.column("h"))[0], matrix(no.column("h"))[0]
        if not len(s):
            s = np.zeros((0, len(pool) + 1 if not fast else 3), np.int64)
        if not len(o):
            o = np.zeros((0, len(default) if not fast else 3), np.int64)
        omega = max(1, geometry.omega)
        order_s, order_o = np.argsort(key_id[chosen], kind="stable"), np.argsort(key_id[~chosen], kind="stable")  # no result hangs on the order of rows
        s, o = s[order_s], o[order_o]
        shard = Shard(
            spots(s, pool, geometry.m),
            spots(s, pool, omega),
            s[:, -1] % omega,
            key_id[chosen][order_s],
            spots(o, default, geometry.m),
            cost[~chosen][order_o],
            key_id[~chosen][order_o],
            geometry,
            tuple(i - 1 for i in default),
            policy,
            fast,
        ).run()
        used = sum(1 for c in shard.cells if c)
        stats = {k: float(v) for k, v in shard.stats.items()} | {
            "positives": float(len(s)),
            "negatives": float(len(o)),
            "ones": float((shard.hits > 0).sum()),
            "used_cells": float(used),
            "kernel_s": time.perf_counter() - begin,
            "peak_kb": float(resource.getrusage(resource.RUSAGE_SELF).ru_maxrss),
        }
        row = {
            "shard": table.column("shard")[0].as_py(),
            "m": geometry.m,
            "omega": geometry.omega,
            "alpha": geometry.alpha,
            "words": shard.words().tolist(),
            "cells": list(shard.cells),
            "stats": list(stats.items()),
        }
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
        return pa.Table.from_pylist([row], kinds)

    return run


def insert_late(filt: FilterSet, positives: DataFrame) -> FilterSet:
    """Add positives under the default subset. Bits are only set, so none is lost; negatives may pass again."""
    m = filt.rows.select("m").first()["m"]
    more = bloom.packed_by_sort(bloom.bit_words(positives, m, filt.family, list(filt.default), filt.shards, filt.fast), m).select("shard", F.col("words").alias("__w"))
    joined = filt.rows.join(more, "shard", "left")
    words = F.when(F.col("__w").isNull(), F.col("words")).otherwise(F.zip_with("words", "__w", lambda x, y: x.bitwiseOR(y)))
    rows = joined.withColumn("words", words).select(*ARTEFACT.names)
    return FilterSet(filt.method, written(rows, "late"), filt.family, filt.shards, filt.default, filt.pool, filt.fast, filt.total_bits, filt.reject_repeats)
