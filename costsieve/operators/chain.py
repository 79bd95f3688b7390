"""The chain table: hash subsets stored as linked walks through small cells, and how a probe reads them back."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

FN, END = 31, 32  # a cell is the function's index plus 32 if a walk may end there; 0 is empty


def try_store(cells, start: int, nexts, subset, policy: str = "seeded", seed: int = 0):
    """Where a subset could go: (writes, last cell, shared cells), or None. Nothing is changed.

    ``cells`` maps a cell to its content, ``nexts[f]`` is the cell that function f (from 0) leads to. Every step either reuses a cell that already names a function of the
    subset still to be placed, or fills an empty one. ``seeded`` picks the function for an empty cell by a seed, ``exhaustive`` tries all orders and
    keeps the one with the most shared cells.
    """
    if policy == "exhaustive":
        return _best(cells, start, nexts, tuple(sorted(subset)), {}, 0)
    left, writes, at, shared, last = sorted(subset), {}, start, 0, start
    while left:
        content = (writes.get(at) or cells[at]) & FN
        if content:
            f = content - 1
            if f not in left:
                return None
            shared += 1
        else:
            f = left[(seed + len(left)) % len(left)]
            writes[at] = f + 1
        left.remove(f)
        last, at = at, nexts[f]
    return writes, last, shared


def _best(cells, at: int, nexts, left: tuple, writes: dict, shared: int):
    content = (writes.get(at) or cells[at]) & FN
    found = None
    for f in left if not content else ((content - 1,) if content - 1 in left else ()):
        rest = tuple(x for x in left if x != f)
        own = writes if content else {**writes, at: f + 1}
        out = _best(cells, nexts[f], nexts, rest, own, shared + bool(content)) if rest else (own, at, shared + bool(content))
        if out and (found is None or out[2] > found[2]):
            found = out
    return found


def commit(cells, stored) -> None:
    writes, last, _ = stored
    for at, content in writes.items():
        cells[at] = content | cells[at] & END
    cells[last] |= END


def lookup(cells, start: int, nexts, k: int, reject_repeats: bool = False):
    """The stored subset that a walk of k cells spells, or None for the default."""
    at, found = start, []
    for _ in range(k):
        content = cells[at]
        if not content & FN:
            return None
        found.append((content & FN) - 1)
        last, at = at, nexts[found[-1]]
    if not cells[last] & END or reject_repeats and len(set(found)) < k:
        return None
    return found


def lookup_batch(cells: np.ndarray, start: np.ndarray, nexts: np.ndarray, k: int, reject_repeats: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """(valid, functions from 0) of many keys at once."""
    n = len(start)
    at, valid, found, content = start.astype(np.int64), np.ones(n, bool), np.zeros((n, k), np.int64), None
    for j in range(k):
        content = cells[at]
        fn = content & FN
        valid &= fn > 0
        found[:, j] = np.maximum(fn.astype(np.int64) - 1, 0)
        at = nexts[np.arange(n), np.minimum(found[:, j], nexts.shape[1] - 1)]
    valid &= (content & END) > 0
    if reject_repeats:
        ordered = np.sort(found, axis=1)
        valid &= (ordered[:, 1:] != ordered[:, :-1]).all(axis=1)
    return valid, found


def walk_relational(keys: DataFrame, cells: DataFrame, k: int) -> DataFrame:
    """The walk as k joins. ``keys``: (key_id, start, nexts array); ``cells``: (cell, fn, ended), empty cells left out. Returns (key_id, subset): null for the default."""
    now = keys.select("key_id", "nexts", F.col("start").alias("at"), F.lit(True).alias("ok"), F.expr("cast(array() as array<int>)").alias("subset"))
    for step in range(k):
        final = step == k - 1
        joined = now.join(cells, now["at"] == cells["cell"], "left")
        ok = F.col("ok") & F.col("fn").isNotNull() & (F.col("ended") if final else F.lit(True))
        now = joined.select(
            "key_id",
            "nexts",
            F.element_at("nexts", F.coalesce(F.col("fn"), F.lit(1)).cast("int")).alias("at"),
            F.coalesce(ok, F.lit(False)).alias("ok"),
            F.concat("subset", F.array(F.coalesce(F.col("fn"), F.lit(0)).cast("int"))).alias("subset"),
        )
    return now.select("key_id", F.when(F.col("ok"), F.array_join("subset", ",")).alias("subset"))


def default_walks(positives: DataFrame, family, omega: int, k: int) -> DataFrame:
    """(key_id, fn, cell): the walk that stores each key's default subset in its own order. Function fn leads from its cell to the next."""
    from ..functions.hashing import START

    spots = [F.pmod(family.column(F.col("k"), i), F.lit(max(1, omega))) for i in (START, *range(1, k))]
    steps = F.array(*[F.struct(F.lit(j + 1).alias("fn"), spot.alias("cell")) for j, spot in enumerate(spots)])
    return positives.select("key_id", F.explode(steps).alias("s")).select("key_id", "s.fn", "s.cell")


def first_round(steps: DataFrame) -> DataFrame:
    """(cell, fn, ended) after one bulk round: a cell goes to the walk of the smallest key that wants it, and a walk is stored if all its cells name its functions."""
    first = steps.groupBy("cell").agg(F.min(F.struct("key_id", "fn")).alias("held"))
    kept = steps.join(first, "cell").groupBy("key_id").agg(F.bool_and(F.col("held.fn") == F.col("fn")).alias("stored"), F.collect_list(F.struct("cell", "fn")).alias("walk"))  # k entries
    last = steps.agg(F.max("fn").alias("last"))  # one row
    cells = kept.where("stored").select(F.explode("walk").alias("w")).select("w.cell", "w.fn")
    return cells.crossJoin(F.broadcast(last)).groupBy("cell").agg(F.first("fn").alias("fn"), F.max(F.col("fn") == F.col("last")).alias("ended"))


def load(cells: DataFrame, omega: int) -> DataFrame:
    return cells.agg(
        F.count(F.lit(1)).alias("used"), F.coalesce(F.sum(F.col("ended").cast("int")), F.lit(0)).cast("bigint").alias("ended"), F.round(F.count(F.lit(1)) / F.lit(omega), 6).alias("load")
    )
