"""Grids of settings, evaluated in one distributed job: build each filter, probe all its keys, and add up the measures.

Settings are dealt to a few lanes and keys to shards; a task holds one shard's keys and runs its lane's settings one after the other. Keys travel as they are, in
compressed pieces, once per lane, and the fewer lanes the more shards there are; a task hashes them under the functions that its settings ask for, each once. What
settings that differ in their costs alone have in common is made once. The standard filter (md5x) stays one bit array over all shards, whatever its size: arrays that
are small together are made beforehand and sent to the tasks that ask for them; otherwise the places that a shard's keys set or ask for travel to the arrays' segments and
answers come back. Both give the same bits and answers. Sums over shards give the measures, so the same job serves any number of keys.
"""

from __future__ import annotations

import math
import time
import tracemalloc
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import geometry, theory
from ..functions.hashing import BASE_A, BASE_B, KERNELS, ROUTER, START, Family, batches, bulk, city64, city_seeded, md5_values, wide_values
from ..operators.baselines import ALPHA, xor_table
from ..operators.custom import shards_for
from ..operators.filters import FilterSet
from ..operators.optimiser import OptimiserPolicy, Shard
from ..sources.shared import ship

POOL_IDS = list(range(1, 23))
IDS = [*POOL_IDS, START, BASE_A, BASE_B, ROUTER]


@dataclass(frozen=True)
class Setting:
    method: str
    bits_per_key: float
    label: str = ""
    k: int = 3
    delta: float = 0.25
    alpha: int = 4
    skew: float = 0.0  # of the costs; below 0 the keys' own costs are used
    seed: int = 1
    policy: OptimiserPolicy = OptimiserPolicy()
    k_fixed: bool = False  # standard filter: use k instead of the best number
    parts: int = 1  # custom filter: so many shards inside this one, each with its own optimiser
    repeats: int = 1  # times are medians of so many runs


class Hashes:
    """A matrix of hash values, one row per key, whose columns are computed when they are first asked for. ``spent`` are the seconds that took, which belong to no filter."""

    spent = 0.0

    def __init__(self, n: int, width: int, column):
        self.n, self.width, self.make, self.held = n, width, column, {}

    def __len__(self) -> int:
        return self.n

    def column(self, i: int) -> np.ndarray:
        i %= self.width
        if i not in self.held:
            begin, inner = time.perf_counter(), Hashes.spent
            self.held[i] = self.make(i)
            Hashes.spent = inner + time.perf_counter() - begin
        return self.held[i]

    def picked(self, columns: list[int]) -> "Hashes":
        return Hashes(self.n, len(columns), lambda i: self.column(columns[i]))

    def __getitem__(self, at):
        """``[rows]`` is a matrix again; ``[rows, columns]`` gives the numbers."""
        if not isinstance(at, tuple):
            return Hashes(len(np.arange(self.n)[at]), self.width, lambda i: self.column(i)[at])
        rows, columns = at
        if isinstance(columns, (int, np.integer)):
            return self.column(columns)[rows]
        chosen = range(*columns.indices(self.width)) if isinstance(columns, slice) else columns
        found = [self.column(i)[rows] for i in chosen]
        return np.stack(found, axis=1) if found else np.zeros((len(self.column(0)[rows]), 0), np.int64)


def _alive(values: Hashes, m: int, k: int, answer) -> np.ndarray:
    """Which keys have a yes for the places of all their functions; ``answer`` says which of some places are set."""
    rows = np.arange(len(values))
    for i in range(k):
        rows = rows[answer(values.column(i)[rows] % m)]
    hit = np.zeros(len(values), bool)
    hit[rows] = True
    return hit


@dataclass
class Sent:
    """Bit arrays of the standard filters over the keys of all shards, by (bits, functions); ``sent`` holds them packed."""

    n: int
    shards: int
    sent: object

    def filter(self, d: "Data", m: int, k: int):
        packed = self.sent.value[m, k]
        begin = clock()
        _bits(d.s[:, list(range(k))] % m, m)  # the shard's part of the work
        took = clock() - begin

        def passes(values: Hashes, positive: bool) -> np.ndarray:
            return _alive(values, m, k, lambda at: (packed[at >> 3] >> (at & 7).astype(np.uint8) & 1).view(bool))

        return passes, float(np.bitwise_count(packed).sum(dtype=np.int64)) / self.shards, took


@dataclass
class Told:
    """What those filters have answered for the places that a shard's keys set or ask for (rows of ANSWERS), each place once and in order."""

    n: int
    shards: int
    sizes: list[tuple[int, int]]
    rows: pa.Table

    def _side(self, m: int, k: int, positive: bool) -> tuple[np.ndarray, float, float]:
        """(answers, the shard's share of the bits that are set, seconds that the places took)"""
        size_is, side_is = (np.asarray(self.rows.column(c)) == v for c, v in (("size", self.sizes.index((m, k))), ("positive", positive)))
        own = self.rows.filter(pa.array(size_is & side_is)).sort_by("segment")
        parts = [
            np.unpackbits(np.frombuffer(pa.decompress(bits.as_buffer(), -(-n // 8), "zstd", asbytes=True), np.uint8), count=n)
            for bits, n in zip(own.column("answers"), own.column("count").to_pylist())
        ]
        return np.concatenate([np.zeros(0, np.uint8), *parts]).view(bool), *(float(np.asarray(own.column(c)).sum()) for c in ("ones", "took"))

    def filter(self, d: "Data", m: int, k: int):
        sides = {positive: self._side(m, k, positive) for positive in (True, False)}

        def passes(values: Hashes, positive: bool) -> np.ndarray:
            answers = sides[positive][0]
            if positive and len(answers) and answers.all():  # all that the keys set was found
                return np.ones(len(values), bool)
            places = _places(values, m, k)
            if len(answers) != len(places):
                raise RuntimeError(f"{len(answers)} answers to {len(places)} places: the keys changed between two reads")

            def answer(at: np.ndarray) -> np.ndarray:
                order, found = np.argsort(at), np.empty(len(at), bool)
                found[order] = answers[np.searchsorted(places, at[order])]
                return found

            return _alive(values, m, k, answer)

        return passes, sides[True][1] + sides[False][1], sides[True][2]


@dataclass
class Data:
    s: Hashes  # hash values of positives, in the order of IDS
    o: Hashes
    ids_s: np.ndarray
    ids_o: np.ndarray
    natural: np.ndarray
    score_s: np.ndarray
    score_o: np.ndarray
    other_s: dict[str, Hashes] = field(default_factory=dict)  # values of other families
    other_o: dict[str, Hashes] = field(default_factory=dict)
    measured: dict[Setting, tuple] = field(default_factory=dict)  # what does not hang on costs
    whole: "Sent | Told | None" = None  # standard filters of all shards together
    started: dict[tuple, tuple[Shard, float]] = field(default_factory=dict)  # the optimiser before its first step, and the seconds it took to get there

    def on(self, family: str) -> "Data":
        """The same keys with the first functions of another family in the place of the default one's."""
        def beside(own: Hashes, rest: Hashes) -> Hashes:
            return Hashes(rest.n, rest.width, lambda i: own.column(i) if i < own.width else rest.column(i))

        return replace(self, s=beside(self.other_s[family], self.s), o=beside(self.other_o[family], self.o))

    def costs(self, setting: Setting) -> np.ndarray:
        n = len(self.o)
        if setting.skew < 0:
            return self.natural
        if not setting.skew:
            return np.ones(n)
        rank = np.random.default_rng(setting.seed).permutation(n) + 1.0
        return rank**-setting.skew


def _bits(places: np.ndarray, m: int) -> np.ndarray:
    bits = np.zeros(m, bool)
    bits[places.ravel()] = True
    return bits


def _standard(d: Data, total: int, k: int, columns: list[int] | None = None):
    m = max(32, total)
    own = columns or list(range(k))
    bits = _bits(d.s[:, own] % m, m)
    return lambda values: bits[values[:, own] % m].all(axis=1), {"ones": bits.sum(), "bits": m}


def _places(values: Hashes, m: int, k: int) -> np.ndarray:
    """Places of all keys in an array of m bits, each once and in order."""
    n, columns = len(values), [values.column(i) for i in range(k)]
    found = np.empty(n * k, np.int64)
    for i, column in enumerate(columns):
        np.mod(column, m, out=found[i * n : (i + 1) * n])
    found.sort()
    return found[np.r_[True, found[1:] != found[:-1]]] if n else found


def _whole_standard(d: Data, setting: Setting):
    """The shard's part of the filter that all shards share. A build takes as long as placing the shard's own keys does."""
    m, k = _whole_size(d.whole.n, setting)
    passes, ones, took = d.whole.filter(d, m, k)
    passes.by_side = True
    return passes, {"ones": ones, "bits": m / d.whole.shards, "own_s": took}


def _whole_size(n: int, setting: Setting) -> tuple[int, int]:
    return max(32, geometry.budget(n, setting.bits_per_key)), setting.k if setting.k_fixed else min(22, geometry.best_k(setting.bits_per_key))


def _parted(d: Data, setting: Setting, total: int, cost: np.ndarray, fast: bool):
    """Shards by the router hash, with disjoint bits and cells, as a build of that many shards makes them."""
    router, own = IDS.index(ROUTER), replace(setting, parts=1)
    made = []
    for p in range(setting.parts):
        s, o = d.s[:, router] % setting.parts == p, d.o[:, router] % setting.parts == p
        part = replace(d, s=d.s[s], o=d.o[o], ids_s=d.ids_s[s], ids_o=d.ids_o[o], started={})
        made.append(_custom(part, own, total // setting.parts, cost[o], fast))

    def rounds(values: np.ndarray) -> np.ndarray:
        out = np.zeros(len(values), np.int64)
        for p, (passes, _) in enumerate(made):
            rows = np.flatnonzero(values[:, router] % setting.parts == p)
            out[rows] = passes.rounds(values[rows]) if len(rows) else 0
        return out

    passes = lambda values: rounds(values) > 0
    passes.rounds = rounds
    return passes, {key: sum(stats[key] for _, stats in made) for key in made[0][1]}


def _custom(d: Data, setting: Setting, total: int, cost: np.ndarray, fast: bool):
    if setting.parts > 1:
        return _parted(d, setting, total, cost, fast)
    if not setting.delta:
        return _standard(d, total, setting.k)
    g = geometry.split(total, setting.delta, setting.alpha)
    k = min(setting.k, g.pool)
    omega = max(1, g.omega)
    a, b = IDS.index(BASE_A), IDS.index(BASE_B)

    def spots(values: np.ndarray, count: int, size: int) -> np.ndarray:
        if not fast:
            return values[:, :count] % size
        return (values[:, [a]] % size + np.arange(1, count + 1)[None, :] * (values[:, [b]] % size)) % size

    start = IDS.index(START)
    alike, shared = (replace(setting, skew=0.0, seed=0, label=""), total), 0.0
    if alike in d.started:
        shared = d.started[alike][1]
    else:
        d.started.clear()  # settings that are alike follow each other
        begin = clock()
        made = Shard(
            spots(d.s, g.pool, g.m), spots(d.s, g.pool, omega), d.s[:, start] % omega, d.ids_s, spots(d.o, k, g.m), cost, d.ids_o, g, tuple(range(k)), setting.policy, fast
        ).indexed()
        d.started[alike] = made, clock() - begin
    shard = d.started[alike][0].anew(cost).run()
    art = {"m": g.m, "omega": g.omega, "words": shard.words(), "cells": np.frombuffer(bytes(shard.cells), np.uint8).astype(np.int64)}
    filt = FilterSet(setting.method, None, Family(), 1, tuple(range(1, k + 1)), tuple(range(1, g.pool + 1)), fast)
    columns = [a, b, start] if fast else [*range(max(k, g.pool)), start]
    stats = dict(shard.stats) | {"ones": (shard.hits > 0).sum(), "used_cells": sum(1 for c in shard.cells if c), "omega": g.omega, "bits": g.total_bits, "shared_s": shared}

    def rounds(values: Hashes) -> np.ndarray:
        return filt.say(values.picked(columns), art)

    passes = lambda values: rounds(values) > 0
    passes.rounds = rounds
    coll = np.flatnonzero(shard.clear == 0)
    stats["owner_bits"] = float(len(coll))
    return passes, stats


def _xor(d: Data, total: int):
    bits = geometry.fingerprint_bits(total / max(len(d.s), 1), max(len(d.s), 1))
    values = d.s[:, [0, 1, 2, 3]]
    table, seed = xor_table(values, bits)
    from ..operators.baselines import _slots

    def passes(v: np.ndarray) -> np.ndarray:
        return np.bitwise_xor.reduce(table[_slots(v, len(table) // 3, seed)], axis=1) == v[:, 3] & (1 << bits) - 1

    return passes, {"bits": len(table) * bits}


def _weighted(d: Data, total: int, cost: np.ndarray, most: int = 12, share: float = 0.01):
    m = max(32, total)
    k = min(most, geometry.best_k(total / max(len(d.s), 1)))
    bits = _bits(d.s[:, :k] % m, m)
    cached = np.argsort(-cost, kind="stable")[: max(1, int(len(cost) * share))] if len(cost) else np.empty(0, int)
    mean = float(np.log2(cost).mean()) if len(cost) else 0.0
    counts = np.clip(np.round(k + np.log2(cost[cached]) - mean), k, most).astype(int)
    extra = dict(zip(d.ids_o[cached].tolist(), counts.tolist()))

    def passes(values: np.ndarray, ids: np.ndarray | None = None) -> np.ndarray:
        need = np.full(len(values), k) if ids is None else np.array([extra.get(i, k) for i in ids.tolist()])
        held = bits[values[:, :most] % m]
        return (held | (np.arange(most)[None, :] >= need[:, None])).all(axis=1)

    passes.by_id = True
    return passes, {"ones": bits.sum(), "bits": m, "cache_rows": len(extra)}


def _learned(d: Data, setting: Setting, total: int, model_bits: int):
    left, n = total - model_bits, max(len(d.s), 1)
    if left < 64:
        return None, {"infeasible": 1}
    cuts = np.unique(np.r_[np.quantile(d.score_s, np.arange(1, 40) / 40), np.quantile(d.score_o, np.arange(1, 40) / 40), 2.0])
    best = (math.inf, 2.0, 0)
    for cut in cuts:
        fp, missed = float((d.score_o >= cut).mean()), max(float((d.score_s < cut).mean()), 1 / n)
        for part in np.arange(0, 1, 0.1) if setting.method == "sandwiched" else (0.0,):
            rate = (ALPHA ** (left * part / n) if part else 1.0) * (fp + (1 - fp) * ALPHA ** (left * (1 - part) / n / missed))
            if rate < best[0]:
                best = (rate, cut, int(left * part))
    _, cut, first_bits = best
    low = d.s[d.score_s < cut]
    back = None
    if len(low):
        back = _standard(replace_s(d, low), left - first_bits, min(22, geometry.best_k((left - first_bits) / len(low))))[0]
    first = _standard(d, first_bits, min(22, geometry.best_k(first_bits / n)))[0] if first_bits >= 64 else None

    def passes(values: np.ndarray, score: np.ndarray) -> np.ndarray:
        yes = score >= cut
        if back is not None:
            yes = yes | back(values)
        return yes & first(values) if first is not None else yes

    passes.by_score = True
    return passes, {"bits": total, "threshold": cut}


def replace_s(d: Data, s: Hashes) -> Data:
    return replace(d, s=s)


def _adaptive(d: Data, total: int, model_bits: int, groups: int = 4):
    m, n = total - model_bits, max(len(d.s), 1)
    stats = {"bits": total}
    if m < 64:
        return None, {"infeasible": 1}
    best = None
    for ratio in (1.5, 2.0, 3.0, 5.0, 9.0):
        shares = np.array([ratio**-i for i in range(groups)])
        cuts = np.quantile(d.score_o, np.cumsum(shares / shares.sum())[:-1])
        share_s, share_o = (np.bincount(np.searchsorted(cuts, x, side="right"), minlength=groups) / max(len(x), 1) for x in (d.score_s, d.score_o))
        for k_max in range(2, 13):
            for low in (0, 1):
                ks = np.round(np.linspace(k_max, low, groups)).astype(int)
                load = 1 - math.exp(-n * float((share_s * ks).sum()) / m)
                rate = float((share_o * load**ks).sum())
                if best is None or rate < best[0]:
                    best = (rate, cuts, ks)
    _, cuts, ks = best
    most = max(1, int(ks.max()))
    need = ks[np.searchsorted(cuts, d.score_s, side="right")]
    used = (d.s[:, :most] % m)[np.arange(most)[None, :] < need[:, None]]
    bits = _bits(used, m)

    def passes(values: np.ndarray, score: np.ndarray) -> np.ndarray:
        count = ks[np.searchsorted(cuts, score, side="right")]
        return (bits[values[:, :most] % m] | (np.arange(most)[None, :] >= count[:, None])).all(axis=1)

    passes.by_score = True
    return passes, stats


def build(d: Data, setting: Setting, cost: np.ndarray, model_bits: int):
    total = geometry.budget(len(d.s), setting.bits_per_key)
    if setting.method in ("custom", "custom-fast"):
        return _custom(d, setting, total, cost, setting.method == "custom-fast")
    if setting.method == "standard" and d.whole:
        return _whole_standard(d, setting)
    if setting.method == "standard":
        return _standard(d, total, setting.k if setting.k_fixed else min(22, geometry.best_k(setting.bits_per_key)))
    if setting.method.startswith("standard-"):
        return _standard(d.on(setting.method.removeprefix("standard-")), total, min(SEEDED, geometry.best_k(setting.bits_per_key)))
    if setting.method == "custom-pool":
        return _custom(d.on("pool"), setting, total, cost, False)
    if setting.method == "xor":
        return _xor(d, total)
    if setting.method == "weighted":
        return _weighted(d, total, cost)
    if setting.method in ("learned", "sandwiched"):
        return _learned(d, setting, total, model_bits)
    if setting.method == "adaptive":
        return _adaptive(d, total, model_bits)
    raise ValueError(f"unknown method {setting.method}")


SEEDED = 16  # functions of other families
LEARNED = ("learned", "sandwiched", "adaptive")
OTHERS = ("standard-pool", "standard-city64", "standard-murmur128", "custom-pool")


def _other_family(name: str, keys: list[bytes]) -> Hashes:
    """Values from the pool's different functions, or from seeds of one function."""
    groups = batches(keys)
    base = bulk(city64, groups) if name == "city64" else None
    makers = {
        "pool": lambda i: bulk(KERNELS[i + 1], groups).astype(np.int64),
        "city64": lambda i: city_seeded(base, np.array([i + 1]))[:, 0],
        "murmur128": lambda i: bulk(lambda batch: wide_values(batch, i + 1), groups).astype(np.int64),
    }
    return Hashes(len(keys), SEEDED, makers[name])


def _family_of(setting: Setting) -> str:
    return setting.method.split("-")[1] if setting.method in OTHERS else ""


def _dealt(settings: list[Setting], lanes: int) -> list[list[int]]:
    """Places of settings per lane: runs of about equal work in an order that keeps families and methods together, so that a lane needs few functions."""
    order = sorted(range(len(settings)), key=lambda i: (_family_of(settings[i]), settings[i].method, settings[i].bits_per_key, i))
    work = np.cumsum([10 if settings[i].method.startswith("custom") else 1 for i in order])
    dealt: list[list[int]] = [[] for _ in range(lanes)]
    for i, upto in zip(order, work):
        dealt[min(lanes - 1, int((upto - 1) * lanes // work[-1]))].append(i)
    return dealt


def spread(n: int) -> list[int]:
    """n numbers that a hash partitioning into n parts sends to one part each."""
    found: dict[int, int] = {}
    number = 0
    while len(found) < n:
        value = KERNELS[3](number.to_bytes(4, "little"))
        found.setdefault((value - (1 << 32) if value >> 31 else value) % n, number)
        number += 1
    return [found[i] for i in range(n)]


def clock() -> float:
    """Seconds without those of hashing: times start from hash values."""
    return time.perf_counter() - Hashes.spent


def _timed(d: Data, setting: Setting, cost: np.ndarray, model_bits: int, memory: bool):
    """(answers for positives, for negatives, statistics, which pass in round two, seconds of building, of probing, bytes), or None if the setting is infeasible."""
    built, probed = [], []
    if setting.repeats > 1 or memory:
        build(d, setting, cost, model_bits)  # warms up, and leaves no keys to be hashed
    if memory:
        tracemalloc.start()
    for _ in range(setting.repeats):
        if memory or setting.repeats > 1:
            d.started.clear()
        begin = clock()
        passes, stats = build(d, setting, cost, model_bits)
        built.append(stats.pop("own_s", clock() - begin) + stats.pop("shared_s", 0.0))
    peak = tracemalloc.get_traced_memory()[1] if memory else 0
    if memory:
        tracemalloc.stop()
    if passes is None:
        return None
    if _family_of(setting):
        d = d.on(_family_of(setting))
    for _ in range(setting.repeats):
        begin = clock()
        if getattr(passes, "by_score", False):
            yes, no = passes(d.s, d.score_s), passes(d.o, d.score_o)
        elif getattr(passes, "by_id", False):
            yes, no = passes(d.s, d.ids_s), passes(d.o, d.ids_o)
        elif getattr(passes, "by_side", False):
            yes, no = passes(d.s, True), passes(d.o, False)
        else:
            answers = getattr(passes, "rounds", passes)
            yes, no = answers(d.s), answers(d.o)
        probed.append(clock() - begin)
    second = no == 2 if hasattr(passes, "rounds") else np.zeros(len(d.o), bool)
    return yes > 0, no > 0, stats, second, built, probed, peak


def _measure(d: Data, setting: Setting, model_bits: int, memory: bool) -> dict[str, float]:
    """Filters that know no costs are built once for all the costs they are weighed by; these settings then share their times."""
    cost = d.costs(setting)
    blind = not setting.method.startswith(("custom", "weighted"))
    alike = replace(setting, skew=0.0, seed=0, label="") if blind else None
    if alike not in d.measured:
        d.measured.clear()  # settings that are alike follow each other
        d.measured[alike] = _timed(d, setting, cost, model_bits, memory)
    found = d.measured[alike] if blind else d.measured.pop(alike)
    if found is None:
        return {"n": len(d.s), "o": len(d.o), "infeasible": 1.0}
    yes, no, stats, second, built, probed, peak = found
    found = {k: float(v) for k, v in stats.items() if k not in ("threshold", "owner_bits")}
    return found | {
        "n": len(d.s),
        "o": len(d.o),
        "fn": float((~yes).sum()),
        "fp": float(no.sum()),
        "fp_round2": float(second.sum()),
        "cost_passed": float(cost[no].sum()),
        "cost_all": float(cost.sum()),
        "build_s": float(np.median(built)),
        "probe_s": float(np.median(probed)),
        "peak_bytes": float(peak),
    }


def _pieces(batches, shards: int):
    """Rows (shard, keys): a shard's keys of the task, or of a long run of its rows, as a compressed Arrow stream. Digits and constants take a fraction of their bytes so."""
    most = min(1 << 20, max(1 << 17, shards << 12))  # rows in memory; pieces stay large enough to be worth their headers

    def packed(held: list[pa.RecordBatch]) -> pa.RecordBatch:
        table = pa.Table.from_batches(held).combine_chunks()
        shard = table.column("shard").to_numpy()
        order, rest = np.argsort(shard, kind="stable"), table.drop_columns(["shard"])
        own, first = np.unique(shard[order], return_index=True)
        found = []
        for rows in np.split(order, first[1:]):
            sink = pa.BufferOutputStream()
            with pa.ipc.new_stream(sink, rest.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as out:
                out.write_table(rest.take(pa.array(rows)).combine_chunks())
            found.append(sink.getvalue().to_pybytes())
        return pa.RecordBatch.from_arrays([pa.array(own, pa.int32()), pa.array(found, pa.binary())], ["shard", "keys"])

    held, n = [], 0
    for batch in batches:
        if batch.num_rows:
            held, n = [*held, batch], n + batch.num_rows
        if n >= most:
            yield packed(held)
            held, n = [], 0
    if held:
        yield packed(held)


SENT_BYTES = 64 << 20  # of a grid's bit arrays together: driver and tasks hold them, and a task unpacks one
SEGMENT = 1 << 17  # bytes of a bit array in a row


def _segments(batches, sizes: list[tuple[int, int]], length: int):
    """Rows (size, segment, bits) of ``length`` bytes: what a task's keys, or a million of them, set in each array, compressed."""
    def made(keys: list[bytes]) -> pa.RecordBatch:
        columns, found = [md5_values(keys, i + 1) for i in range(max(k for _, k in sizes))], []
        for j, (m, k) in enumerate(sizes):
            bits = np.zeros(m, bool)
            for column in columns[:k]:
                bits[column % m] = True
            data = np.packbits(bits, bitorder="little").tobytes()
            found += [(j, at // length, pa.compress(data[at : at + length], "zstd", asbytes=True)) for at in range(0, len(data), length)]
        size, segment, bits = zip(*found)
        return pa.RecordBatch.from_arrays([pa.array(size, pa.int32()), pa.array(segment, pa.int32()), pa.array(bits, pa.binary())], ["size", "segment", "bits"])

    held: list[bytes] = []
    for batch in batches:
        held += batch.column("k").cast(pa.binary()).to_pylist()
        if len(held) >= 1 << 20:
            yield made(held)
            held = []
    if held:
        yield made(held)


def _united(positives: DataFrame, sizes: list[tuple[int, int]]) -> dict[tuple[int, int], np.ndarray]:
    """The packed bit arrays of these sizes over all keys, on the driver: at most SENT_BYTES."""
    segment_bytes = SEGMENT

    def either(rows: pa.Table) -> pa.Table:
        j, segment = rows.column("size")[0].as_py(), rows.column("segment")[0].as_py()
        length = min(segment_bytes, -(-sizes[j][0] // 8) - segment * segment_bytes)
        united = np.zeros(length, np.uint8)
        for bits in rows.column("bits"):
            united |= np.frombuffer(pa.decompress(bits.as_buffer(), length, "zstd", asbytes=True), np.uint8)
        return pa.table({"size": pa.array([j], pa.int32()), "segment": pa.array([segment], pa.int32()), "bits": pa.array([united.tobytes()], pa.binary())})

    schema = "size int, segment int, bits binary"
    parts = positives.where(F.col("k").isNotNull()).select("k").mapInArrow(lambda batches: _segments(batches, sizes, segment_bytes), schema)
    found = {size: np.zeros(-(-size[0] // 8), np.uint8) for size in sizes}
    for row in parts.groupBy("size", "segment").applyInArrow(either, schema).toLocalIterator():
        at = row["segment"] * segment_bytes
        found[sizes[row["size"]]][at : at + len(row["bits"])] = np.frombuffer(bytes(row["bits"]), np.uint8)
    return found


GROUP = 1 << 20  # bytes of a bit array in a group, if no negatives ask for it
PLACES = "size int, segment int, slot int, positive boolean, count int, took double, places binary"
ANSWERS = "slot int, size int, segment int, positive boolean, count int, took double, ones double, answers binary"


def _steps(places: np.ndarray) -> bytes:
    """Rising numbers as their differences, low bytes first, compressed."""
    return pa.compress(np.diff(places, prepend=0).astype("<u4").view(np.uint8).reshape(-1, 4).T.tobytes(), "zstd", asbytes=True)


def _summed(data: pa.Buffer, n: int) -> np.ndarray:
    """The numbers that ``_steps`` was given."""
    planes = np.frombuffer(pa.decompress(data, 4 * n, "zstd", asbytes=True), np.uint8).reshape(4, n)
    return np.cumsum(np.ascontiguousarray(planes.T).view("<u4").ravel(), dtype=np.int64)


def _asked(sides: dict[bool, Hashes], slot: int, sizes: list[tuple[int, int]], wanted: set[tuple[int, int]], length: int) -> pa.Table:
    """Rows of PLACES: what a shard's keys set (positive) or ask for in each segment of ``length`` bits of the arrays that its lane wants."""
    found = []
    for j, (m, k) in enumerate(sizes):
        for positive, values in sides.items() if (m, k) in wanted else ():
            begin = clock()
            places = _places(values, m, k)
            took = clock() - begin
            cuts = np.searchsorted(places, np.arange(0, m + length, length))
            filled = np.flatnonzero(np.diff(cuts)).tolist()
            for segment in filled:
                own = places[cuts[segment] : cuts[segment + 1]] - segment * length
                found.append((j, segment, slot, positive, len(own), took / len(filled), _steps(own)))
    kinds = (pa.int32(), pa.int32(), pa.int32(), pa.bool_(), pa.int32(), pa.float64(), pa.binary())
    columns = list(zip(*found)) if found else [()] * len(kinds)
    return pa.table([pa.array(c, kind) for c, kind in zip(columns, kinds)], names=[c.split()[0] for c in PLACES.split(", ")])


def _answered(rows: pa.Table, length: int, lane_of: dict[int, int]) -> pa.Table:
    """Rows of ANSWERS: a segment with the bits of all shards' positives, looked up. Each lane that asks is told all its set bits, in equal shares."""
    slots, positive, counts = (rows.column(c).to_pylist() for c in ("slot", "positive", "count"))
    places = [_summed(data.as_buffer(), n) for data, n in zip(rows.column("places"), counts)]
    bits = np.zeros(length, bool)
    for own, sets in zip(places, positive):
        if sets:
            bits[own] = True
    lanes = [lane_of[slot] for slot in slots]
    ones = [float(bits.sum()) / lanes.count(lane) for lane in lanes]
    answers = [pa.compress(np.packbits(bits[own]).tobytes(), "zstd", asbytes=True) for own in places]
    own = rows.select(["slot", "size", "segment", "positive", "count", "took"])
    return own.append_column("ones", pa.array(ones, pa.float64())).append_column("answers", pa.array(answers, pa.binary()))


def run(positives: DataFrame, negatives: DataFrame, settings: list[Setting], model=None, lanes: int = 8, memory: bool = False, n: int | None = None, o: int | None = None) -> DataFrame:
    """(setting, metric, value): sums of each metric over shards, by the setting's place in the list. ``model`` adds scores for learned filters. Functions are those of md5x. Keys have their numbers as ids."""
    ship(positives.sparkSession)
    n, o = n if n is not None else positives.count(), o if o is not None else negatives.count()
    shards = shards_for(n + o)
    lanes = max(1, min(lanes, len(settings), -(-2 * lanes // shards)))  # with many shards few lanes keep all cores at work
    dealt, slots = _dealt(settings, lanes), spread(shards * lanes)
    both = positives.select("k", F.lit(0.0).alias("cost"), F.lit(True).alias("positive")).unionByName(
        negatives.select("k", F.col("cost").cast("double").alias("cost"), F.lit(False).alias("positive"))
    )
    both = model.score(both) if model is not None else both.withColumn("score", F.lit(0.0))
    model_bits = model.bits if model is not None else 0
    shard = F.pmod(Family().column(F.col("k"), ROUTER), F.lit(shards)).cast("int") if shards > 1 else F.lit(0)
    routed = both.where(F.col("k").isNotNull()).select(shard.alias("shard"), "positive", "cost", "score", "k")
    packed = routed.mapInArrow(lambda batches: _pieces(batches, shards), "shard int, keys binary").withColumn("lane", F.explode(F.array(*[F.lit(i) for i in range(lanes)])))
    sent = packed.withColumn("slot", F.element_at(F.array(*[F.lit(i) for i in slots]), F.col("shard") * lanes + F.col("lane") + 1)).drop("shard").repartition(len(slots), "slot")
    families = sorted({_family_of(s) for s in settings} - {""})
    whole_of = {i: _whole_size(n, s) for i, s in enumerate(settings) if s.method == "standard"} if shards > 1 else {}
    sizes, length = sorted(set(whole_of.values())), max(64, 8 * GROUP * n // max(n + o, 1))
    told, sent_arrays = sum(m for m, _ in sizes) // 8 > SENT_BYTES, None
    if sizes and not told:
        sent_arrays = Sent(n, shards, positives.sparkSession.sparkContext.broadcast(_united(positives, sizes)))
    lane_of = {slot: i % lanes for i, slot in enumerate(slots)}

    def unpacked(pieces: pa.Table) -> tuple:
        """(positives, negatives, their numbers, costs and scores), in the order of their numbers."""
        table = pa.concat_tables([pa.ipc.open_stream(piece.as_buffer()).read_all() for piece in pieces.column("keys")])
        chosen = np.asarray(table.column("positive"))
        cost, score = (table.column(c).to_numpy() for c in ("cost", "score"))
        every = table.column("k").cast(pa.binary()).to_pylist()
        key_id = md5_values(every, None)
        order = np.argsort(key_id, kind="stable")  # no result hangs on the order of rows
        yes, no = order[chosen[order]], order[~chosen[order]]
        ks, ko = ([every[i] for i in own.tolist()] for own in (yes, no))
        return ks, ko, key_id[yes], key_id[no], cost[no], score[yes], score[no]

    def hashed(keys: list[bytes]) -> Hashes:
        return Hashes(len(keys), len(IDS), lambda i: md5_values(keys, IDS[i]))

    def asked(pieces: pa.Table) -> pa.Table:
        slot = pieces.column("slot")[0].as_py()
        wanted = {whole_of[i] for i in dealt[lane_of[slot]] if i in whole_of}
        ks, ko = unpacked(pieces)[:2] if wanted else ([], [])
        return _asked({True: hashed(ks), False: hashed(ko)}, slot, sizes, wanted, length)

    def answered(rows: pa.Table) -> pa.Table:
        return _answered(rows, length, lane_of)

    def kernel(pieces: pa.Table, answers: pa.Table | None = None) -> pa.Table:
        ks, ko, ids_s, ids_o, cost, score_s, score_o = unpacked(pieces)

        def others(family: str) -> tuple[Hashes, Hashes]:
            return _other_family(family, ks), _other_family(family, ko)

        out: list[tuple[int, str, float]] = []
        # a shard without positives or without negatives still is a part of the filters that all shards share
        if own := [i for i in dealt[pieces.column("lane")[0].as_py()] if ks and ko or i in whole_of]:
            needed = {_family_of(settings[i]) for i in own}
            other = {f: others(f) for f in families if f in needed}
            whole = sent_arrays if answers is None else Told(n, shards, sizes, answers)
            d = Data(hashed(ks), hashed(ko), ids_s, ids_o, cost, score_s, score_o, {f: v[0] for f, v in other.items()}, {f: v[1] for f, v in other.items()}, whole=whole)
            last = None
            for i in own:
                if _family_of(settings[i]) != last:  # a lane has a family's settings in one run, so the values of the one before have served
                    last = _family_of(settings[i])
                    for values in (d.s, d.o, *d.other_s.values(), *d.other_o.values()):
                        values.held.clear()
                out += [(i, k, v) for k, v in _measure(d, settings[i], model_bits, memory).items()]
        cols = list(zip(*out)) if out else [(), (), ()]
        return pa.table({"setting": pa.array(cols[0], pa.int32()), "metric": pa.array(cols[1], pa.string()), "value": pa.array(cols[2], pa.float64())})

    schema = "setting int, metric string, value double"
    if told:
        answers = sent.groupBy("slot").applyInArrow(asked, PLACES).groupBy("size", "segment").applyInArrow(answered, ANSWERS).repartition(len(slots), "slot")
        sums = sent.groupBy("slot").cogroup(answers.groupBy("slot")).applyInArrow(lambda pieces, answers: kernel(pieces, answers), schema)
    else:
        sums = sent.groupBy("slot").applyInArrow(lambda pieces: kernel(pieces), schema)
    return sums.groupBy("setting", "metric").agg(F.sum("value").alias("value"))


METRICS = (
    "n o fn fp fp_round2 cost_passed cost_all collisions keys_freed keys_broken swaps stored fail_swap fail_store shared_cells ones used_cells omega bits "
    "build_s probe_s peak_bytes infeasible"
).split()


def table(workload: str, keyset: str, sums: DataFrame, settings: list[Setting], n: int, o: int) -> DataFrame:
    """One row per method, label and budget: means over the seeds, the spread of the weighted rate, and closed forms beside the measured values."""
    spark = sums.sparkSession
    rows = []
    for i, s in enumerate(settings):
        g = geometry.split(geometry.budget(n, s.bits_per_key), s.delta, s.alpha)
        bound = None
        if s.method.startswith("custom") and s.delta and n and o and g.pool > s.k:
            bound = float(theory.fpr_upper(n, o, g.m, g.omega, s.k, g.pool))
        rows.append((i, s.method, s.label, float(s.bits_per_key), s.k, float(s.delta), s.alpha, float(s.skew), s.seed, bound))
    schema = "setting int, method string, label string, bits_per_key double, k int, delta double, alpha int, skew double, seed int, bound double"
    told = spark.createDataFrame(rows, schema)
    wide = sums.groupBy("setting").pivot("metric", METRICS).agg(F.first("value"))
    joined = wide.join(F.broadcast(told), "setting")  # one row per setting
    keys = F.col("n") + F.col("o")
    per = joined.select(
        "method", "label", "bits_per_key", "k", "delta", "alpha", "skew", "bound",
        (F.col("cost_passed") / F.col("cost_all")).alias("wfpr"), (F.col("fp") / F.col("o")).alias("fpr"),
        "n", "fn", "collisions", "keys_freed", "keys_broken", "stored", "fail_swap", "fail_store", "fp_round2", "infeasible",
        (F.col("used_cells") / F.col("omega")).alias("cell_load"), (F.col("ones") / F.col("bits")).alias("bit_load"), (F.col("bits") / F.col("n")).alias("bits_used"),
        (F.col("build_s") * 1e9 / keys).alias("build_ns"), (F.col("probe_s") * 1e9 / keys).alias("probe_ns"), "peak_bytes",
    )
    mean = "n fpr fn collisions keys_freed keys_broken stored fail_swap fail_store fp_round2 cell_load bit_load bits_used build_ns probe_ns peak_bytes bound infeasible".split()
    grouped = per.groupBy("method", "label", "bits_per_key", "k", "delta", "alpha", "skew").agg(
        F.avg("wfpr").alias("wfpr"), F.coalesce(F.stddev_samp("wfpr"), F.lit(0.0)).alias("wfpr_sd"), F.count(F.lit(1)).alias("runs"), *[F.avg(c).alias(c) for c in mean]
    )
    return grouped.select(F.lit(workload).alias("workload"), F.lit(keyset).alias("keyset"), *grouped.columns)
