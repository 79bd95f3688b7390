"""The two-phase optimiser of one shard: swap a hash function of a sole owner so that a costly negative is rejected, then store the new subset."""

from __future__ import annotations

from collections import deque
from copy import copy
from dataclasses import dataclass, field, replace

import numpy as np

from ..functions.geometry import Geometry
from . import chain


@dataclass(frozen=True)
class OptimiserPolicy:
    candidate_policy: str = "pooled"  # set and harmless clear bits ranked together, or 'tiered': set bits first
    exact_conflicts: bool = True  # a conflict is a negative that would pass after the swap; else as the printed count has it
    max_requeue: int = 2
    strict_gain: bool = False  # swaps must gain, not only not lose
    allow_rechange: bool = False
    order_policy: str = "seeded"
    gain: str = "single"  # 'all': count every collision key that the cleared bit frees
    owner_order: str = "pooled"  # or 'first': one owner after the other
    fast_blind: bool = False
    sticky_single: bool = False  # a bit once hit twice never has an owner again
    seed: int = 42

    @classmethod
    def reference(cls) -> "OptimiserPolicy":
        return cls(exact_conflicts=False, sticky_single=True)

    def but(self, **changes) -> "OptimiserPolicy":
        return replace(self, **changes)


@dataclass
class Shard:
    """What the optimiser works on. Functions are numbered from 0 inside the pool; positions are bit numbers, cells table places."""

    pos_s: np.ndarray  # n x pool
    cell_s: np.ndarray  # n x pool
    start_s: np.ndarray  # n
    ids_s: np.ndarray
    pos_o: np.ndarray  # o x k, under the default subset
    cost_o: np.ndarray
    ids_o: np.ndarray
    geometry: Geometry
    default: tuple[int, ...]
    policy: OptimiserPolicy = field(default_factory=OptimiserPolicy)
    fast: bool = False

    def __post_init__(self):
        self.k = len(self.default)
        n, m = len(self.pos_s), self.geometry.m
        flat = self.pos_s[:, list(self.default)]
        self.hits = np.bincount(flat.ravel(), minlength=m).astype(np.int32) if n else np.zeros(m, np.int32)
        # the owners of a bit added up: where one is left it is that one
        owners = np.repeat(np.arange(n), self.k)
        self.owner = np.bincount(flat.ravel(), weights=owners, minlength=m).astype(np.int64) if n else np.zeros(m, np.int64)
        self.crowded = self.hits > 1
        self.changed: dict[int, tuple[int, ...]] = {}
        self.cells = bytearray(max(self.geometry.omega, 1))
        if len(self.pos_o):
            ordered = np.sort(self.pos_o, axis=1)
            first = np.ones_like(ordered, bool)
            first[:, 1:] = ordered[:, 1:] != ordered[:, :-1]
            self.clear = ((self.hits[ordered] == 0) & first).sum(axis=1).astype(np.int16)
        else:
            self.clear = np.zeros(0, np.int16)
        self.stats = dict.fromkeys(
            ("collisions", "keys_freed", "keys_broken", "swaps", "stored", "fail_swap", "fail_store", "shared_cells", "conflict_tests"), 0
        )

    def indexed(self) -> "Shard":
        self._index()
        return self

    def anew(self, cost_o: np.ndarray) -> "Shard":
        """A shard of the same keys under other costs. Only one that has not run can give it; its positions and index are shared, since no run changes them."""
        other = copy(self)
        other.cost_o, other.changed, other.cells, other.stats = cost_o, {}, bytearray(len(self.cells)), dict(self.stats)
        other.hits, other.owner, other.crowded, other.clear = (x.copy() for x in (self.hits, self.owner, self.crowded, self.clear))
        return other

    # auxiliary indexes

    def _index(self) -> None:
        """Negatives per bit, each once per bit. The fast variant keeps the collision keys only: it never asks whom a newly set bit would let pass."""
        own = np.flatnonzero(self.clear == 0) if self.fast else np.arange(len(self.pos_o))
        ordered = np.sort(self.pos_o[own], axis=1) if len(own) else np.zeros((0, self.k), np.int64)
        first = np.ones_like(ordered, bool)
        first[:, 1:] = ordered[:, 1:] != ordered[:, :-1]
        bits, keys = ordered[first], np.repeat(own, self.k).reshape(-1, self.k)[first]
        order = np.argsort(bits, kind="stable")
        self.bucket_keys = keys[order]
        self.bucket_start = np.zeros(self.geometry.m + 1, np.int64)
        np.cumsum(np.bincount(bits, minlength=self.geometry.m), out=self.bucket_start[1:])

    def bucket(self, bit: int) -> list[int]:
        return self.bucket_keys[self.bucket_start[bit] : self.bucket_start[bit + 1]].tolist()

    def conflict_cost(self, bit: int, cleared: int) -> float:
        """Cost of the negatives that would pass if ``bit`` were set and ``cleared`` were cleared."""
        self.stats["conflict_tests"] += 1
        total = 0.0
        for key in self.bucket(bit):
            if self.policy.exact_conflicts:
                if self.clear[key] == 1 and cleared not in self.pos_o[key].tolist():
                    total += self.cost_o[key]
            else:
                others = [p for p in self.pos_o[key].tolist() if p != bit]
                if len(others) == self.k - 1 and all(self.hits[p] > 0 for p in others):
                    total += self.cost_o[key]
        return total

    def subset(self, owner: int) -> tuple[int, ...]:
        return self.changed.get(owner, self.default)

    def owners_of(self, key: int) -> list[tuple[int, int]]:
        """(owner, bit) of the key's bits that one positive alone has set."""
        found = []
        for bit in dict.fromkeys(self.pos_o[key].tolist()):
            if self.hits[bit] == 1 and not (self.policy.sticky_single and self.crowded[bit]):
                owner = int(self.owner[bit])
                if self.policy.allow_rechange or owner not in self.changed:
                    found.append((owner, bit))
        return found

    def swaps_of(self, owner: int, bit: int, worth: float) -> list[tuple[int, float, tuple[int, ...], int]]:
        """(tier, cost, new subset, landing bit) of the owner's valid swaps off ``bit``."""
        places, subset = self.pos_s[owner].tolist(), self.subset(owner)
        given = next(f for f in subset if places[f] == bit)
        found = []
        for f, landing in enumerate(places):
            if f in subset or landing == bit:
                continue
            if self.hits[landing] > 0:
                tier, cost = 0, 0.0
            elif self.fast:
                if not self.policy.fast_blind:
                    continue
                tier, cost = 1, 0.0
            else:
                cost = self.conflict_cost(landing, bit)
                tier = 2 if cost else 1
            if cost > worth or self.policy.strict_gain and cost >= worth:
                continue
            found.append((tier, cost, tuple(sorted((*[g for g in subset if g != given], f))), landing))
        return found

    def place(self, owner: int, subset: tuple[int, ...]):
        if not self.geometry.omega:
            return None
        seed = int(self.ids_s[owner]) ^ self.policy.seed
        return chain.try_store(self.cells, int(self.start_s[owner]), self.cell_s[owner].tolist(), subset, self.policy.order_policy, seed)

    def run(self) -> "Shard":
        if not hasattr(self, "bucket_keys"):
            self._index()
        colliding = np.flatnonzero(self.clear == 0)
        order = colliding[np.lexsort((self.ids_o[colliding], -self.cost_o[colliding]))]
        self.stats["collisions"] = len(order)
        queue, visits = deque(order.tolist()), {}
        while queue:
            key = queue.popleft()
            if self.clear[key]:
                continue
            visits[key] = visits.get(key, 0) + 1
            owned = self.owners_of(key)
            groups = [owned] if self.policy.owner_order == "pooled" else [[x] for x in owned]
            outcome = "fail_swap"
            for group in groups:
                outcome = self._attempt(key, group, queue, visits, outcome)
                if outcome == "stored":
                    break
            self.stats[outcome] += 1
        return self

    def _worth(self, key: int, bit: int) -> float:
        if self.policy.gain == "single":
            return float(self.cost_o[key])
        return float(sum(self.cost_o[other] for other in self.bucket(bit) if self.clear[other] == 0))

    def _attempt(self, key: int, owned: list[tuple[int, int]], queue: deque, visits: dict, outcome: str) -> str:
        valid = []
        for owner, bit in owned:
            for tier, cost, subset, landing in self.swaps_of(owner, bit, self._worth(key, bit)):
                valid.append((tier, cost, owner, subset, bit, landing))
        free = [v for v in valid if v[0] < 2]
        groups = [[v for v in free if v[0] == 0], [v for v in free if v[0] == 1]] if self.policy.candidate_policy == "tiered" else [free]
        for group in groups:
            placed = [(stored, v) for v in group if (stored := self.place(v[2], v[3]))]
            if placed:
                stored, best = max(placed, key=lambda x: (x[0][2], -x[1][2], x[1][3]))
                self._apply(stored, best, queue, visits)
                return "stored"
        for v in sorted((v for v in valid if v[0] == 2), key=lambda v: (v[1], v[2], v[3])):
            if stored := self.place(v[2], v[3]):
                self._apply(stored, v, queue, visits)
                return "stored"
        return "fail_store" if valid else outcome

    def _apply(self, stored, swap, queue: deque, visits: dict) -> None:
        _, _, owner, subset, bit, landing = swap
        chain.commit(self.cells, stored)
        self.stats["swaps"] += 1
        self.stats["shared_cells"] += stored[2]
        self.changed[owner] = subset
        self.hits[bit] -= 1
        self.owner[bit] -= owner
        for key in self.bucket(bit):
            if self.clear[key] == 0:
                self.stats["keys_freed"] += 1
            self.clear[key] += 1
        was = self.hits[landing]
        self.hits[landing] += 1
        self.owner[landing] += owner
        if was:
            self.crowded[landing] = True
        else:
            for key in self.bucket(landing):
                self.clear[key] -= 1
                if self.clear[key] == 0:
                    self.stats["keys_broken"] += 1
                    if visits.get(key, 0) <= self.policy.max_requeue:
                        queue.append(key)

    def words(self) -> np.ndarray:
        """The bit array, 32 bits in each number."""
        bits = np.zeros(-(-self.geometry.m // 32) * 32, np.uint8)
        bits[: self.geometry.m] = self.hits > 0
        return np.packbits(bits, bitorder="little").view("<u4").astype(np.int64)
