"""Hash families in three renderings that agree: Spark columns, numpy kernels and DuckDB expressions.

A value is a non-negative integer below 2**60; a position is the value modulo the number of cells. Strings are hashed by their UTF-8 bytes.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

#: Ids with a fixed role in every family, beyond those of the pool.
START, ROUTER, BASE_A, BASE_B = 40, 41, 31, 32
M32 = 0xFFFFFFFF


@dataclass(frozen=True)
class Family:
    """Hash functions numbered from 1. ``name`` is md5x (agrees with DuckDB), xx (fastest in the JVM) or pool (22 different functions)."""

    name: str = "md5x"
    seed: int = 0

    def column(self, key: Column, i: int) -> Column:
        if self.name == "md5x":
            return F.conv(F.substring(F.md5(F.concat(F.lit(f"{i}:"), key)), 1, 15), 16, 10).cast("bigint")
        if self.name == "xx":
            return F.shiftrightunsigned(F.xxhash64(F.lit(self.seed * 1000 + i), key), 4)
        if self.name == "pool" and i in COLUMNS:
            return COLUMNS[i](key)
        raise ValueError(f"{self.name} has no column form of function {i}")

    def columns(self, key: Column, ids: list[int]) -> Column:
        return F.array(*[self.column(key, i) for i in ids])

    def doubled(self, key: Column, ids: list[int], m: Column) -> Column:
        """Positions simulated from two values: the first plus i times the second, both reduced beforehand so that nothing overflows."""
        a, b = F.pmod(self.column(key, BASE_A), m), F.pmod(self.column(key, BASE_B), m)
        return F.array(*[F.pmod(a + F.lit(i) * b, m) for i in ids])

    def value(self, key: str, i: int) -> int:
        if self.name == "md5x":
            return int(hashlib.md5(f"{i}:{key}".encode()).hexdigest()[:15], 16)
        if self.name == "pool":
            return KERNELS[i](key.encode())
        raise ValueError(f"{self.name} has no kernel outside Spark")

    def duck(self, expr: str, i: int) -> str:
        if self.name == "md5x":
            return f"('0x' || substr(md5('{i}:' || {expr}), 1, 15))::BIGINT"
        raise ValueError(f"{self.name} has no DuckDB form")


class Batch:
    """Keys of one length as columns of bytes. The kernels below take it as they take one key's bytes, and then compute with arrays of 64 bits."""

    def __init__(self, rows: np.ndarray):
        self.bytes = rows

    def __len__(self) -> int:
        return self.bytes.shape[1]

    def __getitem__(self, at):
        return Batch(self.bytes[:, at]) if isinstance(at, slice) else self.bytes[:, at].astype(np.uint64)

    def __iter__(self):
        return (self[i] for i in range(len(self)))

    def each(self, function) -> np.ndarray:
        """One call per key, for functions of a library."""
        size, data = len(self), self.bytes.tobytes()
        return np.array([function(data[at : at + size]) for at in range(0, len(data), size)] if size else [function(b"")] * len(self.bytes), np.uint64)


def little(data) -> int | np.ndarray:
    """At most eight bytes as a little-endian number."""
    if not isinstance(data, Batch):
        return int.from_bytes(data, "little")
    wide = np.zeros((len(data.bytes), 8), np.uint8)
    wide[:, : len(data)] = data.bytes
    return wide.view("<u8").ravel().astype(np.uint64)


def batches(keys: list[bytes]) -> list[tuple[np.ndarray, Batch]]:
    """(places, batch) per length of key."""
    sizes = np.array([len(k) for k in keys], np.int64)
    found = []
    for size in np.unique(sizes):
        at = np.flatnonzero(sizes == size)
        found.append((at, Batch(np.frombuffer(b"".join([keys[i] for i in at]), np.uint8).reshape(len(at), size))))
    return found


def bulk(kernel, groups: list[tuple[np.ndarray, Batch]]) -> np.ndarray:
    """``kernel`` of every key, as unsigned 64-bit numbers in the keys' order."""
    out = np.zeros(sum(len(at) for at, _ in groups), np.uint64)
    for at, batch in groups:
        out[at] = kernel(batch)
    return out


def md5_values(keys: list[bytes], i: int | None) -> np.ndarray:
    """Function ``i`` of the family md5x for many keys; without ``i`` their numbers, as ``keys.number`` has them."""
    md5, prefix = hashlib.md5, b"" if i is None else f"{i}:".encode()
    return (np.frombuffer(b"".join([md5(prefix + k).digest()[:8] for k in keys]), ">u8") >> np.uint64(4)).astype(np.int64)


# The pool of 22. Byte-wise functions are folds of one step over the bytes; each is stated once as numbers and once as a column.


def _bytes(key: Column) -> Column:
    digits = F.hex(F.encode(key, "UTF-8"))
    n = F.octet_length(key)
    return F.when(n == 0, F.expr("cast(array() as array<bigint>)")).otherwise(
        F.transform(F.sequence(F.lit(1), F.greatest(n, F.lit(1))), lambda i: F.conv(F.substring(digits, i * 2 - 1, F.lit(2)), 16, 10).cast("bigint"))
    )


def _fold(start: int, step, finish=None):
    def column(key: Column) -> Column:
        body = F.aggregate(_bytes(key), F.lit(start).cast("bigint"), lambda h, c: step(h, c, _ColumnOps))
        return finish(body, _ColumnOps) if finish else body

    def kernel(data: bytes) -> int:
        h = start
        for c in data:
            h = step(h, c, _IntOps)
        return finish(h, _IntOps) if finish else h

    return column, kernel


class _ColumnOps:
    @staticmethod
    def shl(x, n):
        return F.shiftleft(x, n).bitwiseAND(F.lit(M32))

    @staticmethod
    def shr(x, n):
        return F.shiftright(x, n)

    @staticmethod
    def xor(x, y):
        return x.bitwiseXOR(y)

    @staticmethod
    def low(x):
        return x.bitwiseAND(F.lit(M32))

    @staticmethod
    def band(x, mask):
        return x.bitwiseAND(F.lit(mask))

    @staticmethod
    def inv(x):
        return x.bitwiseXOR(F.lit(M32))


class _IntOps:
    shl = staticmethod(lambda x, n: x << n & M32)
    shr = staticmethod(lambda x, n: x >> n)
    xor = staticmethod(lambda x, y: x ^ y)
    low = staticmethod(lambda x: x & M32)
    band = staticmethod(lambda x, mask: x & mask)
    inv = staticmethod(lambda x: x ^ M32)


def _fnv(h, c, o):
    return o.low(o.xor(h, c) * 16777619)


def _bkdr(h, c, o):
    return o.low(h * 131 + c)


def _djb(h, c, o):
    return o.low(h * 33 + c)


def _ndjb(h, c, o):
    return o.xor(o.low(h * 33), c)


def _sdbm(h, c, o):
    return o.low(h * 65599 + c)


def _js(h, c, o):
    return o.xor(h, o.low(o.shl(h, 5) + c + o.shr(h, 2)))


def _dek(h, c, o):
    return o.xor(o.xor(o.shl(h, 5), o.shr(h, 27)), c)


def _brp(h, c, o):
    return o.xor(o.xor(o.shl(h, 7), o.shr(h, 25)), c)


def _py(h, c, o):
    return o.xor(o.low(h * 1000003), c)


def _pjw(h, c, o):
    h = o.low(o.shl(h, 4) + c)
    return o.band(o.xor(h, o.shr(o.band(h, 0xF0000000), 24)), 0x0FFFFFFF)


def _elf(h, c, o):
    h = o.low(o.shl(h, 4) + c)
    high = o.band(h, 0xF0000000)
    return o.xor(o.xor(h, o.shr(high, 24)), high)


def _oaat(h, c, o):
    h = o.low(h + c)
    h = o.low(h + o.shl(h, 10))
    return o.xor(h, o.shr(h, 6))


def _oaat_end(h, o):
    h = o.low(h + o.shl(h, 3))
    h = o.xor(h, o.shr(h, 11))
    return o.low(h + o.shl(h, 15))


def _ap_column(key: Column) -> Column:
    o, marked = _ColumnOps, F.transform(_bytes(key), lambda c, i: c + F.pmod(i, F.lit(2)) * 256)
    return F.aggregate(
        marked,
        F.lit(0xAAAAAAAA).cast("bigint"),
        lambda h, c: F.when(c < 256, _ap_even(h, c, o)).otherwise(_ap_odd(h, c - 256, o)),
    )


def _ap_kernel(data: bytes) -> int:
    h = 0xAAAAAAAA
    for i, c in enumerate(data):
        h = _ap_odd(h, c, _IntOps) if i % 2 else _ap_even(h, c, _IntOps)
    return h


def _ap_even(h, c, o):
    return o.xor(h, o.xor(o.shl(h, 7), o.low(o.shr(h, 3) * c)))


def _ap_odd(h, c, o):
    return o.xor(h, o.inv(o.low(o.shl(h, 11) + o.xor(o.shr(h, 5), c))))


def _rs_pair(data: bytes) -> int:
    h, a = 0, 63689
    for c in data:
        h, a = (h * a + c) & M32, a * 378551 & M32
    return h


def _rs_column(key: Column) -> Column:
    start = F.struct(F.lit(0).cast("bigint").alias("h"), F.lit(63689).cast("bigint").alias("a"))

    def step(s: Column, c: Column) -> Column:
        # both factors are below 2**32, so the product is taken in two halves
        high, low = F.shiftright(s["h"], 16), s["h"].bitwiseAND(F.lit(0xFFFF))
        product = (F.shiftleft((high * s["a"]).bitwiseAND(F.lit(0xFFFF)), 16) + low * s["a"]).bitwiseAND(F.lit(M32))
        return F.struct((product + c).bitwiseAND(F.lit(M32)).alias("h"), (s["a"] * F.lit(378551)).bitwiseAND(F.lit(M32)).alias("a"))

    return F.aggregate(_bytes(key), start, step, lambda s: s["h"])


def _mix64(data: bytes) -> int:
    """Integer mix of the first 60 bits of md5: shifts and additions modulo 2**64, then the top 60 bits."""
    mask = (1 << 64) - 1
    x = data.each(lambda d: int(hashlib.md5(d).hexdigest()[:15], 16)) if isinstance(data, Batch) else int(hashlib.md5(data).hexdigest()[:15], 16)
    x = (~x + (x << 21)) & mask
    x ^= x >> 24
    x = (x + (x << 3) + (x << 8)) & mask
    x ^= x >> 14
    x = (x + (x << 2) + (x << 4)) & mask
    x ^= x >> 28
    return (x + (x << 31) & mask) >> 4


def _murmur3(data: bytes, seed: int = 42) -> int:
    h = seed
    for i in range(0, len(data) - len(data) % 4, 4):
        k = little(data[i : i + 4]) * 0xCC9E2D51 & M32
        k = (k << 15 | k >> 17) * 0x1B873593 & M32
        h ^= k
        h = ((h << 13 | h >> 19) & M32) * 5 + 0xE6546B64 & M32
    tail = data[len(data) - len(data) % 4 :]
    if tail:
        k = little(tail) * 0xCC9E2D51 & M32
        h ^= (k << 15 | k >> 17) * 0x1B873593 & M32
    h ^= len(data)
    h = (h ^ h >> 16) * 0x85EBCA6B & M32
    h = (h ^ h >> 13) * 0xC2B2AE35 & M32
    return h ^ h >> 16


def _super_fast(data: bytes, seed: int = 0) -> int:
    h = (len(data) + seed) & M32
    if not data:
        return 0
    for i in range(0, len(data) // 4 * 4, 4):
        h = (h + little(data[i : i + 2])) & M32
        t = (little(data[i + 2 : i + 4]) << 11) ^ h
        h = ((h << 16) ^ t) & M32
        h = (h + (h >> 11)) & M32
    rest = data[len(data) // 4 * 4 :]
    if len(rest) == 3:
        h = (h + little(rest[:2])) & M32
        h ^= h << 16 & M32
        h ^= rest[2] << 18 & M32
        h = (h + (h >> 11)) & M32
    elif len(rest) == 2:
        h = (h + little(rest)) & M32
        h ^= h << 11 & M32
        h = (h + (h >> 17)) & M32
    elif rest:
        h = (h + rest[0]) & M32
        h ^= h << 10 & M32
        h = (h + (h >> 1)) & M32
    for shift, right in ((3, 5), (4, 17), (25, 6)):
        h ^= h << shift & M32
        h = (h + (h >> right)) & M32
    return h


def _lookup(data: bytes, seed: int = 0) -> int:
    """Three 32-bit lanes, mixed after every 12 bytes by subtractions and shifts."""
    a = b = 0x9E3779B9
    c = seed

    def mix(a: int, b: int, c: int) -> tuple[int, int, int]:
        for x, y, z in ((13, 8, 13), (12, 16, 5), (3, 10, 15)):
            a = (a - b - c & M32) ^ c >> x
            b = (b - c - a & M32) ^ (a << y & M32)
            c = (c - a - b & M32) ^ b >> z
        return a, b, c

    left = data
    while len(left) >= 12:
        a, b, c = (x + little(left[4 * i : 4 * i + 4]) & M32 for i, x in enumerate((a, b, c)))
        a, b, c = mix(a, b, c)
        left = left[12:]
    a = a + little(left[:4]) & M32
    b = b + little(left[4:8]) & M32
    c = c + len(data) + (little(left[8:]) << 8) & M32
    return mix(a, b, c)[2]


# The multipliers of the city family.
C0, C1, C2, CM = 0xC3A5C85C97CB3127, 0xB492B66FBE98F273, 0x9AE16A3B2F90404F, 0x9DDFEA08EB382D69
M64 = (1 << 64) - 1


def _city(data: bytes, drop: int = 4) -> int:
    """64-bit function of the city family, by its public definition; without its lowest ``drop`` bits."""
    n = len(data)
    word = lambda at: little(data[at : at + 8])
    turn = lambda x, r: (x >> r | x << 64 - r) & M64
    swap = lambda x: x.byteswap() if isinstance(x, np.ndarray) else int.from_bytes((x & M64).to_bytes(8, "little"), "big")
    mix = lambda x: x ^ x >> 47

    def pair(u: int, v: int, mul: int = CM) -> int:
        a = mix((u ^ v) * mul & M64)
        return mix((v ^ a) * mul & M64) * mul & M64

    def weak(at: int, a: int, b: int) -> tuple[int, int]:
        w, x, y, z = (word(at + 8 * i) for i in range(4))
        a = a + w & M64
        b = turn(b + a + z & M64, 21)
        c = a
        a = a + x + y & M64
        return a + z & M64, b + turn(a, 44) + c & M64

    mul = C2 + 2 * n & M64
    if n > 64:
        x, y = word(n - 40), word(n - 16) + word(n - 56) & M64
        z = pair(word(n - 48) + n & M64, word(n - 24))
        v, w = weak(n - 64, n, z), weak(n - 32, y + C1 & M64, x)
        x = x * C1 + word(0) & M64
        for at in range(0, (n - 1) // 64 * 64, 64):
            x = turn(x + y + v[0] + word(at + 8) & M64, 37) * C1 & M64 ^ w[1]
            y = turn(y + v[1] + word(at + 48) & M64, 42) * C1 + v[0] + word(at + 40) & M64
            z = turn(z + w[0] & M64, 33) * C1 & M64
            v = weak(at, v[1] * C1 & M64, x + w[0] & M64)
            w = weak(at + 32, z + w[1] & M64, y + word(at + 16) & M64)
            z, x = x, z
        h = pair(pair(v[0], w[0]) + mix(y) * C1 + z & M64, pair(v[1], w[1]) + x & M64)
    elif n > 32:
        a, b, c, d, e, f, g = word(0) * C2, word(8), word(n - 24), word(n - 32), word(16) * C2, word(24) * 9, word(n - 8)
        h = word(n - 16) * mul
        u = turn(a + g & M64, 43) + (turn(b, 30) + c) * 9
        v = (a + g & M64 ^ d) + f + 1
        w = swap((u + v) * mul) + h
        x = turn(e + f & M64, 42) + c
        y = (swap((v + w) * mul) + g) * mul
        z = e + f + c
        a = swap((x + z) * mul + y) + b
        h = mix((z + a) * mul + d + h & M64) * mul + x & M64
    elif n > 16:
        a, b, c, d = word(0) * C1 & M64, word(8), word(n - 8) * mul & M64, word(n - 16) * C2
        h = pair(turn(a + b & M64, 43) + turn(c, 30) + d & M64, a + turn(b + C2 & M64, 18) + c & M64, mul)
    elif n >= 8:
        a, b = word(0) + C2 & M64, word(n - 8)
        h = pair(turn(b, 37) * mul + a & M64, (turn(a, 25) + b) * mul & M64, mul)
    elif n >= 4:
        h = pair(n + (little(data[:4]) << 3), little(data[n - 4 :]), mul)
    elif n:
        y, z = data[0] + (data[n >> 1] << 8), n + (data[n - 1] << 2)
        h = mix(y * C2 & M64 ^ z * C0 & M64) * C2 & M64
    else:
        h = C2
    return h >> drop


def _xx(data: bytes) -> int:
    import xxhash

    one = lambda d: xxhash.xxh64_intdigest(d, seed=42) >> 4
    return data.each(one) if isinstance(data, Batch) else one(data)


def _crc(data: bytes) -> int:
    import zlib

    return data.each(zlib.crc32) if isinstance(data, Batch) else zlib.crc32(data)


_FOLDS = {
    6: _fold(2166136261, _fnv),
    8: _fold(0, _oaat, _oaat_end),
    9: _fold(0, _dek),
    11: _fold(0, _py),
    12: _fold(0, _brp),
    15: _fold(5381, _ndjb),
    16: _fold(5381, _djb),
    17: _fold(0, _bkdr),
    18: _fold(0, _pjw),
    19: _fold(1315423911, _js),
    21: _fold(0, _sdbm),
    22: _fold(0, _elf),
}
#: name of each function of the pool, in the registry's order
POOL = (
    "xx city murmur superfast crc32 fnv1a lookup oaat dek hsieh py brp intmix ap ndjb djb bkdr pjw js rs sdbm elf"
).split()
KERNELS = {
    1: _xx,
    2: _city,
    3: _murmur3,
    4: _super_fast,
    5: _crc,
    7: _lookup,
    10: lambda d: _super_fast(d, 0x5BD1E995),
    13: _mix64,
    14: _ap_kernel,
    20: _rs_pair,
} | {i: kernel for i, (_, kernel) in _FOLDS.items()}
COLUMNS = {
    1: lambda key: F.shiftrightunsigned(F.xxhash64(key), 4),
    3: lambda key: F.hash(key).cast("bigint").bitwiseAND(F.lit(M32)),
    5: lambda key: F.crc32(F.encode(key, "UTF-8")),
    14: _ap_column,
    20: _rs_column,
} | {i: column for i, (column, _) in _FOLDS.items()}


def duck_fold(name: str, expr: str) -> str:
    """DuckDB form of a byte fold, for the functions whose step stays below 2**63."""
    start, step = {
        "fnv1a": ("2166136261", "(xor(h, c) * 16777619) & 4294967295"),
        "djb": ("5381", "(h * 33 + c) & 4294967295"),
        "ndjb": ("5381", "xor((h * 33) & 4294967295, c)"),
        "bkdr": ("0", "(h * 131 + c) & 4294967295"),
        "sdbm": ("0", "(h * 65599 + c) & 4294967295"),
        "js": ("1315423911", "xor(h, (((h << 5) & 4294967295) + c + (h >> 2)) & 4294967295)"),
        "dek": ("0", "xor(xor((h << 5) & 4294967295, h >> 27), c)"),
        "brp": ("0", "xor(xor((h << 7) & 4294967295, h >> 25), c)"),
        "py": ("0", "xor((h * 1000003) & 4294967295, c)"),
        "pjw": ("0", "xor((((h << 4) & 4294967295) + c) & 4294967295, ((((h << 4) & 4294967295) + c) & 4026531840) >> 24) & 268435455"),
        "elf": ("0", f"xor(xor({_SHIFTED}, ({_SHIFTED} & 4026531840) >> 24), {_SHIFTED} & 4026531840)"),
        "oaat": ("0", f"xor({_ADDED}, {_ADDED} >> 6)"),
        # bytes at odd places come with 256 added
        "ap": ("2863311530", "CASE WHEN c < 256 THEN xor(h, xor((h << 7) & 4294967295, ((h >> 3) * c) & 4294967295)) ELSE xor(h, xor((((h << 11) & 4294967295) + xor(h >> 5, c - 256)) & 4294967295, 4294967295)) END"),
        "rs": ("{'h': 0::BIGINT, 'a': 63689::BIGINT}", "{'h': ((h.h::HUGEINT * h.a + c.h) & 4294967295)::BIGINT, 'a': (h.a * 378551) & 4294967295}"),
    }[name]
    byte = f"('0x' || substr(hex(encode({expr})), (2 * i - 1)::INT, 2))::BIGINT"
    byte = {"ap": f"{byte} + (i - 1) % 2 * 256", "rs": f"{{'h': {byte}, 'a': 0::BIGINT}}"}.get(name, byte)
    first = start if name == "rs" else f"{start}::BIGINT"
    folded = f"list_reduce(list_concat([{first}], list_transform(range(1, octet_length(encode({expr})) + 1), lambda i: {byte})), lambda h, c: {step})"
    if name == "rs":
        return f"({folded}).h"
    if name == "oaat":
        three = "((h + ((h << 3) & 4294967295)) & 4294967295)"
        mixed = f"xor({three}, {three} >> 11)"
        return f"list_transform([{folded}], lambda h: ({mixed} + (({mixed} << 15) & 4294967295)) & 4294967295)[1]"
    return folded


_SHIFTED = "((((h << 4) & 4294967295) + c) & 4294967295)"
_ADDED = "((((h + c) & 4294967295) + ((((h + c) & 4294967295) << 10) & 4294967295)) & 4294967295)"


# Families of one function and many seeds


def city_seeded(values: np.ndarray, seeds: np.ndarray) -> np.ndarray:
    """Seeded values (60 bits) from the city family's 64-bit ones: its two-word mix of the value, less a constant, and the seed."""
    x = values.astype(np.uint64)[:, None] - np.uint64(C2)
    seeds, mul = seeds.astype(np.uint64)[None, :], np.uint64(CM)
    a = (x ^ seeds) * mul
    a ^= a >> np.uint64(47)
    b = (seeds ^ a) * mul
    b ^= b >> np.uint64(47)
    return ((b * mul) >> np.uint64(4)).astype(np.int64)


def city64(data: bytes) -> int:
    """All 64 bits of the city function."""
    return _city(data, 0)


def wide(data: bytes, seed: int) -> int:
    """128-bit function of the murmur family, by its public definition."""
    low, high = _halves(data, seed)
    return low | high << 64


def wide_values(data, seed: int):
    """``wide`` modulo 2**61 - 1, from its halves: 2**64 leaves 8."""
    prime = (1 << 61) - 1
    low, high = _halves(data, seed)
    return (low % prime + high % prime * 8 % prime) % prime


def _halves(data, seed: int):
    c1, c2 = 0x87C37B91114253D5, 0x4CF5AD432745937F
    turn = lambda x, r: (x << r | x >> 64 - r) & M64

    def final(x: int) -> int:
        x = (x ^ x >> 33) * 0xFF51AFD7ED558CCD & M64
        x = (x ^ x >> 33) * 0xC4CEB9FE1A85EC53 & M64
        return x ^ x >> 33

    n, a, b = len(data), seed, seed
    for at in range(0, n // 16 * 16, 16):
        low, high = little(data[at : at + 8]), little(data[at + 8 : at + 16])
        a ^= turn(low * c1 & M64, 31) * c2 & M64
        a = (turn(a, 27) + b) * 5 + 0x52DCE729 & M64
        b ^= turn(high * c2 & M64, 33) * c1 & M64
        b = (turn(b, 31) + a) * 5 + 0x38495AB5 & M64
    rest = data[n // 16 * 16 :]
    b ^= turn(little(rest[8:]) * c2 & M64, 33) * c1 & M64
    a ^= turn(little(rest[:8]) * c1 & M64, 31) * c2 & M64
    a, b = a ^ n, b ^ n
    a = a + b & M64
    b = a + b & M64
    a, b = final(a), final(b)
    a = a + b & M64
    return a, a + b & M64


def positions(values: np.ndarray, m: int) -> np.ndarray:
    return (values % m).astype(np.int64)
