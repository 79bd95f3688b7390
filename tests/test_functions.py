import math
import random
import zlib

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from costsieve.functions import geometry, keys, theory, zipf
from costsieve.functions.hashing import COLUMNS, KERNELS, POOL, Family

TEXTS = ["", "a", "okey0123456789abcdef", "naïve café", "日本語", "x" * 300, "a\tb\n", "0", "The quick brown fox"]


def test_columns_equal_kernels(spark):
    rows = spark.createDataFrame([(t,) for t in TEXTS], "k string")
    ids = [i for i in sorted(COLUMNS) if i not in (1, 3)]  # those two hash with Spark's own tail rule and seed
    got = rows.select("k", *[COLUMNS[i](F.col("k")).alias(f"f{i}") for i in ids]).collect()
    for r in got:
        for i in ids:
            assert r[f"f{i}"] == KERNELS[i](r["k"].encode()), (POOL[i - 1], r["k"])


def test_md5x_column_equals_value(spark):
    family = Family()
    rows = spark.createDataFrame([(t,) for t in TEXTS], "k string")
    for r in rows.select("k", *[family.column(F.col("k"), i).alias(str(i)) for i in (1, 7, 40)]).collect():
        assert all(r[str(i)] == family.value(r["k"], i) for i in (1, 7, 40))


def test_known_hash_values():
    assert KERNELS[5](b"123456789") == 0xCBF43926 == zlib.crc32(b"123456789")
    assert KERNELS[6](b"a") == 0xE40C292C
    assert KERNELS[16](b"a") == 177670
    assert KERNELS[8](b"a") == 0xCA2E9442
    assert KERNELS[3](b"") == 0x087FCD5C
    assert len(POOL) == 22 == len(KERNELS)


def test_geometry():
    g = geometry.split(1000)
    assert (g.m, g.omega, g.total_bits) == (800, 50, 1000)
    assert geometry.split(1000, 0).omega == 0
    assert [geometry.pool_size(a) for a in (3, 4, 5, 6)] == [3, 7, 15, 22]
    assert geometry.best_k(10) == 7
    assert geometry.fingerprint_bits(8.44, 1_491_178) == 6


def test_theory_worked_values():
    assert theory.bloom_fpr(10, 2) == pytest.approx(0.03286, abs=1e-5)
    assert theory.bloom_fpr(10, 6) == pytest.approx(0.00844, abs=1e-5)
    assert theory.owners_expected(10, 4) == pytest.approx(3.25, abs=0.01)
    assert theory.bloom_fpr(8.44, 6) == pytest.approx(0.01735, abs=5e-5)
    assert theory.fpr_upper(1_491_178, 1_435_527, round(6.75 * 1_491_178), 629_145, 3, 7) == pytest.approx(0.0225, abs=5e-4)
    assert theory.two_round_fpr(0.1, 0.0) == 0.1


@given(st.floats(0, 1), st.floats(0, 1))
def test_two_rounds_expand(f, r):
    assert theory.two_round_fpr(f, r) == pytest.approx(1 - (1 - f) * (1 - r * f))
    assert theory.two_round_fpr(f, r) <= theory.two_round_bound(f, r * 100, 100) + 1e-12


@settings(max_examples=50)
@given(st.integers(2, 9), st.integers(4, 20))
def test_owner_probability_is_a_lower_estimate(k, b):
    rng = np.random.default_rng(k * 100 + b)
    n = 2000
    hits = np.bincount(rng.integers(0, n * b, n * k), minlength=n * b)
    share = (hits == 1).sum() / (hits > 0).sum()
    assert share > theory.owner_prob(b, k) - 0.05


def test_prepare_sums_and_drops_nulls(spark):
    df = spark.createDataFrame([("a", 1, 2.0), ("a", 1, 3.0), ("b", None, 1.0), (None, 2, 1.0)], "x string, y int, c double")
    got = {r["k"]: r["cost"] for r in keys.prepare(df, ["x", "y"], "c").collect()}
    assert got == {"a\x1f1": 5.0}
    with pytest.raises(Exception, match="null key"):
        keys.prepare(df, ["x", "y"], "c", null_policy="fail").collect()


def test_pair_is_disjoint(spark):
    make = lambda ks: spark.createDataFrame([(k,) for k in ks], "k string").select(keys.number(F.col("k")).alias("key_id"), "k", F.lit(1.0).alias("cost"))
    s, o = keys.pair(make("ab"), make("bc"))
    assert {r["k"] for r in o.collect()} == {"c"}


def test_zipf_ranks_are_a_permutation(spark):
    df = spark.createDataFrame([(str(i),) for i in range(500)], "k string")
    got = [r["rank"] for r in zipf.ranked(df, 3).collect()]
    assert sorted(got) == list(range(1, 501))
    costs = [r["cost"] for r in zipf.costs(df, 1.0, 3).collect()]
    assert math.isclose(sum(costs), sum(1 / r for r in range(1, 501)))
    assert {r["cost"] for r in zipf.costs(df, 0.0).collect()} == {1.0}


def test_seeded_shuffles_differ(spark):
    df = spark.createDataFrame([(str(i),) for i in range(50)], "k string")
    a, b = ({r["k"]: r["rank"] for r in zipf.ranked(df, s).collect()} for s in (1, 2))
    assert a != b and random.Random(0).random() < 1


def test_known_values_of_the_seeded_families():
    from costsieve.functions import hashing

    assert hashing.wide(b"hello", 0) == 0x5B1E906A48AE1D19CBD8A7B341BD9B02
    assert hashing.city64(b"hello") == 0xB48BE5A931380CE8 and hashing.city64(b"hello") >> 4 == hashing.KERNELS[2](b"hello")
    seeded = hashing.city_seeded(np.array([hashing.city64(k) for k in (b"a", b"b" * 40)], np.uint64), np.arange(1, 5))
    assert seeded.shape == (2, 4) and len(set(seeded.ravel().tolist())) == 8 and seeded.min() >= 0


def test_ranks_over_ranges_equal_one_window(spark):
    from pyspark.sql import functions as F

    from costsieve.functions import ranks

    rows = [(i, float(i * 7 % 5) if i % 11 else None) for i in range(57)]
    df = spark.createDataFrame(rows, "key_id bigint, cost double").repartition(3)
    order = sorted(rows, key=lambda r: (r[1] is None, -(r[1] or 0.0), r[0]))
    found = {r["key_id"]: r for r in ranks.placed(df, [F.desc_nulls_last("cost"), F.col("key_id")], F.coalesce("cost", F.lit(0.0))).collect()}
    upto = 0.0
    for place, (key, cost) in enumerate(order, 1):
        upto += cost or 0.0
        assert (found[key]["place"], found[key]["upto"]) == (place, upto)
    values = sorted({c for _, c in rows if c is not None}, reverse=True) + [None]
    for r in ranks.ranked_ties(df, "cost").collect():
        assert r["dense"] == values.index(r["cost"]) + 1
        assert r["rank"] == 1 + sum(values.index(c) < values.index(r["cost"]) for _, c in rows)
    tiles = [r["tile"] for r in ranks.tiled(df, [F.col("key_id")], 10).orderBy("key_id").collect()]
    assert tiles == sorted(tiles) and [tiles.count(t) for t in range(1, 11)] == [6] * 7 + [5] * 3
    few = [r["tile"] for r in ranks.tiled(df.where("key_id < 3"), [F.col("key_id")], 10).collect()]
    assert sorted(few) == [1, 2, 3]
    assert ranks.placed(df.where("false"), [F.col("key_id")]).count() == 0
