"""A case for each finding of the third round's review that was right."""

import duckdb
import numpy as np
import pyarrow as pa
import pytest

from costsieve.functions import keys
from costsieve.plans import sweeps, workloads


@pytest.mark.parametrize("most", (0, 1 << 30))
def test_standard_filter_of_a_grid_is_one_array_however_large(spark, small_dir, monkeypatch, most):
    settings = tuple(sweeps.Setting("standard", b, skew=s) for b in workloads.KV_BUDGETS for s in (0.0, 1.0)) + (sweeps.Setting("custom", 8.39),)
    grid = workloads.Grid("one", "kv_orders", settings)
    monkeypatch.setattr(sweeps, "shards_for", lambda n: 5)
    monkeypatch.setattr(sweeps, "GROUP", 200, raising=False)
    for limit in ("SENT_BYTES", "BROADCAST_BYTES"):  # the limit had the second name
        monkeypatch.setattr(sweeps, limit, most, raising=False)
    found = workloads.checked(workloads.measure(spark, small_dir, grid)).collect()
    duck = duckdb.connect()
    duck.execute(f"CREATE VIEW orders AS SELECT * FROM '{small_dir}/orders.parquet'")
    rows = lambda told: sorted(repr(tuple(r)) for r in told)
    assert rows(found) == rows(duck.execute(workloads.checked_sql(grid)).fetchall())


def test_measures_of_a_standard_filter_do_not_hang_on_its_size(spark, small_dir, monkeypatch):
    rows = keys.keyset(spark, small_dir, "join_reduce")
    s, o = rows.where("positive").drop("positive"), rows.where("NOT positive").drop("positive")
    settings = [sweeps.Setting("standard", 6.0, skew=-1.0), sweeps.Setting("standard", 9.0, k=2, k_fixed=True, skew=-1.0)]
    told = lambda: {(r["setting"], r["metric"]): round(r["value"], 6) for r in sweeps.run(s, o, settings).collect() if not r["metric"].endswith("_s")}
    one = told()
    monkeypatch.setattr(sweeps, "shards_for", lambda n: 3)
    for most in (1 << 30, 0):
        monkeypatch.setattr(sweeps, "SENT_BYTES", most, raising=False)
        monkeypatch.setattr(sweeps, "BROADCAST_BYTES", most, raising=False)
        assert told() == one
    assert one[0, "fp"] > 0 and one[0, "ones"] > 0


@pytest.mark.parametrize("most", (0, 1 << 30))
def test_shards_without_positives_count(spark, small_dir, monkeypatch, most):
    s, o = keys.load(spark, small_dir, "kv_half")
    few, settings = s.orderBy("k").limit(3), [sweeps.Setting("standard", 2.0, k=1, k_fixed=True), sweeps.Setting("standard", 40.0)]
    told = lambda: {(r["setting"], r["metric"]): r["value"] for r in sweeps.run(few, o, settings).where("metric IN ('n', 'o', 'fn', 'fp')").collect()}
    one = told()
    monkeypatch.setattr(sweeps, "shards_for", lambda n: 5)
    monkeypatch.setattr(sweeps, "SENT_BYTES", most, raising=False)
    assert told() == one and one[0, "o"] == o.count() and one[0, "fp"] > 0


def test_places_travel_as_differences():
    r = np.random.default_rng(2)
    for places in ([0], [5, 6, 300, 1 << 31], sorted(set(r.integers(0, 1 << 23, 5000).tolist()))):
        own = np.array(places, np.int64)
        assert sweeps._summed(pa.py_buffer(sweeps._steps(own)), len(own)).tolist() == places


def test_answers_say_which_places_are_set():
    side = lambda names: sweeps.Hashes(len(names), 2, lambda i: np.array([hash((n, i)) & 0xFFFF for n in names], np.int64))
    shards = [(side(range(100 * i, 100 * i + 40)), side(range(100 * i + 40, 100 * i + 100))) for i in range(3)]
    m, k, length = 1000, 2, 300
    asked = pa.concat_tables([sweeps._asked({True: s, False: o}, slot, [(m, k)], {(m, k)}, length) for slot, (s, o) in enumerate(shards)])
    parts = [asked.filter(pa.array(np.asarray(asked.column("segment")) == g)) for g in range(4)]
    answers = pa.concat_tables([sweeps._answered(p, length, {0: 0, 1: 0, 2: 0}) for p in parts])
    bits = np.zeros(m, bool)
    for s, _ in shards:
        bits[sweeps._places(s, m, k)] = True
    assert round(sum(answers.column("ones").to_pylist())) == bits.sum()
    for slot, sides in enumerate(shards):
        told = sweeps.Told(1, 3, [(m, k)], answers.filter(pa.array(np.asarray(answers.column("slot")) == slot)))
        passes = told.filter(None, m, k)[0]
        for values, positive in zip(sides, (True, False)):
            want = bits[values.column(0) % m] & bits[values.column(1) % m]
            assert passes(values, positive).tolist() == want.tolist()
