"""A case for each finding of the second round's review that was right."""

import glob
import os
import random

import duckdb
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from costsieve.functions import geometry, hashing, keys, theory
from costsieve.operators import baselines, bloom, chain, custom, filters, optimiser
from costsieve.plans import catalogue, sweeps, workloads


def test_delta_0_is_one_bit_array_however_many_keys(spark, small_dir, monkeypatch):
    s, o = keys.load(spark, small_dir, "join_reduce")
    total = geometry.budget(s.count(), 8.39)
    monkeypatch.setattr(custom, "shards_for", lambda n: -(-n // 300))  # as if a shard held 300 keys
    hits = lambda filt: {(r["key_id"], r["hit"]) for r in filt.probe(o).select("key_id", "hit").collect()}
    assert hits(custom.build(s, o, total, delta=0)) == hits(bloom.build(s, total, k=3))


def test_xor_filter_beyond_what_is_sent_to_tasks(spark, small_dir, monkeypatch):
    s, o = keys.load(spark, small_dir, "kv_half")
    n = s.count()
    for module in (baselines, filters):
        monkeypatch.setattr(module, "BROADCAST_BYTES", 1000)
    filt = baselines.xor_build(s, geometry.budget(n, 8.39))
    assert filt.sent_bytes > 1000 and filt.probe(s).where("NOT hit").count() == 0


def test_xor_filter_of_many_shards_keeps_its_budget(spark, small_dir, monkeypatch):
    s, o = keys.load(spark, small_dir, "kv_half")
    n = s.count()
    monkeypatch.setattr(baselines, "shards_for", lambda n: 4)
    filt = baselines.xor_build(s, geometry.budget(n, 12.0))
    assert filt.shards == 4 and filt.probe(s).where("NOT hit").count() == 0
    assert filt.rows.agg(F.sum("m")).first()[0] <= filt.total_bits


def test_batches_of_keys_hash_as_single_keys_do():
    r = random.Random(5)
    data = [bytes(r.randrange(256) for _ in range(n)) for n in range(140) for _ in range(2)]
    r.shuffle(data)
    groups = hashing.batches(data)
    for i, kernel in hashing.KERNELS.items():
        assert hashing.bulk(kernel, groups).tolist() == [kernel(k) for k in data], i
    assert hashing.bulk(hashing.city64, groups).tolist() == [hashing.city64(k) for k in data]
    assert hashing.bulk(lambda b: hashing.wide_values(b, 7), groups).tolist() == [hashing.wide(k, 7) % ((1 << 61) - 1) for k in data]
    text = [k.hex() for k in data]
    assert hashing.md5_values([k.encode() for k in text], 40).tolist() == [hashing.Family().value(k, 40) for k in text]


def test_filters_that_know_no_costs_are_built_once_for_all_costs(monkeypatch):
    built, r = [], np.random.default_rng(1)
    made = sweeps.build
    monkeypatch.setattr(sweeps, "build", lambda d, setting, *rest: built.append(setting) or made(d, setting, *rest))
    ks, ko = ([f"{side}{i}".encode() for i in range(400)] for side in "so")
    s, o = (sweeps.Hashes(400, len(sweeps.IDS), lambda i, ks=ks: hashing.md5_values(ks, sweeps.IDS[i])) for ks in (ks, ko))
    d = sweeps.Data(s, o, np.arange(400), np.arange(400), np.ones(400), np.zeros(400), np.zeros(400))
    found = [sweeps._measure(d, sweeps.Setting("standard", 6.0, skew=1.0, seed=seed), 0, False) for seed in (1, 2, 3)]
    assert len(built) == 1 and len({x["fp"] for x in found}) == 1 and len({x["cost_passed"] for x in found}) == 3
    assert all(sweeps._measure(d, sweeps.Setting("custom", 8.0, skew=1.0, seed=seed), 0, False)["fn"] == 0 for seed in (1, 2)) and len(built) == 3


def test_grids_send_keys_to_few_lanes_once_there_are_shards(spark, small_dir, monkeypatch):
    rows = keys.keyset(spark, small_dir, "kv_orders")
    s, o = rows.where("positive").drop("positive"), rows.where("NOT positive").drop("positive")
    grid = workloads.bloom_builds()
    monkeypatch.setattr(sweeps, "shards_for", lambda n: 16)
    sent = sweeps.run(s, o, list(grid.settings))
    assert sorted(i for lane in sweeps._dealt(list(grid.settings), 8) for i in lane) == list(range(len(grid.settings)))
    plan = sent._jdf.queryExecution().executedPlan().toString()
    assert "REPARTITION_BY_NUM, " in plan and "hashpartitioning(slot" in plan and ", 16)" in plan
    parts = spark.createDataFrame([(i,) for i in sweeps.spread(16)], "slot int").repartition(16, "slot").select(F.spark_partition_id().alias("p"))
    assert parts.distinct().count() == 16


def inputs(query, *tables: str) -> bool:
    """Whether Spark's own scans read the tables."""
    return all(f"/{t}.parquet" in " ".join(query.inputFiles()) for t in tables)


def agrees(spark, small_dir, name: str) -> DataFrame:
    """The query, after its rows were compared with its SQL's and its types with the SQL's."""
    con = duckdb.connect()
    for path in glob.glob(f"{small_dir}/*.parquet"):
        con.sql(f"CREATE VIEW {os.path.basename(path)[:-8]} AS SELECT * FROM '{path}'")
    found = catalogue.queries()[name](spark, small_dir)
    want = con.sql(catalogue.oracle_sql()[name])
    kinds = {"BIGINT": "bigint", "INTEGER": "int", "DOUBLE": "double", "VARCHAR": "string"}
    assert {c: kinds[str(t)] for c, t in zip(want.columns, want.types)} == dict(found.dtypes)
    assert sorted(map(tuple, found.select(*want.columns).collect())) == sorted(want.fetchall())
    return found


def test_chain_load_stores_walks_of_the_events(spark, small_dir):
    found = agrees(spark, small_dir, "chain_load")
    assert inputs(found, "events") and found.first()["used"] > 0


def test_a_round_of_storing_keeps_whole_walks_only(spark):
    steps = spark.createDataFrame([(1, 1, 5), (1, 2, 6), (2, 1, 6), (2, 2, 7), (3, 1, 5), (3, 2, 8)], "key_id bigint, fn int, cell bigint")
    # key 2 finds function 2 in its first cell; key 3 finds its first function in the cell it shares
    assert sorted(map(tuple, chain.first_round(steps).collect())) == [(5, 1, False), (6, 2, True), (8, 2, True)]


def test_bloom_curve_reads_the_orders(spark, small_dir):
    found = agrees(spark, small_dir, "theory_bloom_curve")
    row = found.where("b = 10 AND k = 7").first()
    assert inputs(found, "orders") and abs(row["fpr"] - theory.bloom_fpr(row["m"] / row["n"], 7)) < 1e-9


def test_owner_estimates_read_the_orders(spark, small_dir):
    found = agrees(spark, small_dir, "theory_owner_prob")
    row = found.where("b = 10 AND k = 7").first()
    assert inputs(found, "orders") and abs(row["owners"] - theory.owners_expected(row["m"] / row["n"], 7)) < 1e-8


def test_two_round_rates_read_the_orders(spark, small_dir):
    found = agrees(spark, small_dir, "theory_two_round")
    row = found.where("b = 8 AND stored_pct = 10").first()
    assert inputs(found, "orders") and row["r"] > 0 and abs(row["total"] - theory.two_round_fpr(row["f"], row["r"])) < 1e-8


def test_bounds_read_the_orders(spark, small_dir):
    found = agrees(spark, small_dir, "theory_bound_curve")
    row = found.where("b = 9").first()
    g = geometry.split(geometry.budget(row["n"], 1.25 * 9))
    assert inputs(found, "orders") and abs(row["bound"] - theory.fpr_upper(row["n"], row["o"], g.m, g.omega, 4, g.pool)) < 1e-8


def test_xor_filter_takes_keys_that_are_given_twice(spark, small_dir):
    s, _ = keys.load(spark, small_dir, "kv_half")
    twice = s.unionByName(s.limit(100))
    filt = baselines.xor_build(twice, geometry.budget(s.count(), 8.39), shards=2)
    assert filt.probe(twice, mode="cogroup").where("NOT hit").count() == 0
    values = np.array([[5, 1], [5, 2], [5, 1], [4, 1]])
    assert baselines.distinct_rows(values).tolist() == [[5, 1], [5, 2], [4, 1]]


def test_xor_filter_has_small_tables(spark, small_dir):
    s, _ = keys.load(spark, small_dir, "kv_half")
    filt = baselines.xor_build(s, 8 * (1 << 20), n=1 << 20)  # as if there were so many keys
    assert filt.shards == 4 and filt.probe(s).where("NOT hit").count() == 0


def test_grids_send_keys_in_compressed_pieces():
    r = random.Random(3)
    names = [f"okey{r.randrange(1 << 64):016x}" for _ in range(20000)]
    rows = pa.RecordBatch.from_pydict({"shard": pa.array([i % 3 for i in range(20000)], pa.int32()), "positive": [i % 2 == 0 for i in range(20000)], "cost": [1.0] * 20000, "score": [0.0] * 20000, "k": names})
    made = list(sweeps._pieces([rows.slice(0, 9000), rows.slice(9000, 0), rows.slice(9000)], 3))
    sent = [(shard, piece) for batch in made for shard, piece in zip(batch.column("shard").to_pylist(), batch.column("keys").to_pylist())]
    back = sorted((k, shard) for shard, piece in sent for k in pa.ipc.open_stream(piece).read_all().column("k").to_pylist())
    assert back == sorted((k, i % 3) for i, k in enumerate(names)) and sum(len(piece) for _, piece in sent) < 13 * len(names)


def test_settings_that_differ_in_costs_start_from_one_optimiser(monkeypatch):
    begun = []
    index = optimiser.Shard._index
    monkeypatch.setattr(optimiser.Shard, "_index", lambda self: begun.append(self) or index(self))
    ks, ko = ([f"{side}{i}".encode() for i in range(2000)] for side in "so")
    fresh = lambda: sweeps.Data(*(sweeps.Hashes(2000, len(sweeps.IDS), lambda i, ks=ks: hashing.md5_values(ks, sweeps.IDS[i])) for ks in (ks, ko)), np.arange(2000), np.arange(2000), np.ones(2000), np.zeros(2000), np.zeros(2000))
    settings = [sweeps.Setting("custom", 8.0, skew=1.0, seed=seed) for seed in (1, 2, 3)]
    told = lambda found: {k: v for k, v in found.items() if not k.endswith("_s")}
    d = fresh()
    together = [told(sweeps._measure(d, s, 0, False)) for s in settings]
    assert len(begun) == 1 and together == [told(sweeps._measure(fresh(), s, 0, False)) for s in settings]


def test_standard_filter_of_a_grid_is_one_array_however_many_shards(spark, small_dir, monkeypatch):
    settings = tuple(sweeps.Setting("standard", b, skew=s) for b in (8.39, 21.81) for s in (0.0, 1.0)) + (sweeps.Setting("standard", 8.39, "k=2", k=2, k_fixed=True), sweeps.Setting("custom", 8.39))
    grid = workloads.Grid("one", "kv_half", settings)
    monkeypatch.setattr(sweeps, "shards_for", lambda n: 5)
    monkeypatch.setattr(sweeps, "SEGMENT", 100)
    found = workloads.checked(workloads.measure(spark, small_dir, grid)).collect()
    duck = duckdb.connect()
    duck.execute(f"CREATE VIEW orders AS SELECT * FROM '{small_dir}/orders.parquet'")
    rows = lambda told: sorted(repr(tuple(r)) for r in told)
    assert rows(found) == rows(duck.execute(workloads.checked_sql(grid)).fetchall())
