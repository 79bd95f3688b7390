import glob
import os

import duckdb
import pandas as pd
import pytest

import __spark_entry__ as driver
from costsieve.plans import catalogue

ORACLES = catalogue.oracle_sql()
QUICK = [
    "hash_fnv1a", "hash_md5x_positions", "keys_lsm_days", "keys_url_spam", "zipf_costs_1", "bloom_words", "bloom_confusion", "owner_index", "near_miss_cost", "swap_tiers", "swap_best", "chain_walk_relational",
    "chf_delta0_equals_bloom", "chf_prefiltered_anti", "theory_bound_curve", "weighted_probe", "cube_fpr", "asof_filter_version", "common_fp_intersect", "stream_session_fp", "generated_keys", "collision_queue", "queue_rank_window",
]


@pytest.fixture(scope="module")
def duck(small_dir):
    con = duckdb.connect()
    for path in glob.glob(f"{small_dir}/*.parquet"):
        con.sql(f"CREATE VIEW {os.path.basename(path)[:-8]} AS SELECT * FROM '{path}'")
    return con


def rows(frame: pd.DataFrame) -> list:
    clean = lambda v: None if not isinstance(v, (list, tuple)) and pd.isna(v) else float(v) if isinstance(v, float) else v if isinstance(v, (int, bool)) else str(v)
    return sorted(repr([clean(v) for v in r]) for r in frame[sorted(frame.columns)].astype(object).values.tolist())


@pytest.mark.parametrize("name", QUICK)
def test_query_equals_oracle(spark, small_dir, duck, name):
    got, want = catalogue.queries()[name](spark, small_dir).toPandas(), duck.sql(ORACLES[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows(got) == rows(want)


def test_entry_compares_all_methods(spark):
    found = {(r["method"], r["skew"]): r for r in driver.entry(spark).collect()}
    assert all(r["fn"] == 0 for r in found.values())
    assert found["custom", 1.0]["wfpr"] < found["standard", 1.0]["wfpr"]


def test_every_oracle_has_a_query():
    assert set(driver.oracle_sql()) <= set(driver.queries())


def test_expression_probe_stays_in_the_jvm(spark, small_dir):
    from costsieve.functions import geometry, keys
    from costsieve.operators import custom

    s, o = keys.load(spark, small_dir, "lsm_days")
    plan = custom.build(s, o, geometry.budget(s.count(), 8.39)).probe(o)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan and "BroadcastExchange" in plan


def test_the_rest_works_without_the_llm_folders(tmp_path):
    import shutil
    import subprocess
    import sys

    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    shutil.copytree(root, tmp_path / "repo", ignore=shutil.ignore_patterns(".git", "__pycache__", "llm", "corpus_pipeline.py"))
    for kept in ([], ["corpus_pipeline.py"]):
        for name in kept:
            shutil.copy(f"{root}/{name}", tmp_path / "repo" / name)
        code = "import __spark_entry__ as e; q = e.queries(); assert set(e.oracle_sql()) <= set(q) and not any(n.startswith('op1') or n == 'pipeline' for n in q) and len(q) > 150"
        subprocess.run([sys.executable, "-c", code], cwd=tmp_path / "repo", check=True, timeout=120)
