"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

``queries`` are wall-clock seconds of whole Spark jobs, builds and probes included; ``kernel_ns_per_key`` is the time of the numeric kernels alone, the figure that
compares with published times per key; ``rates`` are cost-weighted false positive rates.
"""

from __future__ import annotations

import json
import os
import sys
import time

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

from costsieve.functions import geometry, keys, zipf  # noqa: E402
from costsieve.functions.hashing import Family  # noqa: E402
from costsieve.operators import baselines, bloom, custom, joins  # noqa: E402
from costsieve.plans import catalogue, workloads  # noqa: E402

BITS = 10.07


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .appName("costsieve-bench")
        .config("spark.sql.shuffle.partitions", cpus)
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.driver.memory", "12g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    family, took, rates = Family("xx"), {}, {}
    s, o = keys.load(spark, sf_dir, "kv_half")
    s, o = s.cache(), zipf.costs(o, 1.0, 1).cache()
    n, others = s.count(), o.count()
    total = geometry.budget(n, BITS)
    custom.build(s, o, total, family=family)  # starts workers and compiles

    def timed(name, work):
        begin = time.perf_counter()
        out = work()
        took[name] = round(time.perf_counter() - begin, 3)
        return out

    filters = {
        "standard": timed("build_standard", lambda: bloom.build(s, total, family, n=n)),
        "xor": timed("build_xor", lambda: baselines.xor_build(s, total, family, n=n)),
        "weighted": timed("build_weighted", lambda: baselines.weighted_build(s, o, total, family, n=n)),
        "custom": timed("build_custom", lambda: custom.build(s, o, total, family=family)),
        "custom-fast": timed("build_custom_fast", lambda: custom.build(s, o, total, family=family, fast=True)),
        "custom-sharded": timed("build_custom_sharded", lambda: custom.build(s, o, total, family=family, shards=8)),
    }
    for name, filt in filters.items():
        modes = ("expr", "arrow") if name in ("standard", "custom") else ("arrow",) if name != "weighted" else ("expr",)
        for mode in modes:
            cost = F.sum(F.when(F.col("hit"), F.col("cost")).otherwise(0.0)) / F.sum("cost")
            row = timed(f"probe_{name}_{mode}".replace("-", "_"), lambda: filt.probe(o, mode=mode).agg(cost.alias("r")).first())
            rates[name] = round(row["r"], 8)
        if filt.probe(s).where("NOT hit").count():
            raise AssertionError(f"{name} lost a positive")
    lines = keys.table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber")
    right = keys.table(spark, sf_dir, "orders").where("o_orderstatus = 'F'").select("o_orderkey", "o_orderpriority")
    js, jo = keys.load(spark, sf_dir, "join_reduce")
    jf = custom.build(js, jo, geometry.budget(js.count(), BITS), family=family)
    timed("prefiltered_join", lambda: joins.prefiltered(lines, right, "l_orderkey", "o_orderkey", jf).count())
    timed("workload_skewed", lambda: workloads.measure(spark, sf_dir, workloads.space_sweep("kv_half", skew=1.0)).collect())
    kernel = {r["method"]: {"build": round(r["build_ns"], 1), "probe": round(r["probe_ns"], 1)} for r in timed("workload_times", lambda: workloads.costs_of_building(spark, sf_dir).collect())}
    for name in ("owner_index", "swap_best", "bloom_wfpr", "cube_fpr"):
        timed(name, lambda: catalogue.queries()[name](spark, sf_dir).count())
    llm = None
    try:
        from costsieve.llm import queries as llm
    except ModuleNotFoundError as missing:
        if not (missing.name or "").startswith("costsieve.llm"):
            raise
    if llm:
        for name, query in llm.queries().items():
            timed(name, lambda: query(spark, sf_dir).write.format("noop").mode("overwrite").save())
    print(
        json.dumps(
            {
                "metric": "sum of headline queries",
                "value": round(sum(took.values()), 3),
                "unit": "sec",
                "queries": took,
                "sf": os.path.basename(sf_dir.rstrip("/")).removeprefix("sf"),
                "keys": n + others,
                "rates": rates,
                "kernel_ns_per_key": kernel,
            }
        )
    )
    spark.stop()


if __name__ == "__main__":
    main()
