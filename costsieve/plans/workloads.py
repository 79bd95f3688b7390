"""The experiment workloads, each a grid of settings over a key set of the given tables. Budgets are in bits per positive key."""

from __future__ import annotations

import time
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import geometry, keys, theory
from ..operators import baselines
from ..operators.optimiser import OptimiserPolicy
from . import sweeps
from .sweeps import Setting

# The budgets of the two data sets of the experiments as bits per positive key.
URL_BUDGETS = (7.03, 8.44, 11.25, 14.06, 18.28)
KV_BUDGETS = (8.39, 10.07, 13.42, 16.78, 21.81)
SEEDS = tuple(range(1, 11))
PLAIN = ("custom", "custom-fast", "standard", "xor", "weighted")
LEARNED = ("custom", "custom-fast", "learned", "sandwiched", "adaptive")


@dataclass(frozen=True)
class Grid:
    """Settings over one key set; ``model`` adds learned scores."""

    workload: str
    keyset: str
    settings: tuple[Setting, ...]
    model: str | None = None


def measure(spark: SparkSession, sf_dir: str, grid: Grid, memory: bool = False, lanes: int = 8) -> DataFrame:
    """One row per method, label and budget: means over the seeds. Learned filters pay for their model in bits and build time; where it leaves them nothing their measures are null and ``infeasible`` is 1."""
    rows = keys.keyset(spark, sf_dir, grid.keyset)
    s, o = rows.where("positive").drop("positive"), rows.where("NOT positive").drop("positive")
    sizes = {r["positive"]: r["n"] for r in rows.groupBy("positive").agg(F.count(F.lit(1)).alias("n")).collect()}
    n, others = sizes.get(True, 0), sizes.get(False, 0)
    begin = time.perf_counter()
    fitted = baselines.fit_model(s, o, grid.model) if grid.model and n and others else None
    fit_ns = (time.perf_counter() - begin) * 1e9 / max(n + others, 1)
    sums = sweeps.run(s, o, list(grid.settings), model=fitted, memory=memory, lanes=lanes, n=n, o=others)
    found = sweeps.table(grid.workload, grid.keyset, sums, list(grid.settings), n, others)
    # learned filters are not built without their model; its training counts
    learned = F.col("method").isin(*sweeps.LEARNED)
    found = found.withColumn("build_ns", F.when(learned, F.col("build_ns") + fit_ns).otherwise(F.col("build_ns")))
    return found.withColumn("holds", F.col("fpr") <= F.col("bound"))


KEY = ["method", "label", "bits_per_key", "k", "delta", "alpha", "skew"]


def checked(found: DataFrame) -> DataFrame:
    """What must hold whatever the data: all runs made, no positive lost, the budget kept; and the standard filter's rate, which SQL finds too."""
    spare = 32.0 / F.col("n") + 1e-9  # no filter has less than 32 bits
    return found.select(
        *KEY,
        "runs",
        F.coalesce(F.col("fn") == 0, F.col("infeasible") > 0, F.lit(False)).alias("no_positive_lost"),
        F.coalesce(F.col("bits_used") <= F.col("bits_per_key") * 1.0001 + spare, F.col("infeasible") > 0, F.lit(False)).alias("budget_kept"),
        F.when(F.col("method") == "standard", F.round("fpr", 9)).alias("standard_fpr"),
    )


def checked_sql(grid: Grid) -> str:
    """The rows of ``checked``: the grid as values, and standard filters built in SQL."""
    held: dict[tuple, int] = {}
    for s in grid.settings:
        key = (s.method, s.label, float(s.bits_per_key), s.k, float(s.delta), s.alpha, float(s.skew))
        held[key] = held.get(key, 0) + 1
    rows, sizes = [], set()
    for (method, label, bits, k, delta, alpha, skew), runs in held.items():
        own = next(s for s in grid.settings if (s.method, s.label, float(s.bits_per_key), s.k) == (method, label, bits, k))
        functions = (k if own.k_fixed else min(22, geometry.best_k(bits))) if method == "standard" else 0
        sizes |= {(bits, functions)} if functions else set()
        rows.append(f"('{method}', '{label}', {bits}::DOUBLE, {k}::INT, {delta}::DOUBLE, {alpha}::INT, {skew}::DOUBLE, {runs}::BIGINT, {functions})")
    values = f"told(method, label, bits_per_key, k, delta, alpha, skew, runs, functions) AS (VALUES {', '.join(rows)})"
    if not sizes:
        return f"WITH {values} SELECT * EXCLUDE (functions), true AS no_positive_lost, true AS budget_kept, NULL::DOUBLE AS standard_fpr FROM told"
    number = "('0x' || substr(md5(i::VARCHAR || ':' || k), 1, 15))::BIGINT"
    return f"""WITH {values}, keys AS ({keys.duck_keyset(grid.keyset)}), hashed AS (SELECT key_id, positive, i, {number} AS h FROM keys, range(1, {max(f for _, f in sizes) + 1}) r(i)),
    sizes(bits, functions) AS (VALUES {', '.join(f'({b}::DOUBLE, {f})' for b, f in sorted(sizes))}),
    sized AS (SELECT bits, functions, greatest(32, (SELECT count(*) FROM keys WHERE positive) * round(bits * 100)::BIGINT // 100) AS m FROM sizes),
    bits AS (SELECT DISTINCT bits, functions, h % m AS pos FROM hashed, sized WHERE positive AND i <= functions),
    tests AS (SELECT s.bits, s.functions, key_id, bool_and(b.pos IS NOT NULL) AS hit FROM hashed h JOIN sized s ON h.i <= s.functions
              LEFT JOIN bits b ON b.bits = s.bits AND b.functions = s.functions AND b.pos = h.h % s.m WHERE NOT positive GROUP BY ALL),
    rates AS (SELECT bits, functions, round(avg(hit::INT), 9) AS fpr FROM tests GROUP BY ALL)
    SELECT told.* EXCLUDE (functions), true AS no_positive_lost, true AS budget_kept, fpr AS standard_fpr FROM told LEFT JOIN rates ON bits = bits_per_key AND rates.functions = told.functions"""


def _budgets(keyset: str) -> tuple[float, ...]:
    return URL_BUDGETS if keyset.startswith(("url", "words", "shingles", "doc")) else KV_BUDGETS


def delta_sweep(keyset="kv_orders") -> Grid:
    steps = sorted({i / 8 for i in range(9)} | {0.25})
    return Grid("delta", keyset, tuple(Setting("custom", 11.25, f"delta={d}", delta=d) for d in steps))


def k_sweep(keyset="kv_orders") -> Grid:
    return Grid("k", keyset, tuple(Setting(m, 11.25, f"k={k}", k=k, alpha=5 if k > 6 else 4, k_fixed=True) for k in range(2, 9) for m in ("custom", "standard")))


def cell_sweep(keyset="kv_orders") -> Grid:
    settings = [Setting("custom", b, f"alpha={a}", k=2 if a == 3 else 3, alpha=a) for a in (3, 4, 5, 6) for b in URL_BUDGETS]
    return Grid("cell", keyset, tuple(settings + [Setting("custom", b, "alpha=3, degenerate", alpha=3) for b in URL_BUDGETS]))


def space_sweep(keyset="kv_orders", group="plain", skew=0.0, workload="space") -> Grid:
    methods = PLAIN if group == "plain" else LEARNED
    settings = tuple(Setting(m, b, group, skew=skew, seed=seed) for m in methods for b in _budgets(keyset) for seed in (SEEDS if skew else (1,)))
    return Grid(workload, keyset, settings, "logistic" if group == "learned" else None)


def skew_sweep(keyset="kv_orders") -> Grid:
    skews = [round(0.3 * i, 1) for i in range(11)]
    return Grid("skewness", keyset, tuple(Setting(m, 8.44, "", skew=s, seed=seed) for s in skews for m in ("custom", "custom-fast", "standard", "xor") for seed in (SEEDS if s else (1,))))


def bloom_builds(keyset="kv_orders") -> Grid:
    """The standard filter with k different functions of the pool, k seeds of one 64-bit function and k seeds of one 128-bit function, beside the default family, and the custom filter on the pool."""
    methods = ("standard", "standard-pool", "standard-city64", "standard-murmur128", "custom", "custom-pool")
    return Grid("bloom_builds", keyset, tuple(Setting(m, b, "", skew=s, seed=seed) for m in methods for b in _budgets(keyset) for s in (0.0, 1.0) for seed in (SEEDS if s else (1,))))


def costs_of_building(spark, sf_dir, keyset="kv_half", memory=False, repeats=5) -> DataFrame:
    """Kernel time and memory of each method, one after the other on one lane after a warm-up, with factors over the standard filter.

    Times are the medians of ``repeats`` runs. Kernels start from hash values; ``hash_ns`` is the time to make those in the JVM, and what a learned filter's model needs to score a key is part of its ``probe_ns``.
    """
    budget = 10.07 if keyset.startswith("kv") else 8.44
    methods = ("standard", "xor", "custom-fast", "weighted", "custom", "learned", "sandwiched", "adaptive")
    grid = Grid("memory" if memory else "time", keyset, tuple(Setting(m, budget, repeats=1 if memory else repeats) for m in methods), "logistic")
    found = measure(spark, sf_dir, grid, memory=memory, lanes=1)
    s, o = keys.load(spark, sf_dir, keyset)
    both, model = s.unionByName(o).select("k").repartition(spark.sparkContext.defaultParallelism).cache(), baselines.fit_model(s, o, "logistic")
    count = max(both.count(), 1)

    def cpu_ns(frame: DataFrame) -> float:
        took = []
        for _ in range(3):
            begin = time.perf_counter()
            frame.write.format("noop").mode("overwrite").save()
            took.append(time.perf_counter() - begin)
        return sorted(took)[1] * 1e9 * spark.sparkContext.defaultParallelism / count

    hashing, scoring = cpu_ns(both.select(sweeps.Family().columns(F.col("k"), sweeps.IDS).alias("h"))), cpu_ns(model.score(both))
    both.unpersist()
    learned = F.col("method").isin(*sweeps.LEARNED)
    found = found.withColumn("hash_ns", F.lit(hashing)).withColumn("score_ns", F.when(learned, F.lit(scoring)))
    found = found.withColumn("probe_ns", F.col("probe_ns") + F.coalesce("score_ns", F.lit(0.0)))
    base = Window.partitionBy("workload", "keyset").orderBy(F.when(F.col("method") == "standard", 0).otherwise(1))
    for column in ("build_ns", "probe_ns", "peak_bytes"):
        found = found.withColumn(f"{column}_factor", F.col(column) / F.nullif(F.first(column).over(base), F.lit(0.0)))
    return found


def bound_sweep(keyset="kv_half", by="k") -> Grid:
    """Measured rate of the bit array after optimising against the closed-form bound."""
    settings = (
        [Setting("custom", 12.5, f"k={k}", k=k, alpha=5 if k > 6 else 4) for k in range(2, 11)]
        if by == "k"
        else [Setting("custom", 1.25 * b, f"b={b}", k=4) for b in range(4, 14)]
    )
    return Grid(f"bound_by_{by}", keyset, tuple(settings))


def owner_share(spark, sf_dir, keyset="kv_half") -> DataFrame:
    """Share of set bits, as collision keys map to them, that have a single owner, against its lower estimate."""
    from ..operators import steps

    s, o = keys.load(spark, sf_dir, keyset)
    n = s.count()
    parts = []
    for b in range(4, 14):
        state = steps.State(s, o, b * n, 4)
        share = state.candidate_shares().select(
            F.lit("owner_by_b").alias("workload"),
            F.lit(keyset).alias("keyset"),
            F.lit(float(b)).alias("bits_per_key"),
            F.col("share").alias("measured"),
            F.lit(theory.owner_prob(b, 4)).alias("estimate"),
        )
        parts.append(share)
    return reduce(DataFrame.unionByName, parts)


def natural_costs(keyset="join_reduce") -> Grid:
    return Grid("natural", keyset, tuple(Setting(m, b, "natural", skew=-1.0) for m in PLAIN for b in _budgets(keyset)))


def shard_sweep(keyset="kv_half") -> Grid:
    """One optimiser over all keys against 4 and 16 that each know a part of them."""
    return Grid("shards", keyset, tuple(Setting("custom", 10.07, f"shards={p}", skew=s, seed=seed, parts=p) for p in (1, 4, 16) for s in (0.0, 1.0) for seed in (SEEDS if s else (1,))))


def ablate(keyset="kv_orders") -> Grid:
    base = OptimiserPolicy()
    policies = {
        "default": base,
        "as printed": OptimiserPolicy.reference(),
        "tiered": base.but(candidate_policy="tiered"),
        "strict gain": base.but(strict_gain=True),
        "rechange": base.but(allow_rechange=True),
        "exhaustive order": base.but(order_policy="exhaustive"),
        "gain over all": base.but(gain="all"),
        "owner by owner": base.but(owner_order="first"),
        "no requeue": base.but(max_requeue=0),
    }
    settings = [Setting("custom", 8.39, name, skew=1.0, seed=seed, policy=p) for name, p in policies.items() for seed in SEEDS]
    settings += [Setting("custom-fast", 8.39, name, skew=1.0, seed=seed, policy=base.but(fast_blind=blind)) for name, blind in (("fast", False), ("fast, blind", True)) for seed in SEEDS]
    return Grid("ablation", keyset, tuple(settings))


def flagship_grid(keyset="kv_orders") -> Grid:
    """The plain methods under one budget, uniform and skewed."""
    return Grid("flagship", keyset, tuple(Setting(m, 8.44, "", skew=s, seed=seed) for m in PLAIN for s in (0.0, 1.0) for seed in (SEEDS if s else (1,))))


def flagship(spark, sf_dir) -> DataFrame:
    return measure(spark, sf_dir, flagship_grid())
