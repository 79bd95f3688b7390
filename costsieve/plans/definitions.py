"""All queries of the filter engine, each with its DuckDB twin where SQL can express it."""

from __future__ import annotations

from functools import partial

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import geometry, keys, theory, zipf
from ..functions.hashing import KERNELS, POOL, Family, duck_fold
from ..operators import baselines, bloom, chain, custom, joins, measures, reports, rounds
from ..operators.optimiser import OptimiserPolicy
from ..operators.steps import State
from ..sources import files
from ..streaming import streams
from . import workloads
from .catalogue import register

BUDGET = 8.39  # bits per key of most queries below
MD5 = Family("md5x")


def md5(i, expr: str = "k") -> str:
    """DuckDB value of function ``i``, a number or a column."""
    return f"('0x' || substr(md5({i}::VARCHAR || ':' || {expr}), 1, 15))::BIGINT"


def sized(spark: SparkSession, d: str, name: str, bits: float = BUDGET):
    """(positives, negatives, geometry) of a key set; the number of positives is counted."""
    s, o = keys.load(spark, d, name)
    return s, o, geometry.split(geometry.budget(s.count(), bits))


def prelude(name: str, bits: float = BUDGET, k: int = 3) -> str:
    """CTEs of a key set under a budget: keys, s, o, g(omega, m), sp and op (positions), hits, ob (negatives' distinct bits), cls (number of clear bits)."""
    return f"""
keys AS ({keys.duck_keyset(name)}), s AS (SELECT key_id, k FROM keys WHERE positive), o AS (SELECT key_id, k, cost FROM keys WHERE NOT positive),
t AS (SELECT count(*) * {round(bits * 100)} // 100 AS total FROM s), g AS (SELECT total // 5 // 4 AS omega, total - total // 5 // 4 * 4 AS m FROM t),
sp AS (SELECT key_id, i, {md5('i')} % (SELECT m FROM g) AS pos FROM s, range(1, {k + 1}) r(i)),
hits AS (SELECT pos, count(*) AS hits, min(key_id) AS owner FROM sp GROUP BY pos),
op AS (SELECT DISTINCT key_id, cost, {md5('i')} % (SELECT m FROM g) AS pos FROM o, range(1, {k + 1}) r(i)),
ob AS (SELECT op.*, hits.hits, hits.owner FROM op LEFT JOIN hits USING (pos)),
cls AS (SELECT key_id, cost, sum(CASE WHEN hits IS NULL THEN 1 ELSE 0 END)::BIGINT AS clear FROM ob GROUP BY ALL)"""


def swaps_prelude(name: str) -> str:
    return f"""{prelude(name)},
coll AS (SELECT key_id FROM cls WHERE clear = 0),
cand AS (SELECT key_id, cost, pos, owner FROM ob WHERE hits = 1 AND key_id IN (SELECT key_id FROM coll)),
alt AS (SELECT key_id AS owner, i::INT AS fn, {md5('i')} % (SELECT m FROM g) AS landing FROM s, range(4, 8) r(i) WHERE key_id IN (SELECT owner FROM cand)),
swaps AS (SELECT c.*, fn, landing FROM cand c JOIN alt USING (owner) WHERE landing <> pos),
near AS (SELECT ob.pos AS landing, key_id AS victim, cost AS vc FROM ob WHERE hits IS NULL AND key_id IN (SELECT key_id FROM cls WHERE clear = 1)),
loss AS (SELECT w.pos, w.landing, sum(vc) AS loss FROM (SELECT DISTINCT pos, landing FROM swaps) w JOIN near USING (landing)
         WHERE NOT EXISTS (SELECT 1 FROM ob WHERE ob.key_id = near.victim AND ob.pos = w.pos) GROUP BY ALL),
graded AS (SELECT x.key_id, x.cost, x.pos, x.owner, x.fn, x.landing,
           CASE WHEN h.pos IS NOT NULL THEN 0.0 ELSE coalesce(l.loss, 0.0) END::DOUBLE AS loss,
           CASE WHEN h.pos IS NOT NULL THEN 0 WHEN coalesce(l.loss, 0.0) = 0 THEN 1 ELSE 2 END::INT AS tier
           FROM swaps x LEFT JOIN hits h ON h.pos = x.landing LEFT JOIN loss l ON l.pos = x.pos AND l.landing = x.landing)"""


def state(spark, d, name="join_reduce") -> State:
    s, o, g = sized(spark, d, name)
    return State(s, o, g.m)


def _hashing() -> None:
    orders = lambda spark, d: keys.table(spark, d, "orders").select(keys.canonical("o_orderkey", "o_orderpriority").alias("k"))
    duck_key = "SELECT o_orderkey::VARCHAR || chr(31) || o_orderpriority AS k FROM orders"
    for name in ("fnv1a", "djb", "ndjb", "bkdr", "sdbm", "js", "dek", "brp", "py", "pjw", "oaat", "ap", "rs", "elf"):
        i = POOL.index(name) + 1
        register(
            f"hash_{name}",
            lambda spark, d, i=i: orders(spark, d).select("k", Family("pool").column(F.col("k"), i).alias("h")),
            f"SELECT k, ({duck_fold(name, 'k')})::BIGINT AS h FROM ({duck_key})",
        )
    register(
        "hash_md5x_positions",
        lambda spark, d: orders(spark, d).select("k", F.posexplode(F.array(*[F.pmod(MD5.column(F.col("k"), i), F.lit(100003)) for i in range(1, 8)])).alias("i", "pos")),
        f"SELECT k, (i - 1)::INT AS i, {md5('i')} % 100003 AS pos FROM ({duck_key}), range(1, 8) r(i)",
    )
    register(
        "hash_double_positions",
        lambda spark, d: orders(spark, d).select("k", F.posexplode(MD5.doubled(F.col("k"), list(range(1, 8)), F.lit(100003).cast("bigint"))).alias("i", "pos")),
        f"SELECT k, (i - 1)::INT AS i, ({md5(31)} % 100003 + i * ({md5(32)} % 100003)) % 100003 AS pos FROM ({duck_key}), range(1, 8) r(i)",
    )

    def pool(spark, d):
        def run(batches):
            import pyarrow as pa

            for batch in batches:
                ks = batch.column("k").to_pylist()
                for i, name in enumerate(POOL, 1):
                    yield pa.RecordBatch.from_arrays([pa.array(ks), pa.array([name] * len(ks)), pa.array([KERNELS[i](k.encode()) for k in ks], pa.int64())], ["k", "fn", "h"])

        from ..sources.shared import ship

        ship(spark)
        return orders(spark, d).mapInArrow(run, "k string, fn string, h bigint")

    register("hash_pool_22", pool)
    register("hash_skew", lambda spark, d: reports.hash_skew(keys.load(spark, d, "kv_half")[0], 1009))


def _keysets() -> None:
    for name in keys.KEYSETS:
        register(
            f"keys_{name}",
            lambda spark, d, name=name: keys.keyset(spark, d, name),
            keys.duck_keyset(name),
        )
    register(
        "keys_disjoint",
        lambda spark, d: _union([_overlap(spark, d, n) for n in keys.KEYSETS]),
        " UNION ALL ".join(f"SELECT '{n}' AS keyset, 0::BIGINT AS common" for n in keys.KEYSETS),
    )
    for label, skew in (("0", 0.0), ("1", 1.0)):
        register(
            f"zipf_costs_{label}",
            lambda spark, d, skew=skew: zipf.costs(keys.load(spark, d, "kv_half")[1], skew, 1).select("key_id", F.round("cost", 9).alias("cost")),
            f"SELECT key_id, round(pow(rank::DOUBLE, {-skew}), 9)::DOUBLE AS cost FROM ({zipf.duck_rank('SELECT * FROM (' + keys.duck_keyset('kv_half') + ') WHERE NOT positive', 1)})",
        )
    shuffles = lambda spark, d: _union([zipf.costs(keys.load(spark, d, "lsm_days")[1], 1.0, s).agg(F.lit(s).alias("seed"), F.round(F.sum("cost"), 6).alias("total"), F.max_by("k", "cost").alias("top")) for s in range(1, 11)])
    lsm = "SELECT * FROM (" + keys.duck_keyset("lsm_days") + ") WHERE NOT positive"
    register(
        "zipf_shuffles_10",
        shuffles,
        " UNION ALL ".join(f"SELECT {s}::INT AS seed, round(sum(1.0 / rank), 6)::DOUBLE AS total, min_by(k, rank) AS top FROM ({zipf.duck_rank(lsm, s)})" for s in range(1, 11)),
    )
    register(
        "natural_costs",
        lambda spark, d: _union([keys.load(spark, d, n)[1].agg(F.lit(n).alias("keyset"), F.count(F.lit(1)).alias("n"), F.sum("cost").alias("total"), F.max("cost").alias("most")) for n in ("join_reduce", "words", "lsm_days", "doc_block")]),
        " UNION ALL ".join(f"SELECT '{n}' AS keyset, count(*) AS n, sum(cost) AS total, max(cost) AS most FROM ({keys.duck_keyset(n)}) WHERE NOT positive" for n in ("join_reduce", "words", "lsm_days", "doc_block")),
    )
    register(
        "cost_lorenz",
        lambda spark, d: reports.lorenz(keys.load(spark, d, "lsm_days")[1]),
        f"SELECT key_id, cost, row_number() OVER w AS place, round(sum(cost) OVER (ORDER BY cost DESC, key_id ROWS UNBOUNDED PRECEDING) / sum(cost) OVER (), 9) AS share FROM ({lsm}) WINDOW w AS (ORDER BY cost DESC, key_id)",
    )
    register(
        "cost_bands",
        lambda spark, d: reports.cost_band(keys.table(spark, d, "orders")),
        "WITH b AS (SELECT * FROM (VALUES ('low', 0.0, 1000.0), ('mid', 1000.0, 100000.0), ('high', 100000.0, 1e18)) v(band, low, high)) SELECT band, count(*) AS n FROM orders JOIN b ON o_totalprice >= low AND o_totalprice < high GROUP BY band",
    )
    register(
        "heavy_keys",
        lambda spark, d: reports.heavy(keys.load(spark, d, "words")[1], 25),
        f"SELECT k, cost FROM ({keys.duck_keyset('words')}) WHERE NOT positive ORDER BY cost DESC, key_id LIMIT 25",
    )


def _overlap(spark, d, name) -> DataFrame:
    s, o = keys.load(spark, d, name)
    return s.select("k").intersect(o.select("k")).agg(F.lit(name).alias("keyset"), F.count(F.lit(1)).alias("common"))


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def _standard() -> None:
    def words(spark, d):
        s, _, g = sized(spark, d, "kv_half")
        return bloom.bit_words(s, g.m, MD5, [1, 2, 3]).select("word", "bits")

    register("bloom_words", words, f"WITH {prelude('kv_half')} SELECT pos // 32 AS word, bit_or(1::BIGINT << (pos % 32)::INT) AS bits FROM sp GROUP BY 1")

    def probed(spark, d, name="join_reduce", bits=BUDGET, k=3):
        s, o, g = sized(spark, d, name, bits)
        return bloom.build(s, g.m, MD5, k=k).probe(o)

    register(
        "bloom_probe",
        lambda spark, d: probed(spark, d).select("key_id", "hit"),
        f"WITH {prelude('join_reduce')} SELECT key_id, clear = 0 AS hit FROM cls",
    )

    def packed(spark, d):
        from ..sources.functions import pack_bits

        s, _, g = sized(spark, d, "lsm_days")
        at = State(s, s, g.m).positions.select(F.expr("pos div 1024").alias("block"), F.col("pos") % 1024)
        blocks = at.toDF("block", "pos").groupBy("block").agg(pack_bits("pos").alias("bits"))
        each = blocks.select("block", F.posexplode(F.expr("transform(sequence(1, length(bits)), i -> cast(conv(hex(substring(bits, i, 1)), 16, 10) as bigint))")).alias("byte", "value"))
        return each.where("value > 0")

    register("bloom_packed_bytes", packed, f"WITH {prelude('lsm_days')} SELECT pos // 1024 AS block, (pos % 1024 // 8)::INT AS byte, bit_or(1::BIGINT << (pos % 8)::INT) AS value FROM sp GROUP BY 1, 2")

    def confusion(spark, d):
        s, o, g = sized(spark, d, "join_reduce")
        f = bloom.build(s, g.m, MD5, k=3)
        both = f.probe(s.withColumn("positive", F.lit(True))).unionByName(f.probe(o.withColumn("positive", F.lit(False))))
        return both.groupBy("positive", "hit").agg(F.count(F.lit(1)).alias("n"))

    register(
        "bloom_confusion",
        confusion,
        f"WITH {prelude('join_reduce')} SELECT false AS positive, clear = 0 AS hit, count(*) AS n FROM cls GROUP BY ALL UNION ALL SELECT true, true, count(*) FROM s",
    )
    rate = "round(sum(CASE WHEN clear = 0 THEN cost ELSE 0 END) / sum(cost), 9) AS wfpr, round(avg((clear = 0)::INT), 9) AS fpr"
    measure = lambda df: df.agg(F.round(F.sum(F.when(F.col("hit"), F.col("cost")).otherwise(0.0)) / F.sum("cost"), 9).alias("wfpr"), F.round(F.avg(F.col("hit").cast("int")), 9).alias("fpr"))
    register("bloom_wfpr", lambda spark, d: measure(probed(spark, d)), f"WITH {prelude('join_reduce')} SELECT {rate} FROM cls")
    register(
        "bloom_k_sweep",
        lambda spark, d: _union([measure(probed(spark, d, "lsm_days", BUDGET, k)).withColumn("k", F.lit(k)) for k in (2, 4, 6, 8)]),
        " UNION ALL ".join(f"SELECT * FROM (WITH {prelude('lsm_days', BUDGET, k)} SELECT {rate}, {k}::INT AS k FROM cls)" for k in (2, 4, 6, 8)),
    )
    register(
        "bloom_budget_sweep",
        lambda spark, d: _union([measure(probed(spark, d, "lsm_days", b)).withColumn("bits_per_key", F.lit(b)) for b in workloads.KV_BUDGETS]),
        " UNION ALL ".join(f"SELECT * FROM (WITH {prelude('lsm_days', b)} SELECT {rate}, {b}::DOUBLE AS bits_per_key FROM cls)" for b in workloads.KV_BUDGETS),
    )

    def united(spark, d):
        s, o, g = sized(spark, d, "kv_half")
        even = F.col("key_id") % 3 == 0
        a, b = bloom.build(s.where(even), g.m, MD5, k=3), bloom.build(s.where(~even), g.m, MD5, k=3)
        return bloom.union(a, b).probe(o).select("key_id", "hit")

    register("bloom_union", united, f"WITH {prelude('kv_half')} SELECT key_id, clear = 0 AS hit FROM cls")


def _steps() -> None:
    base, sw = prelude("join_reduce"), swaps_prelude("join_reduce")
    for name, make, sql in (
        ("owner_index", lambda s: s.owner_index, f"WITH {base} SELECT pos, hits, owner FROM hits"),
        ("owner_share", lambda s: s.candidate_shares().select(F.round("share", 9).alias("share")), f"WITH {base} SELECT round(avg((hits = 1)::INT), 9) AS share FROM ob WHERE key_id IN (SELECT key_id FROM cls WHERE clear = 0)"),
        ("owner_prob_empirical", lambda s: s.owner_prob_empirical(), f"""WITH {base}, n AS (SELECT count(*)::DOUBLE AS n FROM s), met AS (SELECT pos, i, count(*) AS c, count(*) / (SELECT n FROM n) AS p FROM sp GROUP BY ALL),
          spread AS (SELECT pos, sum(c) AS hits, sum(p) AS p, min(1 - p) AS least, sum(CASE WHEN p < 1 THEN ln(1 - p) END) AS missed FROM met GROUP BY pos)
          SELECT count(*) AS bits, round(avg(CASE WHEN least > 0 THEN (SELECT n FROM n) * p / (exp(-(SELECT n FROM n) * missed) - 1) ELSE 0 END), 9) AS estimate, round(avg((hits = 1)::INT), 9) AS measured FROM spread"""),
        ("collision_queue", lambda s: s.queue(), f"WITH {base} SELECT key_id, cost, row_number() OVER (ORDER BY cost DESC, key_id) AS place FROM cls WHERE clear = 0"),
        ("reliance_index", lambda s: s.reliance_index(), f"WITH {base} SELECT pos, count(*) AS keys, sum(cost) AS cost FROM ob WHERE key_id IN (SELECT key_id FROM cls WHERE clear > 0) GROUP BY pos"),
        ("near_miss_cost", lambda s: s.near_miss_cost(), f"WITH {base} SELECT pos, sum(cost) AS cost, count(*) AS keys FROM ob WHERE hits IS NULL AND key_id IN (SELECT key_id FROM cls WHERE clear = 1) GROUP BY pos"),
        ("candidate_owners", lambda s: s.candidates, f"WITH {sw} SELECT * FROM cand"),
        ("candidate_swaps", lambda s: s.swaps, f"WITH {sw} SELECT key_id, cost, pos, owner, fn, landing FROM swaps"),
        ("swap_tiers", lambda s: s.graded, f"WITH {sw} SELECT * FROM graded"),
        ("swap_best", lambda s: s.best(), f"WITH {sw} SELECT * EXCLUDE (r) FROM (SELECT *, row_number() OVER (PARTITION BY key_id ORDER BY loss, tier, owner, fn, pos) AS r FROM graded WHERE loss <= cost) WHERE r = 1"),
        ("swap_give_up", lambda s: s.given_up(), f"WITH {sw} SELECT key_id, cost FROM cls WHERE clear = 0 AND key_id NOT IN (SELECT key_id FROM graded WHERE loss <= cost)"),
    ):
        register(name, lambda spark, d, make=make: make(state(spark, d)), sql)


STORED = ((0, 3, False), (1, 5, True), (2, 1, False), (4, 2, True), (5, 4, False), (7, 6, True), (8, 7, False), (10, 2, False), (11, 3, True), (13, 1, True))
TABLE = 16


def _chains() -> None:
    def walk(spark, d):
        cells = spark.createDataFrame(STORED, "cell bigint, fn int, ended boolean")
        s, o = keys.load(spark, d, "lsm_days")
        rows = s.unionByName(o).select("key_id", F.pmod(MD5.column(F.col("k"), 40), F.lit(TABLE)).alias("start"), F.array(*[F.pmod(MD5.column(F.col("k"), i), F.lit(TABLE)) for i in range(1, 8)]).alias("nexts"))
        return chain.walk_relational(rows, F.broadcast(cells), 3)

    values = ", ".join(f"({c}, {f}, {str(e).lower()})" for c, f, e in STORED)
    sql = f"WITH cells(cell, fn, ended) AS (VALUES {values}), k0 AS (SELECT key_id, k, {md5(40)} % {TABLE} AS spot FROM ({keys.duck_keyset('lsm_days')})), "
    for j in range(3):
        sql += f"w{j} AS (SELECT p.*, c.fn AS f{j}, c.ended AS e{j} FROM k{j} p LEFT JOIN cells c ON c.cell = p.spot), "
        sql += f"k{j + 1} AS (SELECT * REPLACE ({md5(f'coalesce(f{j}, 1)')} % {TABLE} AS spot) FROM w{j}), "
    sql += "z AS (SELECT 1) SELECT key_id, CASE WHEN f0 IS NOT NULL AND f1 IS NOT NULL AND f2 IS NOT NULL AND e2 THEN f0 || ',' || f1 || ',' || f2 END AS subset FROM k3"
    register("chain_walk_relational", walk, sql)

    def load(spark, d):
        s, _, g = sized(spark, d, "lsm_days")
        return chain.load(chain.first_round(chain.default_walks(s, MD5, g.omega, 3)), g.omega)

    register(
        "chain_load",
        load,
        f"""WITH {prelude('lsm_days')}, steps AS (SELECT key_id, 1 AS fn, {md5(40)} % (SELECT omega FROM g) AS cell FROM s UNION ALL SELECT key_id, i + 1, {md5('i')} % (SELECT omega FROM g) FROM s, range(1, 3) r(i)),
        first AS (SELECT cell, min(key_id * 4::HUGEINT + fn) AS held FROM steps GROUP BY cell),
        kept AS (SELECT key_id FROM steps JOIN first USING (cell) GROUP BY key_id HAVING bool_and(held % 4 = fn)),
        cells AS (SELECT cell, bool_or(fn = 3) AS ended FROM steps WHERE key_id IN (SELECT key_id FROM kept) GROUP BY cell)
        SELECT count(*) AS used, coalesce(sum(ended::INT), 0)::BIGINT AS ended, round(count(*) / (SELECT omega FROM g), 6) AS load FROM cells""",
    )


def _built(spark, d, name="kv_half", **options):
    s, o = keys.load(spark, d, name)
    n = s.count()
    return s, o, custom.build(s, o, geometry.budget(n, BUDGET), family=MD5, **options)


def _zero(filt, s) -> DataFrame:
    return filt.probe(s).agg(F.count(F.lit(1)).alias("n"), F.sum((~F.col("hit")).cast("int")).alias("misses"))


def _zero_sql(name: str) -> str:
    return f"SELECT count(*) AS n, 0::BIGINT AS misses FROM ({keys.duck_keyset(name)}) WHERE positive"


def _custom() -> None:
    for name, options in (("chf_zero_fn", {}), ("chf_fast_zero_fn", {"fast": True}), ("chf_sharded_zero_fn", {"shards": 4}), ("chf_printed_zero_fn", {"policy": OptimiserPolicy.reference()})):
        def query(spark, d, options=options):
            s, _, f = _built(spark, d, **options)
            return _zero(f, s)

        register(name, query, _zero_sql("kv_half"))
    for name in ("join_reduce", "lsm_days", "words", "url_half", "doc_block"):
        def query(spark, d, name=name):
            s, _, f = _built(spark, d, name)
            return _zero(f, s)

        register(f"chf_zero_fn_{name}", query, _zero_sql(name))

    def delta0(spark, d):
        s, o = keys.load(spark, d, "join_reduce")
        total = geometry.budget(s.count(), BUDGET)
        return custom.build(s, o, geometry.split(total).m, family=MD5, delta=0).probe(o).select("key_id", "hit")

    register("chf_delta0_equals_bloom", delta0, f"WITH {prelude('join_reduce')} SELECT key_id, clear = 0 AS hit FROM cls")

    def probes(spark, d):
        _, o, f = _built(spark, d, "join_reduce", shards=3)
        modes = [f.probe(o, mode=m).select("key_id", F.col("round").alias(m)) for m in ("expr", "arrow", "cogroup")]
        joined = modes[0].join(modes[1], "key_id").join(modes[2], "key_id")
        return joined.agg(F.count(F.lit(1)).alias("n"), F.sum((~(F.col("expr").eqNullSafe(F.col("arrow")) & F.col("expr").eqNullSafe(F.col("cogroup")))).cast("int")).alias("differ"))

    register("chf_probe_modes_agree", probes, f"SELECT count(*) AS n, 0::BIGINT AS differ FROM ({keys.duck_keyset('join_reduce')}) WHERE NOT positive")

    def saved(spark, d):
        from ..operators.filters import FilterSet
        from ..sources.shared import Staging

        s, _, f = _built(spark, d, "lsm_days")
        path = f"{Staging(spark, 'saved').path}/filter"
        f.save(path)
        return _zero(FilterSet.load(spark, path), s)

    register("chf_save_load_zero_fn", saved, _zero_sql("lsm_days"))

    def late(spark, d):
        s, o = keys.load(spark, d, "kv_half")
        early = F.col("key_id") % 5 != 0
        f = custom.build(s.where(early), o, geometry.budget(s.count(), BUDGET), family=MD5)
        return _zero(custom.insert_late(f, s.where(~early)), s)

    register("chf_late_insert_zero_fn", late, _zero_sql("kv_half"))

    for how in ("semi", "inner", "anti"):
        register(f"chf_prefiltered_{how}", partial(_prefiltered, how=how), PREFILTERED[how])

    def by_round(spark, d):
        _, o, f = _built(spark, d)
        return f.probe(o).rollup("round").agg(F.count(F.lit(1)).alias("n"), F.sum("cost").alias("cost"))

    register("chf_rounds", by_round)
    register("chf_stats", lambda spark, d: _built(spark, d)[2].rows.select("shard", F.explode("stats").alias("stat", "value")).where("stat NOT IN ('kernel_s', 'peak_kb')"))

    def trace(spark, d):
        from ..sources.functions import trace_keys

        s, o, f = _built(spark, d, "lsm_days")
        return trace_keys(f, o)

    register("chf_trace", trace)

    def bulk(spark, d):
        s, o = keys.load(spark, d, "lsm_days")
        g = geometry.split(geometry.budget(s.count(), BUDGET))
        found = rounds.run(s, o, g, family=MD5, max_rounds=3)
        return spark.createDataFrame(found.history, "round int, cost_passed double, collisions bigint")

    register("chf_bulk_rounds", bulk)

    def bulk_zero(spark, d):
        s, o = keys.load(spark, d, "lsm_days")
        return _zero(rounds.build(s, o, geometry.budget(s.count(), BUDGET), family=MD5, max_rounds=2), s)

    register("chf_bulk_rounds_zero_fn", bulk_zero, _zero_sql("lsm_days"))

    def measured(spark, d):
        s, o, f = _built(spark, d, "join_reduce")
        known, unseen = o.where("key_id % 5 <> 0"), o.where("key_id % 5 = 0")
        return measures.evaluate(custom.build(s, known, geometry.budget(s.count(), BUDGET), family=MD5), s, known, unseen)

    register("measure_unseen", measured)
    register("measure_misread", lambda spark, d: (lambda s, o, f: measures.misread_rate(f, o))(*_built(spark, d)))
    register("measure_load", lambda spark, d: measures.load(_built(spark, d, shards=4)[2]))
    register("measure_rounds", lambda spark, d: (lambda s, o, f: measures.rates_by_round(f, o))(*_built(spark, d)))

    def shuffles(spark, d):
        s, o = keys.load(spark, d, "lsm_days")
        return measures.over_shuffles(bloom.build(s, geometry.budget(s.count(), BUDGET), MD5), o, 1.0, range(1, 11))

    register("measure_over_shuffles", shuffles)

    def blocked(spark, d):
        s, _, f = _built(spark, d, "doc_block")
        docs = keys.table(spark, d, "documents").select("doc_id", F.md5("text").alias("digest"))
        return joins.prefiltered(docs, s.select("k"), "digest", "k", f, "semi").select("doc_id")

    register("use_blocklist", blocked, f"SELECT doc_id FROM documents WHERE md5(text) IN (SELECT k FROM ({keys.duck_keyset('doc_block')}) WHERE positive)")

    def look_up(spark, d):
        s, _, f = _built(spark, d, "lsm_days")
        events = keys.table(spark, d, "events")
        asked = events.select("event_id", keys.user_day(events).alias("day"))
        found = joins.prefiltered(asked, s.select("k"), "day", "k", f, "semi")
        return found.groupBy(F.substring_index("day", keys.SEPARATOR, -1).alias("day")).agg(F.count(F.lit(1)).alias("n"))

    register(
        "use_point_lookup",
        look_up,
        f"SELECT strftime(ts, '%Y-%m-%d') AS day, count(*) AS n FROM events WHERE user_id::VARCHAR || chr(31) || strftime(ts, '%Y-%m-%d') IN (SELECT k FROM ({keys.duck_keyset('lsm_days')}) WHERE positive) GROUP BY 1",
    )

    def sql_functions(spark, d):
        from ..sources.functions import register_filter

        s, o, f = _built(spark, d, "lsm_days")
        register_filter(spark, f, "cf_contains")
        s.createOrReplaceTempView("cf_positives")
        return spark.sql("SELECT count(*) AS n, sum(CASE WHEN cf_contains(k) THEN 0 ELSE 1 END) AS misses FROM cf_positives")

    register("chf_sql_contains", sql_functions, _zero_sql("lsm_days"))


PREFILTERED = {
    "semi": "SELECT l_orderkey, l_linenumber FROM lineitem WHERE l_orderkey IN (SELECT o_orderkey FROM orders WHERE o_orderstatus = 'F')",
    "anti": "SELECT l_orderkey, l_linenumber FROM lineitem WHERE l_orderkey NOT IN (SELECT o_orderkey FROM orders WHERE o_orderstatus = 'F')",
    "inner": "SELECT l_orderkey, l_linenumber, o_orderpriority FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE o_orderstatus = 'F'",
}


def _prefiltered(spark, d, how: str) -> DataFrame:
    _, _, f = _built(spark, d, "join_reduce")
    lines = keys.table(spark, d, "lineitem").select("l_orderkey", "l_linenumber")
    right = keys.table(spark, d, "orders").where("o_orderstatus = 'F'").select("o_orderkey", "o_orderpriority")
    out = joins.prefiltered(lines, right, "l_orderkey", "o_orderkey", f, how)
    return out.select("l_orderkey", "l_linenumber", *(["o_orderpriority"] if how == "inner" else []))


#: Rows of the closed forms: each priority's orders are a filter's keys and the other orders are asked for.
CLASSES = "classes AS (SELECT o_orderpriority AS class, count(*) AS n, (SELECT count(*) FROM orders WHERE o_orderpriority IS NOT NULL) - count(*) AS o FROM orders WHERE o_orderpriority IS NOT NULL GROUP BY 1)"


def classes(spark, d) -> DataFrame:
    """(class, n, o): keys of each class of orders, and those of all others."""
    sizes = keys.table(spark, d, "orders").where(F.col("o_orderpriority").isNotNull()).groupBy(F.col("o_orderpriority").alias("class")).agg(F.count(F.lit(1)).alias("n"))
    return sizes.crossJoin(F.broadcast(sizes.agg(F.sum("n").alias("all")))).select("class", "n", (F.col("all") - F.col("n")).alias("o"))  # one row


def _theory() -> None:
    number = lambda name: F.col(name).cast("double")

    def shared(spark, d):
        """The classes' keys in arrays of b bits for the mean class's keys, so that a class has more bits per key the fewer keys it has."""
        told = classes(spark, d).withColumn("b", F.explode(F.sequence(F.lit(4), F.lit(20)))).withColumn("k", F.explode(F.sequence(F.lit(1), F.lit(10))))
        return told.withColumn("m", F.expr("(n + o) * b div 5")).withColumn("x", F.col("k") * number("n") / F.col("m"))

    grid = f"WITH {CLASSES}, grid AS (SELECT *, k * n::DOUBLE / m AS x FROM (SELECT class, n, o, b::INT AS b, k::INT AS k, (n + o) * b // 5 AS m FROM classes, range(4, 21) x(b), range(1, 11) y(k)))"

    def curve(spark, d):
        rate = theory.columns.bloom_fpr(F.col("x"), F.col("k"))
        return shared(spark, d).select("class", "b", "k", "n", "m", F.round(rate, 9).alias("fpr"))

    register("theory_bloom_curve", curve, f"{grid} SELECT class, b, k, n, m, round(pow(1 - exp(-x), k), 9) AS fpr FROM grid")

    def owners(spark, d):
        owner = theory.columns.owner_prob(F.col("x"))
        return shared(spark, d).select("class", "b", "k", "n", "m", F.round(owner, 9).alias("owner_prob"), F.round(F.col("k") * owner, 9).alias("owners"))

    register("theory_owner_prob", owners, f"{grid} SELECT class, b, k, n, m, round(x / (exp(x) - 1), 9) AS owner_prob, round(k * (x / (exp(x) - 1)), 9) AS owners FROM grid")

    def two(spark, d):
        """The rate of a bit array with three functions, and a table that misreads as often as a walk of three cells meets none that is empty."""
        told = classes(spark, d).withColumn("b", F.explode(F.sequence(F.lit(4), F.lit(13)))).withColumn("stored_pct", F.explode(F.sequence(F.lit(0), F.lit(10))))
        sized = told.withColumn("total", F.expr("n * b")).withColumn("omega", F.greatest(F.expr("total div 5 div 4"), F.lit(1))).withColumn("m", F.expr("total - total div 5 div 4 * 4"))
        cells = F.least(F.expr("n * stored_pct div 100 * 3").cast("double") / F.col("omega"), F.lit(1.0))
        rates = sized.select("class", "b", "stored_pct", theory.columns.bloom_fpr(3 * number("n") / F.col("m"), F.lit(3)).alias("f"), F.pow(cells, F.lit(3)).alias("r"))
        return rates.select("class", "b", "stored_pct", F.round("f", 9).alias("f"), F.round("r", 9).alias("r"), F.round(theory.two_round_fpr(F.col("f"), F.col("r")), 9).alias("total"))

    register(
        "theory_two_round",
        two,
        f"""WITH {CLASSES}, t AS (SELECT class, n, b::INT AS b, p::INT AS stored_pct, n * b AS total FROM classes, range(4, 14) x(b), range(0, 11) y(p)),
        g AS (SELECT *, greatest(total // 5 // 4, 1) AS omega, total - total // 5 // 4 * 4 AS m FROM t),
        e AS (SELECT class, b, stored_pct, pow(1 - exp(-3 * n::DOUBLE / m), 3) AS f, pow(least((n * stored_pct // 100 * 3)::DOUBLE / omega, 1.0::DOUBLE), 3) AS r FROM g)
        SELECT class, b, stored_pct, round(f, 9) AS f, round(r, 9) AS r, round(f + r * f - r * f * f, 9) AS total FROM e""",
    )

    def bound(spark, d):
        told = classes(spark, d).withColumn("b", F.explode(F.sequence(F.lit(4), F.lit(13)))).withColumn("total", F.expr("n * (b * 125) div 100"))
        sized = told.withColumn("omega", F.expr("total div 5 div 4")).withColumn("m", F.expr("total - omega * 4"))
        rate = theory.columns.fpr_upper(number("n"), number("o"), number("m"), number("omega"), 4, geometry.pool_size(4))
        return sized.where("n > 0 AND o > 0").select("class", "b", "n", "o", F.round(rate, 9).alias("bound"))

    register(
        "theory_bound_curve",
        bound,
        f"""WITH {CLASSES}, a AS (SELECT class, b, n, o, n * (b * 125) // 100 AS total FROM classes, range(4, 14) x(b) WHERE n > 0 AND o > 0), g AS (SELECT class, b, n, o, (total // 5 // 4)::DOUBLE AS omega, (total - total // 5 // 4 * 4)::DOUBLE AS m FROM a),
        p AS (SELECT *, pow(1 - exp(-4.0::DOUBLE * n / m), 4) AS f, 1 - exp(-4.0::DOUBLE * n / m) AS p FROM g), q AS (SELECT *, p + (1 - p) * exp(-(4.0::DOUBLE * o / m) * pow(p, 3)) AS q FROM p),
        w AS (SELECT *, 1 - pow(1 - q, 3) AS sw FROM q) SELECT class, b::INT AS b, n, o, round(f - greatest(0.0::DOUBLE, f * o * sw * (omega - 16) / (omega + f * o * sw * 16)) / o, 9) AS bound FROM w""",
    )


def _baselines() -> None:
    def xor(spark, d):
        s, o = keys.load(spark, d, "kv_half")
        return s, o, baselines.xor_build(s, geometry.budget(s.count(), BUDGET), MD5)

    register("xor_zero_fn", lambda spark, d: (lambda s, o, f: _zero(f, s))(*xor(spark, d)), _zero_sql("kv_half"))
    register("xor_fpr", lambda spark, d: (lambda s, o, f: f.probe(o).agg(F.avg(F.col("hit").cast("int")).alias("fpr")))(*xor(spark, d)))

    def weighted(spark, d):
        s, o = keys.load(spark, d, "join_reduce")
        return s, o, baselines.weighted_build(s, o, geometry.budget(s.count(), BUDGET), MD5)

    register("weighted_zero_fn", lambda spark, d: (lambda s, o, f: _zero(f, s))(*weighted(spark, d)), _zero_sql("join_reduce"))
    k = geometry.best_k(BUDGET)
    register(
        "weighted_probe",
        lambda spark, d: (lambda s, o, f: f.probe(o).select("key_id", "hit"))(*weighted(spark, d)),
        f"""WITH keys AS ({keys.duck_keyset('join_reduce')}), s AS (SELECT * FROM keys WHERE positive), o AS (SELECT * FROM keys WHERE NOT positive),
        g AS (SELECT count(*) * {round(BUDGET * 100)} // 100 AS m FROM s), mean AS (SELECT avg(log2(cost)) AS a FROM o),
        cache AS (SELECT key_id, least(greatest(round({k} + log2(cost) - (SELECT a FROM mean))::INT, {k}), 12) AS kk FROM o ORDER BY cost DESC, key_id LIMIT (SELECT greatest(1, floor(count(*) * 0.01)::INT) FROM o)),
        bits AS (SELECT DISTINCT {md5('i')} % (SELECT m FROM g) AS pos FROM s, range(1, {k + 1}) r(i)),
        tests AS (SELECT o.key_id, {md5('i')} % (SELECT m FROM g) AS pos FROM o LEFT JOIN cache USING (key_id), range(1, 13) r(i) WHERE i <= coalesce(kk, {k}))
        SELECT key_id, bool_and(bits.pos IS NOT NULL) AS hit FROM tests LEFT JOIN bits USING (pos) GROUP BY key_id""",
    )

    def grouped(spark, d):
        s, o = keys.load(spark, d, "kv_half")
        return s, o, baselines.grouped_build(s, geometry.budget(s.count(), BUDGET), MD5)

    register("grouped_zero_fn", lambda spark, d: (lambda s, o, f: _zero(f, s))(*grouped(spark, d)), _zero_sql("kv_half"))
    register("grouped_fpr", lambda spark, d: (lambda s, o, f: f.probe(o).agg(F.avg(F.col("hit").cast("int")).alias("fpr")))(*grouped(spark, d)))

    def learned(spark, d, kind="learned", model="logistic"):
        s, o = keys.load(spark, d, "url_traits")
        n = s.count()
        fitted = baselines.fit_model(s, o, model, features=64)
        total = geometry.budget(n, 10.0 if model == "logistic" else 32.0)
        build = partial(baselines.adaptive_build) if kind == "adaptive" else partial(baselines.learned_build, sandwiched=kind == "sandwiched")
        made = build(s, o, fitted, total, MD5, n=n)
        if not made.feasible:
            raise ValueError(f"the model of {fitted.bits} bits leaves nothing of {total}")
        return s, o, made

    for kind in ("learned", "sandwiched", "adaptive"):
        register(f"{kind}_zero_fn", lambda spark, d, kind=kind: (lambda s, o, f: _zero(f, s))(*learned(spark, d, kind)), _zero_sql("url_traits"))
    register("learned_mlp_zero_fn", lambda spark, d: (lambda s, o, f: _zero(f, s))(*learned(spark, d, "learned", "mlp")), _zero_sql("url_traits"))

    def exact(spark, d):
        s, o = keys.load(spark, d, "lsm_days")
        return baselines.exact_probe(s.unionByName(o), s).select("key_id", "hit")

    register("exact_membership", exact, f"SELECT key_id, positive AS hit FROM ({keys.duck_keyset('lsm_days')})")
    register("spark_runtime_filter_join", reports.runtime_filter_join, "SELECT o_orderpriority, count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE o_orderstatus = 'F' GROUP BY 1")


def _workloads() -> None:
    w = workloads
    for name, grid in (
        ("w1_delta", w.delta_sweep()),
        ("w1_delta_url", w.delta_sweep("url_half")),
        ("w1_delta_join_reduce", w.delta_sweep("join_reduce")),
        ("w2_k", w.k_sweep()),
        ("w2_k_url", w.k_sweep("url_half")),
        ("w2_k_url_traits", w.k_sweep("url_traits")),
        ("w3_cell", w.cell_sweep()),
        ("w3_cell_url", w.cell_sweep("url_half")),
        ("w3_cell_url_traits", w.cell_sweep("url_traits")),
        ("w4_uniform_url", w.space_sweep("url_half", workload="w4")),
        ("w4_uniform_url_spam", w.space_sweep("url_spam", workload="w4")),
        ("w4_uniform_url_traits", w.space_sweep("url_traits", workload="w4")),
        ("w4_uniform_words", w.space_sweep("words", workload="w4")),
        ("w5_uniform_url_learned", w.space_sweep("url_traits", "learned", workload="w5")),
        ("w6_uniform_kv", w.space_sweep(workload="w6")),
        ("w7_uniform_kv_learned", w.space_sweep(group="learned", workload="w7")),
        ("w8_skewed_url", w.space_sweep("url_half", skew=1.0, workload="w8")),
        ("w8_skewed_url_traits", w.space_sweep("url_traits", skew=1.0, workload="w8")),
        ("w9_skewed_url_learned", w.space_sweep("url_traits", "learned", 1.0, "w9")),
        ("w10_skewed_kv", w.space_sweep(skew=1.0, workload="w10")),
        ("w11_skewed_kv_learned", w.space_sweep(group="learned", skew=1.0, workload="w11")),
        ("w12_skewness", w.skew_sweep()),
        ("w12_skewness_url", w.skew_sweep("url_half")),
        ("w13_bloom_builds", w.bloom_builds()),
        ("w17_bound_by_k", w.bound_sweep(by="k")),
        ("w18_bound_by_b", w.bound_sweep(by="b")),
        ("w20_natural_join_reduce", w.natural_costs()),
        ("w20_natural_lsm", w.natural_costs("lsm_days")),
        ("w20_natural_doc_block", w.natural_costs("doc_block")),
        ("w20_natural_words", w.natural_costs("words")),
        ("w22_shards", w.shard_sweep()),
        ("chf_ablation", w.ablate()),
        ("chf_wfpr_by_method", w.flagship_grid()),
    ):
        register(name, lambda spark, d, grid=grid: w.measure(spark, d, grid))
        register(f"{name}_checked", lambda spark, d, grid=grid: w.checked(w.measure(spark, d, grid)), w.checked_sql(grid))
    register("w14_w15_times", lambda spark, d: w.costs_of_building(spark, d))
    register("w16_build_memory", lambda spark, d: w.costs_of_building(spark, d, memory=True))
    register("w19_owner_by_b", w.owner_share)


for _part in (_hashing, _keysets, _standard, _steps, _chains, _custom, _theory, _baselines, _workloads):
    _part()
for _name, _query, _sql in (*reports.QUERIES, *files.QUERIES, *streams.QUERIES):
    register(_name, _query, _sql)
