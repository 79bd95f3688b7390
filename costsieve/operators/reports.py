"""Reports around the filters: costs of false positives by dimension, bands, ranks, versions and look-ups."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import geometry, keys, ranks
from ..functions.hashing import Family
from . import bloom

BITS = 839  # hundredths of bits per key


def hash_skew(positives: DataFrame, m: int, functions: int = 7, family: Family = Family()) -> DataFrame:
    """Per function: the fullest of m positions and chi-square against an even spread."""
    pairs = F.array(*[F.struct(F.lit(i).alias("fn"), F.pmod(family.column(F.col("k"), i), F.lit(m)).alias("pos")) for i in range(1, functions + 1)])
    hits = positives.select(F.explode(pairs).alias("p")).groupBy("p.fn", "p.pos").agg(F.count(F.lit(1)).alias("n"))
    sums = hits.groupBy("fn").agg(F.max("n").alias("fullest"), F.sum("n").alias("total"), F.sum(F.col("n") * F.col("n")).alias("squares"))
    return sums.select("fn", "fullest", (F.col("squares") * m / F.col("total") - F.col("total")).alias("chi_square"))


def lorenz(df: DataFrame) -> DataFrame:
    """Cumulated share of the cost, dearest keys first."""
    placed = ranks.placed(df.select("key_id", "cost"), [F.desc("cost"), F.col("key_id")], F.col("cost"))
    total = F.broadcast(df.agg(F.sum("cost").alias("total")))  # one row
    return placed.crossJoin(total).select("key_id", "cost", "place", F.round(F.col("upto") / F.col("total"), 9).alias("share"))


def heavy(df: DataFrame, n: int) -> DataFrame:
    return df.orderBy(F.desc("cost"), "key_id").limit(n).select("k", "cost")


def cost_band(orders: DataFrame) -> DataFrame:
    """Range join of costs to bands, which are few."""
    bands = orders.sparkSession.createDataFrame([("low", 0.0, 1000.0), ("mid", 1000.0, 100000.0), ("high", 100000.0, 1e18)], "band string, low double, high double")
    joined = orders.join(F.broadcast(bands), (F.col("o_totalprice") >= F.col("low")) & (F.col("o_totalprice") < F.col("high")))
    return joined.groupBy("band").agg(F.count(F.lit(1)).alias("n"))


def runtime_filter_join(spark, d) -> DataFrame:
    """A plain join, for Spark's own run-time filter to act on."""
    lines, orders = keys.table(spark, d, "lineitem"), keys.table(spark, d, "orders").where("o_orderstatus = 'F'")
    return lines.join(orders, lines.l_orderkey == orders.o_orderkey).groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity"))


def false_positives(spark, d) -> DataFrame:
    """Orders that are no positives of kv_half but pass its standard filter: orders' columns and ``hit`` for all negatives."""
    s, o = keys.load(spark, d, "kv_half")
    m = s.count() * BITS // 100
    probed = bloom.build(s, m, Family(), k=3).probe(o).select("k", "hit")
    orders = keys.table(spark, d, "orders").withColumn("k", F.concat(F.lit("okey"), F.substring(F.md5(F.col("o_orderkey").cast("string")), 1, 16)))
    return orders.join(probed, "k")


_MD5 = "('0x' || substr(md5(i::VARCHAR || ':' || k), 1, 15))::BIGINT"
_FP = f"""keys AS ({keys.duck_keyset('kv_half')}), g AS (SELECT count(*) * {BITS} // 100 AS m FROM keys WHERE positive),
bits AS (SELECT DISTINCT {_MD5} % (SELECT m FROM g) AS pos FROM keys, range(1, 4) r(i) WHERE positive),
tests AS (SELECT k, {_MD5} % (SELECT m FROM g) AS pos FROM keys, range(1, 4) r(i) WHERE NOT positive),
probed AS (SELECT k, bool_and(bits.pos IS NOT NULL) AS hit FROM tests LEFT JOIN bits USING (pos) GROUP BY k),
fp AS (SELECT * FROM orders JOIN probed ON probed.k = 'okey' || substr(md5(o_orderkey::VARCHAR), 1, 16))"""


def _dims(spark, d) -> DataFrame:
    fp = false_positives(spark, d).where("hit")
    c, n, r = (keys.table(spark, d, t) for t in ("customer", "nation", "region"))
    joined = fp.join(c, fp.o_custkey == c.c_custkey).join(F.broadcast(n), F.col("c_nationkey") == n.n_nationkey).join(F.broadcast(r), F.col("n_regionkey") == r.r_regionkey)
    return joined.groupBy("r_name").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("o_totalprice"), 2).alias("cost"))


def _grouped(kind: str):
    def query(spark, d) -> DataFrame:
        fp = false_positives(spark, d).withColumn("h", F.col("hit").cast("int"))
        if kind == "sets":
            fp.createOrReplaceTempView("cf_fp")
            return spark.sql("SELECT o_orderstatus, o_orderpriority, sum(h) AS fp, count(*) AS n FROM cf_fp GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority))")
        return getattr(fp, kind)("o_orderstatus", "o_orderpriority").agg(F.sum("h").alias("fp"), F.count(F.lit(1)).alias("n"))

    return query


def _grouped_sql(how: str) -> str:
    return f"WITH {_FP} SELECT o_orderstatus, o_orderpriority, sum(hit::INT)::BIGINT AS fp, count(*) AS n FROM fp GROUP BY {how}"


def _top(spark, d) -> DataFrame:
    return false_positives(spark, d).where("hit").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10).select("o_orderkey", "o_totalprice")


def _pivot(spark, d) -> DataFrame:
    fp = false_positives(spark, d).where("hit")
    return fp.groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1))).na.fill(0)


def _filters_of_two(spark, d):
    s, o = keys.load(spark, d, "lsm_days")
    m = s.count() * BITS // 100
    a = bloom.build(s, m, Family(), k=2).probe(o).where("hit").select("k")
    b = bloom.build(s, m, Family(), k=4).probe(o).where("hit").select("k")
    return a, b


def _two_sql(op: str) -> str:
    parts = []
    for k in (2, 4):
        parts.append(
            f"""SELECT k FROM (SELECT k, bool_and(pos IN (SELECT {_MD5} % (SELECT m FROM g) FROM keys, range(1, {k + 1}) r(i) WHERE positive)) AS hit
            FROM (SELECT k, {_MD5} % (SELECT m FROM g) AS pos FROM keys, range(1, {k + 1}) r(i) WHERE NOT positive) GROUP BY k) WHERE hit"""
        )
    return f"WITH keys AS ({keys.duck_keyset('lsm_days')}), g AS (SELECT count(*) * {BITS} // 100 AS m FROM keys WHERE positive) ({parts[0]}) {op} ({parts[1]})"


def as_of(events: DataFrame, versions: DataFrame) -> DataFrame:
    """Each event with the latest version at its time: both in one stream of rows, the last version carried on per user."""
    both = events.select("user_id", "ts", "event_id", F.lit(None).cast("bigint").alias("version")).unionByName(
        versions.select("user_id", "ts", F.lit(None).cast("bigint").alias("event_id"), "version")
    )
    order = Window.partitionBy("user_id").orderBy("ts", F.col("version").asc_nulls_last(), "event_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    carried = both.withColumn("version", F.last("version", ignorenulls=True).over(order))
    return carried.where("event_id IS NOT NULL").select("event_id", F.coalesce("version", F.lit(-1)).alias("version"))


def _as_of(spark, d) -> DataFrame:
    e = keys.table(spark, d, "events")
    return as_of(e.where("event_type <> 'purchase'"), e.where("event_type = 'purchase'").select("user_id", "ts", F.col("event_id").alias("version")))


def _interval(spark, d) -> DataFrame:
    e = keys.table(spark, d, "events")
    p = e.where("event_type = 'purchase'").select(F.col("user_id").alias("u"), F.col("ts").alias("at"), F.col("event_id").alias("purchase"))
    hits = e.where("event_type <> 'purchase'").join(p, (F.col("user_id") == F.col("u")) & (F.col("ts") >= F.col("at")) & (F.col("ts") <= F.col("at") + F.expr("INTERVAL 1 HOUR")))
    return hits.select("purchase", "event_id")


def _lag(spark, d) -> DataFrame:
    s, o = keys.load(spark, d, "lsm_days")
    n = s.count()
    rows = None
    for b in (400, 600, 839, 1007):
        rate = bloom.build(s, n * b // 100, Family(), k=3).probe(o).agg(F.lit(b).alias("bits"), F.sum(F.col("hit").cast("int")).alias("fp"))
        rows = rate if rows is None else rows.unionByName(rate)
    return rows.select("bits", "fp", F.coalesce(F.lag("fp").over(Window.orderBy("bits")) - F.col("fp"), F.lit(0)).alias("gain"))


_LAG = "WITH keys AS ({0}), r AS ({1}) SELECT bits::INT AS bits, fp, coalesce(lag(fp) OVER (ORDER BY bits) - fp, 0) AS gain FROM r".format(
    keys.duck_keyset("lsm_days"),
    " UNION ALL ".join(
        f"""SELECT {b} AS bits, sum(hit::INT)::BIGINT AS fp FROM (SELECT k, bool_and(pos IN (SELECT {_MD5} % (SELECT count(*) * {b} // 100 FROM keys WHERE positive) FROM keys, range(1, 4) r(i) WHERE positive)) AS hit
        FROM (SELECT k, {_MD5} % (SELECT count(*) * {b} // 100 FROM keys WHERE positive) AS pos FROM keys, range(1, 4) r(i) WHERE NOT positive) GROUP BY k)"""
        for b in (400, 600, 839, 1007)
    ),
)
_ORDERS_COST = "SELECT o_orderkey, o_totalprice FROM orders"

QUERIES = (
    ("join_fp_by_region", _dims, f"WITH {_FP} SELECT r_name, count(*) AS n, round(sum(o_totalprice), 2) AS cost FROM fp JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey WHERE hit GROUP BY r_name"),
    ("cube_fpr", _grouped("cube"), _grouped_sql("CUBE (o_orderstatus, o_orderpriority)")),
    ("rollup_fpr", _grouped("rollup"), _grouped_sql("ROLLUP (o_orderstatus, o_orderpriority)")),
    ("grouping_sets_fpr", _grouped("sets"), _grouped_sql("GROUPING SETS ((o_orderstatus), (o_orderpriority))")),
    ("pivot_methods", _pivot, f"WITH {_FP} SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS F, count(*) FILTER (o_orderstatus = 'O') AS O, count(*) FILTER (o_orderstatus = 'P') AS P FROM fp WHERE hit GROUP BY 1"),
    ("top_fp", _top, f"WITH {_FP} SELECT o_orderkey, o_totalprice FROM fp WHERE hit ORDER BY o_totalprice DESC, o_orderkey LIMIT 10"),
    ("common_fp_intersect", lambda spark, d: (lambda a, b: a.intersect(b))(*_filters_of_two(spark, d)), _two_sql("INTERSECT")),
    ("except_fp", lambda spark, d: (lambda a, b: a.exceptAll(b))(*_filters_of_two(spark, d)), _two_sql("EXCEPT ALL")),
    ("union_keysets", lambda spark, d: keys.load(spark, d, "lsm_days")[0].select("k").unionByName(keys.load(spark, d, "join_reduce")[0].select("k")).distinct(),
     f"SELECT k FROM ({keys.duck_keyset('lsm_days')}) WHERE positive UNION SELECT k FROM ({keys.duck_keyset('join_reduce')}) WHERE positive"),
    ("asof_filter_version", _as_of, "SELECT e.event_id, coalesce(p.version, -1) AS version FROM (SELECT * FROM events WHERE event_type <> 'purchase') e ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS version FROM events WHERE event_type = 'purchase' GROUP BY ALL) p ON e.user_id = p.user_id AND e.ts >= p.ts"),
    ("interval_lookup", _interval, "SELECT p.event_id AS purchase, e.event_id FROM events e JOIN events p ON e.user_id = p.user_id AND e.ts >= p.ts AND e.ts <= p.ts + INTERVAL 1 HOUR WHERE p.event_type = 'purchase' AND e.event_type <> 'purchase'"),
    ("lag_budget_gain", _lag, _LAG),
    ("queue_rank_window", lambda spark, d: ranks.ranked_ties(keys.load(spark, d, "lsm_days")[1].select("key_id", "cost"), "cost").select("key_id", "dense", "rank"),
     f"SELECT key_id, dense_rank() OVER (ORDER BY cost DESC)::INT AS dense, rank() OVER (ORDER BY cost DESC) AS rank FROM ({keys.duck_keyset('lsm_days')}) WHERE NOT positive"),
    ("ntile_cost", lambda spark, d: ranks.tiled(keys.table(spark, d, "orders").select("o_orderkey", "o_totalprice"), [F.col("o_totalprice"), F.col("o_orderkey")], 10).select("o_orderkey", "tile"),
     "SELECT o_orderkey, ntile(10) OVER (ORDER BY o_totalprice, o_orderkey)::INT AS tile FROM orders"),
    ("url_parts", lambda spark, d: keys.table(spark, d, "pages").select("page_id", *keys.url_parts(F.col("url"))),
     "SELECT page_id, regexp_extract(url, '^([a-z]+)://', 1) AS scheme, regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS host, regexp_extract(url, '^[a-z]+://[^/?#]+([^?#]*)', 1) AS path FROM pages"),
    ("shingle_counts", lambda spark, d: keys.load(spark, d, "shingles")[1].groupBy("cost").agg(F.count(F.lit(1)).alias("n")),
     f"SELECT cost, count(*) AS n FROM ({keys.duck_keyset('shingles')}) WHERE NOT positive GROUP BY cost"),
    ("user_day_bucket", lambda spark, d: keys.table(spark, d, "events").groupBy(F.date_format("ts", "yyyy-MM-dd").alias("day")).agg(F.count_distinct("user_id").alias("users"), F.round(F.sum("value"), 4).alias("value")),
     "SELECT strftime(ts, '%Y-%m-%d') AS day, count(DISTINCT user_id) AS users, round(sum(value), 4) AS value FROM events GROUP BY 1"),
    ("json_cost", lambda spark, d: keys.table(spark, d, "events").groupBy(keys.canonical("user_id").alias("k")).agg(F.sum(F.get_json_object("props", "$.k").cast("bigint") + 1).alias("cost")),
     "SELECT user_id::VARCHAR AS k, sum((props::JSON ->> 'k')::BIGINT + 1)::BIGINT AS cost FROM events GROUP BY 1"),
    ("embedding_norms", lambda spark, d: keys.table(spark, d, "embeddings").select("vec_id", F.round(F.sqrt(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))), 6).alias("norm")),
     "SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE))), 6) AS norm FROM embeddings"),
    ("distinct_sizing", lambda spark, d: keys.table(spark, d, "lineitem").agg(F.count_distinct("l_orderkey").alias("orders"), F.count_distinct("l_partkey").alias("parts")),
     "SELECT count(DISTINCT l_orderkey) AS orders, count(DISTINCT l_partkey) AS parts FROM lineitem"),
    ("approx_sizing", lambda spark, d: keys.table(spark, d, "lineitem").agg(F.approx_count_distinct("l_orderkey").alias("orders"), F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey")).alias("parts")), None),
    ("percentile_costs", lambda spark, d: keys.table(spark, d, "orders").agg(*[F.round(F.expr(f"percentile(o_totalprice, {q / 100})"), 4).alias(f"p{q}") for q in (10, 50, 90, 99)]),
     "SELECT " + ", ".join(f"round(quantile_cont(o_totalprice, {q / 100}), 4) AS p{q}" for q in (10, 50, 90, 99)) + " FROM orders"),
)


def budget_of(positives: DataFrame, bits_per_key: float) -> int:
    return geometry.budget(positives.count(), bits_per_key)
