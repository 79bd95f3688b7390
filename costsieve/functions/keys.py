"""Key sets: canonical keys, positives and negatives with costs, and the sets of the experiments on the given tables."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

SEPARATOR = "\x1f"


def number(text: Column) -> Column:
    """60 bits of md5 as a number."""
    return F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("bigint")


def canonical(*cols: str | Column) -> Column:
    return F.concat_ws(SEPARATOR, *[(F.col(c) if isinstance(c, str) else c).cast("string") for c in cols])


def prepare(df: DataFrame, cols: list[str], cost: str | None = None, null_policy: str = "drop") -> DataFrame:
    """(key_id, k, cost): one row per distinct key, costs summed. A null key matches nothing in SQL, so it is dropped, or refused."""
    if null_policy not in ("drop", "fail"):
        raise ValueError(f"unknown null policy {null_policy}")
    known = df
    for c in cols:
        if null_policy == "drop":
            known = known.where(F.col(c).isNotNull())
        else:
            known = known.withColumn(c, F.coalesce(F.col(c), F.raise_error(F.lit(f"null key in {c}")).cast(df.schema[c].dataType)))
    amount = F.sum(F.coalesce(F.col(cost), F.lit(0)).cast("double")) if cost else F.lit(1.0)
    grouped = known.groupBy(canonical(*cols).alias("k")).agg(amount.alias("cost"))
    return grouped.select(number(F.col("k")).alias("key_id"), "k", "cost")


def pair(positives: DataFrame, negatives: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The two sets made disjoint: a key that is positive is no negative."""
    return positives, negatives.join(positives.select("k"), "k", "left_anti").select("key_id", "k", "cost")


def top_negatives(negatives: DataFrame, n: int) -> DataFrame:
    """The n costliest negatives; the order of ties is fixed by the key."""
    return negatives.orderBy(F.desc("cost"), "key_id").limit(n)


def shingles(df: DataFrame, text: str, n: int = 5) -> DataFrame:
    """(k, cost): runs of n lower-case tokens with their numbers of occurrences."""
    tokens = F.filter(F.split(F.lower(F.col(text)), r"\s+"), lambda t: t != "")
    return (
        df.select(tokens.alias("t"))
        .where(F.size("t") >= n)
        .select(F.explode(F.transform(F.sequence(F.lit(1), F.size("t") - (n - 1)), lambda i: F.array_join(F.slice("t", i, n), " "))).alias("k"))
        .groupBy("k")
        .agg(F.count(F.lit(1)).cast("double").alias("cost"))
    )


def words(df: DataFrame, text: str) -> DataFrame:
    return (
        df.select(F.explode(F.split(F.lower(F.col(text)), "[^a-z]+")).alias("k")).where("k <> ''").groupBy("k").agg(F.count(F.lit(1)).cast("double").alias("cost"))
    )


def url_parts(url: Column) -> list[Column]:
    return [
        F.regexp_extract(url, r"^([a-z]+)://", 1).alias("scheme"),
        F.regexp_extract(url, r"^[a-z]+://([^/:?#]+)", 1).alias("host"),
        F.regexp_extract(url, r"^[a-z]+://[^/?#]+([^?#]*)", 1).alias("path"),
    ]


def user_day(events: DataFrame) -> Column:
    return canonical("user_id", F.date_format("ts", "yyyy-MM-dd"))


@dataclass(frozen=True)
class KeySet:
    """A set of keys of one experiment: ``spark`` gives (k, cost, positive), ``duck`` the same as SQL."""

    name: str
    spark: Callable[[SparkSession, str], DataFrame]
    duck: str


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _order_key(column: str = "o_orderkey") -> Column:
    return F.concat(F.lit("okey"), F.substring(F.md5(F.col(column).cast("string")), 1, 16))


def _kv(flag: Callable[[], Column]):
    return lambda spark, d: table(spark, d, "orders").select(_order_key().alias("k"), F.lit(1.0).alias("cost"), flag().alias("positive"))


def _urls(flag: Callable[[], Column]):
    def rows(spark: SparkSession, d: str) -> DataFrame:
        urls = table(spark, d, "pages").where(F.col("url").isNotNull()).groupBy("url").agg(F.lit(1.0).alias("cost"))
        return urls.select(F.col("url").alias("k"), "cost", flag().alias("positive"))

    return rows


def _join_reduce(spark: SparkSession, d: str) -> DataFrame:
    lines = table(spark, d, "lineitem").groupBy("l_orderkey").agg(F.count(F.lit(1)).cast("double").alias("cost"))
    orders = table(spark, d, "orders").select("o_orderkey", "o_orderstatus")
    joined = lines.join(orders, lines.l_orderkey == orders.o_orderkey)
    return joined.select(F.col("l_orderkey").cast("string").alias("k"), "cost", (F.col("o_orderstatus") == "F").alias("positive"))


def _lsm(spark: SparkSession, d: str) -> DataFrame:
    events = table(spark, d, "events")
    grouped = events.groupBy(user_day(events).alias("k")).agg(
        F.count(F.lit(1)).cast("double").alias("cost"), F.max(F.col("event_type") == "purchase").alias("positive")
    )
    return grouped.select("k", "cost", "positive")


def _texts(make: Callable[[DataFrame, str], DataFrame]):
    def rows(spark: SparkSession, d: str) -> DataFrame:
        hit = make(table(spark, d, "benchmark"), "text").select("k", "cost", F.lit(True).alias("positive"))
        rest = make(table(spark, d, "documents"), "text").join(hit.select("k"), "k", "left_anti")
        return hit.unionByName(rest.select("k", "cost", F.lit(False).alias("positive")))

    return rows


def _doc_block(spark: SparkSession, d: str) -> DataFrame:
    docs = table(spark, d, "documents").join(table(spark, d, "labels"), "doc_id")
    grouped = docs.groupBy(F.md5("text").alias("k")).agg(F.max("n_chars").cast("double").alias("cost"), (F.min("quality") == 0).alias("positive"))
    return grouped.select("k", "cost", "positive")


def _traits(orders: DataFrame) -> DataFrame:
    """URLs whose host tells for 24 of 25 keys whether they are positive: as many as there are orders, so that a budget of few bits per key holds a model."""
    told = orders.select("o_orderkey", F.col("o_orderpriority").isin("1-URGENT", "2-HIGH").alias("positive"), (number(F.concat(F.lit("trait"), F.col("o_orderkey").cast("string"))) % 25).cast("int").alias("noise"))
    hosts = [F.element_at(F.array(*[F.lit(h) for h in names.split()]), F.col("noise") % 4 + 1) for names in ("spam-farm casino-win free-bets cheap-pills", "daily-news city-blog book-shop open-wiki")]
    host = F.when(F.col("positive") == (F.col("noise") != 0), hosts[0]).otherwise(hosts[1])
    k = F.concat(F.lit("https://"), host, F.lit(".example/"), F.substring(F.md5(F.col("o_orderkey").cast("string")), 1, 12))
    return told.select(k.alias("k"), F.lit(1.0).alias("cost"), "positive")


_NUM = "('0x' || substr(md5({}), 1, 15))::BIGINT"
_SPAM = "spam-farm|casino-win|free-bets|cheap-pills"
_DUCK_SHINGLES = (
    "SELECT array_to_string(list_slice(t, i, i + 4), ' ') AS k FROM (SELECT t, unnest(range(1, len(t) - 3)) AS i FROM "
    "(SELECT list_filter(regexp_split_to_array(lower(text), '\\s+'), lambda x: x <> '') AS t FROM {}) WHERE len(t) >= 5)"
)
_DUCK_WORDS = "SELECT k FROM (SELECT unnest(regexp_split_to_array(lower(text), '[^a-z]+')) AS k FROM {}) WHERE k <> ''"


def _duck_texts(part: str) -> str:
    hit, rest = (f"SELECT k, count(*)::DOUBLE AS cost FROM ({part.format(t)}) GROUP BY k" for t in ("benchmark", "documents"))
    return f"SELECT k, cost, true AS positive FROM ({hit}) UNION ALL SELECT k, cost, false FROM ({rest}) WHERE k NOT IN (SELECT k FROM ({hit}))"


KEYSETS = {
    s.name: s
    for s in (
        KeySet(
            "kv_orders",
            _kv(lambda: F.col("o_orderpriority").isin("1-URGENT", "2-HIGH")),
            "SELECT 'okey' || substr(md5(o_orderkey::VARCHAR), 1, 16) AS k, 1.0::DOUBLE AS cost, o_orderpriority IN ('1-URGENT', '2-HIGH') AS positive FROM orders",
        ),
        KeySet(
            "kv_half",
            _kv(lambda: number(F.col("o_orderkey").cast("string")) % 2 == 0),
            f"SELECT 'okey' || substr(md5(o_orderkey::VARCHAR), 1, 16) AS k, 1.0::DOUBLE AS cost, {_NUM.format('o_orderkey::VARCHAR')} % 2 = 0 AS positive FROM orders",
        ),
        KeySet(
            "url_spam",
            _urls(lambda: F.col("url").rlike(_SPAM)),
            f"SELECT url AS k, 1.0::DOUBLE AS cost, regexp_matches(url, '{_SPAM}') AS positive FROM (SELECT DISTINCT url FROM pages WHERE url IS NOT NULL)",
        ),
        KeySet(
            "url_half",
            _urls(lambda: number(F.col("url")) % 2 == 0),
            f"SELECT url AS k, 1.0::DOUBLE AS cost, {_NUM.format('url')} % 2 = 0 AS positive FROM (SELECT DISTINCT url FROM pages WHERE url IS NOT NULL)",
        ),
        KeySet(
            "url_traits",
            lambda spark, d: _traits(table(spark, d, "orders")),
            "SELECT 'https://' || CASE WHEN positive = (noise <> 0) THEN ['spam-farm', 'casino-win', 'free-bets', 'cheap-pills'][noise % 4 + 1] ELSE ['daily-news', 'city-blog', 'book-shop', 'open-wiki'][noise % 4 + 1] END "
            "|| '.example/' || substr(md5(o_orderkey::VARCHAR), 1, 12) AS k, 1.0::DOUBLE AS cost, positive "
            f"FROM (SELECT o_orderkey, o_orderpriority IN ('1-URGENT', '2-HIGH') AS positive, {_NUM.format("'trait' || o_orderkey::VARCHAR")} % 25 AS noise FROM orders)",
        ),
        KeySet(
            "join_reduce",
            _join_reduce,
            "SELECT l_orderkey::VARCHAR AS k, count(*)::DOUBLE AS cost, any_value(o_orderstatus) = 'F' AS positive FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY l_orderkey",
        ),
        KeySet(
            "lsm_days",
            _lsm,
            "SELECT user_id::VARCHAR || chr(31) || strftime(ts, '%Y-%m-%d') AS k, count(*)::DOUBLE AS cost, bool_or(event_type = 'purchase') AS positive FROM events GROUP BY 1",
        ),
        KeySet("words", _texts(words), _duck_texts(_DUCK_WORDS)),
        KeySet("shingles", _texts(shingles), _duck_texts(_DUCK_SHINGLES)),
        KeySet(
            "doc_block",
            _doc_block,
            "SELECT md5(text) AS k, max(n_chars)::DOUBLE AS cost, min(quality) = 0 AS positive FROM documents JOIN labels USING (doc_id) GROUP BY 1",
        ),
    )
}


def keyset(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """(key_id, k, cost, positive) of one experiment's keys."""
    rows = KEYSETS[name].spark(spark, sf_dir)
    return rows.select(number(F.col("k")).alias("key_id"), "k", "cost", "positive")


def load(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, DataFrame]:
    """(positives, negatives), each (key_id, k, cost)."""
    rows = keyset(spark, sf_dir, name)
    return rows.where("positive").drop("positive"), rows.where("NOT positive").drop("positive")


def duck_keyset(name: str) -> str:
    return f"SELECT {_NUM.format('k')} AS key_id, k, cost, positive FROM ({KEYSETS[name].duck})"
