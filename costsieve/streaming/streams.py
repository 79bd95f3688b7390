"""Filters on streams: probes, windows of false-positive cost, late positives, de-duplication and costs learnt from failed look-ups."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import geometry, keys
from ..functions.hashing import Family
from ..operators import bloom, custom
from ..operators.filters import FilterSet
from ..sources.shared import Staging, ship


def source(spark: SparkSession, path: str, schema, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def drained(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream to its end into a table and return it."""
    place = Staging(stream.sparkSession, "stream")
    path, check = f"{place.path}/rows", f"{place.path}/state"
    if mode == "append":
        stream.writeStream.format("parquet").option("path", path).option("checkpointLocation", check).trigger(availableNow=True).start().awaitTermination()
        return stream.sparkSession.read.schema(stream.schema).parquet(path)
    made = []

    def work(batch: DataFrame, number: int) -> None:
        made.append(f"{path}/{number}")
        batch.write.mode("overwrite").parquet(made[-1])

    stream.writeStream.foreachBatch(work).outputMode(mode).option("checkpointLocation", check).trigger(availableNow=True).start().awaitTermination()
    if not made:
        return stream.sparkSession.createDataFrame([], stream.schema)
    # each batch of a complete table replaces the one before
    return stream.sparkSession.read.schema(stream.schema).parquet(*(made[-1:] if mode == "complete" else made))


def each_batch(stream: DataFrame, work: Callable[[DataFrame, int], None]) -> None:
    place = Staging(stream.sparkSession, "stream")
    stream.writeStream.foreachBatch(work).option("checkpointLocation", f"{place.path}/state").trigger(availableNow=True).start().awaitTermination()


def probe(stream: DataFrame, filt: FilterSet, key: str = "k") -> DataFrame:
    """A stream met with a static filter; stateless."""
    return filt.probe(stream, key, "expr")


def fp_by_window(probed: DataFrame, kind: str = "tumbling", watermark: str = "1 day") -> DataFrame:
    """Rows and cost per window of rows that the filter passes. ``probed`` has ts, cost and hit."""
    windows = {"tumbling": F.window("ts", "1 day"), "sliding": F.window("ts", "2 days", "1 day"), "session": F.session_window("ts", "6 hours")}
    held = probed.where("hit").withWatermark("ts", watermark)
    grouped = held.groupBy(windows[kind].alias("w"), *(["user_id"] if kind == "session" else []))
    out = grouped.agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("cost"), 4).alias("cost"))
    wall = lambda c: F.col(c).cast("timestamp_ntz")
    return out.select(wall("w.start").alias("begin"), wall("w.end").alias("end"), *(["user_id"] if kind == "session" else []), "n", "cost")


def dedup(stream: DataFrame, cols: list[str], watermark: str = "1 day") -> DataFrame:
    return stream.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(cols)


def cost_state(stream: DataFrame) -> DataFrame:
    """(k, cost): running cost of failed look-ups per key, kept in the state store as batches come."""
    from pyspark.sql.streaming.state import GroupStateTimeout

    ship(stream.sparkSession)

    def run(key, batches, state):
        total = state.get[0] if state.exists else 0.0
        for pdf in batches:
            total += float(pdf["cost"].sum())
        state.update((total,))
        yield pd.DataFrame({"k": [key[0]], "cost": [total]})

    return stream.groupBy("k").applyInPandasWithState(run, "k string, cost double", "total double", "update", GroupStateTimeout.NoTimeout)


def rebuild_per_batch(spark: SparkSession, stream: DataFrame, positives: DataFrame, total_bits: int, threshold: float) -> FilterSet:
    """Add up the cost of look-ups batch by batch; whenever what came since the last build passes ``threshold``, build anew from the costs so far.

    Costs are kept as a table that each batch replaces by a new one.
    """
    held = {"filter": None, "costs": None, "since": 0.0}

    def work(batch: DataFrame, _: int) -> None:
        now = batch.groupBy("k").agg(F.sum("cost").alias("cost"))
        if held["costs"] is not None:
            now = held["costs"].unionByName(now).groupBy("k").agg(F.sum("cost").alias("cost"))
        held["costs"] = Staging(spark, "learnt").table(now, "costs")
        held["since"] += batch.agg(F.coalesce(F.sum("cost"), F.lit(0.0))).first()[0]
        if held["filter"] is None or held["since"] >= threshold:
            negatives = held["costs"].join(positives.select("k"), "k", "left_anti").select(keys.number(F.col("k")).alias("key_id"), "k", "cost")
            held["filter"], held["since"] = custom.build(positives, negatives, total_bits), 0.0

    each_batch(stream, work)
    return held["filter"]


def late_positives(spark: SparkSession, stream: DataFrame, filt: FilterSet) -> FilterSet:
    """Keys that arrive after the build are put in under the default functions, batch by batch."""
    held = {"filter": filt}

    def work(batch: DataFrame, _: int) -> None:
        held["filter"] = custom.insert_late(held["filter"], batch.select("k").distinct())

    each_batch(stream, work)
    return held["filter"]


def _look_ups(df: DataFrame) -> DataFrame:
    return df.select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", keys.user_day(df).alias("k"), F.col("value").alias("cost"))


def _events(spark, d) -> DataFrame:
    """The events table as a file stream of several files in order of time."""
    table = keys.table(spark, d, "events")
    path = f"{Staging(spark, 'events').path}/files"
    table.repartitionByRange(5, "ts").sortWithinPartitions("ts").write.parquet(path)
    return source(spark, path, table.schema)


def _filter(spark, d) -> FilterSet:
    s, _ = keys.load(spark, d, "lsm_days")
    return bloom.build(s, s.count() * 839 // 100, Family(), k=3)


def _windowed(kind: str):
    def query(spark, d) -> DataFrame:
        stream = fp_by_window(probe(_look_ups(_events(spark, d)), _filter(spark, d)), kind, "60 days")
        return drained(stream, "complete")

    return query


_HASH = "('0x' || substr(md5(i::VARCHAR || ':' || k), 1, 15))::BIGINT"
_HITS = f"""keys AS ({keys.duck_keyset('lsm_days')}), g AS (SELECT count(*) * 839 // 100 AS m FROM keys WHERE positive),
bits AS (SELECT DISTINCT {_HASH} % (SELECT m FROM g) AS pos FROM keys, range(1, 4) r(i) WHERE positive),
pass AS (SELECT k FROM (SELECT k, {_HASH} % (SELECT m FROM g) AS pos FROM keys, range(1, 4) r(i)) LEFT JOIN bits USING (pos) GROUP BY k HAVING bool_and(bits.pos IS NOT NULL)),
look AS (SELECT event_id, ts, user_id, value AS cost FROM events WHERE user_id::VARCHAR || chr(31) || strftime(ts, '%Y-%m-%d') IN (SELECT k FROM pass))"""


def _dedup(spark, d) -> DataFrame:
    stream = _events(spark, d)
    twice = stream.withColumn("ts", F.col("ts").cast("timestamp")).withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2))))
    return drained(dedup(twice, ["event_id"], "60 days").select("event_id"))


def _costs(spark, d) -> DataFrame:
    # state is updated per batch; the last total of a key is its largest, as costs are not negative
    out = drained(cost_state(_look_ups(_events(spark, d)).select("k", F.abs("cost").alias("cost"))), "update")
    return out.groupBy("k").agg(F.round(F.max("cost"), 4).alias("cost"))


def _late(spark, d) -> DataFrame:
    s, o = keys.load(spark, d, "lsm_days")
    early = s.where(F.col("key_id") % 4 != 0)
    filt = custom.build(early, o, geometry.budget(s.count(), 8.39))
    purchases = _events(spark, d).where("event_type = 'purchase'")
    filt = late_positives(spark, purchases.select(keys.user_day(purchases).alias("k")), filt)
    return filt.probe(s).agg(F.count(F.lit(1)).alias("n"), F.sum((~F.col("hit")).cast("int")).alias("misses"))


def _rebuild(spark, d) -> DataFrame:
    s, _ = keys.load(spark, d, "lsm_days")
    stream = _look_ups(_events(spark, d)).select("k", F.abs("cost").alias("cost"))
    filt = rebuild_per_batch(spark, stream, s, geometry.budget(s.count(), 8.39), 1e5)
    return filt.probe(s).agg(F.count(F.lit(1)).alias("n"), F.sum((~F.col("hit")).cast("int")).alias("misses"))


_ZERO = f"SELECT count(*) AS n, 0::BIGINT AS misses FROM ({keys.duck_keyset('lsm_days')}) WHERE positive"
QUERIES = (
    ("stream_tumbling_fp", _windowed("tumbling"), f"WITH {_HITS} SELECT time_bucket(INTERVAL 1 DAY, ts) AS begin, time_bucket(INTERVAL 1 DAY, ts) + INTERVAL 1 DAY AS \"end\", count(*) AS n, round(sum(cost), 4) AS cost FROM look GROUP BY ALL"),
    ("stream_sliding_fp", _windowed("sliding"), f"WITH {_HITS}, two AS (SELECT time_bucket(INTERVAL 1 DAY, ts) - to_days(x::INT) AS begin, cost FROM look, range(0, 2) r(x)) SELECT begin, begin + INTERVAL 2 DAY AS \"end\", count(*) AS n, round(sum(cost), 4) AS cost FROM two GROUP BY ALL"),
    ("stream_session_fp", _windowed("session"), f"""WITH {_HITS}, marks AS (SELECT *, CASE WHEN ts < lag(ts) OVER w + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM look WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
     numbered AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS session FROM marks)
     SELECT min(ts) AS begin, max(ts) + INTERVAL 6 HOUR AS "end", user_id, count(*) AS n, round(sum(cost), 4) AS cost FROM numbered GROUP BY user_id, session"""),
    ("stream_dedup", _dedup, "SELECT event_id FROM events"),
    ("stream_cost_state", _costs, "SELECT user_id::VARCHAR || chr(31) || strftime(ts, '%Y-%m-%d') AS k, round(sum(abs(value)), 4) AS cost FROM events GROUP BY 1"),
    ("stream_late_positives", _late, _ZERO),
    ("stream_rebuild", _rebuild, _ZERO),
)
