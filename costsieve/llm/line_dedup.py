"""Removal of repeated runs of lines: a suffix array of line ids by distributed prefix doubling, in DataFrame expressions only.

A document is the sequence of its non-blank lines. Round 0 sorts the distinct lines that occur twice or more (by 128-bit names) over all tasks and numbers them in that order. Lines that occur once
end every repeated run, so they cut documents into segments, and segments with fewer than ``min_words`` words go. Round k + 1 sorts the pairs
(rank of the 2**k lines at a place, rank of the 2**k lines after them) in the same way: equal ranks mean equal prefixes, ranks follow the prefixes' order, and a place whose prefix nobody shares has no rank
and leaves the doubling. Ranks are exact names: only lines are ever compared by a hash.

A run of n lines is covered by two prefixes of 2**k lines, k the whole part of log2(n), so (n, rank at its begin, rank at its end) names the interval of the suffix array whose longest common
prefix has n lines or more. The intervals looked at are those of the shortest runs with ``min_words`` words that begin, or end, at a place: together they cover every repeated run of
``min_words`` words or more to its last line, since a line from which the run still has ``min_words`` words begins one of the first kind, and any other lies in the one that ends with the run. Doubling stops where such
runs are covered, at log2(min_words) rounds at most. The first place of an interval stays; the lines of later places are deleted, and neighbouring deletions merge into maximal runs.

Only names and places are exchanged, never lines; copies are aggregated before, and no task holds more than its ranges or one document.

Defined results: a null text is empty and stays null; blank lines are never deleted and never part of a run; places are ordered by doc_id (null last), then the text's name, then line; a later
place that overlaps the first in its own document stays; rows that repeat a doc_id with the same text share their places, so neither loses lines to the other, and rows that share a doc_id but not the
text are documents of their own; an empty table gives an empty result; other columns are ignored (report) or passed through (``remove``).
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import columns
from .staging import Staging

WORD = r"[^\x20\x09-\x0D]+"
SALT = 0x5EED  # of the second half of a line's name


def _names(docs: DataFrame) -> DataFrame:
    """(doc_id, row, own array<struct<a, b, words>>): the non-blank lines by name."""
    plain = columns.documents(docs).withColumn("row", columns.row_name(F.col("text")))
    full = F.filter(F.split("text", "\n", -1), lambda x: F.regexp_like(x, F.lit(WORD)))
    named = F.transform(full, lambda x: F.struct(F.xxhash64(x).alias("a"), F.xxhash64(F.lit(SALT), x).alias("b"), F.regexp_count(x, F.lit(WORD)).alias("words")))
    return plain.select("doc_id", "row", named.alias("own"))


def _ranked(pairs: DataFrame, stage: Staging, name: str) -> DataFrame:
    """(a, b, rank) of the pairs (a, b) that occur twice or more: a number that grows in their order over all tasks."""
    held = pairs.groupBy("a", "b").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("a", "b")
    return stage.table(held.repartitionByRange("a", "b").sortWithinPartitions("a", "b").withColumn("rank", F.monotonically_increasing_id()), name)


def _segments(docs: DataFrame, min_words: int, stage: Staging) -> DataFrame:
    """(doc_id, row, segment, base, ahead, back, ranks): maximal sequences of repeated lines with ``min_words`` words or more.

    ``ahead`` and ``back`` hold, for every place, the lines of the shortest run with ``min_words`` words that begins or ends there, or 0.
    """
    lines = stage.table(_names(docs), "lines")
    flat = lines.select("doc_id", "row", F.posexplode("own").alias("place", "line")).select("doc_id", "row", "place", "line.*")
    known = flat.join(_ranked(flat, stage, "ranks"), ["a", "b"]).select("doc_id", "row", "place", "words", "rank").dropDuplicates(["doc_id", "row", "place"])
    within = Window.partitionBy("doc_id", "row").orderBy("place")
    islands = known.withColumn("segment", F.col("place") - F.row_number().over(within))
    total = F.sum("words").over(Window.partitionBy("doc_id", "row", "segment").orderBy("place").rowsBetween(Window.unboundedPreceding, Window.currentRow))
    islands = islands.withColumn("total", total)
    held = islands.groupBy("doc_id", "row", "segment").agg(F.sort_array(F.collect_list(F.struct("place", "words", "total", "rank"))).alias("s"), F.max("total").alias("all"))
    held = held.where(F.col("all") >= min_words)
    # every line has a word, so no run looks further than ``min_words`` lines; ``total`` grows, so counting what is below a bound finds a place
    ahead = F.transform(
        "s",
        lambda x, i: F.when(
            F.col("all") - x["total"] + x["words"] >= min_words,
            F.size(F.filter(F.slice("s", i + 1, min_words), lambda y: y["total"] - x["total"] + x["words"] < min_words)) + 1,
        ).otherwise(0),
    )
    back = F.transform(
        "s",
        lambda x, i: F.when(
            x["total"] >= min_words,
            F.size(F.filter(F.slice("s", F.greatest(i + 2 - min_words, F.lit(1)), F.least(i + 1, F.lit(min_words))), lambda y: x["total"] - y["total"] + y["words"] < min_words)) + 1,
        ).otherwise(0),
    )
    return stage.table(held.select("doc_id", "row", "segment", F.col("s")[0]["place"].alias("base"), ahead.alias("ahead"), back.alias("back"), F.col("s.rank").alias("ranks")), "segments")


def _windows(now: DataFrame, level: int) -> DataFrame:
    """(doc_id, row, place, lines, a, b): the runs of 2**level lines or more, but fewer than twice as many, whose two covering prefixes are both shared."""
    step = 1 << level

    def run(i: Column, lines: Column) -> Column:
        # lines is 0 where there is no such run
        fits = (lines >= step) & (lines < 2 * step) & (i >= 0)
        return F.when(fits, F.struct(i.alias("i"), lines.alias("lines"), F.get("ranks", i).alias("a"), F.get("ranks", i + lines - step).alias("b")))

    begins = F.transform("ahead", lambda n, i: run(i, n))
    ends = F.transform("back", lambda n, i: run(i - n + 1, n))
    held = now.select("doc_id", "row", "base", F.explode(F.filter(F.concat(begins, ends), lambda r: r["a"].isNotNull() & r["b"].isNotNull())).alias("r"))
    return held.select("doc_id", "row", (F.col("base") + F.col("r.i")).alias("place"), "r.lines", "r.a", "r.b")


def _doubled(now: DataFrame, level: int, stage: Staging) -> DataFrame | None:
    """Segments that hold longer runs, with the ranks of twice as many lines; nothing if no such prefix is shared."""
    step = 1 << level
    left = now.where((F.array_max("ahead") >= 2 * step) | (F.array_max("back") >= 2 * step))
    key = ["doc_id", "row", "segment"]
    pairs = left.select(*key, F.posexplode(F.transform("ranks", lambda a, i: F.struct(a.alias("a"), F.get("ranks", i + step).alias("b")))).alias("i", "p")).select(*key, "i", "p.a", "p.b")
    whole = F.col("a").isNotNull() & F.col("b").isNotNull()
    ranks = _ranked(pairs.where(whole), stage, "ranks")
    if not ranks.head(1):
        return None
    found = pairs.where(whole).join(ranks, ["a", "b"], "left").select(*key, "i", "rank")
    every = found.unionByName(pairs.where(~whole).select(*key, "i", F.lit(None).cast("bigint").alias("rank")))
    dense = every.groupBy(*key).agg(F.sort_array(F.collect_list(F.struct("i", "rank"))).alias("s")).select(*[F.col(c).alias(f"__{c}") for c in key], F.col("s.rank").alias("ranks"))
    same = reduce(lambda x, y: x & y, [F.col(c).eqNullSafe(F.col(f"__{c}")) for c in key])
    return stage.table(left.drop("ranks").join(dense, same).drop(*[f"__{c}" for c in key]), "segments")


def intervals(docs: DataFrame, min_words: int, stage: Staging) -> DataFrame:
    """(doc_id, row, place, lines, a, b), written: the places of shared runs; (lines, a, b) names an interval of the suffix array."""
    now, level, parts = _segments(docs, min_words, stage), 0, []
    while now is not None:
        parts.append(_windows(now, level))
        now = _doubled(now, level, stage) if 2 << level <= min_words else None
        level += 1
    return stage.table(reduce(DataFrame.unionByName, parts), "runs")


def repeated(docs: DataFrame, min_words: int = 50) -> DataFrame:
    """(doc_id, row, runs array<struct<begin, end, source>>): by document, the maximal spans [begin, end) of non-blank lines at later places, with the doc_id that keeps their first lines."""
    stage = Staging(docs.sparkSession, "line-dedup")
    runs = intervals(docs, min_words, stage)
    place = F.struct(F.col("doc_id").isNull().alias("last"), "doc_id", "row", "place")
    first = runs.groupBy("lines", "a", "b").agg(F.min(place).alias("first"), F.max(place).alias("final")).where("first <> final").drop("final")
    found = runs.join(stage.table(first, "intervals"), ["lines", "a", "b"])
    same = F.col("doc_id").eqNullSafe(F.col("first.doc_id")) & (F.col("row") == F.col("first.row"))
    later = found.where(~same | (F.col("place") >= F.col("first.place") + F.col("lines")))
    spans = later.groupBy("doc_id", "row", "place").agg(F.max("lines").alias("lines"), F.min("first.doc_id").alias("source")).withColumn("end", F.col("place") + F.col("lines"))
    before = Window.partitionBy("doc_id", "row").orderBy("place")
    reach = F.max("end").over(before.rowsBetween(Window.unboundedPreceding, -1))
    fresh = spans.withColumn("fresh", F.coalesce(F.col("place") > reach, F.lit(True)).cast("int")).withColumn("run", F.sum("fresh").over(before))
    merged = fresh.groupBy("doc_id", "row", "run").agg(F.min("place").alias("begin"), F.max("end").alias("end"), F.min_by("source", "place").alias("source"))
    return merged.groupBy("doc_id", "row").agg(F.sort_array(F.collect_list(F.struct("begin", "end", "source"))).alias("runs"))


def _left(text: Column, spans: Column) -> Column:
    """The text without the non-blank lines whose number among the non-blank lies in a span."""
    lines = F.split(text, "\n", -1)
    numbered = F.transform(lines, lambda x: F.regexp_like(x, F.lit(WORD)))
    flags = F.flatten(F.transform(spans, lambda s: F.sequence(s["begin"], s["end"] - 1)))
    order = F.filter(F.transform(numbered, lambda full, i: F.when(full, i)), lambda i: i.isNotNull())
    gone = F.transform(flags, lambda p: F.get(order, p))
    return F.array_join(F.transform(F.array_except(F.sequence(F.lit(0), F.size(lines) - 1), gone), lambda i: F.get(lines, i)), "\n")


NONE = "cast(array() as array<struct<begin:int,end:int,source:bigint>>)"


def report(docs: DataFrame, min_words: int = 50) -> DataFrame:
    """(doc_id, n_lines, n_removed, runs, text): one row per document; ``runs`` are maximal spans of removed non-blank lines."""
    found = repeated(docs, min_words).select(F.col("doc_id").alias("__doc"), F.col("row").alias("__row"), F.col("runs").alias("__runs"))
    plain = columns.documents(docs).withColumn("row", columns.row_name(F.col("text")))
    joined = plain.join(found, F.col("doc_id").eqNullSafe(F.col("__doc")) & (F.col("row") == F.col("__row")), "left")
    spans = joined.select("doc_id", "text", F.coalesce("__runs", F.expr(NONE)).alias("runs"))
    return spans.select(
        "doc_id",
        F.when(F.col("text") == "", F.lit(0)).otherwise(F.size(F.split("text", "\n", -1))).cast("bigint").alias("n_lines"),
        F.aggregate("runs", F.lit(0).cast("bigint"), lambda a, s: a + s["end"] - s["begin"]).alias("n_removed"),
        "runs",
        F.when(F.size("runs") == 0, F.col("text")).otherwise(_left(F.col("text"), F.col("runs"))).alias("text"),
    )


def remove(docs: DataFrame, min_words: int = 50) -> DataFrame:
    """``docs`` with the later copies of repeated runs deleted from their text; all columns kept."""
    found = repeated(docs, min_words).select(F.col("doc_id").alias("__doc"), F.col("row").alias("__row"), F.col("runs").alias("__runs"))
    plain = columns.positional(docs)
    key, text = (F.col(f"__c{columns.place(docs, c)}") for c in ("doc_id", "text"))
    joined = plain.join(found, key.cast("bigint").eqNullSafe(F.col("__doc")) & (columns.row_name(text) == F.col("__row")), "left")
    name = f"__c{columns.place(docs, 'text')}"
    return joined.withColumn(name, F.when(F.col("__runs").isNull(), text).otherwise(_left(text, F.col("__runs")))).select(*plain.columns).toDF(*docs.columns)


#: Brute force: every pair of places with equal lines, their longest common runs, and of these the ones with 50 words.
ORACLE = r"""
WITH l AS (SELECT doc_id, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) AS no FROM documents WHERE coalesce(text, '') <> ''),
     c AS (SELECT doc_id, no, line, len(regexp_extract_all(line, '[^\x20\x09-\x0D]+')) AS words FROM l),
     s AS (SELECT doc_id, line, no, words, row_number() OVER (PARTITION BY doc_id ORDER BY no) - 1 AS place, sum(words) OVER (PARTITION BY doc_id ORDER BY no) AS total FROM c WHERE words > 0),
     p AS (SELECT a.doc_id AS source, b.doc_id, b.place, b.place - a.place AS far FROM s a JOIN s b ON a.line = b.line AND (a.doc_id < b.doc_id OR (a.doc_id = b.doc_id AND a.place < b.place))),
     i AS (SELECT *, place - row_number() OVER (PARTITION BY source, doc_id, far ORDER BY place) AS island FROM p),
     m AS (SELECT source, doc_id, far, min(place) AS b, max(place) AS e FROM i GROUP BY source, doc_id, far, island),
     r AS (SELECT DISTINCT doc_id, b, e FROM m WHERE source <> doc_id
           UNION SELECT doc_id, b, least(e, b + far - 1) AS e FROM (SELECT doc_id, far, e, unnest(range(b, e + 1)) AS b FROM m WHERE source = doc_id)),
     k AS (SELECT r.* FROM r JOIN s x ON x.doc_id = r.doc_id AND x.place = r.b JOIN s y ON y.doc_id = r.doc_id AND y.place = r.e WHERE y.total - x.total + x.words >= 50),
     g AS (SELECT DISTINCT k.doc_id, s.no FROM k JOIN s ON s.doc_id = k.doc_id AND s.place BETWEEN k.b AND k.e),
     t AS (SELECT c.doc_id, count(*) FILTER (g.no IS NOT NULL) AS n_removed, string_agg(c.line, chr(10) ORDER BY c.no) FILTER (g.no IS NULL) AS left_text
           FROM c LEFT JOIN g ON g.doc_id = c.doc_id AND g.no = c.no GROUP BY c.doc_id)
SELECT d.doc_id, CASE WHEN coalesce(d.text, '') = '' THEN 0 ELSE len(string_split(d.text, chr(10))) END AS n_lines, coalesce(n_removed, 0) AS n_removed,
       sha256(coalesce(left_text, '')) AS text_sha256
FROM documents d LEFT JOIN t ON t.doc_id = d.doc_id
"""
