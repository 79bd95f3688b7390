"""Exact de-duplication over an extendible-hash index kept on shared files.

Texts are equal when they are identical after every run of ASCII white space has become one space. A text's 64-bit hash is its address. The directory doubles a few bits
at a time: every round counts the addresses of overfull buckets only, under longer prefixes, and closes the buckets that now hold at most ``capacity`` addresses, until none is
overfull. It needs as many rounds as the data ask for and is never gathered on the driver. The index, a written table, holds one row per distinct fingerprint: its bucket, its address, its place in the chain of
fingerprints that share the address, the SHA-256 of the normalised text, and the number of rows.

Texts whose fingerprint occurs twice or more are read again and sent to the bucket's owner, equal ones already collapsed to one. Owners are tasks that hold ranges of
(bucket, address); each walks its chains, compares the texts under one link byte by byte, and gives every link its smallest doc_id and its number of rows. Fingerprints that occur once need no comparison.

Defined results: a null text is the empty text; a null doc_id is larger than any other; rows that repeat a kept
doc_id with the same text are all marked as kept in the report, and ``deduplicate`` returns one of them; rows that share a doc_id but not
the text are decided each by its own text; an empty table gives an empty result; other columns are ignored (report) or passed through (``deduplicate``).
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import columns
from .staging import Staging

SPACE_RUN = r"[\x20\x09-\x0D]+"


@dataclass(frozen=True)
class IndexOptions:
    capacity: int = 1 << 14  # addresses of a bucket; a chain of fingerprints under one address counts once
    step: int = 8  # bits by which a round doubles the directory
    address_bits: int = 63  # fewer make addresses collide, for tests


def normalised(text: Column) -> Column:
    return F.regexp_replace(F.coalesce(text, F.lit("")), SPACE_RUN, " ")


def fingerprints(docs: DataFrame, options: IndexOptions = IndexOptions()) -> DataFrame:
    """(doc_id, address, sha): what the index keeps of a text."""
    norm = columns.documents(docs).select("doc_id", normalised(F.col("text")).alias("norm"))
    return norm.select("doc_id", _address(F.col("norm"), options).alias("address"), F.sha2("norm", 256).alias("sha"))


def _address(norm: Column, options: IndexOptions) -> Column:
    return F.shiftrightunsigned(F.xxhash64(norm), 64 - options.address_bits)


def _prefix(address: Column, depth: int, options: IndexOptions) -> Column:
    """The first ``depth`` bits of an address."""
    return F.shiftright(address, options.address_bits - depth)


def directory(addresses: DataFrame, stage: Staging, options: IndexOptions = IndexOptions()) -> DataFrame:
    """(depth, prefix): the buckets, by the bits that their addresses share. ``addresses`` are distinct.

    A round looks at ``step`` more bits of what is still overfull. A bucket is a prefix that fits and whose parent, one bit shorter, overflowed.
    """
    closed, depth, open_rows = [], 0, addresses
    while True:
        deeper = min(depth + options.step, options.address_bits)
        hist = open_rows.groupBy(_prefix(F.col("address"), deeper, options).alias("slot")).agg(F.count(F.lit(1)).alias("n"))
        levels = hist.select("slot", "n", F.explode(F.sequence(F.lit(depth), F.lit(deeper))).alias("depth"))
        prefix = F.expr(f"shiftright(slot, {deeper} - depth)").alias("prefix")
        held = stage.table(levels.groupBy("depth", prefix).agg(F.sum("n").alias("held")), "levels")
        overfull = held.where(F.col("held") > options.capacity)
        parents = overfull.select((F.col("depth") + 1).alias("depth"), F.col("prefix").alias("parent"), F.lit(True).alias("split"))
        fits = held.where(F.col("held") <= options.capacity).withColumn("parent", F.shiftright("prefix", 1)).join(parents, ["depth", "parent"], "left")
        closed.append(fits.where("split OR depth = 0").select("depth", "prefix"))
        full = overfull.where(F.col("depth") == deeper).select(F.col("prefix").alias("__prefix"))
        if deeper == options.address_bits or not full.head(1):
            return stage.table(reduce(DataFrame.unionByName, closed), "directory")
        open_rows = addresses.join(full, _prefix(F.col("address"), deeper, options) == F.col("__prefix"), "left_semi")
        depth = deeper


def build_index(prints: DataFrame, stage: Staging, options: IndexOptions = IndexOptions()) -> DataFrame:
    """(depth, bucket, address, link, sha, n), written by tasks that hold ranges of (bucket, address). A bucket is named by its first address."""
    buckets = directory(prints.select("address").distinct(), stage, options)
    depths = sorted(r["depth"] for r in buckets.select("depth").distinct().collect())  # at most 64 numbers
    entries = prints.groupBy("address", "sha").agg(F.count(F.lit(1)).alias("n"))
    # an address has one prefix of each depth in use, and just one of them is a bucket
    slots = [F.struct(F.lit(d).alias("depth"), _prefix(F.col("address"), d, options).alias("prefix")) for d in depths or [0]]
    owned = entries.withColumn("slot", F.explode(F.array(*slots))).select("address", "sha", "n", "slot.*").join(buckets, ["depth", "prefix"])
    owned = owned.withColumn("bucket", F.when(F.col("depth") > 0, F.expr(f"shiftleft(prefix, {options.address_bits} - depth)")).otherwise(F.lit(0).cast("bigint")))
    link = F.row_number().over(Window.partitionBy("bucket", "address").orderBy("sha"))
    return stage.table(owned.repartitionByRange("bucket", "address").select("depth", "bucket", "address", link.alias("link"), "sha", "n"), "index")


def resolve(docs: DataFrame, index: DataFrame, options: IndexOptions = IndexOptions()) -> DataFrame:
    """(address, sha, keep_id, n) of every link with two rows or more, found by the owners on the texts themselves.

    Equal texts collapse before the shuffle, so a hot group sends one copy per task. Two different texts under one SHA-256 would
    stop the job rather than be merged.
    """
    doubtful = index.where(F.col("n") > 1).select("bucket", "address", "link", "sha")
    texts = columns.documents(docs).select("doc_id", normalised(F.col("text")).alias("norm")).withColumn("address", _address(F.col("norm"), options))
    linked = texts.join(doubtful, "address").where(F.sha2("norm", 256) == F.col("sha"))
    same = linked.groupBy("bucket", "address", "link", "sha", "norm").agg(F.min("doc_id").alias("keep_id"), F.count(F.lit(1)).alias("n"))
    own = same.repartitionByRange("bucket", "address").groupBy("bucket", "address", "link", "sha")
    found = own.agg(F.min("keep_id").alias("keep_id"), F.sum("n").alias("n"), F.min("norm").alias("least"), F.max("norm").alias("most"))
    clash = F.raise_error(F.lit("two different texts share one SHA-256"))
    checked = F.when(F.col("least") != F.col("most"), clash.cast("bigint")).otherwise(F.col("keep_id"))
    return found.select("address", "sha", checked.alias("keep_id"), "n")


def duplicate_report(docs: DataFrame, options: IndexOptions = IndexOptions()) -> DataFrame:
    """(doc_id, keep_id, group_size, kept, text_sha256): one row per document."""
    stage = Staging(docs.sparkSession, "exact-dedup")
    prints = stage.table(fingerprints(docs, options), "prints")
    index = build_index(prints, stage, options)
    groups = stage.table(resolve(docs, index, options), "groups")
    found = prints.join(groups, ["address", "sha"], "left")
    keep = F.when(F.col("n").isNull(), F.col("doc_id")).otherwise(F.col("keep_id"))
    return found.select(
        "doc_id",
        keep.alias("keep_id"),
        F.coalesce(F.col("n"), F.lit(1)).cast("bigint").alias("group_size"),
        keep.eqNullSafe(F.col("doc_id")).alias("kept"),
        F.col("sha").alias("text_sha256"),
    )


def deduplicate(docs: DataFrame, options: IndexOptions = IndexOptions()) -> DataFrame:
    """The rows that stay, with all their columns. Rows without a doc_id stay."""
    report = duplicate_report(docs, options).select(F.col("doc_id").alias("__doc"), F.col("text_sha256").alias("__sha"), "kept")
    row = ["__doc", "__sha"]
    plain = columns.positional(docs)
    key, text = (F.col(f"__c{columns.place(docs, c)}") for c in ("doc_id", "text"))
    own = plain.withColumn("__doc", key.cast("bigint"))
    # Texts are looked at only where a doc_id has several rows of which one is kept.
    ids = report.where(F.col("__doc").isNotNull()).groupBy("__doc").agg(F.count(F.lit(1)).alias("n"), F.max("kept").alias("some"), F.min("kept").alias("all"))
    ids = ids.where(~F.col("all") | (F.col("n") > 1))
    once = own.join(ids.select("__doc"), "__doc", "left_anti")
    several = own.join(ids.where("some").select("__doc"), "__doc", "left_semi").withColumn("__sha", F.sha2(normalised(text), 256))
    many = several.join(report.where("kept").select(*row), row, "left_semi").dropDuplicates(row)
    return once.select(*plain.columns).unionByName(many.select(*plain.columns)).toDF(*docs.columns)


ORACLE = r"""
WITH norm AS (SELECT doc_id, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g') AS t FROM documents),
     per AS (SELECT t, min(doc_id) AS keep_id, count(*) AS n FROM norm GROUP BY t)
SELECT d.doc_id, p.keep_id, p.n AS group_size, d.doc_id = p.keep_id AS kept, sha256(d.t) AS text_sha256
FROM norm d JOIN per p ON d.t = p.t
"""
