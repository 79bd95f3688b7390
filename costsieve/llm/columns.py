"""Column handling shared by the operators: inputs may carry any extra columns, even clashing ones."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def positional(df: DataFrame, prefix: str = "__c") -> DataFrame:
    """The same rows under names that can clash with nothing."""
    return df.toDF(*[f"{prefix}{i}" for i in range(len(df.columns))])


def place(df: DataFrame, name: str) -> int:
    """Index of a column: the exact name first, else the only one that differs in case."""
    if name in df.columns:
        return df.columns.index(name)
    alike = [i for i, c in enumerate(df.columns) if c.lower() == name.lower()]
    if len(alike) != 1:
        raise ValueError(f"no single column {name!r} in {df.columns}")
    return alike[0]


def pick(df: DataFrame, **wanted: str) -> DataFrame:
    """Project ``new=old`` columns, whatever else the frame holds."""
    plain = positional(df)
    return plain.select(*[F.col(f"__c{place(df, old)}").alias(new) for new, old in wanted.items()])


def documents(df: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id bigint, text string) of a documents table; a null text counts as empty."""
    found = pick(df, doc_id=doc_id, text=text)
    return found.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.coalesce(F.col("text"), F.lit("")).alias("text"))


def row_name(text: Column) -> Column:
    """A 64-bit name of a text; with its doc_id it tells rows apart that share one."""
    return F.xxhash64(F.coalesce(text, F.lit("")))


def without(df: DataFrame, gone: DataFrame) -> DataFrame:
    """Rows of ``df`` whose (doc_id, row name) is not in the frame ``gone``; all columns kept, rows without a doc_id too."""
    plain = positional(df)
    left = gone.toDF("__gone", "__row")
    key, text = (F.col(f"__c{place(df, c)}") for c in ("doc_id", "text"))
    return plain.join(left, (key.cast("bigint") == F.col("__gone")) & (row_name(text) == F.col("__row")), "left_anti").toDF(*df.columns)


def lower_ascii(text: Column) -> Column:
    """Lower-case A-Z only."""
    return F.translate(text, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


BLOCK = 256


def located(text: Column, pattern: str | Column, measure=F.length) -> Column:
    """array<struct<begin int, size int, found string>> of the leftmost, non-overlapping matches, which are never empty, in units of ``measure``.

    Begins are running sums over the gaps and matches before. Arrays grow by copying, so sums are taken inside blocks and then over blocks: the work stays near the number of matches, however many a text has.
    """
    none = F.expr("cast(array() as array<struct<begin:int,size:int,found:string>>)")

    def places(found: Column) -> Column:
        pairs = F.zip_with(F.split(text, pattern, -1), found, lambda g, m: F.struct(measure(g).alias("gap"), measure(m).alias("size"), m.alias("found")))  # the last gap has no match after it
        return F.when(F.size(found) == 0, none).otherwise(bound(F.filter(pairs, lambda p: p["found"].isNotNull()), lambda p: _summed(p, none)))

    return bound(F.regexp_extract_all(text, F.lit(pattern), F.lit(0)), places)


def bound(value: Column, body) -> Column:
    """``body(value)`` with the value computed once, however often the body uses it."""
    return F.element_at(F.transform(F.array(value), body), 1)


def _summed(pairs: Column, none: Column) -> Column:
    def run(begin: Column, block: Column) -> Column:
        start = F.struct(begin.alias("at"), none.alias("out"))

        def step(state: Column, pair: Column) -> Column:
            here = state["at"] + pair["gap"]
            one = F.struct(here.alias("begin"), pair["size"].alias("size"), pair["found"].alias("found"))
            return F.struct((here + pair["size"]).alias("at"), F.concat(state["out"], F.array(one)).alias("out"))

        return F.aggregate(block, start, step, lambda s: s["out"])

    def blocks(state: Column, i: Column) -> Column:
        block = F.slice(state["pairs"], i * BLOCK + 1, F.lit(BLOCK))
        total = F.aggregate(block, F.lit(0), lambda a, p: a + p["gap"] + p["size"])
        return F.struct((state["at"] + total).alias("at"), state["pairs"].alias("pairs"), F.concat(state["starts"], F.array(state["at"])).alias("starts"))

    many = F.struct(F.lit(0).alias("at"), pairs.alias("pairs"), F.expr("cast(array() as array<int>)").alias("starts"))
    count = F.sequence(F.lit(0), F.floor((F.size(pairs) - 1) / BLOCK).cast("int"))
    split = F.aggregate(count, many, blocks, lambda s: F.flatten(F.transform(s["starts"], lambda at, i: run(at, F.slice(s["pairs"], i * BLOCK + 1, F.lit(BLOCK))))))
    return F.when(F.size(pairs) <= BLOCK, run(F.lit(0), pairs)).otherwise(split)
