"""From raw documents to packed training sequences, stage by stage.

Each stage takes (spark, docs, sf_dir) and returns a frame; what it returns is written and read again before the next stage. Language identification drops
documents without a language (those without a letter where no labels are there to learn from), exact and near de-duplication keep one document of each group, the secret scan replaces secrets by a mark, and
packing places the tokens of what is left. All stages but the last return the columns of documents.

Every stage decides row by row: where one doc_id stands for several texts, each text has its own fate. A null doc_id is never linked or dropped for its id.
An empty table passes through all stages. Other columns, whatever their names, are carried along.
"""

from __future__ import annotations

import threading
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from costsieve.llm import byte_tokens, columns, exact_dedup, language_id, near_dedup, packing, secrets
from costsieve.llm.queries import tokenizer_path
from costsieve.llm.staging import Staging, shared_dir

LEAST_SCORE = 0.3  # below it a language is a guess

_mine = threading.local()  # tables of this thread's last stage: pipelines that run at once do not meet


def _stage(index: int, function):
    """Tables that the stage before has left behind go when this one starts: by then its result has been written."""

    def call(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        before, made = getattr(_mine, "made", (None, []))
        for old in made if before == index - 1 else []:
            old.drop()
        with Staging.collected() as now:
            out = function(spark, docs, sf_dir)
        _mine.made = (index, now)
        return out

    call.__doc__ = function.__doc__
    return call


def _language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows whose text has a language. Null and empty texts and those without a letter go; equal texts share their fate; repeated rows all stay or all go."""
    model = language_id.learn(docs)
    if model is None:  # no label to learn from: only texts without a letter have no language
        plain, text = columns.positional(docs), F.col(f"__c{columns.place(docs, 'text')}")
        return plain.where(F.regexp_like(F.coalesce(text, F.lit("")), F.lit(r"\p{L}"))).toDF(*docs.columns)
    found = language_id.identified(docs, model).where((F.col("__lang") != language_id.UNDETERMINED) & (F.col("__score") >= LEAST_SCORE))
    return found.drop("__lang", "__score").toDF(*docs.columns)


def _exact(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each normalised text, the one with the smallest doc_id; rows without a doc_id stay. Null counts as empty."""
    return exact_dedup.deduplicate(docs)


def _near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The smallest doc_id's rows of each group of near copies. Texts without words, and rows without a doc_id, are linked with nothing and stay."""
    return near_dedup.deduplicate(docs)


def _secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All rows, secrets cut out of their texts. A null text stays null."""
    return secrets.redact(docs)


def _packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Places of all pieces. A null or empty text is the end id alone; rows that repeat a doc_id are documents of their own."""
    encoding = byte_tokens.encoding(tokenizer_path("byte_bpe_50k.json"), end_id=0, keep_white=True)
    return packing.pack(docs, capacity=2048, encoding=encoding)


STAGES = [
    (name, _stage(i, function))
    for i, (name, function) in enumerate(
        (("language_id", _language), ("exact_dedup", _exact), ("near_dedup", _near), ("secret_scan", _secrets), ("best_fit_packing", _packing))
    )
]

#: SQL has no language model, so the pipeline is tested against a brute-force version instead.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the whole documents table."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    place = f"{shared_dir(spark)}/costsieve/pipeline-{uuid.uuid4().hex}"
    for name, function in STAGES[:-1]:
        function(spark, docs, sf_dir).write.parquet(f"{place}/{name}")
        docs = spark.read.parquet(f"{place}/{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
