import zlib

import corpus_pipeline
import numpy as np
import public_tokenizers
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from costsieve.llm import language_id, secrets

from .test_llm import brute_near, brute_secrets, norm


def redacted(text, spans):
    out, at = "", 0
    for begin, end in sorted(spans):
        if begin >= at:
            out += text[at:begin] + "[REDACTED]"
        at = max(at, end)
    return out + text[at:]


def test_pipeline_against_brute_force(spark, small_dir):
    docs = spark.read.parquet(f"{small_dir}/documents.parquet")
    said = {r["doc_id"]: r for r in language_id.identify(docs).collect()}
    rows = sorted((r["doc_id"], r["text"]) for r in docs.collect())
    rows = [(d, t) for d, t in rows if said[d]["lang_pred"] != "und" and said[d]["score"] >= corpus_pipeline.LEAST_SCORE]
    first = {}
    for d, t in rows:
        first.setdefault(norm(t), d)
    rows = [(d, t) for d, t in rows if first[norm(t)] == d]
    kept = {d for d, _, _, keep in brute_near(rows) if keep}
    rows = [(d, t) for d, t in rows if d in kept]
    tokens = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    tokens.encode_special_tokens = True
    want = []
    for d, t in rows:
        base, more = brute_secrets(t, secrets.ScanOptions())
        t = redacted(t, [(s[0], s[2]) for s in base + more])
        ids = tokens.encode(t, add_special_tokens=False).ids + [0]
        first_end = len(ids) % 2048 or min(len(ids), 2048)
        bounds = [0, *range(first_end, len(ids) + 1, 2048)]
        want += [(d, i, a, b - a, zlib.crc32(np.array(ids[a:b], "<u4").tobytes())) for i, (a, b) in enumerate(zip(bounds, bounds[1:]))]
    out = corpus_pipeline.run(spark, small_dir).collect()
    assert sorted((r["doc_id"], r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in out) == sorted(want)


def test_stages_keep_the_columns_of_documents(spark, small_dir):
    docs = spark.read.parquet(f"{small_dir}/documents.parquet").where(F.col("doc_id") < 40)
    assert [name for name, _ in corpus_pipeline.STAGES] == ["language_id", "exact_dedup", "near_dedup", "secret_scan", "best_fit_packing"]
    for _, stage in corpus_pipeline.STAGES[:-1]:
        assert stage(spark, docs, small_dir).columns == docs.columns


def test_empty_documents(spark, small_dir, tmp_path):
    docs = spark.read.parquet(f"{small_dir}/documents.parquet").where("false")
    for _, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, small_dir)
    assert corpus_pipeline.STAGES[-1][1](spark, docs, small_dir).count() == 0


def test_unlabelled_documents_with_letters_stay(spark, small_dir):
    docs = spark.createDataFrame([(1, "clean text"), (2, "日本語"), (3, "123 !?"), (4, None), (5, ""), (None, "no id")], "doc_id bigint, text string")
    docs = docs.withColumn("lang", F.lit(None).cast("string"))
    out = corpus_pipeline.STAGES[0][1](spark, docs, small_dir)
    assert out.columns == docs.columns and sorted(r["doc_id"] or 0 for r in out.collect()) == [0, 1, 2]
