"""Corpus pipeline: documents of good quality, without repeated lines, near copies and benchmark passages, as token ids.

Each stage takes (spark, docs, sf_dir) and works on all that the one before kept; run() writes each as Parquet in the
shared folder and reads it again, so that a lost executor costs one stage's tasks at most.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from schemaloom.llm import bpe, fmindex, lines, quality, simhash
from schemaloom.llm.shared import Scratch, unused


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the neighbours' vote accepts. Labels outside the held-out fold alone are learnt from."""
    model = quality.fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return quality.score(docs, model).where("predicted = 1").select(docs.columns)


def cut_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without lines that others repeat; n_chars counts what is left. A document may be left empty."""
    kept = lines.drop_repeated_lines(docs)
    changed = {"text": F.col("kept_text")} | ({"n_chars": F.length("kept_text").cast("long")} if "n_chars" in docs.columns else {})
    return kept.withColumns(changed).select(docs.columns)


def one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document with the smallest id of each group of near copies: five-word shingles, similarity 0.8 or more."""
    node = unused("node", docs)
    later = simhash.near_copies(docs).where("node <> component").select(F.col("node").alias(node))
    later = later.hint("merge")  # the same plan at every size
    return docs.join(later, F.coalesce("doc_id", F.lit(simhash.NO_ID)) == F.col(node), "left_anti").select(docs.columns)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no more of the benchmark than the rule allows."""
    found = fmindex.find_benchmark(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
    return found.where(~fmindex.contaminated()).select(docs.columns)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256, ids."""
    import public_tokenizers

    return bpe.encode_words(docs, public_tokenizers.path("word_bpe_49k.json"), with_ids=True)


STAGES = [
    ("quality classifier", keep_quality),
    ("line dedup", cut_lines),
    ("simhash near-dedup", one_of_each_group),
    ("benchmark decontamination", drop_contaminated),
    ("bpe encoding and decoding", encode),
]

#: The neighbours' vote is beyond SQL: tests/llm/test_corpus_exact.py holds the rows against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    scratch = Scratch(spark, "pipeline")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (_, stage) in enumerate(STAGES):
        docs = scratch.table(f"stage-{k}", stage(spark, docs, sf_dir))
        if k:
            scratch.drop(f"stage-{k - 1}")
    return docs
