"""Corpus pipeline: toxicity, line dedup, n-gram Jaccard join, decontamination, byte-level BPE.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame, written as Parquet and read again
as the next one's documents. Toxic documents go; lines that repeat or nearly repeat stay once, and
documents that lose every line go; of each group of near duplicates the smallest id stays;
contaminated documents go; the last stage returns the digests of each text's ids and round trip.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from anglegraph.llm import byte_bpe, decontaminate, jaccard_join, line_dedup, toxicity
from anglegraph.llm.common import written


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def stage_toxicity(spark, docs, sf_dir):
    return toxicity.reject_toxic(docs, _table(spark, sf_dir, "labels"))


def stage_line_dedup(spark, docs, sf_dir):
    return line_dedup.dedup_lines(docs)


def stage_jaccard_join(spark, docs, sf_dir):
    return jaccard_join.keep_one(docs)


def stage_decontamination(spark, docs, sf_dir):
    return decontaminate.filter_contaminated(docs, _table(spark, sf_dir, "benchmark"))


def stage_byte_bpe(spark, docs, sf_dir):
    import public_tokenizers as tokenizers

    return byte_bpe.round_trip(docs, tokenizers.path("byte_bpe_multi_50k.tiktoken"), tokenizers.PATTERN)


STAGES = [
    ("toxicity", stage_toxicity),
    ("line_dedup", stage_line_dedup),
    ("ngram_jaccard_join", stage_jaccard_join),
    ("benchmark_decontamination", stage_decontamination),
    ("byte_bpe", stage_byte_bpe),
]

ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
