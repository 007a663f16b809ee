"""Five stages from raw documents to token ids; each calls one operator of ``parinflate.llm``.

A stage takes (spark, docs, sf_dir) and gives what the next one gets as ``docs``, written and read again as Parquet in between.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from parinflate.llm import byte_bpe, exact_dedup, importance, minhash_dedup, mixing
from parinflate.runtime import materialize, table


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in the importance sample stay."""
    return importance.sample(docs, table(spark, sf_dir, "labels"))


def exact(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts the row with the largest id stays."""
    return exact_dedup.survivors(docs)


def near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of a component of near copies (five words, similarity 0.8) the least id stays."""
    return minhash_dedup.survivors(docs, least=80)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sources are taken up to their targets; a document taken twice is there twice, one per source ends at the budget."""
    return mixing.mixed(docs)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids and the digests of ids and of what they decode to."""
    return byte_bpe.round_trip(docs).withColumnRenamed("id", "doc_id")


STAGES = [("quality_classifier", quality), ("exact_dedup", exact), ("near_dedup", near), ("mix_sources", mix), ("byte_bpe", encode)]

#: Stages 1, 3, 4 and 5 are no SQL; tests/llm/test_pipeline.py holds the rows of each stage against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents; of the result, one row per text that the mix takes."""
    docs = table(spark, sf_dir, "documents")
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = materialize(docs, f"stage-{name}")
    return docs
