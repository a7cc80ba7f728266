"""Corpus pipeline: language identification, near-duplicates, decontamination, mixing, token output.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; ``run`` writes each stage's rows as Parquet in the shared
folder and reads them back for the next. All stages but the last return the columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ldpspark.llm import common, decontaminate, language_id, mixing, near_dedup, token_output
from ldpspark.sources.ship import ship

#: Least cosine with the chosen language: twice the deviation of a text that shares no trigram with it. Texts below it and texts
#: without letters go. Clean texts of one word come close to it (least of sf0.1: 0.034), so it can not be much higher.
LEAST_SCORE = 2 / language_id.DIMENSIONS**0.5


def by_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in a language that the labelled folds teach."""
    return language_id.identify(docs, train=~common.held_out(F.col("doc_id")), keep=LEAST_SCORE)


def without_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group linked by five-word shingles at a similarity of 0.8 or more, and all without words."""
    return near_dedup.deduplicated(docs, width=5, similarity=(80, 100), wordless=True)


def without_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents of which under a twentieth of the words lie in 13-word windows of the benchmark."""
    return decontaminate.clean(docs, common.table(spark, sf_dir, "benchmark"))


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in as many copies as the mix of sources takes."""
    return mixing.mix(docs, odds="size")


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every copy, from the written blocks."""
    return token_output.token_output(docs)


STAGES = [
    ("language ID", by_language), ("MinHash near-dedup", without_copies), ("benchmark decontamination", without_benchmark),
    ("mixing sources to target weights", mixed), ("token-ID / binary output", tokens),
]

#: Trained profiles, sketches and tokenizers have no SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages over ``documents``, each written and read again."""
    ship(spark)
    docs = common.table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = common.stored(stage(spark, docs, sf_dir), "stage-" + name.split()[0].lower())
    return STAGES[-1][1](spark, docs, sf_dir)
