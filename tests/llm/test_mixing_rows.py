"""Sizes of texts with odd characters, ranks, and cuts that need several levels of bins."""

import re

import pytest
from pyspark.sql import functions as F

from ldpspark.llm import mixing


def test_sizes_of_odd_texts(spark):
    texts = ["a\x00b \x00", "\x00", " \x00 \x00\n", "", None, "a\tb\x0bc\x0cd\re\nf", "\n\n\n", "é ü x", "\x1ca\x85b", " lead", "trail "]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r[0]: r[1] for r in df.select("doc_id", mixing.word_count(F.col("text"))).collect()}
    assert got == {k: len(re.findall(r"[^\x20\x09-\x0D]+", t or "")) for k, t in enumerate(texts)}


@pytest.mark.parametrize("ordered", [50_000, 3])
def test_levels_of_bins_agree_and_fit(spark, monkeypatch, ordered):
    """The same cut from one level of bins or from as many as it takes; also with ids that tell nothing."""
    df = spark.range(600).select(F.col("id").alias("doc_id"), F.concat_ws(" ", F.array_repeat(F.concat(F.lit("w"), "id"), (F.col("id") % 17 + 1).cast("int"))).alias("text"), F.lit("s").alias("source"))
    want = {r["doc_id"]: r["copies"] for r in mixing.plan_copies(df, total_share=0.7, odds="size").collect()}
    monkeypatch.setattr(mixing, "ORDERED", ordered)
    monkeypatch.setattr(mixing, "BINS", 4)
    assert {r["doc_id"]: r["copies"] for r in mixing.plan_copies(df, total_share=0.7, odds="size").collect()} == want
    same = mixing.plan_copies(df.withColumn("doc_id", F.lit(5)), total_share=0.7).collect()
    assert sum(r["size"] * r["copies"] for r in same) == pytest.approx(same[0]["target"], abs=9)
    assert len({r["copies"] for r in same}) == 2


def test_pareto_ranks_by_brute_force(spark):
    """The rows up to the cut are those of least rank; larger documents are taken more often."""
    df = spark.range(3000).select(F.col("id").alias("doc_id"), F.concat_ws(" ", F.array_repeat(F.lit("x"), F.when(F.col("id") % 2 == 0, 4).otherwise(100).cast("int"))).alias("text"), F.lit("s").alias("source"))
    got = mixing.plan_copies(df, total_share=0.3, odds="size").collect()
    share = {n: sum(r["copies"] for r in got if r["size"] == n) / 1500 for n in (4, 100)}
    assert share[100] > 3 * share[4] > 0 and sum(r["size"] * r["copies"] for r in got) == pytest.approx(got[0]["target"], abs=50)
