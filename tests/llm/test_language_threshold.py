"""What the pipeline's language stage lets through."""

import random

from ldpspark.llm import language_id

SCRIPTS = {"cyrillic": (0x430, 0x450), "greek": (0x3B1, 0x3C9), "thai": (0xE01, 0xE2F), "han": (0x4E00, 0x9000), "arabic": (0x621, 0x64A), "hebrew": (0x5D0, 0x5EB), "kana": (0x3041, 0x3097)}


def planted():
    rng, out = random.Random(6), []
    for name, (lo, hi) in SCRIPTS.items():
        out += [(name, " ".join("".join(chr(rng.randrange(lo, hi)) for _ in range(rng.randrange(1, longest))) for _ in range(n))) for n in (1, 3, 20, 200) for longest in (2, 3, 9)]
    return out + [("no words", " ".join("".join(rng.choice("bcdfghjkmpqvwxz") for _ in range(7)) for _ in range(n))) for n in (5, 20) for _ in range(100)]


def test_untaught_scripts_go_and_clean_texts_stay(spark, sf):
    import corpus_pipeline as P

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = [(10**7 + k, text, None, name, len(text)) for k, (name, text) in enumerate(planted())]
    kept = P.by_language(spark, docs.unionByName(spark.createDataFrame(rows, docs.schema)), sf)
    through = {r["source"]: r["count"] for r in kept.filter("doc_id >= 10000000").groupBy("source").count().collect()}
    assert set(through) <= {"no words"} and through.get("no words", 0) <= 0.2 * 200
    symbol = language_id.letters()
    lettered = [r["doc_id"] for r in docs.select("doc_id", "text").collect() if any(symbol[ord(c)] for c in r["text"] or "")]
    assert sorted(r["doc_id"] for r in kept.filter("doc_id < 10000000").collect()) == sorted(lettered)


def test_threshold_lies_above_the_noise():
    import corpus_pipeline as P

    assert P.LEAST_SCORE >= 2 / language_id.DIMENSIONS**0.5
