"""What de-duplication keeps: rows without ids, without words, and repeated rows."""

from ldpspark.llm import near_dedup

COPY = " ".join(f"w{i}" for i in range(60))


def kept(spark, rows, **options):
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    return sorted(((r["doc_id"], r["text"]) for r in near_dedup.deduplicated(df, **options).collect()), key=repr)


def test_unlike_documents_without_ids_stay(spark):
    rows = [(None, f"text {i} is like no other, as {i * 7} shows {i}", "a") for i in range(8)] + [(None, COPY, "a"), (None, COPY + " more", "a"), (1, "with id", "a")]
    out = kept(spark, rows)
    assert len(out) == 8 + 1 + 1 and sum(t.startswith("w0") for _, t in out) == 1


def test_rows_without_words_stay(spark):
    rows = [(1, None, "a"), (2, "", "a"), (2, "", "b"), (3, " \t\n\x0b\x0c\r", "a"), (None, None, "a"), (4, " ", "a"), (5, "word", "a")]
    assert kept(spark, rows, wordless=True) == sorted(((i, t) for i, t, _ in rows), key=repr)
    assert kept(spark, rows) == [(4, " "), (5, "word")]


def test_one_of_repeated_rows_stays(spark):
    rows = [(7, COPY, "a")] * 5 + [(8, COPY + " more", "a")] + [(None, "text without id and " + COPY[::-1], "b")] * 40 + [(9, "once", "c"), (9, "once", "d"), (9, "not twice", "c")]
    assert kept(spark, rows) == sorted([(7, COPY), (None, "text without id and " + COPY[::-1]), (9, "once"), (9, "not twice")], key=repr)
