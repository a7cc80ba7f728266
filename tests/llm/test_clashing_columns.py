"""Every name that an operator uses inside, as an extra column of its input: same results, and columns come back untouched."""

import inspect
import re

import pytest
from pyspark.sql import functions as F

from ldpspark.llm import common, components, decontaminate, html_extract, language_id, license_scan, mixing, near_dedup, token_output, topk, toxicity, url_filter

COPY = " ".join(f"w{i}" for i in range(40))
DOCS = [(i, f"{COPY} {COPY[::-1]} {i % 3}" if i % 2 else f"the cat number {i} sat on mat {i * i} all rights reserved", "en" if i % 3 else "fr", "ab"[i % 2]) for i in range(24)] + [(3, None, "en", "a"), (None, "word", "en", None), (5, "", "fr", "b")]
BENCH = [(1, "the cat number 4 sat on mat 16 all rights reserved"), (2, None)]
LABELS = [(i, i % 2) for i in range(24)]


def names(*modules):
    """All words in quotes in the modules' code, which covers each name of a column."""
    text = "".join(inspect.getsource(m) for m in (*modules, common, components))
    return sorted({x.lower() for q in re.findall(r"\"([^\"\n]*)\"|'([^'\n]*)'", text) for x in re.findall(r"[A-Za-z_][A-Za-z_0-9]*", "".join(q))} - {"lang", "doc_id", "text", "source", "page_id", "url", "html", "vec_id", "embedding", "toxic", "item_id"})


def wide(df, extra):
    return df.select(*[F.lit("KEEP").alias(x) for x in extra[: len(extra) // 2]], "*", *[F.lit("KEEP").alias(x) for x in extra[len(extra) // 2 :]])


def docs(spark):
    return spark.createDataFrame(DOCS, "doc_id long, text string, lang string, source string")


def bench(spark):
    return spark.createDataFrame(BENCH, "item_id long, text string")


def labels(spark):
    return spark.createDataFrame(LABELS, "doc_id long, toxic int")


DOCUMENTS = [
    ("scan", lambda s, d: license_scan.scan(d), [license_scan]), ("tokens", lambda s, d: token_output.token_output(d), [token_output]), ("toxicity", lambda s, d: toxicity.toxicity(d, labels(s)), [toxicity]),
    ("language", lambda s, d: language_id.identify(d), [language_id]), ("kept languages", lambda s, d: language_id.identify(d, keep=0.02), [language_id]), ("near", lambda s, d: near_dedup.near_duplicates(d), [near_dedup]),
    ("deduplicated", lambda s, d: near_dedup.deduplicated(d, wordless=True), [near_dedup]), ("copies", lambda s, d: mixing.plan_copies(d, odds="size"), [mixing]), ("mix", lambda s, d: mixing.mix(d, odds="size"), [mixing]),
    ("contamination", lambda s, d: decontaminate.contamination(d, bench(s), n=5), [decontaminate]), ("sliced", lambda s, d: decontaminate.contamination(d, bench(s), n=5, slice_bytes=30), [decontaminate]),
    ("clean", lambda s, d: decontaminate.clean(d, bench(s), n=5), [decontaminate]), ("clean, sliced", lambda s, d: decontaminate.clean(d, bench(s), n=5, slice_bytes=30), [decontaminate]),
]


@pytest.mark.parametrize("name,operator,modules", DOCUMENTS, ids=[x[0] for x in DOCUMENTS])
def test_document_operators(spark, name, operator, modules):
    extra = names(*modules)
    assert len(extra) > 30
    plain = operator(spark, docs(spark))
    got = operator(spark, wide(docs(spark), extra))
    if got.columns != plain.columns:  # rows are returned whole
        assert got.columns == wide(docs(spark), extra).columns
        assert got.filter(" OR ".join(f"`{x}` <> 'KEEP' OR `{x}` IS NULL" for x in extra)).count() == 0
    assert sorted(map(repr, got.select(*[F.col(f"`{c}`") for c in plain.columns]).collect())) == sorted(map(repr, plain.collect()))


def test_other_operators(spark):
    pages = spark.createDataFrame([(i, f"http://h.org/{i}", f"<body><div><p>Menu</p><p>Print</p></div><div><p>Story {i} of its own</p></div></body>") for i in range(6)], "page_id long, url string, html string")
    rules = spark.createDataFrame([(1, "org", "/", "block")], "tier int, host string, path string, verdict string")
    vectors = spark.createDataFrame([(i, [float(i % 7), float(i % 5)]) for i in range(40)], "vec_id long, embedding array<double>")
    for operator, df, module in (
        (html_extract.extract, pages, html_extract), (lambda d: url_filter.judge(d, rules), pages, url_filter), (lambda d: topk.search(d, F.col("vec_id") % 10 == 0, k=3), vectors, topk),
    ):
        assert sorted(map(repr, operator(wide(df, names(module))).collect())) == sorted(map(repr, operator(df).collect()))
