"""Pages that are copies of each other have no vote of their own and keep their article."""

import pytest

from ldpspark.llm import html_extract

PLAIN = "<html><body>{1}<div><p>First paragraph of the story.</p><p>Second one {0}with more.</p><p>The third ends it.</p></div></body></html>"
TEXT = "First paragraph of the story. Second one with more. The third ends it."


def texts(spark, rows):
    return {r["page_id"]: r["text"] for r in html_extract.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}


@pytest.mark.parametrize("n", [3, 4, 6])
def test_copies_keep_their_article(spark, n):
    page = PLAIN.format("", "")
    rows = [(i, f"http://urls.org/{i}", page) for i in range(n)] + [(100 + i, "http://rows.org/1", page) for i in range(n)]
    # copies but for what no text shows
    rows += [(200 + i, f"http://marks.org/{i}", PLAIN.format(f"<!-- {i} -->", "")) for i in range(n)]
    rows += [(300 + i, f"http://dates.org/{i}", PLAIN.format("", f"<p>{i} May</p>")) for i in range(n)]
    out = texts(spark, rows)
    assert {out[k] for k in out if k < 300} == {TEXT}
    assert all(out[300 + i] == f"{i} May {TEXT}" for i in range(n))


def test_copies_of_a_declared_article_keep_it(spark):
    page = "<html><body><!-- {0} --><article><h1>Title</h1><p>One story for all.</p><p>And its end.</p></article></body></html>"
    rows = [(i, f"http://a.org/{i}", page.format(i)) for i in range(10)] + [(50 + i, f"http://b.org/{i}", page.format(0)) for i in range(10)]
    assert set(texts(spark, rows).values()) == {"Title One story for all. And its end."}


def test_copies_among_other_pages(spark):
    frame = "<html><body><div><p>Join our list</p><p>Small print</p><p>Made here</p></div><div><div>{0}</div></div></body></html>"
    story = "<p>A story that many pages tell.</p><p>It goes on at some length.</p><p>Then it ends.</p>"
    rows = [(i, f"http://h.org/{i}", frame.format(story + f"<!-- {i} -->")) for i in range(4)]
    rows += [(10 + i, f"http://h.org/own{i}", frame.format(f"<p>Own story {i} with words enough.</p><p>Line {i} of it.</p>")) for i in range(3)]
    rows.append((20, "http://h.org/none", frame.format("")))
    out = texts(spark, rows)
    assert {out[i] for i in range(4)} == {"A story that many pages tell. It goes on at some length. Then it ends."}
    assert out[10] == "Own story 0 with words enough. Line 0 of it." and out[20] == ""


def test_repeated_rows_have_one_vote(spark):
    pages = [("h", i, f"<p>a</p><b>b</b><i>c{i}</i><u>d</u>") for i in range(3)]
    seen = lambda rows: {r["host"]: (r["n"], sorted(r["tokens"])) for r in html_extract.templates(spark.createDataFrame(rows, "host string, key long, html string")).collect()}
    assert seen(pages) == seen(pages + pages[:2] + pages[:1]) and seen(pages)["h"][0] == 3
