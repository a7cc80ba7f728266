"""Listed canonical URLs, the filter made by an aggregation, and hosts with very many labels."""

import time

import numpy as np
from pyspark.sql import functions as F

from ldpspark.llm import url_filter as U


def test_filter_by_aggregation_equals_the_one_by_hand(spark):
    for n in (1, 40, 5000):
        codes = np.random.default_rng(n).integers(-(2**63), 2**63, n)
        table = U.filter_blocks(spark.createDataFrame([(int(x),) for x in codes], "code long"), n)
        assert (table == U.build_filter(codes, n)).all()


def test_listed_urls_are_canonical(spark):
    listed = U.listing(spark.createDataFrame([(x,) for x in ["HTTP://WWW.Bad.org/", "https://me:pw@ugly.net.:8080/x/", "http://bad.org", None, "no scheme", "http:///path", "ftp://www.deep.er.com/a/b?q#f"]], "url string"))
    assert sorted((r["host"], r["path"]) for r in listed.collect()) == [("bad.org", ""), ("deep.er.com", "/a/b"), ("ugly.net", "/x")]
    rules = spark.createDataFrame([(1, "org", "/", "allow", False)], "tier int, host string, path string, verdict string, canonical boolean")
    urls = ["http://bad.org", "http://www.bad.org:80", "http://a.bad.org./x", "http://notbad.org", "http://bad.org/x", "http://u@ugly.net:1/x/y", "http://ugly.net/", "http://bad.org.net", "http://org/", "http://bad.org:80/"]
    got = U.judge(spark.createDataFrame(list(enumerate(urls)), "page_id long, url string"), rules.union(listed)).collect()
    # a rule takes the host as it is written, so not one with a port or a closing dot
    want = ["block", "block", "block", "allow", "allow", "block", "allow", "allow", "allow", "block"]
    assert {r["page_id"]: r["verdict"] for r in got} == dict(enumerate(want))


def test_hosts_of_many_labels_take_linear_time(spark):
    df = spark.createDataFrame([(k, "http://" + "a." * n + "x.org/" + "p" * n) for k, n in enumerate((4_000, 30_000, 300_000))], "page_id long, url string")
    rules = spark.createDataFrame([(0, "x.org", "/p", "block")], "tier int, host string, path string, verdict string")
    start = time.time()
    assert U.judge(df, rules).filter(F.col("verdict") == "block").count() == 3
    assert time.time() - start < 20
