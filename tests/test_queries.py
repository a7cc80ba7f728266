"""Every query against DuckDB where it has SQL, and invariants where it has none."""

import datetime
import math

import pytest
from pyspark.sql import functions as F

from ldpspark import workloads as W
from ldpspark.operators import decode, measure
from ldpspark.operators.heavy import ExpanderHeavyHitters
from ldpspark.operators.oracle import DirectOracle, exact_counts
from ldpspark.operators.randomizers import unbias
from ldpspark.plans import planner
from ldpspark.sources import sinks, views


def plain(v):
    if isinstance(v, float):
        return repr(v + 0.0)
    if isinstance(v, datetime.datetime):
        return v.replace(tzinfo=None)
    return v


@pytest.mark.parametrize("name", sorted(W.ORACLES))
def test_against_sql(spark, duck, sf, name):
    df = W.QUERIES[name](spark, sf)
    cols = sorted(df.columns)
    ours = sorted(str(tuple(plain(r[c]) for c in cols)) for r in df.collect())
    rel = duck.sql(W.ORACLES[name])
    assert sorted(rel.columns) == cols
    names = list(rel.columns)
    theirs = sorted(str(tuple(plain(dict(zip(names, r, strict=True))[c]) for c in cols)) for r in rel.fetchall())
    assert ours == theirs


@pytest.mark.parametrize("name", sorted(set(W.QUERIES) - set(W.ORACLES)))
def test_runs(spark, sf, name):
    assert W.QUERIES[name](spark, sf).limit(3).count() > 0


def test_views_have_one_row_a_user(spark, sf):
    for name in ("u_planted", "u_order_status", "u_person", "u_word", "v_signs16"):
        assert views.assert_one_message(views.view(spark, sf, name)).limit(1).count() == 0


def test_server_needs_the_transcript_only(spark, sf, tmp_path):
    users = views.view(spark, sf, "u_planted")
    h = ExpanderHeavyHitters(W.plan_for(60_000))
    path = sinks.write_transcript(h.reports(users), str(tmp_path / "t"))
    back = sinks.read_transcript(spark, path).drop("user")
    found = {r["item"]: r["est"] for r in h.from_reports(back.withColumn("m", F.col("m").cast("long"))).collect()}
    assert set(found) == {11, 2222, 40404}


def test_no_python_before_the_sums(spark, sf):
    h = ExpanderHeavyHitters(W.plan_for(60_000))
    plan = h.coordinate_sums(h.reports(views.view(spark, sf, "u_planted")))._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Pandas" not in plan and "partial_sum" in plan


def test_oracle_error_over_seeds(spark, sf):
    users = views.view(spark, sf, "u_qty")
    truth = {r[0]: r[1] for r in exact_counts(users).collect()}
    errors = []
    for seed in range(6):
        o = DirectOracle(1.0, 6, seed=seed, role="seeds")
        errors += [r["est"] - truth[r["item"]] for r in o.estimate(o.fit(o.reports(users)), users).collect()]
    sd = unbias(1.0) * math.sqrt(60_000)
    assert abs(sum(errors) / len(errors)) <= 5 * sd / math.sqrt(len(errors))
    assert 0.8 <= math.sqrt(sum(e * e for e in errors) / len(errors)) / sd <= 1.25


def test_events_imply_recovery(spark, sf):
    users = views.view(spark, sf, "u_planted")
    for seed in (7, 8):
        h = ExpanderHeavyHitters(planner.plan(60_000, 4.0, seed=seed))
        found = {r["item"] for r in h.run(users).collect()}
        assert {11, 2222} <= found and len(found) <= 4


def test_components_in_a_task_and_by_rounds_agree(spark, sf, tmp_path):
    lists = W._lists(spark, sf).filter("b < 40")
    edges = decode.layered_edges(lists, W.CODE)
    n = iter(range(100))

    def store(df):
        path = str(tmp_path / str(next(n)))
        df.write.parquet(path)
        return spark.read.parquet(path)

    a = decode.components(lists, edges, W.CODE).collect()
    b = decode.components_by_rounds(lists, edges, W.CODE, store).collect()
    assert sorted(map(tuple, a)) == sorted(map(tuple, b))


def test_split_transform_agrees(spark, sf):
    from ldpspark.functions.hadamard import transform

    o = DirectOracle(2.0, 6)
    sums = o.fit(o.reports(views.view(spark, sf, "u_qty"))).withColumn("part", F.lit(0).cast("long"))
    a = {r["cell"]: r["total"] for r in transform(sums, 6).collect()}
    b = {r["cell"]: r["total"] for r in transform(sums, 6, local_bits=3).collect()}
    assert a == pytest.approx(b)


def test_cap_keeps_exactly_the_best(spark):
    rows = [(0, 0, y, y, float(y % 5)) for y in range(20)]
    df = spark.createDataFrame(rows, "b long, m long, y long, z long, est double")
    kept = decode.cap_lists(df, 6).collect()
    assert len(kept) == 6 and {r["y"] for r in kept} == {4, 9, 14, 19, 3, 8}
    assert decode.unique_y(df.union(df.filter("y = 1"))).collect()[0]["held"] == 2


def test_measures(spark):
    answer = spark.createDataFrame([(1, 10.0), (2, 4.0)], "item long, est double")
    truth = spark.createDataFrame([(1, 12), (3, 7)], "item long, f long")
    r = measure.list_error(answer, truth).first()
    assert (r["max_error"], r["largest_missed"], r["list_size"]) == (4.0, 7, 2)
    r = measure.recall(answer, truth, 7).first()
    assert (r["heavy"], r["found"], r["false_positives"]) == (2, 1, 1)


def test_late_rows_and_duplicates_of_a_stream(spark, sf, tmp_path):
    from ldpspark.streaming import collect

    batch = collect.reports(spark.read.parquet(f"{sf}/events.parquet"), W.STREAM)
    high = batch.agg(F.max("ts")).first()[0]
    assert collect.late_rows(batch, str(high), "1 day").first()["late"] == batch.filter(F.col("ts") < F.lit(high) - F.expr("interval 1 day")).count()


def test_error_shrinks_with_eps_and_grows_with_n(spark, sf):
    e = {r["eps"]: r["rmse"] for r in W.error_by_eps(spark, sf).collect()}
    assert e[0.5] > e[1.0] > e[2.0] > e[4.0]
    n = sorted((r["n"], r["rmse"]) for r in W.error_by_n(spark, sf).collect())
    assert n[0][1] < n[-1][1]


def test_hashes_agree_with_python(spark):
    from ldpspark.functions.dialect import SPARK, coefficients, linear, linear_value, polynomial, polynomial_value

    items = [0, 1, 77, 2**31 - 1, 2**31, 2**45 + 12345, 2**62 - 1]
    poly, (a0, a1, b) = coefficients("p", 1, 8), coefficients("l", 1, 3)
    df = spark.createDataFrame([(x,) for x in items], "item long")
    for r in df.select("item", F.expr(polynomial(SPARK, "item", poly)).alias("p"), F.expr(linear(SPARK, "item", str(a0), str(a1), str(b))).alias("l")).collect():
        assert r["p"] == polynomial_value(r["item"], poly) and r["l"] == linear_value(r["item"], a0, a1, b)
