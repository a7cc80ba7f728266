"""Cost measures: the comparison table of the three methods as formulas, and counts on actual reports."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bounds

#: method: measure: text over n, x (domain size), eps, beta. Logarithmic factors are left out where the theory leaves them.
COSTS = {
    "main": {"server_time": "n", "user_time": "1", "server_memory": "sqrt(n)", "user_memory": "1", "communication": "1", "public_bits": "1", "error": bounds.FORMULAS["main_error"]},
    "single_hash": {"server_time": "n", "user_time": "1", "server_memory": "sqrt(n)", "user_memory": "1", "communication": "1", "public_bits": "1", "error": bounds.FORMULAS["single_hash_error"]},
    "oldest": {"server_time": "pow(n, 2.5)", "user_time": "pow(n, 1.5)", "server_memory": "n * n", "user_memory": "pow(n, 1.5)", "communication": "1", "public_bits": "pow(n, 1.5)", "error": bounds.FORMULAS["oldest_error"]},
}


def table(grid: DataFrame) -> DataFrame:
    """n, x, eps, beta, method, measure, value for a grid (n, x, eps, beta) of doubles."""
    rows = F.array(*[F.struct(F.lit(m).alias("method"), F.lit(k).alias("measure"), F.expr(t).cast("double").alias("value")) for m, c in COSTS.items() for k, t in c.items()])
    return grid.select("n", "x", "eps", "beta", F.explode(rows).alias("r")).select("n", "x", "eps", "beta", "r.method", "r.measure", F.round("r.value", 4).alias("value"))


def table_sql(grid: str) -> str:
    return " UNION ALL ".join(f"SELECT n, x, eps, beta, '{m}' AS method, '{k}' AS measure, round(CAST({t} AS DOUBLE), 4) AS value FROM ({grid})" for m, c in COSTS.items() for k, t in c.items())


def server_memory(coordinate_sums: DataFrame, final_sums: DataFrame) -> DataFrame:
    """Rows and bytes of the sums that a server keeps (8 bytes each), those of the coordinates and of the final oracle."""
    kept = coordinate_sums.select("s").unionAll(final_sums.select("s"))
    return kept.agg(F.count("*").alias("rows"), (F.count("*") * 8).alias("bytes"))


def message_bits(reports: DataFrame, columns: list[str]) -> DataFrame:
    """For each column of a report, the bits that its largest value takes."""
    longest = [F.ceil(F.log2(F.max(F.abs(F.col(c))) + 1)).cast("long").alias(c) for c in columns]
    row = reports.agg(*longest)
    return row.select(F.explode(F.array(*[F.struct(F.lit(c).alias("field"), F.col(c).alias("bits")) for c in columns])).alias("x")).select("x.field", "x.bits")


def plan_costs(spark: SparkSession, plan) -> DataFrame:
    """Counted costs of a plan: what server, user and channel do."""
    import math

    k = 1 << plan.cell_bits
    rows = [
        ("server sums", float(plan.code.m * k + plan.oracle_rows * (1 << plan.oracle_bits))), ("server transform operations", float(plan.code.m * k * plan.cell_bits + plan.oracle_rows * plan.oracle_bits * (1 << plan.oracle_bits))),
        ("server reports read", float(plan.n)), ("user parities", float(plan.code.s + 2)), ("user hashes", float(plan.code.d + 3)), ("report sign bits", 2.0),
        ("report public bits", float(math.ceil(math.log2(plan.code.m)) + plan.cell_bits + math.ceil(math.log2(plan.oracle_rows)) + plan.oracle_bits)), ("user parameters", float(3 * plan.code.m + plan.code.s * plan.code.m + 6 * plan.oracle_rows)),
    ]
    return spark.createDataFrame(rows, "measure string, value double")
