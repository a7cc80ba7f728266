"""SQL surface: functions for use in spark.sql, and table functions."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import Row, SparkSession
from pyspark.sql.functions import udtf

from .dialect import SPARK


def register(spark: SparkSession, eps: float = 1.0, seed: int = 1, groups: int = 7) -> list[str]:
    """Temporary SQL functions ldp_uniform, ldp_bit, ldp_group, ldp_cell and the table functions; returns their names.

    The scalar ones are SQL expressions, so the optimizer inlines them.
    """
    import math

    from ldpspark.operators.code import ExpanderCode

    keep = math.exp(eps) / (math.exp(eps) + 1)
    code = ExpanderCode()
    bodies = {
        "ldp_uniform(role STRING, seed BIGINT, k STRING) RETURNS DOUBLE": f"{SPARK.digits('md5(concat_ws(chr(58), role, cast(seed as string), k))', 1, 13)} / {float(1 << 52)!r}D",
        "ldp_bit(x BIGINT, k STRING) RETURNS BIGINT": f"CASE WHEN {SPARK.below(SPARK.digest('bit', seed, 'k'), 1, keep)} THEN x ELSE 1 - x END",
        "ldp_group(k STRING) RETURNS BIGINT": f"{SPARK.digits(SPARK.digest('expander', seed, 'k'), 1, 8)} % {groups}",
        "ldp_cell(x BIGINT, m BIGINT) RETURNS BIGINT": f"{code.y_text(SPARK, 'x', 'm')} * {1 << code.z_bits} + {code.z_text(SPARK, 'x', 'm')}",
    }
    for head, body in bodies.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
    spark.udtf.register("encode_item", encode_item)
    spark.udtf.register("domain_range", domain_range)
    return [h.split("(")[0] for h in bodies] + ["encode_item", "domain_range"]


@udtf(returnType="m int, y int, z long")
class encode_item:  # noqa: N801
    """Rows (m, y, z) of an item's code word."""

    def __init__(self) -> None:
        from ldpspark.operators.code import ExpanderCode

        self.code = ExpanderCode()

    def eval(self, item: int) -> Iterator[tuple[int, int, int]]:
        for m, (y, z) in enumerate(self.code.encode(item)):
            yield m, y, z


@udtf(returnType="item long")
class domain_range:  # noqa: N801
    """All items of a small domain."""

    def eval(self, bits: int) -> Iterator[tuple[int]]:
        for i in range(1 << bits):
            yield (i,)


@udtf(returnType="b long, item long, agree int")
class decode_lists:  # noqa: N801
    """Items of the buckets' lists, given as a table argument (b, m, y, z) partitioned by b."""

    def __init__(self) -> None:
        self.rows: dict[int, list[tuple[int, int, int]]] = {}

    def eval(self, row: Row) -> None:
        self.rows.setdefault(row["b"], []).append((row["m"], row["y"], row["z"]))

    def terminate(self) -> Iterator[tuple[int, int, int]]:
        from ldpspark.operators.code import ExpanderCode
        from ldpspark.operators.decode import Bucket

        for b, rows in self.rows.items():
            for item, n in Bucket(ExpanderCode(), rows).decode(4).items():
                yield b, item, n
