"""``ldp_reports``: a Python data source that replays a transcript's sums as single reports, for load tests.

Options: ``users``, ``eps``, ``bits``, ``seed``, ``partitions`` and ``items`` (comma-joined, drawn in turn). A partition
makes its own users' reports; nothing is held but the row being made.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class Span(InputPartition):
    def __init__(self, lo: int, hi: int):
        self.lo, self.hi = lo, hi


class ReportReader(DataSourceReader):
    def __init__(self, options: dict):
        self.users, self.eps, self.bits = int(options.get("users", 1000)), float(options.get("eps", 1.0)), int(options.get("bits", 6))
        self.seed, self.parts = int(options.get("seed", 1)), int(options.get("partitions", 4))
        self.items = [int(x) for x in options.get("items", "1,2,3").split(",")]

    def partitions(self) -> list[Span]:
        step = -(-self.users // self.parts)
        return [Span(lo, min(self.users, lo + step)) for lo in range(0, self.users, step)]

    def read(self, partition: Span) -> Iterator[tuple[int, int, int]]:
        limit = math.floor(math.exp(self.eps) / (math.exp(self.eps) + 1) * (1 << 52))
        for user in range(partition.lo, partition.hi):
            g = hashlib.md5(f"direct:{self.seed}:{user}".encode()).hexdigest()
            r, item = int(g[:8], 16) % (1 << self.bits), self.items[user % len(self.items)]
            sign = (1 - 2 * ((r & item).bit_count() % 2)) * (1 if int(g[8:21], 16) < limit else -1)
            yield user, r, sign


class Reports(DataSource):
    @classmethod
    def name(cls) -> str:
        return "ldp_reports"

    def schema(self) -> str:
        return "user bigint, r bigint, s bigint"

    def reader(self, schema) -> ReportReader:
        return ReportReader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(Reports)
