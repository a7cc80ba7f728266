"""Transcripts, sums and shared folders."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir of the session; a temporary folder only where it is unset."""
    path = spark.conf.get("spark.checkpoint.dir", None)
    if not path:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        path = held.get() if held.isDefined() else None
    if not path:
        path = tempfile.mkdtemp(prefix="shared-")
        spark.sparkContext.setCheckpointDir(path)
    return f"{path.rstrip('/')}/{uuid.uuid4().hex}"


def write_transcript(reports: DataFrame, path: str, round_no: int = 0) -> str:
    """Reports by round and coordinate, so that one coordinate can be decoded again by itself."""
    reports.withColumn("round", F.lit(round_no)).write.mode("overwrite").partitionBy("round", "m").parquet(path)
    return path


def read_transcript(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path)


def import_reports(spark: SparkSession, path: str, kind: str, schema: str) -> DataFrame:
    """Reports from CSV or JSON files with a declared schema."""
    return spark.read.schema(schema).option("header", "true").format(kind).load(path)
