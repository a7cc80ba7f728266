"""Collection of reports from streams: windows, late data, one message a user, budgets, folding into stored sums."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ldpspark.functions.dialect import SPARK
from ldpspark.operators.oracle import DirectOracle

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``events`` as a stream of files (a pattern, as the table may be one file or a folder of files)."""
    return spark.readStream.schema(EVENTS).parquet(f"{sf_dir}/events.parque[t]")


def reports(events: DataFrame, oracle: DirectOracle) -> DataFrame:
    """user, ts, r, s: the event type reported through the small-domain oracle. Row-local, for streams and tables."""
    from ldpspark.sources.views import VIEWS

    item = VIEWS["u_event_type"][2](SPARK)
    drawn = events.select(F.col("event_id").alias("user"), "ts", F.expr(item).cast("long").alias("item")).filter("item is not null")
    r, s = oracle.row_sign(SPARK, "item", "user")
    return drawn.select("user", "ts", F.expr(r).alias("r"), F.expr(s).alias("s"))


def tumbling(reports: DataFrame, length: str = "1 day", late: str = "1 hour") -> DataFrame:
    """start, r, s, n of windows that don't overlap; rows later than the watermark are dropped."""
    w = F.window("ts", length)
    return reports.withWatermark("ts", late).groupBy(w, "r").agg(F.sum("s").alias("s"), F.count("*").alias("n")).select(F.col("window.start").alias("start"), "r", "s", "n")


def sliding(reports: DataFrame, length: str = "2 days", step: str = "1 day", late: str = "1 hour") -> DataFrame:
    w = F.window("ts", length, step)
    return reports.withWatermark("ts", late).groupBy(w, "r").agg(F.sum("s").alias("s"), F.count("*").alias("n")).select(F.col("window.start").alias("start"), "r", "s", "n")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """user_id, start, n of bursts of events."""
    w = F.session_window("ts", gap)
    return events.withWatermark("ts", late).groupBy("user_id", w).agg(F.count("*").alias("n")).select("user_id", F.col("session_window.start").alias("start"), "n")


def one_message(reports: DataFrame, late: str = "1 hour") -> DataFrame:
    """The first report of each user within the watermark."""
    return reports.withWatermark("ts", late).dropDuplicatesWithinWatermark(["user"])


def late_rows(batch: DataFrame, high: str, late: str) -> DataFrame:
    """Rows of a micro-batch that its watermark drops, counted."""
    return batch.filter(F.col("ts") < F.expr(f"timestamp'{high}' - interval {late}")).agg(F.count("*").alias("late"))


def ledger(events: DataFrame, eps: float, limit: float) -> DataFrame:
    """user_id, spent, refused: running budget of each user over the whole stream, kept as state."""

    def spend(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        spent, refused = state.get if state.exists else (0.0, 0)
        for frame in frames:
            for _ in range(len(frame)):
                if spent + eps <= limit + 1e-12:
                    spent += eps
                else:
                    refused += 1
        state.update((spent, refused))
        yield pd.DataFrame({"user_id": [key[0]], "spent": [spent], "refused": [refused]})

    return events.select("user_id", "event_id").groupBy("user_id").applyInPandasWithState(spend, "user_id long, spent double, refused long", "spent double, refused long", "update", "NoTimeout")


def with_rounds(reports: DataFrame, rounds: DataFrame) -> DataFrame:
    """Stream-static join: every report with the round (round, starts, ends) that holds its time."""
    return reports.join(F.broadcast(rounds), (F.col("ts") >= F.col("starts")) & (F.col("ts") < F.col("ends")))


def announced(reports: DataFrame, announcements: DataFrame, within: str = "1 hour", late: str = "2 hours") -> DataFrame:
    """Stream-stream interval join: reports of users up to ``within`` after an announcement (a_user, a_ts)."""
    a, b = announcements.withWatermark("a_ts", late), reports.withWatermark("ts", late)
    return b.join(a, (F.col("user") == F.col("a_user")) & (F.col("ts") >= F.col("a_ts")) & (F.col("ts") <= F.col("a_ts") + F.expr(f"interval {within}")))


def fold(stream: DataFrame, path: str, checkpoint: str):
    """Every micro-batch's sums written under its own number: a repeated batch overwrites itself, sums just add up."""

    def add(batch: DataFrame, number: int) -> None:
        batch.groupBy("r").agg(F.sum("s").alias("s"), F.count("*").alias("n")).write.mode("overwrite").parquet(f"{path}/batch={number}")

    return stream.writeStream.foreachBatch(add).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def folded(spark: SparkSession, path: str) -> DataFrame:
    """Sums over all micro-batches so far."""
    return spark.read.parquet(path).groupBy("r").agg(F.sum("s").alias("s"), F.sum("n").alias("n"))


def finished(stream: DataFrame, path: str, checkpoint: str, mode: str = "append") -> DataFrame:
    """Runs a stream over what is there now and returns the rows it has written."""
    spark = stream.sparkSession
    if mode == "append":
        q = stream.writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.read.schema(stream.schema).parquet(path)

    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")

    q = stream.writeStream.outputMode(mode).foreachBatch(put).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    last = spark.read.parquet(path)
    return last.filter(F.col("batch") == last.agg(F.max("batch")).first()[0]).drop("batch")
