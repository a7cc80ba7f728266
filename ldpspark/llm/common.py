"""Helpers shared by the training-data operators: input shaping, shared folders, Arrow batches."""

from __future__ import annotations

import contextlib
import ctypes
import gc
import tempfile
import uuid
from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ldpspark.sources.ship import ship

#: Bytes that are not part of a word ``[^\x00-\x2F\x3A-\x60\x7B-\x7F]+`` become a blank, A-Z become a-z.
WORD_TABLE = bytes(
    c + 32 if 65 <= c <= 90 else c if 48 <= c <= 57 or 97 <= c <= 122 or c >= 128 else 32 for c in range(256)
)
#: Java / RE2 pattern of everything between such words, once A-Z are lower-cased.
NON_WORD = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def ascii_words(text: bytes | None) -> list[bytes]:
    """Lower-cased runs of ASCII letters, digits and non-ASCII bytes; null has none."""
    return text.translate(WORD_TABLE).split() if text else []


_CACHES: dict[str, Callable[[], None]] = {}


def own(name: str, clear: Callable[[], None]) -> None:
    """Called by an operator's step at its start in a Python worker, which Spark keeps for later tasks of any operator.

    What other operators have kept in this worker is let go, and freed memory goes back to the system.
    """
    _CACHES[name] = clear
    for other in [x for x in _CACHES if x != name]:
        _CACHES.pop(other)()
    gc.collect()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # a C library without this call
        ctypes.CDLL(None).malloc_trim(0)


def held_out(doc_id: Column, folds: int = 5) -> Column:
    """True for the fold crc32(doc_id as text) mod ``folds`` = 0 (a null id counts as empty text)."""
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % folds == 0


#: Rows of whole texts that go to a Python worker at a time; Spark's own value of 10,000 makes batches of tens of MB, twice in native memory.
BATCH_ROWS, BATCH_BYTES = 400, 1 << 20


def small_batches(spark: SparkSession) -> None:
    """Bounds Arrow batches (a session setting that can change at any time)."""
    if int(spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")) > BATCH_ROWS:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(BATCH_ROWS))
        spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(BATCH_BYTES))


def shared_dir(spark: SparkSession) -> str:
    """The folder that the cluster shares (spark.checkpoint.dir); a temporary one only where none is set and all runs on one machine."""
    small_batches(spark)
    path = spark.conf.get("spark.checkpoint.dir", None)
    if not path:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        path = held.get() if held.isDefined() else None
    if not path:
        if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
            raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        path = tempfile.mkdtemp(prefix="shared-")
        spark.sparkContext.setCheckpointDir(path)
    return path.rstrip("/")


def stored(df: DataFrame, name: str) -> DataFrame:
    """``df`` written as Parquet below the shared folder and read back: lineage ends at files all executors see."""
    path = f"{shared_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship(spark)
    small_batches(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def binary_list(column: pa.Array) -> list[bytes | None]:
    """String column as bytes, without decoding."""
    return column.cast(pa.large_binary() if pa.types.is_large_string(column.type) else pa.binary()).to_pylist()


def batches(
    df: DataFrame, step: Callable[[Iterator[pa.RecordBatch]], Iterable[pa.RecordBatch]], schema: str
) -> DataFrame:
    return df.mapInArrow(step, schema)


def uniform(*parts: Column) -> Column:
    """Keyed uniform number in [0, 1) of 52 bits: leading md5 digits of the colon-joined parts (null: empty)."""
    key = F.concat_ws(":", *[F.coalesce(p.cast("string"), F.lit("")) for p in parts])
    return F.conv(F.substring(F.md5(key), 1, 13), 16, 10).cast("long") / F.lit(float(1 << 52))


def small(df: DataFrame, rows: int = 200_000, weight: Column | None = None) -> DataFrame:
    """``df``, a stored table, with a broadcast hint if it is counted to have at most ``rows`` rows.

    weight: values of a row, for tables with arrays; then their sum is held to ten times ``rows`` as well.
    """
    if weight is None:
        return F.broadcast(df) if df.limit(rows + 1).count() <= rows else df
    n, values = df.agg(F.count("*"), F.sum(weight)).first()
    return F.broadcast(df) if n <= rows and (values or 0) <= 10 * rows else df


def join_counted(rows: DataFrame, counted: DataFrame, key: str, count: str, share: int = 50_000) -> DataFrame:
    """Inner join of ``rows`` with the stored table ``counted`` (one row a key, ``count`` the rows that hold it).

    Keys that hold over one in ``share`` of all rows, at most ``share`` of them whatever the data, are broadcast, so no
    task gets all rows of a hot key; the others are joined as Spark sees fit.
    """
    total = counted.agg(F.sum(count)).first()[0] or 0
    hot = F.col(count) > total / share
    if not counted.filter(hot).limit(1).count() or counted.limit(share + 1).count() <= share:
        return rows.join(small(counted, share), key)
    heavy = F.broadcast(counted.filter(hot))
    return rows.join(heavy, key).union(rows.join(heavy.select(key), key, "left_anti").join(counted.filter(~hot), key))
