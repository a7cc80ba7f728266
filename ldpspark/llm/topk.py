"""Exact top-k search: tiled matrix products of query blocks and shards, partial selection in each tile, tree merging.

Queries are dealt into blocks of about ``block_bytes``, candidates into shards of about ``shard_bytes`` (smaller where that
would leave cores idle). One shuffle brings each block and each shard together. A task multiplies the block with tile after
tile of its shard and keeps, for each query, the ``k`` best so far, ties going to the smaller id. The lists of the shards
are merged in a tree: each level joins the lists of a query over at most ``fan_in`` neighbouring shards, so no merge holds
more than ``fan_in * k`` entries, whatever the number of shards. Equal candidate rows are counted before they are dealt, so
neither a very common vector nor a very common id fills a shard.

Vectors are whole numbers floor(scale * x). Products are formed in floating point while no partial sum can reach 2^53,
else in Python integers, so scores are exact; scores beyond 64 bits are an error.

Defined results: vectors that are null or hold a null or non-finite component take no part; vectors are compared with those
of their own length; rows with the query's own id are no candidates of it; repeated candidate rows count one by one; of
several vectors of a query's id the least is the query; fewer candidates than k give all of them; an empty table gives no
rows. Null ids are out.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common as C

BLOCK_BYTES, SHARD_BYTES, LEAST_BYTES, TILE, FAN_IN = 8 << 20, 64 << 20, 1 << 20, 2048, 16


def whole(vectors: pa.ChunkedArray, scale: int) -> np.ndarray:
    """Matrix of floor(scale * x) of usable vectors of one length."""
    held = vectors.combine_chunks()
    return np.floor(scale * held.flatten().to_numpy(zero_copy_only=False).astype(np.float64)).reshape(len(held), -1)


def scores(queries: np.ndarray, tile: np.ndarray) -> np.ndarray:
    """Exact integer products, queries x tile."""
    bound = queries.shape[1] * np.abs(queries).max(initial=0) * np.abs(tile).max(initial=0)
    if bound < 2**53:
        return (queries @ tile.T).astype(np.int64)
    big = np.array([[int(x) for x in q] for q in queries], object) @ np.array([[int(x) for x in t] for t in tile], object).T
    return big.astype(np.int64)


def best(score: np.ndarray, ids: np.ndarray, valid: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The k best of each row by (score falling, id rising), invalid ones last."""
    if score.shape[1] > 4 * k:
        # a first cut by score alone keeps all ties at the k-th place
        floor = np.iinfo(np.int64).min
        s = np.where(valid, score, floor)
        least = np.partition(s, -k, axis=1)[:, -k][:, None]
        keep = (s >= least).any(axis=0) if (s >= least).sum() > 8 * k * len(s) else None
        if keep is None:
            width = int((s >= least).sum(axis=1).max())
            at = np.argpartition(-(s >= least).astype(np.int8), width - 1, axis=1)[:, :width] if width < s.shape[1] else np.tile(np.arange(s.shape[1]), (len(s), 1))
            score, ids, valid = (np.take_along_axis(x, at, axis=1) for x in (score, ids, valid))
        else:
            score, ids, valid = score[:, keep], ids[:, keep], valid[:, keep]
    order = np.lexsort((ids, -score.astype(np.float64) if np.abs(score).max(initial=0) < 2**53 else -score, ~valid), axis=1)[:, :k]
    return tuple(np.take_along_axis(x, order, axis=1) for x in (score, ids, valid))


def top(qids: np.ndarray, queries: np.ndarray, ids: np.ndarray, candidates: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(scores, ids, valid) of the k best candidates of each query, tile by tile."""
    held: list[list[np.ndarray]] = []
    for q in range(0, len(qids), 1024):
        at = slice(q, q + 1024)
        now = [np.zeros((len(qids[at]), 0), x) for x in (np.int64, np.int64, bool)]
        for lo in range(0, len(ids), TILE):
            own = ids[lo : lo + TILE]
            s = best(scores(queries[at], candidates[lo : lo + TILE]), np.broadcast_to(own, (len(qids[at]), len(own))), own[None, :] != qids[at][:, None], k)
            now = list(best(*(np.concatenate([x, y], axis=1) for x, y in zip(now, s, strict=True)), k))
        held.append(now)
    return tuple(np.concatenate([h[j] for h in held]) for j in range(3))


def search(
    candidates: DataFrame, is_query: Column, *, id_col: str = "vec_id", vector_col: str = "embedding", k: int = 20, scale: int = 64,
    block_bytes: int = BLOCK_BYTES, shard_bytes: int = SHARD_BYTES, least_bytes: int = LEAST_BYTES, fan_in: int = FAN_IN,
) -> DataFrame:
    """query_id, rank (from 1), id, score: the k best candidates of every row for which ``is_query`` holds."""
    spark = candidates.sparkSession
    rows = candidates.select(F.col(id_col).cast("long").alias("i"), F.col(vector_col).alias("v"), is_query.alias("q"))
    rows = rows.filter("i is not null and v is not null and forall(v, x -> x is not null and not isnan(x) and abs(x) < double('infinity'))").withColumn("n", F.size("v"))
    queries = rows.filter("q").groupBy("i").agg(F.min("v").alias("v")).withColumn("n", F.size("v"))
    sizes = rows.groupBy("n").agg(F.count("*").alias("rows"), F.count_if("q").alias("queries"))
    size, cores = F.col("n") * 8, spark.sparkContext.defaultParallelism
    blocks = F.greatest(F.lit(1), F.ceil(F.col("queries") * size / block_bytes))
    # as many shards as their size asks for; more, for all cores, while they are not too small
    shards = F.greatest(F.lit(1), F.ceil(F.col("rows") * size / shard_bytes), F.least(F.ceil(F.lit(2 * cores) / blocks), F.floor(F.col("rows") * size / least_bytes)))
    sizes = C.stored(sizes.filter("queries > 0").select("n", blocks.cast("int").alias("blocks"), shards.cast("int").alias("shards")), "sizes")
    most = sizes.agg(F.max("shards")).first()[0]
    if most is None:
        return spark.createDataFrame([], "query_id long, rank int, id long, score long")
    sizes = C.small(sizes)
    left = queries.join(sizes, "n").select("n", "i", "v", F.pmod(F.xxhash64("i"), "blocks").cast("int").alias("block"), F.explode(F.sequence(F.lit(0), F.col("shards") - 1)).alias("shard"))
    counted = rows.groupBy(F.col("i").alias("c"), F.col("v").alias("w")).agg(F.least(F.count("*"), F.lit(k)).cast("int").alias("times")).withColumn("n", F.size("w"))
    right = counted.join(sizes, "n").select(F.col("n").alias("n"), "c", "w", "times", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("block"), F.pmod(F.xxhash64("c", "w"), "shards").cast("int").alias("shard"))

    def pair(key: tuple, block: pa.Table, shard: pa.Table) -> pa.Table:
        if not block.num_rows or not shard.num_rows:
            return pa.table({"query_id": pa.array([], pa.int64()), "shard": pa.array([], pa.int32()), "top": pa.array([], pa.list_(pa.struct([("s", pa.int64()), ("i", pa.int64())])))})
        qids, times = block.column("i").to_numpy(), shard.column("times").to_numpy()
        score, ids, valid = top(qids, whole(block.column("v"), scale), np.repeat(shard.column("c").to_numpy(), times), np.repeat(whole(shard.column("w"), scale), times, axis=0), k)
        offsets = pa.array(np.concatenate(([0], np.cumsum(valid.sum(axis=1)))).astype(np.int32))
        lists = pa.ListArray.from_arrays(offsets, pa.StructArray.from_arrays([pa.array(-score[valid]), pa.array(ids[valid])], ["s", "i"]))
        return pa.table({"query_id": pa.array(qids), "shard": pa.array(np.full(len(qids), key[2].as_py(), np.int32)), "top": lists})

    keys = ("n", "block", "shard")
    tops = left.groupBy(*keys).cogroup(right.groupBy(*keys)).applyInArrow(pair, "query_id bigint, shard int, top array<struct<s:bigint,i:bigint>>")
    for _ in range(max(1, math.ceil(math.log(max(2, most), fan_in)))):
        tops = tops.groupBy("query_id", F.floor(F.col("shard") / fan_in).alias("shard")).agg(F.slice(F.array_sort(F.flatten(F.collect_list("top"))), 1, k).alias("top"))
    found = tops.select("query_id", F.posexplode("top").alias("p", "t"))
    return found.select("query_id", (F.col("p") + 1).cast("int").alias("rank"), F.col("t.i").alias("id"), (-F.col("t.s")).alias("score"))


def op3_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contract: queries are the rows whose id is divisible by 20, k is 20, components are floor(64 x)."""
    found = search(C.table(spark, sf_dir, "embeddings"), F.col("vec_id") % 20 == 0)
    return found.withColumnRenamed("id", "vec_id").select("query_id", "rank", "vec_id", "score")


OP3_SQL = """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(64 * CAST(x AS DOUBLE))) AS e FROM embeddings
  WHERE embedding IS NOT NULL AND list_bool_and(list_transform(embedding, lambda x: x IS NOT NULL AND isfinite(x)))),
s AS (SELECT q.vec_id AS query_id, c.vec_id, CAST(list_inner_product(q.e, c.e) AS BIGINT) AS score
  FROM v q JOIN v c ON q.vec_id % 20 = 0 AND q.vec_id <> c.vec_id),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS n FROM s)
SELECT query_id, CAST(n AS INTEGER) AS rank, vec_id, score FROM r WHERE n <= 20
"""
