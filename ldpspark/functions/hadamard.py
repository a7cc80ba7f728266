"""Walsh-Hadamard transform of sums kept as rows, in one task a part or split over many."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Cells of a task: 2^22 doubles are 32 MB, of which the transform holds a few copies.
LOCAL_BITS = 22


def butterfly(x: np.ndarray) -> np.ndarray:
    """Transform along the last axis, whose length is a power of two."""
    x, h, n = x.astype(np.float64, copy=True), 1, x.shape[-1]
    while h < n:
        y = x.reshape(*x.shape[:-1], n // (2 * h), 2, h)
        x = np.stack([y[..., 0, :] + y[..., 1, :], y[..., 0, :] - y[..., 1, :]], axis=-2).reshape(x.shape)
        h *= 2
    return x


def dense(rows: np.ndarray, sums: np.ndarray, bits: int) -> np.ndarray:
    out = np.zeros(1 << bits)
    np.add.at(out, rows, sums)
    return out


def transform(sums: DataFrame, bits: int, local_bits: int = LOCAL_BITS) -> DataFrame:
    """(part, cell, total) for sums (part, r, s): total = sum over r of sign(r, cell) * s.

    Up to ``local_bits`` a part is one group. Beyond, the matrix is the product of one on the low and one on the high
    bits, see :func:`transform_blocks`.
    """
    if bits <= local_bits:

        def whole(g: pd.DataFrame) -> pd.DataFrame:
            t = butterfly(dense(g["r"].to_numpy(), g["s"].to_numpy(), bits))
            return pd.DataFrame({"part": g["part"].iloc[0], "cell": np.arange(1 << bits), "total": t})

        return sums.select("part", "r", "s").groupBy("part").applyInPandas(whole, "part bigint, cell bigint, total double")
    finish = lambda part, first, t: pd.DataFrame({"part": part, "cell": first + np.arange(len(t)), "total": t})
    return transform_blocks(sums, bits, bits // 2, finish, "part bigint, cell bigint, total double", local_bits)


def transform_blocks(sums: DataFrame, bits: int, low: int, finish: Callable[[int, int, np.ndarray], pd.DataFrame], schema: str, local_bits: int | None = None) -> DataFrame:
    """``finish`` of runs of neighbouring cells, whole blocks of 2^low, given the part, the first cell and the totals.

    The high bits of the row are transformed first, for each value of the low bits, then the low bits within a block. A
    group of either step takes as many values or blocks as fit into 2^local_bits cells, and at least one.
    """
    high, local = bits - low, LOCAL_BITS if local_bits is None else local_bits
    values, blocks = (max(0, min(own, local - other)) for own, other in ((low, high), (high, low)))

    def block(g: pd.DataFrame, outer: str, inner: str, taken: int, size: int) -> tuple[int, np.ndarray]:
        first = int(g[outer].iloc[0]) >> taken << taken
        x = np.zeros((1 << taken, 1 << size))
        np.add.at(x, (g[outer].to_numpy() - first, g[inner].to_numpy()), g["s"].to_numpy())
        return first, butterfly(x)

    def upper(g: pd.DataFrame) -> pd.DataFrame:
        first, t = block(g, "lo", "hi", values, high)
        lo, hi = np.divmod(np.arange(t.size), 1 << high)
        return pd.DataFrame({"part": g["part"].iloc[0], "lo": first + lo, "hi": hi, "s": t.ravel()})

    def lower(g: pd.DataFrame) -> pd.DataFrame:
        first, t = block(g, "hi", "lo", blocks, low)
        return finish(int(g["part"].iloc[0]), first << low, t.ravel())

    cut = sums.select("part", F.shiftright("r", low).alias("hi"), F.col("r").bitwiseAND((1 << low) - 1).alias("lo"), F.col("s").cast("double").alias("s"))
    half = cut.groupBy("part", F.shiftright("lo", values)).applyInPandas(upper, "part bigint, lo bigint, hi bigint, s double")
    return half.groupBy("part", F.shiftright("hi", blocks)).applyInPandas(lower, schema)
