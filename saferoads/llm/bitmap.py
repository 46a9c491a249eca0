"""A bitmap of fixed size that keeps most rows without a partner out of a shuffle.

It never decides a result: a set bit only means that a row may have a partner, and the join that follows is exact.
When the keys outgrow it, all rows pass and the join does the work alone.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from saferoads.llm.blocks import lean

BITS = 26


def bitmap_of(keys: DataFrame, column: str, bits: int = BITS) -> np.ndarray:
    """keys: a bigint column of hashes. 2^bits bits, in 64-bit words; at most 2^(bits - 6) rows reach the driver."""
    bit = F.col(column).bitwiseAND((1 << bits) - 1)
    words = (
        keys.select(F.shiftright(bit, 6).alias("w"), F.call_function("shiftleft", F.lit(1).cast("bigint"), bit.bitwiseAND(63).cast("int")).alias("v"))
        .groupBy("w").agg(F.bit_or("v").alias("v")).toArrow()
    )
    out = np.zeros(1 << (bits - 6), np.int64)
    out[words.column("w").to_numpy()] = words.column("v").to_numpy()
    return out.view(np.uint64)


def marked(hashes: np.ndarray, bitmap: np.ndarray) -> np.ndarray:
    bit = hashes.view(np.uint64) & np.uint64(len(bitmap) * 64 - 1)
    return (bitmap[bit >> np.uint64(6)] >> (bit & np.uint64(63)) & np.uint64(1)).astype(bool)


def keep_marked(df: DataFrame, column: str, bitmap: np.ndarray, wanted: bool = True) -> DataFrame:
    """Rows of df whose bit is set, or with wanted=False the others."""
    sent = df.sparkSession.sparkContext.broadcast(bitmap)

    @lean
    def run(batches):
        for batch in batches:
            keep = marked(batch.column(column).to_numpy(), sent.value)
            yield batch.filter(pa.array(keep if wanted else ~keep))

    return df.mapInArrow(run, df.schema)
