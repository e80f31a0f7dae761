"""Python forms of mask functions, for comparison with the expressions, and SQL names."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from tierbit.functions.crc import code

#: A 32-bit de Bruijn word, whose top five bits name each shift.
DE_BRUIJN = 0x077CB531


def _shift_table() -> np.ndarray:
    table = np.zeros(32, np.int64)
    for i in range(32):
        table[(DE_BRUIJN << i & 0xFFFFFFFF) >> 27] = i
    return table


@F.pandas_udf(T.ArrayType(T.IntegerType()))
def debruijn_bits(masks: pd.Series) -> pd.Series:
    """Offsets of set bits of 32-bit masks, each lowest bit isolated and looked up."""
    table = _shift_table()
    m = masks.to_numpy(np.int64)
    out: list[list[int]] = [[] for _ in m]
    live = np.flatnonzero(m)
    m = m.copy()
    while len(live):
        low = m[live] & -m[live]
        at = 31 - table[(low * DE_BRUIJN & 0xFFFFFFFF) >> 27]
        for i, x in zip(live, at):
            out[i].append(int(x))
        m[live] ^= low
        live = live[m[live] != 0]
    return pd.Series([sorted(x) for x in out])


@F.pandas_udf(T.LongType())
def mask_or(masks: pd.Series) -> int:
    """Grouped OR, the counterpart of bit_or."""
    return int(np.bitwise_or.reduce(masks.to_numpy(np.int64))) if len(masks) else 0


def code_udf(k: int, r: int):
    @F.pandas_udf(T.StringType())
    def run(digests: pd.Series) -> pd.Series:
        return digests.map(lambda d: f"{code(bytes.fromhex(d), k, r):0{k // 4}x}")

    return run


@F.udtf(returnType=T.StructType([T.StructField("pos", T.LongType())]))
class DecodeMask:
    """Rows of positions for a leaf node and its mask."""

    def eval(self, node: int, mask: int, b: int):
        for i in range(b):
            if mask >> (b - 1 - i) & 1:
                yield (node * b + i,)


def register(spark: SparkSession, b: int = 32) -> None:
    """SQL names: tb_bits_on(mask), tb_rank(mask, offset) as SQL functions, tb_decode(node, mask, b) as a table function."""
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION tb_bits_on(mask BIGINT) RETURNS ARRAY<INT> RETURN filter(sequence(0, {b - 1}), i -> getbit(mask, {b - 1} - i) = 1)")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION tb_rank(mask BIGINT, place INT) RETURNS INT RETURN CASE WHEN place = 0 THEN 0 ELSE bit_count(shiftrightunsigned(mask, {b} - place)) END")
    spark.udtf.register("tb_decode", DecodeMask)
