"""SQL functions: scalar expressions, pandas functions and table functions for use in spark.sql."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


@F.pandas_udf(T.DoubleType())
def entropy_of(n: pd.Series) -> float:
    """Grouped aggregate: Shannon entropy of a column of weights."""
    w = n.to_numpy(float)
    w = w[w > 0]
    return float(-(w / w.sum() * np.log2(w / w.sum())).sum()) if len(w) else 0.0


@F.pandas_udf(T.DoubleType())
def read_bits(syms: pd.Series, bits: pd.Series) -> pd.Series:
    """Bits of a read under an order-0 table given as an array of bits by symbol."""
    return pd.Series([float(np.asarray(b)[np.asarray(s, int)].sum()) for s, b in zip(syms, bits)])


class Windows:
    """Table function: (ctx, sym) of all windows of an array with ``l`` previous values."""

    def eval(self, syms: list, l: int, m: int):  # noqa: E741
        for i in range(l, len(syms or [])):
            yield sum(syms[i - k] * m ** (k - 1) for k in range(1, l + 1)), syms[i]


class Runs:
    """Table function: (sym, length) of the runs of an array."""

    def eval(self, syms: list):
        at = 0
        syms = syms or []
        for i in range(1, len(syms) + 1):
            if i == len(syms) or syms[i] != syms[at]:
                yield syms[at], i - at
                at = i


def register(spark: SparkSession) -> None:
    """entropy_of, read_bits, windows_of, runs_of, and SQL functions ctx_code, bits_of, half_life where the server has them."""
    spark.udf.register("entropy_of", entropy_of)
    spark.udf.register("read_bits", read_bits)
    spark.udtf.register("windows_of", F.udtf(Windows, returnType="ctx long, sym int"))
    spark.udtf.register("runs_of", F.udtf(Runs, returnType="sym int, length int"))
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION half_life(eta DOUBLE) RETURNS DOUBLE RETURN -1 / log2(eta)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION bits_of(n DOUBLE, total DOUBLE) RETURNS DOUBLE RETURN log2(total / n)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION ctx_code(near INT, far INT, m INT) RETURNS BIGINT RETURN near + CAST(m AS BIGINT) * far")
