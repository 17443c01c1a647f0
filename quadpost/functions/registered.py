"""Codec functions for SQL and for grouped aggregation."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


@F.pandas_udf(T.LongType())
def bits(names: pd.Series, values: pd.Series) -> pd.Series:
    """Bits that a codec takes for an array."""
    from quadpost.codecs.base import codec

    return pd.Series([codec(n).bits(np.asarray(v)) for n, v in zip(names, values, strict=True)])


def bits_of_group(name: str):
    """Bits per integer of a group's arrays."""

    @F.pandas_udf(T.DoubleType())
    def run(values: pd.Series) -> float:
        from quadpost.codecs.base import codec

        c = codec(name)
        return float(sum(c.bits(np.asarray(v)) for v in values)) / max(1, sum(len(v) for v in values))

    return run


@F.udtf(returnType="pos bigint, value bigint")
class Decode:
    """The values of one encoded block as rows."""

    def eval(self, name: str, n: int, ctrl: bytes, data: bytes, exc: bytes):
        from quadpost.codecs.base import Block, codec

        for pos, value in enumerate(codec(name).decode(Block(n, bytes(ctrl), bytes(data), bytes(exc))).tolist()):
            yield pos, value


def register(spark: SparkSession) -> None:
    spark.udf.register("quadpost_bits", bits)
    spark.udtf.register("quadpost_decode", Decode)
