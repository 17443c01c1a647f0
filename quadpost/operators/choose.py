"""Choosing a codec for each block by its exact size."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from quadpost.functions.expressions import quad_bits, size_expr, value_bits

#: For speed, codecs from fast to slow in decoding as one core of the development machine had them (`fast_first` gives a machine's own order).
FAST_FIRST = ("ql_8_b", "ql_1_cu", "gvb", "quad_bp128", "g8cu", "vbyte", "packed_binary", "gamma", "rice")
SPEED_LOSS = 0.25


def fast_first(sweep: DataFrame) -> tuple[str, ...]:
    """Codecs from fast to slow in decoding, from the rows of a codec sweep (one row a codec and build)."""
    best = sweep.groupBy("codec").agg(F.max("decode_mis").alias("mis"))
    return tuple(r["codec"] for r in best.orderBy(F.desc("mis"), "codec").collect())


def choose_codec(df: DataFrame, candidates: tuple[str, ...], goal: str = "size", col: str = "values", order: tuple[str, ...] = FAST_FIRST) -> DataFrame:
    """``df`` with ``chosen``: the smallest of ``candidates``, ties by name; for goal "speed" the first of ``order`` that takes at most SPEED_LOSS more bits."""
    bound = df.withColumn("_q_bits", value_bits(F.col(col))).withColumn("_q_need", quad_bits(F.col("_q_bits")))
    each = F.struct(*[size_expr(n, F.col(col), F.col("_q_bits"), F.col("_q_need")).cast("long").alias(n) for n in candidates])
    sized = bound.withColumn("_q_sizes", each)
    sizes = {n: F.col("_q_sizes")[n] for n in candidates}
    best = F.array_min(F.array(*[F.struct(b.alias("bits"), F.lit(n).alias("codec")) for n, b in sizes.items()]))
    chosen = best["codec"]
    if goal != "size":
        for n in reversed([c for c in order if c in candidates]):
            chosen = F.when(sizes[n] <= best["bits"] * (1 + SPEED_LOSS), F.lit(n)).otherwise(chosen)
    return sized.withColumn("chosen", chosen).drop("_q_bits", "_q_need", "_q_sizes")
