"""Extendible hashing of rows into byte-limited shards, in DataFrame operations only.

A row's key has a 60-bit hash. The directory is indexed by the leading bits of
that hash: a bucket is a bit prefix, and a bucket over its byte limit splits on
one more bit, until each fits. A row's shard is thus the shortest prefix of its
hash whose rows fit the limit, which depends on the rows alone.

Defined cases: a null text has 0 bytes; a null key hashes as an empty string; a
row larger than the limit gets a shard of its own key (``oversize`` is true);
repeated keys that hash alike and exceed the limit together go to numbered
overflow pages of that bucket; an empty table gives no shards. Other columns of
the input pass through; the operator's own columns replace any of the same name.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql import Window as W

from quadpost.llm.staging import written

HASH_BITS = 60
#: Bits that the first directory has beyond the number of shards of an even spread.
SLACK_BITS = 4
#: Bits added at a time where buckets are still too large.
STEP_BITS = 8
#: Shards' worth of bytes that one window of an overflow chain numbers.
CHAIN = 64


def key_hash(key: Column) -> Column:
    """The first 60 bits of the key's MD5."""
    return F.conv(F.substring(F.md5(F.coalesce(key.cast("string"), F.lit(""))), 1, HASH_BITS // 4), 16, 10).cast("long")


def _prefix(hashed: Column, depth: Column | int) -> Column:
    depth = F.lit(depth) if isinstance(depth, int) else depth
    return F.call_function("shiftright", hashed, (F.lit(HASH_BITS) - depth).cast("int"))


def _directory(cells: DataFrame, low: int, high: int, limit: int) -> DataFrame:
    """For each cell (a prefix of ``high`` bits): its bucket's depth in low..high, or null if all are too large.

    Bytes are summed by bucket, partial sums first. A bucket is a leaf if it fits and the
    one that it was split from did not; the directory has one entry for each of the
    cells that a leaf takes up.
    """
    tall = cells.select("bytes", "least", "most", "rows", F.explode(F.sequence(F.lit(low), F.lit(high))).alias("depth"), "cell")
    tall = tall.withColumn("prefix", F.call_function("shiftright", F.col("cell"), F.lit(high) - F.col("depth")))
    sums = tall.groupBy("depth", "prefix").agg(F.sum("bytes").alias("shard_bytes"), (F.min("least") == F.max("most")).alias("one_key"), F.sum("rows").alias("rows"))
    sums = written(sums.withColumn("fits", (F.col("shard_bytes") <= limit) | F.col("one_key")), "shard-buckets")
    born = sums.where(~F.col("fits")).select((F.col("depth") + 1).alias("depth"), F.explode(F.array(F.col("prefix") * 2, F.col("prefix") * 2 + 1)).alias("prefix"))
    leaves = sums.where("fits").join(born.unionByName(sums.where(F.col("depth") == low).select("depth", "prefix")), ["depth", "prefix"], "left_semi")
    wide = F.lit(high) - F.col("depth")
    first = F.call_function("shiftleft", F.col("prefix"), wide)
    entries = leaves.select(F.explode(F.sequence(first, first + F.call_function("shiftleft", F.lit(1).cast("long"), wide) - 1)).alias("cell"), "depth", "prefix", "shard_bytes", "rows", "one_key")
    large = sums.where((F.col("depth") == high) & ~F.col("fits")).select(F.col("prefix").alias("cell"), *[F.lit(None).cast(t).alias(c) for c, t in (("depth", "int"), ("prefix", "long"), ("shard_bytes", "long"), ("rows", "long"), ("one_key", "boolean"))])
    return entries.unionByName(large)


def assign_shards(df: DataFrame, key: str, size: Column, limit: int) -> DataFrame:
    """``df`` with columns shard (bits of its bucket), depth, page, n_bytes, shard_bytes, oversize.

    The directory is a table joined on the hash prefix; nothing is collected but
    two totals and, while buckets are too large, their number.
    """
    spark = df.sparkSession
    own = ["shard", "depth", "page", "n_bytes", "shard_bytes", "oversize"]
    rows = df.select(
        *[F.col(f"`{c}`") for c in df.columns if c not in own], F.coalesce(size, F.lit(0)).cast("long").alias("n_bytes"), key_hash(F.col(f"`{key}`")).alias("_q_hash")
    )
    total = rows.agg(F.sum("n_bytes")).first()[0] or 0
    high = min(HASH_BITS, max(0, math.ceil(math.log2(max(1.0, total / limit)))) + SLACK_BITS)
    low, left, found = 0, rows.select("_q_hash", "n_bytes"), None
    while True:
        cells = left.groupBy(_prefix(F.col("_q_hash"), high).alias("cell")).agg(
            F.sum("n_bytes").alias("bytes"), F.min("_q_hash").alias("least"), F.max("_q_hash").alias("most"), F.count("*").alias("rows")
        )
        level = written(_directory(cells, low, high, limit), "shard-directory")
        done = level.where("depth IS NOT NULL").select(F.lit(high).alias("high"), "*")
        found = done if found is None else found.unionByName(done)
        more = level.where("depth IS NULL").select("cell")
        if high == HASH_BITS or more.isEmpty():
            break
        low, at, high = high + 1, high, min(HASH_BITS, high + STEP_BITS)
        left = left.join(more, _prefix(F.col("_q_hash"), at) == F.col("cell"), "left_semi")
    # each directory level that has leaves is one equality join: a row meets its cell at one level only
    levels = [r[0] for r in found.select("high").distinct().orderBy("high").collect()]
    spots = F.explode(F.array(*[F.struct(F.lit(h).alias("high"), _prefix(F.col("_q_hash"), h).alias("cell")) for h in levels or [high]]))
    placed = (
        rows.withColumn("_q_spot", spots)
        .withColumns({"_q_high": F.col("_q_spot.high"), "_q_cell": F.col("_q_spot.cell")})
        .join(found.withColumnsRenamed({"high": "_q_high", "cell": "_q_cell", "prefix": "_q_prefix", "rows": "_q_rows", "one_key": "_q_one"}), ["_q_high", "_q_cell"])
    )
    out = placed.withColumn("shard", F.when(F.col("depth") == 0, F.lit("")).otherwise(F.lpad(F.bin("_q_prefix"), F.col("depth"), F.lit("0"))))
    out = out.withColumn("_q_chain", F.col("_q_one") & (F.col("_q_rows") > 1) & (F.col("shard_bytes") > limit))
    plain = out.where(~F.col("_q_chain")).withColumn("page", F.lit(0))
    keep = [c for c in rows.columns if not c.startswith("_q_")]
    cols = [*[F.col(f"`{c}`") for c in keep if c != "n_bytes"], "n_bytes", "shard", F.col("depth").cast("int").alias("depth"), F.col("page").cast("int").alias("page"), "shard_bytes", (F.col("shard_bytes") > limit).alias("oversize")]
    result = plain.select(*cols)
    if not found.where((F.col("one_key")) & (F.col("rows") > 1) & (F.col("shard_bytes") > limit)).isEmpty():
        result = result.unionByName(_chains(out.where("_q_chain"), limit).select(*cols))
    return result


def _chains(rows: DataFrame, limit: int) -> DataFrame:
    """Overflow pages for repeated keys: each chain is dealt to salts, and each salt numbers its own rows."""
    salted = written(
        rows.withColumn("_q_salt", F.pmod(F.xxhash64(F.monotonically_increasing_id()), F.greatest(F.lit(1), F.ceil(F.col("shard_bytes") / (CHAIN * limit))))), "shard-chains"
    )
    by = W.partitionBy("shard", "_q_salt").orderBy("n_bytes")
    most = F.max("n_bytes").over(W.partitionBy("shard", "_q_salt"))
    room = F.lit(limit) - most
    before = F.sum("n_bytes").over(by.rowsBetween(W.unboundedPreceding, -1))
    numbered = salted.withColumn("_q_page", F.when(room >= most, F.floor(F.coalesce(before, F.lit(0)) / F.greatest(room, F.lit(1)))).otherwise(F.row_number().over(by) - 1))
    spot = ["shard", "_q_salt", "_q_page"]
    numbered = numbered.withColumn("shard_bytes", F.sum("n_bytes").over(W.partitionBy(*spot)))
    # one row per page is numbered, not one per row of a repeated key
    pages = numbered.select(*spot).distinct().withColumn("page", F.row_number().over(W.partitionBy("shard").orderBy("_q_salt", "_q_page")))
    return numbered.join(pages, spot)


def write_shards(assigned: DataFrame, path: str, files: int) -> None:
    """One folder per first bits, rows of a shard together; shards stay within files dealt by shard."""
    assigned.repartition(files, "shard", "page").sortWithinPartitions("shard", "page").write.parquet(path)
