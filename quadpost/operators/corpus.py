"""Texts to postings, gaps and blocks."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from quadpost.sources.shared import written

TOKEN_BREAK = r"[^\p{L}\p{N}]+"
BLOCK = 512
#: Lists shorter than this are left to variable byte codes.
SHORT_LIST = 64
#: Documents of one shard. A window never sees more of a list than a shard's part,
#: and gaps start again at the shard's first possible document, so they fit 32 bits.
SHARD_DOCS = 1 << 20


def tokens(docs: DataFrame) -> DataFrame:
    """(doc_id, term), one row per token."""
    return docs.select("doc_id", F.explode(F.split(F.lower("text"), TOKEN_BREAK)).alias("term")).where("term != ''")


def postings(docs: DataFrame) -> DataFrame:
    """(term, doc_id, tf); counted on the map side first."""
    return tokens(docs).groupBy("term", "doc_id").agg(F.count("*").alias("tf"))


def sharded_postings(docs: DataFrame, shard_docs: int = SHARD_DOCS) -> DataFrame:
    """(term, shard, doc_id, tf) of ``postings``, dealt once by (term, shard): windows, blocks and counts of a shard's list need no further exchange.

    A text's tokens are sorted and counted where the text is read; the sum is for an id with several texts.
    """
    words = docs.select("doc_id", F.sort_array(F.split(F.lower("text"), TOKEN_BREAK)).alias("t"))
    starts = F.filter(F.sequence(F.lit(0), F.size("t") - 1), lambda i: (i == 0) | (F.get("t", i) != F.get("t", i - 1)))
    words = words.select("doc_id", "t", starts.alias("starts"))
    runs = F.transform("starts", lambda at, i: F.struct(F.get("t", at).alias("term"), (F.coalesce(F.get("starts", i + 1), F.size("t")) - at).cast("long").alias("tf")))
    rows = words.select("doc_id", F.explode(runs).alias("x")).select("x.term", F.floor(F.col("doc_id") / shard_docs).alias("shard"), "doc_id", "x.tf").where("term != '' AND shard IS NOT NULL")
    return rows.repartition("term", "shard").groupBy("term", "shard", "doc_id").agg(F.sum("tf").alias("tf"))


def doc_lengths(docs: DataFrame) -> DataFrame:
    words = F.filter(F.split(F.lower("text"), TOKEN_BREAK), lambda t: t != "")
    return docs.select("doc_id", F.size(words).cast("long").alias("n")).groupBy("doc_id").agg(F.sum("n").alias("len")).where("len > 0")


def dictionary(found: DataFrame) -> DataFrame:
    """(term, df, cf, n_blocks) of postings."""
    return found.groupBy("term").agg(F.count("*").alias("df"), F.sum("tf").alias("cf")).withColumn("n_blocks", F.ceil(F.col("df") / BLOCK))


def long_lists(found: DataFrame, least: int = SHORT_LIST) -> DataFrame:
    """Postings of terms with at least ``least`` of them.

    The frequencies are one aggregation and an equality join on the term, so a head
    term's postings may be split over tasks.
    """
    keep = found.groupBy("term").count().where(F.col("count") >= least).select("term")
    return found.join(keep, "term", "left_semi")


def _within():
    return W.partitionBy("term", "shard").orderBy("doc_id")


def gaps(found: DataFrame, shard_docs: int = SHARD_DOCS) -> DataFrame:
    """(term, shard, pos, doc_id, gap, tf): gaps start from a virtual predecessor before the shard's first document."""
    sharded = found if "shard" in found.columns else found.withColumn("shard", F.floor(F.col("doc_id") / shard_docs))
    before = F.lag("doc_id").over(_within())
    return sharded.select(
        "term", "shard", (F.row_number().over(_within()) - 1).cast("long").alias("pos"), "doc_id", (F.col("doc_id") - F.coalesce(before, F.col("shard") * shard_docs - 1)).alias("gap"), "tf"
    )


def blocks(rows: DataFrame, size: int = BLOCK) -> DataFrame:
    """(term, shard, block, n, first_doc, last_doc, gaps, tfs): at most ``size`` postings each, in order."""
    numbered = rows.withColumn("block", F.floor(F.col("pos") / size))
    held = F.sort_array(F.collect_list(F.struct("pos", "gap", "tf")))
    return (
        numbered.groupBy("term", "shard", "block")
        .agg(F.count("*").cast("int").alias("n"), F.min("doc_id").alias("first_doc"), F.max("doc_id").alias("last_doc"), held.alias("h"))
        .select("term", "shard", "block", "n", "first_doc", "last_doc", F.col("h.gap").alias("gaps"), F.col("h.tf").alias("tfs"))
    )


def doc_ids(rows: DataFrame, shard_docs: int = SHARD_DOCS) -> DataFrame:
    """Document ids again from gaps: a running sum inside the shard."""
    so_far = _ordered_sum("gap")
    return rows.select("term", "shard", "pos", (F.col("shard") * shard_docs - 1 + so_far).alias("doc_id"))


def _ordered_sum(name: str):
    return F.sum(name).over(W.partitionBy("term", "shard").orderBy("pos").rowsBetween(W.unboundedPreceding, W.currentRow))


def dense_doc_ids(docs: DataFrame, key: str) -> DataFrame:
    """``docs`` with dense_id from 0 in the order of ``key``: range partitions, their sizes, and one offset each.

    No task orders more than a range. The ranges are a table of the shared folder, each row
    with its range and place: planned twice, they would be sampled and coalesced apart. The
    offsets are one row per range.
    """
    own = docs.columns
    ranged = docs.repartitionByRange(F.col(f"`{key}`")).sortWithinPartitions(F.col(f"`{key}`"))
    held = written(ranged.select(*[F.col(f"`{c}`") for c in own], F.spark_partition_id().alias("_q_part"), F.monotonically_increasing_id().alias("_q_at")), "ranged")
    start = held.groupBy("_q_part").agg(F.count("*").alias("_q_size"), F.min("_q_at").alias("_q_first"))
    before = F.coalesce(F.sum("_q_size").over(W.orderBy("_q_part").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    offsets = start.select("_q_part", "_q_first", before.alias("_q_before"))
    return held.join(F.broadcast(offsets), "_q_part").select(*[F.col(f"`{c}`") for c in own], (F.col("_q_at") - F.col("_q_first") + F.col("_q_before")).alias("dense_id"))
