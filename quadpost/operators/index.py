"""The compressed index: blocks of 512 postings with their ranges as skip pointers."""

from __future__ import annotations

from collections.abc import Iterator
from time import perf_counter_ns

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from quadpost.codecs.base import Block
from quadpost.operators import corpus
from quadpost.operators.blocks import decoded, encode_blocks, sizes

#: Two longs: a block's first and last document.
SKIP_BITS = 128
#: The gap codec's short-list fallback.
SHORT_CODEC = "vbyte"
GAP_BYTES = ("g_codec", "g_n", "g_ctrl", "g_data", "g_exc")
TF_BYTES = ("t_codec", "t_ctrl", "t_data", "t_exc")


def index_blocks(found: DataFrame, size: int = corpus.BLOCK, shard_docs: int = corpus.SHARD_DOCS) -> DataFrame:
    """Blocks (term, shard, block, df, n, first_doc, last_doc, max_tf, gaps, tfs) of postings, not yet encoded.

    A block's first gap is kept as 1, counted from first_doc - 1, so every block decodes on
    its own. The list lengths come from the postings, before windows and blocks; of
    ``sharded_postings`` they meet the blocks by (term, shard), so that only counts move.
    """
    dealt = "shard" in found.columns
    if dealt:
        # tf is read so that both sides have the same exchange, which is then made once
        own = found.groupBy("term", "shard").agg(F.count(F.when(F.col("tf") > 0, 1)).alias("own"))
        df = own.select("term", "shard", F.sum("own").over(W.partitionBy("term")).alias("df"))
    else:
        df = found.groupBy("term").agg(F.count("*").alias("df"))
    local = F.concat(F.array(F.lit(1).cast("long")), F.slice("gaps", F.lit(2), F.size("gaps")))
    rows = corpus.blocks(corpus.gaps(found, shard_docs), size)
    return rows.join(df, ["term", "shard"] if dealt else ["term"]).select("term", "shard", "block", "df", "n", "first_doc", "last_doc", F.array_max("tfs").alias("max_tf"), local.alias("gaps"), "tfs")


def build_index(found: DataFrame, name: str = "quad_selector", size: int = corpus.BLOCK, shard_docs: int = corpus.SHARD_DOCS) -> DataFrame:
    """Index rows (term, shard, block, df, n, first_doc, last_doc, max_tf, g_*, t_*) of postings (term, doc_id, tf)."""
    coded = encode_blocks(index_blocks(found, size, shard_docs), name, "gaps", prefix="g_", short=SHORT_CODEC)
    return encode_blocks(coded, name, "tfs", prefix="t_", short=SHORT_CODEC)


def write_index(index: DataFrame, path: str, files: int) -> None:
    """Sorted by (term, first_doc) in term ranges, so that a term's filter reads few row groups."""
    index.repartitionByRange(files, "term", "first_doc").sortWithinPartitions("term", "first_doc").write.mode("overwrite").parquet(path)


def unpacked(batch: pa.RecordBatch | pa.Table, tfs: bool = True) -> tuple[np.ndarray, np.ndarray, np.ndarray | None]:
    """(postings of each row, documents, frequencies) of index rows, one row after another."""
    c = {n: batch[n].to_pylist() for n in batch.schema.names if n[:2] in ("g_", "t_")}
    counts = np.array(c["g_n"], np.int64)
    part = lambda p: decoded(c[f"{p}_codec"], [Block(*b) for b in zip(c["g_n"], c[f"{p}_ctrl"], c[f"{p}_data"], c[f"{p}_exc"], strict=True)]) if len(counts) else np.zeros(0, np.int64)
    run_sum = np.cumsum(part("g"))
    before = np.concatenate([[0], run_sum])[np.cumsum(counts) - counts]  # gaps are summed up inside each block
    docs = run_sum + np.repeat(batch["first_doc"].to_numpy() - 1 - before, counts)
    return counts, docs, part("t") if tfs else None


def decode_postings(index: DataFrame, tfs: bool = True) -> DataFrame:
    """(term, doc_id, tf) of index rows; without ``tfs`` their bytes are not read and tf is absent."""
    kept = index.select("term", "first_doc", *(GAP_BYTES + TF_BYTES if tfs else GAP_BYTES))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            counts, docs, found = unpacked(batch, tfs)
            columns = [batch["term"].take(pa.array(np.repeat(np.arange(len(counts)), counts))), pa.array(docs, pa.int64())]
            yield pa.RecordBatch.from_arrays(columns + ([pa.array(found, pa.int64())] if tfs else []), ["term", "doc_id"] + (["tf"] if tfs else []))

    return kept.mapInArrow(run, "term string, doc_id bigint" + (", tf bigint" if tfs else ""))


def decode_ns(index: DataFrame) -> DataFrame:
    """(blocks, postings, ns) of each task: nanoseconds inside the codecs while both areas of index rows are decoded."""
    names = [f"{p}_{c}" for p in "gt" for c in ("codec", "n", "ctrl", "data", "exc")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        blocks, postings, ns = 0, 0, 0
        for batch in batches:
            if not batch.num_rows:
                continue
            for at in (0, 5):
                used, *areas = (batch.column(at + k).to_pylist() for k in range(5))
                held = [Block(*b) for b in zip(*areas, strict=True)]
                began = perf_counter_ns()
                decoded(used, held)
                ns += perf_counter_ns() - began
            blocks, postings = blocks + batch.num_rows, postings + sum(areas[0])
        yield pa.RecordBatch.from_pydict({"blocks": [blocks], "postings": [postings], "ns": [ns]})

    return index.select(*names).mapInArrow(run, "blocks bigint, postings bigint, ns bigint")


def index_bits(index: DataFrame) -> DataFrame:
    """Total (postings, gap_bits, tf_bits, skip_bits, bits) of an index."""
    bits = lambda p: F.sum(F.col(f"{p}_ctrl_bits") + F.col(f"{p}_data_bits") + F.col(f"{p}_exc_bits") + F.col(f"{p}_head_bits"))
    total = index.agg(F.sum("n").cast("long").alias("postings"), bits("g").alias("gap_bits"), bits("t").alias("tf_bits"), (F.count("*") * SKIP_BITS).alias("skip_bits"))
    return total.withColumn("bits", F.expr("gap_bits + tf_bits + skip_bits"))


def index_sizes(found: DataFrame, names: tuple[str, ...]) -> DataFrame:
    """(codec, postings, gap_bits, tf_bits, skip_bits, bits) of the indexes that ``names`` would make: one pass encodes every block by each."""
    both = F.array(*[F.struct(F.lit(seq).alias("seq"), F.col(c).alias("values")) for seq, c in (("gap", "gaps"), ("tf", "tfs"))])
    held = index_blocks(found).select("df", F.explode(both).alias("x")).select("df", "x.seq", "x.values")
    long = sizes(held.where(F.col("df") >= corpus.SHORT_LIST).drop("df"), list(names))
    short = sizes(held.where(F.col("df") < corpus.SHORT_LIST).drop("df"), [SHORT_CODEC])
    grid = F.explode(F.array(*map(F.lit, names)))  # one row per codec and sequence after the aggregation
    part = lambda df: df.groupBy("codec", "seq").agg(F.sum("n").alias("n"), F.sum("bits").alias("bits"), F.count("*").alias("blocks"))
    parts = part(long).unionByName(part(short).withColumn("codec", grid))
    of = lambda seq, c: F.sum(F.when(F.col("seq") == seq, F.col(c)).otherwise(0))
    total = parts.groupBy("codec").agg(of("gap", "n").alias("postings"), of("gap", "bits").alias("gap_bits"), of("tf", "bits").alias("tf_bits"), (of("gap", "blocks") * SKIP_BITS).alias("skip_bits"))
    return total.withColumn("bits", F.expr("gap_bits + tf_bits + skip_bits"))


def merge_segments(segments: DataFrame, name: str = "quad_selector", size: int = corpus.BLOCK) -> DataFrame:
    """One index of local, uncompressed segments (seg, term, doc_id, tf). A document in two segments is an error."""
    twice = segments.select("seg", "doc_id").distinct().groupBy("doc_id").count().where("count > 1")
    if not twice.isEmpty():
        raise ValueError("segments share documents")
    return build_index(segments.select("term", "doc_id", "tf"), name, size)


def build_segments(docs: DataFrame, limit: int) -> DataFrame:
    """Local, uncompressed segments (seg, term, doc_id, tf) of about ``limit`` bytes of text each.

    Documents are dealt to as many segments as the text needs by a hash of their id; one aggregation makes all segments.
    """
    total = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    count = max(1, -(-total // limit))
    dealt = docs.select("doc_id", "text", F.pmod(F.xxhash64("doc_id"), F.lit(count)).cast("int").alias("seg"))
    words = dealt.select("seg", "doc_id", F.explode(F.split(F.lower("text"), corpus.TOKEN_BREAK)).alias("term")).where("term != ''")
    return words.groupBy("seg", "term", "doc_id").agg(F.count("*").alias("tf"))


def write_segments(segments: DataFrame, path: str) -> None:
    """One folder per segment; writing again replaces the segments that come, and no others."""
    segments.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("seg").parquet(path)
