"""Segments from a stream of documents, and gaps that continue across batches."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from quadpost.operators import corpus

DOCS = "doc_id bigint, text string"


def read_documents(spark: SparkSession, path: str, files: int = 1) -> DataFrame:
    """A stream of (doc_id, text); ``files`` per batch is the limit at which a segment is flushed."""
    return spark.readStream.schema(DOCS).option("maxFilesPerTrigger", files).parquet(path)


def write_segment(batch: DataFrame, seg: int, path: str) -> None:
    """One local, uncompressed segment. A batch that comes again overwrites its own segment only."""
    corpus.postings(batch).write.mode("overwrite").parquet(f"{path}/seg={seg}")


def ingest(docs: DataFrame, path: str, checkpoint: str) -> None:
    """Takes what is there, one segment a batch, and ends."""
    query = docs.writeStream.option("checkpointLocation", checkpoint).trigger(availableNow=True).foreachBatch(lambda df, seg: write_segment(df, seg, path)).start()
    query.awaitTermination()


def read_segments(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("term string, doc_id bigint, tf bigint, seg int").parquet(path)


def unrepeated(events: DataFrame, key: str, time: str, late: str = "1 hour") -> DataFrame:
    """Each key once while the watermark holds it; what comes later than ``late`` is dropped, so a sealed segment stays sealed."""
    return events.withWatermark(time, late).dropDuplicatesWithinWatermark([key])


def windowed_counts(events: DataFrame, time: str, key: str, window: str = "1 hour", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Postings that arrive per window and list."""
    w = F.window(time, window, slide) if slide else F.window(time, window)
    return events.withWatermark(time, late).groupBy(w.alias("w"), key).agg(F.count("*").alias("postings")).select(F.col("w.start").alias("start"), key, "postings")


def streamed_gaps(postings: DataFrame) -> DataFrame:
    """(term, doc_id, gap) of a stream of (term, doc_id), ascending per term over the batches.

    The state of a list is its last document. One that does not ascend is an error of the feed and gets no gap.
    """

    def run(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        last = state.get[0] if state.exists else -1
        docs = pd.concat(list(frames))["doc_id"].sort_values().drop_duplicates()
        docs = docs[docs > last]
        if len(docs):
            gaps = docs.diff()
            gaps.iloc[0] = docs.iloc[0] - last
            state.update((int(docs.iloc[-1]),))
            yield pd.DataFrame({"term": key[0], "doc_id": docs.astype("int64"), "gap": gaps.astype("int64")})

    return postings.groupBy("term").applyInPandasWithState(run, "term string, doc_id bigint, gap bigint", "last bigint", "append", "NoTimeout")
