"""Repeated word windows by super-k-mer partitioning.

A window is ``WINDOW`` consecutive words. Its minimiser is the least of the
``GRAM``-word grams in it, where grams that are common in the corpus come last and
others go by their hash. Consecutive windows with one minimiser make a super-k-mer,
which is a run of WINDOW - 1 more words than it has windows. All equal windows have
equal minimisers, so they meet in the minimiser's bucket.

1. All texts' grams are counted. What a batch has too rarely is left out of its
   counts, so that those with a ``COMMON``-th of all occurrences are found whatever
   the input's order, and no more than ``COMMON`` grams are common. A passage that
   very many documents have in ever new surroundings thus gives no minimiser to the
   windows that reach over its edge, and its own windows are few different ones.
2. Every document gives its super-k-mers as narrow rows: minimiser, 128-bit hash of
   the packed words, document, place. Equal super-k-mers collapse before they move.
3. A later copy of a whole super-k-mer is decided by that alone: all its windows
   start in an earlier document.
4. Where one minimiser has several different super-k-mers, the first copy of each
   travels as one packed string to its bucket. There the windows of a bounded chunk
   of minimisers are sorted, by doubling the words that their ranks stand for, and
   counted exactly, with their least document.
5. Covered words come back to their documents as spans.

Defined cases: null texts have no words; texts shorter than a window have none;
rows with equal doc_id and text are one document and get one answer each; a null
doc_id counts as smaller than all others; an empty table gives no rows; extra
columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from quadpost.llm.staging import shuffle_parts, written

WINDOW, GRAM = 50, 6
#: At most so many grams are common: those with at least this part of all occurrences.
COMMON = 1 << 20
#: Windows of one super-k-mer: a longer run, such as one word said again and again, is cut into equal ones.
MOST_WINDOWS = 256
#: Packed bytes that one bucket should hold, and that are sorted at a time (more only if one minimiser has more).
BUCKET_BYTES, CHUNK_BYTES = 8 << 20, 4 << 20
_ODD = np.uint64(0x9E3779B97F4A7C15)


def _mix(x: np.ndarray) -> np.ndarray:
    """The finaliser of the public splitmix64 generator; it is bijective, so the least hash is an even choice."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _rolled(hashes: np.ndarray, size: int) -> np.ndarray:
    """A 64-bit hash of every run of ``size`` words from the words' hashes."""
    out = np.zeros(len(hashes) - size + 1, np.uint64)
    for j in range(size):
        out = out * _ODD + hashes[j : j + len(out)]
    return _mix(out)


def _least(values: np.ndarray, width: int) -> np.ndarray:
    """The minimum of every ``width`` consecutive values, by doubling."""
    have, size = values, 1
    while 2 * size <= width:
        have, size = np.minimum(have[: len(have) - size], have[size:]), 2 * size
    if size < width:
        shift = width - size
        have = np.minimum(have[: len(have) - shift], have[shift:])
    return have


def words(text: str | None) -> list[bytes]:
    return text.encode("utf-8", "surrogatepass").split() if text else []


def grams(ws: list[bytes], gram: int = GRAM) -> np.ndarray:
    return _rolled(np.fromiter(map(xxhash.xxh3_64_intdigest, ws), np.uint64, len(ws)), gram)


def _none() -> np.ndarray:
    return np.zeros(0, np.uint64)


def super_kmers(ws: list[bytes], window: int = WINDOW, gram: int = GRAM, common: np.ndarray | None = None) -> list[tuple[int, int, int]]:
    """(first window, number of windows, minimiser) for each super-k-mer of a text's words. common: ascending hashes of the grams that come last."""
    if len(ws) < window:
        return []
    hashed = grams(ws, gram)
    order = hashed >> np.uint64(1)
    if common is not None and len(common):
        at = np.minimum(np.searchsorted(common, hashed), len(common) - 1)
        order |= (common[at] == hashed).astype(np.uint64) << np.uint64(63)
    least = _least(order, window - gram + 1)
    starts = np.flatnonzero(np.concatenate([[True], least[1:] != least[:-1]]))
    counts = np.diff(np.append(starts, len(least)))
    if counts.max() > MOST_WINDOWS:
        pieces = -(-counts // MOST_WINDOWS)
        inner = np.arange(int(pieces.sum())) - np.repeat(np.cumsum(pieces) - pieces, pieces)
        starts = np.repeat(starts, pieces) + MOST_WINDOWS * inner
        counts = np.diff(np.append(starts, len(least)))
    return list(zip(starts.tolist(), counts.tolist(), least[starts].view(np.int64).tolist(), strict=True))


def _count_grams(window: int, gram: int, most: int):
    """Per batch: the grams with at least ``most``-th of its occurrences, and under gram null all of its occurrences."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [grams(ws, gram) for t in batch.column(0) if len(ws := words(t.as_py())) >= window]
            hashed, n = np.unique(np.concatenate(found) if found else _none(), return_counts=True)
            keep = n >= max(2, n.sum() / most)
            yield pa.RecordBatch.from_arrays([pa.array([None, *hashed[keep].view(np.int64).tolist()], pa.int64()), pa.array([int(n.sum()), *n[keep].tolist()], pa.int64())], ["gram", "n"])

    return run


def common_grams(docs: DataFrame, window: int = WINDOW, gram: int = GRAM, most: int = COMMON) -> np.ndarray:
    """Hashes of the grams with at least a ``most``-th of all occurrences, ascending: at most ``most`` of them."""
    counts = docs.select(F.col("text").cast("string")).where("text IS NOT NULL").mapInArrow(_count_grams(window, gram, most), "gram long, n long").groupBy("gram").agg(F.sum("n").alias("n"))
    counts = written(counts, "gram-counts")
    total = counts.where("gram IS NULL").agg(F.sum("n")).first()[0] or 0
    held = counts.where(F.col("gram").isNotNull() & (F.col("n") >= max(2, total / most))).select("gram").toArrow()
    return np.sort(np.array(held.column(0), np.int64).view(np.uint64))


_LEAST = -(1 << 63)


def _keyed(docs: DataFrame) -> DataFrame:
    """(doc, low, th, text): low is doc with null as the least; low and th name a document."""
    doc = F.col("doc_id").cast("long")
    return docs.select(doc.alias("doc"), F.coalesce(doc, F.lit(_LEAST)).alias("low"), F.xxhash64("text").alias("th"), F.col("text").cast("string").alias("text"))


_KMERS = "low long, th long, start int, windows int, mini long, b1 long, b2 long"
_PACKED = "mini long, b1 long, b2 long, low long, windows int, packed binary"
_RUNS = "mini long, b1 long, b2 long, first int, last int"


def _batch(rows: list[tuple], schema: str) -> pa.RecordBatch:
    fields = [f.split() for f in schema.split(", ")]
    kinds = {"long": pa.int64(), "int": pa.int32(), "binary": pa.binary()}
    columns = zip(*rows, strict=True) if rows else [[]] * len(fields)
    return pa.RecordBatch.from_arrays([pa.array(c, kinds[k]) for c, (_, k) in zip(columns, fields, strict=True)], [n for n, _ in fields])


def _cut(window: int, gram: int, common):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: list[tuple] = []
            for doc, th, text in zip(*(batch.column(k).to_pylist() for k in (0, 1)), batch.column(2), strict=True):
                ws = words(text.as_py())
                for start, n, mini in super_kmers(ws, window, gram, common.value):
                    high, low = divmod(xxhash.xxh3_128_intdigest(b" ".join(ws[start : start + n + window - 1])), 1 << 64)
                    out.append((doc, th, start, n, mini, high - (1 << 63), low - (1 << 63)))
            yield _batch(out, _KMERS)

    return run


def _packed(window: int):
    """Wanted super-k-mers of each text as packed strings."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for low, text, wanted in zip(batch.column(1).to_pylist(), batch.column(2), batch.column(3).to_pylist(), strict=True):
                ws = words(text.as_py())
                out += [(w["mini"], w["b1"], w["b2"], low, w["windows"], b" ".join(ws[w["start"] : w["start"] + w["windows"] + window - 1])) for w in wanted]
            yield _batch(out, _PACKED)

    return run


def _ranks(codes: np.ndarray, window: int) -> np.ndarray:
    """The rank of the ``window`` words from each place on in sorted order: ranks of double the words from pairs of ranks."""
    ranks, size = codes.astype(np.int64), 1
    while size < window:
        step = min(size, window - size)
        pair = ranks[: len(ranks) - step] * (int(ranks.max()) + 1) + ranks[step:]
        ranks, size = np.unique(pair, return_inverse=True)[1], size + step
    return ranks


def _decided(table: pa.Table, window: int) -> pa.RecordBatch:
    """Runs (first, last) of each super-k-mer's windows that a smaller document has too."""
    counts, low = table.column("windows").to_numpy().astype(np.int64), table.column("low").to_numpy()
    coded = pa.array(b" ".join(table.column("packed").to_pylist()).split(b" "), pa.binary()).dictionary_encode()
    lengths = counts + window - 1
    row = np.repeat(np.arange(len(counts)), counts)
    inner = np.arange(len(row)) - np.repeat(np.cumsum(counts) - counts, counts)
    rank = _ranks(coded.indices.to_numpy(), window)[np.repeat(np.cumsum(lengths) - lengths, counts) + inner]
    order = np.lexsort((low[row], rank))
    heads = np.flatnonzero(np.concatenate([[True], np.diff(rank[order]) != 0]))
    least = np.empty(len(row), np.int64)
    least[order] = np.repeat(low[row][order][heads], np.diff(np.append(heads, len(row))))
    hit = least < low[row]
    begins = hit & ((inner == 0) | ~np.concatenate([[False], hit[:-1]]))
    ends = hit & ((inner == counts[row] - 1) | ~np.concatenate([hit[1:], [False]]))
    at = pa.array(row[begins])
    return pa.RecordBatch.from_arrays([*(table.column(n).combine_chunks().take(at) for n in ("mini", "b1", "b2")), pa.array(inner[begins], pa.int32()), pa.array(inner[ends], pa.int32())], ["mini", "b1", "b2", "first", "last"])


def _count(window: int, chunk: int):
    """Sorts the windows of a bucket, whose rows come in the order of minimisers, chunk by chunk of whole minimisers."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0
        for batch in batches:
            held.append(batch)
            size += batch.nbytes
            if size < chunk:
                continue
            table = pa.Table.from_batches(held).combine_chunks()
            minis = table.column("mini").to_numpy()
            cut = int(np.searchsorted(minis, minis[-1]))
            if cut:
                yield _decided(table.slice(0, cut), window)
            held = table.slice(cut).combine_chunks().to_batches()
            size = sum(b.nbytes for b in held)
        if sum(b.num_rows for b in held):
            yield _decided(pa.Table.from_batches(held), window)

    return run


def covered_spans(docs: DataFrame, window: int = WINDOW, gram: int = GRAM, common: int = COMMON, chunk: int = CHUNK_BYTES) -> DataFrame:
    """(low, th, spans): for each document the word spans (from, to) that windows of smaller documents cover."""
    spark, rows = docs.sparkSession, _keyed(docs)
    last = spark.sparkContext.broadcast(common_grams(docs, window, gram, common))  # at most COMMON longs
    kmers = written(rows.where("text IS NOT NULL").select("low", "th", "text").mapInArrow(_cut(window, gram, last), _KMERS), "superkmers")
    body = ["mini", "b1", "b2"]
    bodies = kmers.groupBy(*body).agg(F.min(F.struct("low", "th", "start", "windows")).alias("at"), F.max("low").alias("high"))
    every = W.partitionBy("mini")  # the different super-k-mers of a minimiser
    shared = bodies.withColumns({"kinds": F.count("*").over(every), "a": F.min("at.low").over(every), "b": F.max("high").over(every)}).where("a < b")
    first = written(shared.select(*body, "at.*", "kinds"), "first-superkmers")
    # of each first copy with a rival under its minimiser: the packed string
    rival = first.where("kinds > 1").select("low", "th", F.struct(*body, "start", "windows").alias("w"))
    asked = rival.groupBy("low", "th").agg(F.collect_list("w").alias("wanted"))
    # the text travels once: the join of dedup_substrings has the same exchange
    fetch = rows.join(asked, ["low", "th"]).select("doc", "low", "text", "wanted")
    # words of a text are about six bytes, and a super-k-mer about seventy words
    total = rival.count() * 6 * (window + 20)
    buckets = max(shuffle_parts(spark), -(-total // BUCKET_BYTES))
    dealt = fetch.mapInArrow(_packed(window), _PACKED).repartition(buckets, "mini").sortWithinPartitions("mini")
    decided = dealt.mapInArrow(_count(window, chunk), _RUNS).groupBy(*body).agg(F.collect_list(F.struct("first", "last")).alias("runs"))
    # back to every place: whole later copies, and the runs of first copies
    verdict = first.select(*body, F.col("low").alias("least")).join(decided, body, "left")
    placed = kmers.join(verdict, body)
    whole = F.array(F.struct(F.lit(0).alias("first"), (F.col("windows") - 1).alias("last")))
    spots = placed.select("low", "th", "start", F.explode(F.when(F.col("low") > F.col("least"), whole).otherwise(F.col("runs"))).alias("r"))
    spans = spots.select("low", "th", F.struct((F.col("start") + F.col("r.first")).alias("from"), (F.col("start") + F.col("r.last") + window).alias("to")).alias("s"))
    return spans.groupBy("low", "th").agg(F.collect_list("s").alias("spans"))


def _kept(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        n, gone, texts = [], [], []
        for text, spans in zip(batch.column(2), batch.column(3).to_pylist(), strict=True):
            ws = words(text.as_py())
            n.append(len(ws))
            kept, end, lost = [], 0, 0
            for a, b in sorted((s["from"], s["to"]) for s in spans or ()):
                a = max(a, end)
                if b > a:
                    kept += ws[end:a]
                    lost, end = lost + b - a, b
            kept += ws[end:]
            gone.append(lost)
            texts.append(b" ".join(kept))
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(gone, pa.int64()), pa.array([hashlib.sha256(t).hexdigest() for t in texts], pa.string()), pa.array(texts, pa.binary())], ["doc_id", "n_words", "n_removed", "kept_sha256", "kept"])


def dedup_substrings(docs: DataFrame, window: int = WINDOW, gram: int = GRAM, common: int = COMMON, chunk: int = CHUNK_BYTES) -> DataFrame:
    """(doc_id, n_words, n_removed, kept_sha256, kept binary): each document without the words that repeat a smaller document's windows."""
    spans = covered_spans(docs, window, gram, common, chunk)
    joined = _keyed(docs).join(spans, ["low", "th"], "left").select("doc", "low", "text", "spans")
    return joined.mapInArrow(_kept, "doc_id long, n_words long, n_removed long, kept_sha256 string, kept binary")
