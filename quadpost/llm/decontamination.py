"""Benchmark decontamination with a distributed positional inverted index of the training texts.

The index is a stored table. Documents are dealt to segments as they are read; a
row is one term's postings in one segment: its token positions there, ascending
(documents follow each other with a gap, so no phrase crosses a border). The row
of term 0 has each document's start instead, and the documents' ids and lengths.

A phrase query is a distributed join. Every phrase is asked by its rarest term (by
the postings counted in the whole index): it travels to the segments that have
postings of that term, where it meets the lists of the asked terms. There lists are
intersected from the rarest on, each shifted by the term's offset in the phrase.
Proximity queries go the same way. A segment's lists are bounded by its bytes.

Defined cases: null and empty texts have no words and match nothing; benchmark
rows with a null id or without words give no window; repeated items with one id
count as one item; an empty table on either side gives rows without hits; extra
columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from quadpost.llm.staging import written

#: Letters A-Z become a-z; ASCII other than letters and digits becomes a space.
_TABLE = bytes(c + 32 if 65 <= c <= 90 else c if 48 <= c <= 57 or 97 <= c <= 122 or c >= 128 else 32 for c in range(256))
WINDOW = 13
#: Documents and bytes of text that one segment holds at most (one longer document makes its own).
SEGMENT_DOCS, SEGMENT_BYTES = 4096, 8 << 20
#: A partition numbers its segments from its own number times this.
NUMBERS = 1 << 32
#: The term of the rows that have the documents' starts.
STARTS = 0
#: Rows of postings in one batch.
_ROWS = 4096

POSTINGS = "seg long, term long, n int, positions array<int>, doc_ids array<long>, lengths array<int>"
_SCHEMA = pa.schema([("seg", pa.int64()), ("term", pa.int64()), ("n", pa.int32()), ("positions", pa.list_(pa.int32())), ("doc_ids", pa.list_(pa.int64())), ("lengths", pa.list_(pa.int32()))])
HITS = "seg long, ordinal int, n_hit long, n_items long, items_sha256 string"


def words(text: str | None) -> list[bytes]:
    return text.encode("utf-8", "surrogatepass").translate(_TABLE).split() if text else []


def term_id(word: bytes) -> int:
    """64 bits of the word's hash; never that of the starts."""
    return (xxhash.xxh3_64_intdigest(word) - (1 << 63)) or 1


# --- the index -----------------------------------------------------------------------------------------------------


def _lists(values: np.ndarray, ends: np.ndarray, kind: pa.DataType) -> pa.ListArray:
    return pa.ListArray.from_arrays(pa.array(np.concatenate([[0], ends]), pa.int32()), pa.array(values, kind))


def _segment(seg: int, ids: list, texts: list[list[bytes]]) -> Iterator[pa.RecordBatch]:
    lengths = np.fromiter(map(len, texts), np.int64, len(texts))
    starts = np.cumsum(lengths + 1) - lengths - 1  # a gap of one after each document
    position = np.arange(int(lengths.sum())) + np.repeat(np.arange(len(texts)), lengths)
    coded = pa.array([w for t in texts for w in t], pa.binary()).dictionary_encode()
    terms = np.fromiter(map(term_id, coded.dictionary.to_pylist()), np.int64, len(coded.dictionary))
    codes = coded.indices.to_numpy()
    order = np.argsort(codes, kind="stable")
    counts = np.bincount(codes, minlength=len(terms)) if len(codes) else np.zeros(0, np.int64)
    yield pa.RecordBatch.from_arrays([pa.array([v], f.type) for v, f in zip((seg, STARTS, len(ids), starts.tolist(), ids, lengths.tolist()), _SCHEMA, strict=True)], schema=_SCHEMA)
    ends, position = np.cumsum(counts), position[order]
    for a in range(0, len(terms), _ROWS):
        z = min(len(terms), a + _ROWS)
        first = int(ends[a] - counts[a])
        none = pa.nulls(z - a, pa.list_(pa.int64())), pa.nulls(z - a, pa.list_(pa.int32()))
        yield pa.RecordBatch.from_arrays([pa.array(np.full(z - a, seg), pa.int64()), pa.array(terms[a:z]), pa.array(counts[a:z], pa.int32()), _lists(position[first : ends[z - 1]], ends[a:z] - first, pa.int32()), *none], schema=_SCHEMA)


def _segments(most_docs: int, most_bytes: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seg, ids, texts, size = TaskContext.get().partitionId() * NUMBERS, [], [], 0
        for batch in batches:
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                text = text.as_py()
                if ids and (len(ids) >= most_docs or size + len(text or "") > most_bytes):
                    yield from _segment(seg, ids, texts)
                    seg, ids, texts, size = seg + 1, [], [], 0
                ids.append(doc)
                texts.append(words(text))
                size += len(text or "")
        if ids:
            yield from _segment(seg, ids, texts)

    return run


def build_index(docs: DataFrame, segment_docs: int = SEGMENT_DOCS, segment_bytes: int = SEGMENT_BYTES) -> DataFrame:
    """The positional index of every word of (doc_id, text), as a stored table of postings rows."""
    return written(docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(_segments(segment_docs, segment_bytes), POSTINGS), "postings")


def documents(index: DataFrame) -> DataFrame:
    """(seg, ordinal, doc_id, n_words) of the indexed documents."""
    rows = index.where(F.col("term") == STARTS).select("seg", F.posexplode(F.arrays_zip("doc_ids", "lengths")).alias("ordinal", "d"))
    return rows.select("seg", "ordinal", F.col("d.doc_ids").alias("doc_id"), F.col("d.lengths").cast("long").alias("n_words"))


# --- what is asked -------------------------------------------------------------------------------------------------


def item_windows(text: str | None, size: int = WINDOW) -> list[list[bytes]]:
    """The windows of an item's words: ``size`` in a row; an item of fewer is one window."""
    ws = words(text)
    return [ws[i : i + size] for i in range(max(1, len(ws) - size + 1))] if ws else []


def _cut_windows(size: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [(item, list(map(term_id, w))) for item, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True) if item is not None for w in item_windows(text, size)]
            yield pa.RecordBatch.from_arrays([pa.array([i for i, _ in rows], pa.string()), pa.array([t for _, t in rows], pa.list_(pa.int64()))], ["item", "terms"])

    return run


def windows_of(benchmark: DataFrame, size: int = WINDOW) -> DataFrame:
    """(query, terms, items): every distinct window of (item_id, text) and the ids of the items that have it."""
    cut = benchmark.select(F.col("item_id").cast("string"), F.col("text").cast("string")).mapInArrow(_cut_windows(size), "item string, terms array<long>")
    return cut.groupBy("terms").agg(F.sort_array(F.collect_set("item")).alias("items")).select(F.xxhash64("terms").alias("query"), "terms", "items")


def _asked(index: DataFrame, queries: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(seg, terms, items) of the segments that have each query's rarest term, and the postings of all asked terms; queries with a term that the index lacks go."""
    spots = queries.select("query", F.explode(F.array_distinct("terms")).alias("term"))
    lists = index.join(spots.select("term").distinct(), "term", "left_semi").select("seg", "term", "n", "positions")
    counts = lists.groupBy("term").agg(F.sum("n").alias("total"))
    known = spots.join(counts, "term").groupBy("query").agg(F.count("*").alias("known"), F.min(F.struct("total", "term")).alias("rarest"))
    routed = queries.join(known, "query").where(F.col("known") == F.size(F.array_distinct("terms"))).select("terms", "items", F.col("rarest.term").alias("term"))
    return routed.join(lists.select("seg", "term"), "term").select("seg", "terms", "items"), lists


class Segment:
    """The asked lists of one segment, by term."""

    def __init__(self, table: pa.Table):
        columns = {n: table.column(n) for n in ("term", "positions")}
        held = [(t, p.values.to_numpy()) for t, p in zip(columns["term"].to_pylist(), columns["positions"], strict=True)]
        self.lists = dict(held)
        self.starts = self.lists.pop(STARTS, np.zeros(0, np.int64))

    def owner(self, at: np.ndarray) -> np.ndarray:
        return np.searchsorted(self.starts, at, side="right") - 1

    def phrase(self, terms: list[int]) -> np.ndarray:
        """Where the phrase starts: lists from the rarest on, each shifted to the phrase's start."""
        if not all(t in self.lists for t in terms):
            return np.zeros(0, np.int64)
        order = sorted(range(len(terms)), key=lambda j: len(self.lists[terms[j]]))
        at = self.lists[terms[order[0]]] - order[0]
        for j in order[1:]:
            if not len(at):
                break
            other = self.lists[terms[j]]
            i = np.searchsorted(other, at + j)
            at = at[(i < len(other)) & (other[np.minimum(i, len(other) - 1)] == at + j)]
        return at

    def near(self, terms: list[int], within: int) -> np.ndarray:
        """Positions of the rarest term that have every other term at most ``within`` tokens away, in the same document."""
        if not all(t in self.lists for t in terms):
            return np.zeros(0, np.int64)
        first, *rest = sorted(terms, key=lambda t: len(self.lists[t]))
        at = self.lists[first]
        doc = self.owner(at)
        after = np.append(self.starts[1:], np.iinfo(np.int32).max)
        low, high = np.maximum(at - within, self.starts[doc]), np.minimum(at + within, after[doc] - 1)
        keep = np.ones(len(at), bool)
        for t in rest:
            other = self.lists[t]
            keep &= np.searchsorted(other, low) < np.searchsorted(other, high, side="right")
        return at[keep]


def _answer(index: DataFrame, queries: DataFrame, answer: Callable[[int, Segment, list, list], pa.Table], schema: str) -> DataFrame:
    """What ``answer`` gives for every segment that is asked, of its lists and its queries."""
    asked, lists = _asked(index, queries)
    starts = index.where(F.col("term") == STARTS).select("seg", "term", "n", "positions")
    held = lists.unionByName(starts).groupBy("seg")

    def run(key, left, right):
        if not len(right):
            return answer(0, None, [], [])
        return answer(key[0].as_py(), Segment(left), right.column("terms").to_pylist(), right.column("items").to_pylist())

    return held.cogroup(asked.groupBy("seg")).applyInArrow(run, schema)


def _covered(starts: np.ndarray, sizes: np.ndarray) -> int:
    """How many positions the spans cover; starts ascending."""
    ends = np.maximum.accumulate(starts + sizes)
    return int((ends - np.maximum(starts, np.concatenate([[starts[0]], ends[:-1]]))).clip(0).sum())


def _hits(seg: int, segment: Segment | None, terms: list, items: list) -> pa.Table:
    at, sizes, which = [], [], []
    for k, t in enumerate(terms):
        here = segment.phrase(t)
        if len(here):
            at.append(here)
            sizes.append(np.full(len(here), len(t)))
            which.append(np.full(len(here), k))
    rows = []
    if at:
        at, sizes, which = map(np.concatenate, (at, sizes, which))
        order = np.argsort(at, kind="stable")
        at, sizes, which = at[order].astype(np.int64), sizes[order], which[order]
        doc = segment.owner(at)
        for part in np.split(np.arange(len(at)), np.flatnonzero(np.diff(doc)) + 1):
            ids = sorted({i for k in np.unique(which[part]).tolist() for i in items[k]})
            rows.append((seg, int(doc[part[0]]), _covered(at[part], sizes[part]), len(ids), hashlib.sha256(",".join(ids).encode()).hexdigest()))
    names = [f.split()[0] for f in HITS.split(", ")]
    kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.string())
    return pa.table({n: pa.array([r[i] for r in rows], k) for i, (n, k) in enumerate(zip(names, kinds, strict=True))})


def phrase_hits(index: DataFrame, queries: DataFrame) -> DataFrame:
    """(seg, ordinal, n_hit, n_items, items_sha256) of every document in which a phrase of (query, terms, items) occurs: how many words the occurrences cover, and the items they come from."""
    return _answer(index, queries, _hits, HITS)


def proximity_hits(index: DataFrame, queries: DataFrame, within: int) -> DataFrame:
    """(item, doc_id, position): where the rarest term of each of (item_id, text) stands with all its others at most ``within`` words away."""
    whole = queries.where("item_id IS NOT NULL").select(F.col("item_id").cast("string").alias("item_id"), "text")
    asked = windows_of(whole, np.iinfo(np.int32).max)

    def near(seg: int, segment: Segment | None, terms: list, items: list) -> pa.Table:
        out: list[tuple] = []
        for t, ids in zip(terms, items, strict=True):
            at = segment.near(list(dict.fromkeys(t)), within)
            doc = segment.owner(at)
            out += [(i, seg, d, p) for d, p in zip(doc.tolist(), (at - segment.starts[doc]).tolist(), strict=True) for i in ids]
        return pa.table({n: pa.array([r[k] for r in out], kind) for k, (n, kind) in enumerate((("item", pa.string()), ("seg", pa.int64()), ("ordinal", pa.int32()), ("position", pa.int64())))})

    found = _answer(index, asked, near, "item string, seg long, ordinal int, position long")
    return found.join(documents(index), ["seg", "ordinal"]).select("item", "doc_id", "position")


def contamination(docs: DataFrame, benchmark: DataFrame, size: int = WINDOW, segment_docs: int = SEGMENT_DOCS) -> DataFrame:
    """One row per document: doc_id, n_words, n_hit, n_items, items_sha256, contaminated."""
    index = build_index(docs, segment_docs)
    hits = phrase_hits(index, written(windows_of(benchmark, size), "windows"))
    none = hashlib.sha256(b"").hexdigest()
    whole = documents(index).join(hits, ["seg", "ordinal"], "left")
    n_hit = F.coalesce("n_hit", F.lit(0)).cast("long")
    return whole.select(
        "doc_id", "n_words", n_hit.alias("n_hit"), F.coalesce("n_items", F.lit(0)).cast("long").alias("n_items"), F.coalesce("items_sha256", F.lit(none)).alias("items_sha256"), ((n_hit > 0) & (20 * n_hit >= F.col("n_words"))).alias("contaminated")
    )
