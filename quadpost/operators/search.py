"""Ranked AND and OR queries over the compressed index: BM25, block skipping, safe early termination."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from quadpost.operators.corpus import TOKEN_BREAK
from quadpost.operators.index import GAP_BYTES, TF_BYTES, decode_postings, unpacked
from quadpost.sources.shared import written

K = 10
K1, B = 1.2, 0.75
#: A term in more than this share of documents is no query term.
STOP_SHARE = 0.5
#: Documents of one range: the unit of skipping and of document-at-a-time scoring.
RANGE_DOCS = 4096
#: Documents of one range of OR: its bounds decide what is decoded.
OR_RANGE_DOCS = 512
#: Ranges that a task of OR holds at once.
CHUNK_RANGES = 16
#: Ranges that give a query of OR its first threshold.
FIRST_RANGES = 4
#: Documents among which WAND looks for pivots together.
STRETCH_DOCS = 1024
#: Scores are compared after rounding to six digits, so what is this close below a threshold may still tie.
_SLACK = 2e-6


def query_terms(benchmark: DataFrame, words: DataFrame, n_docs: int) -> DataFrame:
    """(query_id, term, df): windows of two to four tokens of each passage, without stopwords, repeats and unknown terms.

    Window w of passage i starts at token 3w and has 2 + w mod 3 tokens; its id is 100 i + w.
    """
    split = F.filter(F.split(F.lower("text"), TOKEN_BREAK), lambda t: t != "")
    windows = F.transform(
        F.sequence(F.lit(0), F.greatest(F.lit(0), (F.size("t") / 3).cast("int") - 1)), lambda w: F.struct(w.alias("w"), F.slice(F.col("t"), w * 3 + 1, 2 + w % 3).alias("terms"))
    )
    cut = benchmark.select("item_id", split.alias("t")).select("item_id", F.explode(windows).alias("x"))
    asked = cut.select((F.col("item_id") * 100 + F.col("x.w")).alias("query_id"), F.explode(F.array_distinct("x.terms")).alias("term"))
    stop = words.where(F.col("df") > STOP_SHARE * n_docs).select("term")
    return asked.join(stop, "term", "left_anti").join(words.select("term", "df"), "term").select("query_id", "term", "df")


def idf(df: Column, n_docs: int) -> Column:
    return F.log(1 + (n_docs - df + 0.5) / (df + 0.5))


def bm25(tf: Column, df: Column, length: Column, n_docs: int, mean_length: float) -> Column:
    return idf(df, n_docs) * tf * (K1 + 1) / (tf + K1 * (1 - B + B * length / mean_length))


def top(scored: DataFrame, k: int = K) -> DataFrame:
    """(query_id, rank, doc_id, score): the best k of each query, ties to the smaller doc_id. Partial ranks go before the shuffle."""
    rounded = scored.select("query_id", "doc_id", F.round("score", 6).alias("score"))
    order = W.partitionBy("query_id").orderBy(F.desc("score"), "doc_id")
    return rounded.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "doc_id", "score")


class Searcher:
    """An index with what BM25 needs beside it. Only two numbers are collected: documents and their mean length."""

    def __init__(self, index: DataFrame, lengths: DataFrame, n_docs: int | None = None, mean_length: float | None = None):
        self.index, self.lengths = index, lengths
        if n_docs is None or mean_length is None:
            n_docs, total = lengths.agg(F.count("*"), F.sum("len")).first()
            mean_length = float(total or 0) / max(1, n_docs)
        self.n_docs, self.mean_length = n_docs, mean_length

    # -- parts --

    def _blocks_of(self, terms: DataFrame) -> DataFrame:
        """Index rows of the asked terms only, each once."""
        return self.index.join(terms.select("term").distinct(), "term", "left_semi")

    def _scored(self, hits: DataFrame) -> DataFrame:
        """(query_id, doc_id, term, part) of hits with tf and df."""
        part = bm25(F.col("tf"), F.col("df"), F.col("len"), self.n_docs, self.mean_length)
        return hits.join(self.lengths, "doc_id").select("query_id", "doc_id", "term", part.alias("part"))

    # -- AND --

    def candidates(self, asked: DataFrame) -> DataFrame:
        """(query_id, doc_id) of each query's rarest term."""
        rare = asked.groupBy("query_id").agg(F.min(F.struct("df", "term")).alias("r")).select("query_id", F.col("r.term").alias("term"))
        return rare.join(decode_postings(self._blocks_of(rare), tfs=False), "term").select("query_id", "doc_id")

    def skipped_blocks(self, asked: DataFrame, found: DataFrame) -> DataFrame:
        """Index rows whose document range holds a candidate of a query that asks their term.

        Candidates and blocks meet by (term, document range), then by the exact bounds.
        """
        spots = asked.select("query_id", "term").join(found, "query_id").select("term", F.floor(F.col("doc_id") / RANGE_DOCS).alias("range"), "doc_id").distinct()
        wide = self._blocks_of(asked).select("term", "shard", "block", "first_doc", "last_doc")
        ranged = wide.withColumn("range", F.explode(F.sequence(F.floor(F.col("first_doc") / RANGE_DOCS), F.floor(F.col("last_doc") / RANGE_DOCS))))
        hit = ranged.join(spots, ["term", "range"]).where("doc_id BETWEEN first_doc AND last_doc").select("term", "shard", "block").distinct()
        return self.index.join(hit, ["term", "shard", "block"], "left_semi")

    def and_documents(self, asked: DataFrame) -> DataFrame:
        """(query_id, doc_id, term, df, tf) of documents that have all terms of a query."""
        found = self.candidates(asked)
        hits = decode_postings(self.skipped_blocks(asked, found))
        wanted = asked.join(hits, "term").join(found, ["query_id", "doc_id"], "left_semi")
        need = asked.groupBy("query_id").agg(F.count("*").alias("need"))
        whole = wanted.groupBy("query_id", "doc_id").agg(F.count("*").alias("have")).join(need, "query_id").where("have = need").select("query_id", "doc_id")
        return wanted.join(whole, ["query_id", "doc_id"], "left_semi")

    def and_topk(self, asked: DataFrame, k: int = K) -> DataFrame:
        return top(self._scored(self.and_documents(asked)).groupBy("query_id", "doc_id").agg(F.sum("part").alias("score")), k)

    # -- OR --

    def parts(self, asked: DataFrame) -> DataFrame:
        """(query_id, doc_id, term, part) of every posting that a query touches."""
        return self._scored(asked.join(decode_postings(self._blocks_of(asked)), "term"))

    def or_topk(self, asked: DataFrame, k: int = K) -> DataFrame:
        return top(self.parts(asked).groupBy("query_id", "doc_id").agg(F.sum("part").alias("score")), k)

    def block_bounds(self, asked: DataFrame) -> DataFrame:
        """(term, shard, block, range, bound): the most that a posting of the block can give in a document range, from the block's largest frequency and the range's shortest document. Nothing is decoded."""
        width = lambda c: F.floor(F.col(c) / OR_RANGE_DOCS)
        shortest = self.lengths.groupBy(width("doc_id").alias("range")).agg(F.min("len").alias("least"))
        held = self._blocks_of(asked).select("term", "shard", "block", "df", "max_tf", F.explode(F.sequence(width("first_doc"), width("last_doc"))).alias("range"))
        bound = bm25(F.col("max_tf"), F.col("df"), F.col("least"), self.n_docs, self.mean_length)
        return held.join(shortest, "range").select("term", "shard", "block", "range", bound.alias("bound"))

    def blocks_in(self, asked: DataFrame, ranges: DataFrame, bounds: DataFrame) -> DataFrame:
        """Index rows that hold an asked term in a range (query_id, range) of its query."""
        spots = asked.select("query_id", "term").join(ranges, "query_id").select("term", "range").distinct()
        return self.index.join(bounds.join(spots, ["term", "range"]).select("term", "shard", "block").distinct(), ["term", "shard", "block"], "left_semi")

    def _in_chunks(self, asked: DataFrame, live: DataFrame, bounds: DataFrame, evaluate: Callable, k: int) -> DataFrame:
        """(query_id, doc_id, score) that ``evaluate`` finds in the live ranges (query_id, range, theta), a chunk of ranges at a time.

        Only compressed blocks, live ranges and lengths move to a chunk's task: a list is decoded
        there once for all queries, and rows of queries times postings are never made.
        """
        chunk = lambda c, width: F.floor(F.col(c) / width).alias("chunk")
        spots = asked.select("query_id", "term").join(live, "query_id").select("term", "range").distinct()
        where = bounds.join(spots, ["term", "range"], "left_semi").select("term", "shard", "block", chunk("range", CHUNK_RANGES)).distinct()
        blocks = self._blocks_of(asked).join(where, ["term", "shard", "block"]).select("chunk", "term", "df", "first_doc", "last_doc", *GAP_BYTES, *TF_BYTES)
        most = bounds.groupBy("term").agg(F.max("bound").alias("bound"))
        lists = asked.join(most, "term").groupBy("query_id").agg(F.sort_array(F.collect_list(F.struct("bound", "term"))).alias("l"))
        mine = live.groupBy("query_id", chunk("range", CHUNK_RANGES)).agg(F.collect_list("range").alias("ranges"), F.max("theta").alias("theta"))
        rows = mine.join(lists, "query_id").select("chunk", "query_id", "theta", F.col("l.term").alias("terms"), F.col("l.bound").alias("bounds"), "ranges", F.lit(None).cast("array<bigint>").alias("lens"))
        held = self.lengths.groupBy(chunk("doc_id", CHUNK_RANGES * OR_RANGE_DOCS)).agg(F.collect_list(F.struct("doc_id", "len")).alias("h"))
        none = lambda kind: F.lit(None).cast(kind)
        sizes = held.select("chunk", none("bigint"), none("double"), none("array<string>"), none("array<double>"), F.col("h.doc_id"), F.col("h.len"))
        both = blocks.groupBy("chunk").cogroup(rows.union(sizes).groupBy("chunk"))
        return both.applyInArrow(_in_chunk(evaluate, self.n_docs, self.mean_length, k), "query_id bigint, doc_id bigint, score double")

    def prune(self, asked: DataFrame, k: int = K) -> tuple[DataFrame, DataFrame, DataFrame]:
        """What an OR query must look at: block bounds, bounds (query_id, term, range, bound), and its live ranges (query_id, range, theta).

        A range's bound is the sum of its terms' bounds. The ranges of the largest bounds are
        scored first; their k-th best score is the threshold theta, and ranges below it are dead.
        A block spans ranges where it has no posting, so those ranges may hold fewer than k
        documents or none: then theta is 0 and every range is live.
        """
        bounds = written(self.block_bounds(asked), "block-bounds")
        each = asked.select("query_id", "term").join(bounds.groupBy("term", "range").agg(F.max("bound").alias("bound")), "term")
        total = written(each.groupBy("query_id", "range").agg(F.sum("bound").alias("most")), "range-bounds")
        # of equal bounds always the same ranges: the plan below reads ``best`` twice
        order = W.partitionBy("query_id").orderBy(F.desc("most"), F.desc("range"))
        best = total.withColumn("at", F.row_number().over(order)).where(F.col("at") <= FIRST_RANGES).select("query_id", "range", F.lit(0.0).alias("theta"))
        scores = top(self._in_chunks(asked, written(best, "first-ranges"), bounds, _every, k), k)
        theta = scores.groupBy("query_id").agg(F.when(F.count("*") == k, F.min("score")).otherwise(0.0).alias("theta"))
        known = total.join(theta, "query_id", "left").withColumn("theta", F.coalesce("theta", F.lit(0.0)))
        live = known.where(F.col("most") >= F.col("theta") - _SLACK).select("query_id", "range", "theta")
        return bounds, each, written(live, "live-ranges")

    def or_maxscore(self, asked: DataFrame, k: int = K) -> DataFrame:
        """Candidates come from the essential lists' live ranges only; the others are decoded where a candidate can still win."""
        bounds, _, live = self.prune(asked, k)
        return top(self._in_chunks(asked, live, bounds, _maxscore, k), k)

    def or_wand(self, asked: DataFrame, k: int = K) -> DataFrame:
        """Document at a time inside every live range: the pivot is the first list at which the bounds reach the threshold."""
        bounds, _, live = self.prune(asked, k)
        return top(self._in_chunks(asked, live, bounds, _wand, k), k)


class _Chunk:
    """The asked lists of a chunk of ranges: blocks are decoded when they are first needed."""

    def __init__(self, blocks: pa.Table, first: int, docs: np.ndarray, lens: np.ndarray, n_docs: int, mean_length: float):
        self.blocks, self.first, self.n_docs = blocks.combine_chunks().sort_by([("term", "ascending"), ("first_doc", "ascending")]), first, n_docs
        self.size = CHUNK_RANGES * OR_RANGE_DOCS
        self.norm = np.full(self.size, np.nan)
        self.norm[docs - first] = K1 * (1 - B + B * lens / mean_length)
        self.rows: dict[str, list[int]] = {}
        for i, term in enumerate(self.blocks["term"].to_pylist()):
            self.rows.setdefault(term, []).append(i)
        self.ends = (self.blocks["last_doc"].to_numpy() - first) // OR_RANGE_DOCS
        self.starts = (self.blocks["first_doc"].to_numpy() - first) // OR_RANGE_DOCS
        self.lists: dict[int, tuple[np.ndarray, np.ndarray]] = {}

    def of(self, term: str, ranges: np.ndarray) -> list[int]:
        """The blocks of a term that span one of ``ranges``."""
        before = np.concatenate([[0], np.cumsum(ranges)])
        return [i for i in self.rows.get(term, ()) if before[min(self.ends[i] + 1, CHUNK_RANGES)] > before[max(self.starts[i], 0)]]

    def decode(self, rows: set[int]) -> None:
        """The parts of blocks that are not decoded yet; what lies beyond the chunk or has no length is left out."""
        fresh = sorted(i for i in rows if i not in self.lists)
        if not fresh:
            return
        taken = self.blocks.take(pa.array(fresh))
        counts, docs, tfs = unpacked(taken)
        df = taken["df"].to_numpy().astype(float)
        weight = np.repeat(np.log(1 + (self.n_docs - df + 0.5) / (df + 0.5)), counts)
        at = docs - self.first
        norm = np.where((at >= 0) & (at < self.size), self.norm[np.clip(at, 0, self.size - 1)], np.nan)
        parts = weight * tfs * (K1 + 1) / (tfs + norm)
        ends = np.cumsum(counts)
        for i, a, z in zip(fresh, ends - counts, ends, strict=True):
            inside = ~np.isnan(parts[a:z])
            self.lists[i] = at[a:z][inside], parts[a:z][inside]

    def list(self, term: str, ranges: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(places in the chunk, parts) of a decoded term inside ``ranges``."""
        held = [self.lists[i] for i in self.of(term, ranges)]
        if not held:
            return np.zeros(0, np.int64), np.zeros(0)
        at, parts = (np.concatenate(x) for x in zip(*held, strict=True)) if len(held) > 1 else held[0]
        if ranges.all():
            return at, parts
        inside = ranges[at // OR_RANGE_DOCS]
        return at[inside], parts[inside]


def _kth(scores: np.ndarray, k: int) -> float:
    return float(np.partition(scores, len(scores) - k)[len(scores) - k]) if len(scores) >= k else 0.0


def _best(at: np.ndarray, scores: np.ndarray, k: int, theta: float = 0.0) -> tuple[np.ndarray, np.ndarray]:
    """What reaches ``theta`` and the k-th best score, ties of rounded scores with it."""
    kept = scores >= max(theta, _kth(scores, k)) - _SLACK
    return at[kept], scores[kept]


def _every(held: _Chunk, asked: list[dict], k: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    held.decode({i for q in asked for t in q["terms"] for i in held.of(t, q["ranges"])})
    for q in asked:
        total = np.zeros(held.size)
        for t in q["terms"]:
            at, parts = held.list(t, q["ranges"])
            total[at] += parts
        found = np.flatnonzero(total)
        yield _best(found, total[found], k)


def _maxscore(held: _Chunk, asked: list[dict], k: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    split = [np.cumsum(q["bounds"]) >= q["theta"] - _SLACK for q in asked]
    held.decode({i for q, s in zip(asked, split, strict=True) for t, e in zip(q["terms"], s, strict=True) if e for i in held.of(t, q["ranges"])})
    alive, wanted = [], set()
    for q, s in zip(asked, split, strict=True):
        total = np.zeros(held.size)
        for t in (t for t, e in zip(q["terms"], s, strict=True) if e):
            at, parts = held.list(t, q["ranges"])
            total[at] += parts
        found = np.flatnonzero(total)
        first, rest = total[found], float(np.sum(np.array(q["bounds"])[~s]))
        can = first + rest >= max(q["theta"], _kth(first, k)) - _SLACK
        found, first = found[can], first[can]
        spots = np.zeros(CHUNK_RANGES, bool)
        spots[found // OR_RANGE_DOCS] = True
        alive.append((found, first, spots))
        wanted |= {i for t, e in zip(q["terms"], s, strict=True) if not e for i in held.of(t, spots)}
    held.decode(wanted)
    for q, s, (found, first, spots) in zip(asked, split, alive, strict=True):
        total = np.zeros(held.size)
        total[found] = first
        for t in (t for t, e in zip(q["terms"], s, strict=True) if not e):
            at, parts = held.list(t, spots)
            total[at] += parts
        yield _best(found, total[found], k, q["theta"])


def _in_chunk(evaluate: Callable, n_docs: int, mean_length: float, k: int) -> Callable:
    schema = pa.schema([("query_id", pa.int64()), ("doc_id", pa.int64()), ("score", pa.float64())])

    def run(key: tuple, blocks: pa.Table, rows: pa.Table) -> pa.Table:
        first = key[0].as_py() * CHUNK_RANGES * OR_RANGE_DOCS
        asked = rows.filter(pc.is_valid(rows["query_id"])).drop_columns(["lens"]).to_pylist()
        sizes = rows.filter(pc.is_null(rows["query_id"]))
        if not asked or not blocks.num_rows or not sizes.num_rows:
            return schema.empty_table()
        for q in asked:
            spots = np.zeros(CHUNK_RANGES, bool)
            spots[np.array(q["ranges"]) - first // OR_RANGE_DOCS] = True
            q["ranges"] = spots
        held = _Chunk(blocks, first, pc.list_flatten(sizes["ranges"]).to_numpy(), pc.list_flatten(sizes["lens"]).to_numpy(), n_docs, mean_length)
        found = list(evaluate(held, asked, k))
        ids = np.repeat(np.array([q["query_id"] for q in asked], np.int64), [len(at) for at, _ in found])
        return pa.table([pa.array(ids), pa.array(np.concatenate([at for at, _ in found]).astype(np.int64) + first), pa.array(np.concatenate([s for _, s in found]))], schema=schema)

    return run


def wand(lists: list[tuple[np.ndarray, np.ndarray]], k: int, theta: float) -> tuple[list[tuple[float, int]], int]:
    """(score, -doc) of lists (ascending docs, parts) that reach ``theta`` and the k-th best score, and how many documents were scored.

    More than k come back where scores below the k-th best may still equal it when rounded: the ranking decides them.
    """
    docs, scores, scored = wand_arrays(lists, k, theta)
    return list(zip(scores.tolist(), (-docs).tolist(), strict=True)), scored


def wand_arrays(lists: list[tuple[np.ndarray, np.ndarray]], k: int, theta: float) -> tuple[np.ndarray, np.ndarray, int]:
    """(docs, scores, scored) of ``wand``. The pivots of a stretch of documents are found together: those whose lists' bounds reach the threshold as it is at its start."""
    lists = [x for x in lists if len(x[0])]
    bounds = [float(p.max()) for _, p in lists]
    at = [0] * len(lists)
    kept: list[tuple[np.ndarray, np.ndarray]] = []
    heap, scored = np.zeros(0), 0
    while True:
        live = [i for i, a in enumerate(at) if a < len(lists[i][0])]
        floor = max(theta, float(heap.min()) if len(heap) == k else 0.0) - _SLACK
        if not live or sum(bounds[i] for i in live) < floor:
            break
        begin = min(int(lists[i][0][at[i]]) for i in live)
        reach, pieces = np.zeros(STRETCH_DOCS), []
        for i in live:
            d, p = lists[i]
            end = at[i] + int(np.searchsorted(d[at[i] : at[i] + STRETCH_DOCS], begin + STRETCH_DOCS))
            spots = d[at[i] : end] - begin
            reach[spots] += bounds[i]
            pieces.append((spots, p[at[i] : end]))
            at[i] = end
        pivots = np.flatnonzero((reach > 0) & (reach >= floor))
        if not len(pivots):
            continue
        total = np.zeros(STRETCH_DOCS)
        for spots, parts in pieces:
            total[spots] += parts
        scored += len(pivots)
        scores = total[pivots]
        good = scores >= floor
        if good.any():
            kept.append((pivots[good] + begin, scores[good]))
            heap = np.concatenate([heap, scores[good]])
            if len(heap) > k:
                heap = np.partition(heap, len(heap) - k)[-k:]
    floor = max(theta, float(heap.min()) if len(heap) == k else 0.0) - _SLACK
    found, scores = (np.concatenate(x) for x in zip(*kept, strict=True)) if kept else (np.zeros(0, np.int64), np.zeros(0))
    good = scores >= floor
    return found[good], scores[good], scored


def _wand(held: _Chunk, asked: list[dict], k: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    held.decode({i for q in asked for t in q["terms"] for i in held.of(t, q["ranges"])})
    for q in asked:
        docs, scores, _ = wand_arrays([held.list(t, q["ranges"]) for t in q["terms"]], k, q["theta"])
        yield docs, scores
