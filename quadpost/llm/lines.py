"""Repeated line runs by a suffix array over line ids.

The corpus is one sequence of line ids, each document ended by a border that
equals nothing. Prefix doubling sorts its suffixes: round i ranks every suffix
by its first 2^i lines, from the ranks of the two halves of that prefix. Ranks
come from a range-partitioned sort of the distinct pairs, so no task sees more
than a range. A suffix whose prefix no other has is settled and leaves; a suffix
with a settled second half cannot repeat either. So a round holds only what
still repeats, in suffix array order, and doubling goes on until nothing does.

Suffixes of equal rank after round i are an interval of the longest-common-prefix
array of at least 2^i lines. A member after the interval's first starts a later
copy. Of each such suffix the deepest interval counts; neighbouring suffixes whose
first members are neighbours too make one run, whose length is exact: the lines
that the suffixes have beside one another, and the depth of the last. Deleted is
every line of a run of ``RUN_LINES`` lines or more, and a run of one line of
``MIN_WORDS`` words or more.

Defined cases: a null text has no lines and stays null; blank lines are never
deleted and end a run; "earlier" is by doc_id (null first), then text hash, then
line number; rows with equal doc_id and text are one document, and all of them
keep or lose the same lines; an empty table gives no rows; extra columns pass
through. A document that loses all its lines has an empty text.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from quadpost.llm.staging import drop, shuffle_parts, written

RUN_LINES, MIN_WORDS = 2, 5


def _key():
    return [F.col("doc_id").cast("long").alias("_q_doc"), F.xxhash64("text").alias("_q_hash")]


def line_ids(docs: DataFrame) -> DataFrame:
    """(_q_doc, _q_hash, pos, a, b, words) for every line that is not blank; (a, b) is the line's 128-bit id."""
    lines = docs.where("text IS NOT NULL").select(*_key(), F.posexplode(F.split("text", "\n")).alias("pos", "line"))
    return lines.where(F.col("line").rlike(r"\S")).select(
        "_q_doc", "_q_hash", "pos", F.xxhash64("line").alias("a"), F.xxhash64(F.lit(1), "line").alias("b"), F.size(F.split(F.trim("line"), r"\s+")).alias("words")
    )


def _ranked(suffixes: DataFrame, pair: list[str]) -> DataFrame:
    """Suffixes whose pair repeats, with its rank in sorted order and the first position that has it."""
    spark = suffixes.sparkSession
    at = F.struct("_q_doc", "_q_hash", "pos")
    repeated = suffixes.groupBy(*pair).agg(F.min(at).alias("first"), F.max(at).alias("last")).where("first != last").drop("last")
    ordered = repeated.repartitionByRange(shuffle_parts(spark), *pair).sortWithinPartitions(*pair)
    ranks = written(ordered.withColumn("rank", F.monotonically_increasing_id()), "line-ranks")
    keep = [c for c in suffixes.columns if c not in (*pair, "rank", "first")]
    ranked = written(suffixes.drop("first").join(ranks.withColumnRenamed("rank", "_q_rank"), pair).select(*keep, F.col("_q_rank").alias("rank"), "first"), "suffixes")
    drop(ranks)
    return ranked


def suffix_rounds(lines: DataFrame, length: int | None = None) -> list[tuple[int, DataFrame]]:
    """[(2^i, suffixes that share their first 2^i lines with another: position, words, rank, first)], until all are settled (or 2^i >= length)."""
    now, size, out = _ranked(lines, ["a", "b"]), 1, []
    while not now.isEmpty():
        out.append((size, now))
        if length and size >= length:
            break
        by = W.partitionBy("_q_doc", "_q_hash").orderBy("pos").rangeBetween(size, size)
        pairs = now.select("_q_doc", "_q_hash", "pos", "words", F.col("rank").alias("head"), F.first("rank").over(by).alias("tail")).where("tail IS NOT NULL")
        now, size = _ranked(pairs, ["head", "tail"]), size * 2
    return out


def repeated_runs(lines: DataFrame) -> DataFrame | None:
    """(_q_doc, _q_hash, pos, n, words, source): every later copy of a run of ``n`` lines from line ``pos`` on, and where it stands first; None if no line repeats.

    ``words`` are those of the run's first line.
    """
    found = None
    for size, suffixes in suffix_rounds(lines):
        copies = suffixes.where(F.struct("_q_doc", "_q_hash", "pos") > F.col("first")).select("_q_doc", "_q_hash", "pos", F.struct(F.lit(size).alias("size"), "first", "words").alias("copy"))
        found = copies if found is None else found.unionByName(copies)
    if found is None:
        return None
    deepest = found.groupBy("_q_doc", "_q_hash", "pos").agg(F.max_by("copy", "copy.size").alias("copy"))
    by = W.partitionBy("_q_doc", "_q_hash").orderBy("pos")
    before = F.lag("copy").over(by)
    source, earlier = F.col("copy.first"), before["first"]
    follows = (F.lag("pos").over(by) == F.col("pos") - 1) & (before["size"] == F.col("copy.size")) & earlier["_q_doc"].eqNullSafe(source["_q_doc"]) & (earlier["_q_hash"] == source["_q_hash"]) & (earlier["pos"] == source["pos"] - 1)
    runs = deepest.withColumn("fresh", F.when(follows, 0).otherwise(1)).withColumn("run", F.sum("fresh").over(by))
    return runs.groupBy("_q_doc", "_q_hash", "run").agg(
        F.min("pos").alias("pos"), (F.count("*") - 1 + F.max("copy.size")).cast("int").alias("n"), F.min_by("copy.words", "pos").alias("words"), F.min_by("copy.first", "pos").alias("source")
    ).drop("run")


def later_copies(docs: DataFrame) -> DataFrame:
    """(_q_doc, _q_hash, _q_cut array of line numbers, _q_longest): the lines of later copies of repeated runs."""
    runs = repeated_runs(line_ids(docs))
    if runs is None:
        return docs.sparkSession.createDataFrame([], "_q_doc bigint, _q_hash bigint, _q_cut array<int>, _q_longest int")
    cut = runs.where((F.col("n") >= RUN_LINES) | (F.col("words") >= MIN_WORDS))
    lines = cut.select("_q_doc", "_q_hash", "n", F.explode(F.sequence("pos", F.col("pos") + F.col("n") - 1)).alias("pos"))
    return lines.groupBy("_q_doc", "_q_hash").agg(F.collect_set("pos").alias("_q_cut"), F.max("n").alias("_q_longest"))


def _cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        names = batch.schema.names
        texts, cuts = batch.column(names.index("text")).to_pylist(), batch.column(names.index("_q_cut")).to_pylist()
        kept, total, gone = [], [], []
        for text, cut in zip(texts, cuts, strict=True):
            parts, drop = text.split("\n") if text is not None else [], set(cut or ())
            total.append(len(parts))
            gone.append(len(drop))
            kept.append(text if not drop else "\n".join(x for i, x in enumerate(parts) if i not in drop))
        longest = batch.column(names.index("_q_longest")).fill_null(0)
        columns = {n: batch.column(i) for i, n in enumerate(names) if n not in ("_q_cut", "_q_longest")} | {"text": pa.array(kept, pa.string()), "n_lines": pa.array(total, pa.int64()), "n_removed": pa.array(gone, pa.int64()), "longest_run": longest}
        yield pa.RecordBatch.from_arrays(list(columns.values()), list(columns))


_OWN = ("n_lines", "n_removed", "longest_run", "_q_doc", "_q_hash", "_q_cut", "_q_longest")


def dedup_lines(docs: DataFrame) -> DataFrame:
    """``docs`` with later copies of repeated line runs cut out of text, and columns n_lines, n_removed and longest_run (lines of the longest run cut)."""
    own = docs.select(*[F.col(f"`{c}`") for c in docs.columns if c not in _OWN])
    keyed = own.select("*", *_key())
    cuts = later_copies(docs).withColumnsRenamed({"_q_doc": "_q_d", "_q_hash": "_q_h"})
    joined = keyed.join(cuts, keyed["_q_doc"].eqNullSafe(cuts["_q_d"]) & (keyed["_q_hash"] == cuts["_q_h"]), "left").select(*[F.col(f"`{c}`") for c in own.columns], "_q_cut", "_q_longest")
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString() if f.name != 'text' else 'string'}" for f in own.schema)
    return joined.mapInArrow(_cut, f"{fields}, n_lines long, n_removed long, longest_run int")
