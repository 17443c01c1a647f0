"""The experiments: speed, size, query rate and ablations, each as one table.

Speeds are wall clock of numpy kernels inside Arrow tasks and are never compared
by value; sizes are exact.
"""

from __future__ import annotations

from time import perf_counter

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from quadpost.codecs import lanes, quad_length, quad_selector
from quadpost.codecs.base import names as codec_names
from quadpost.operators import blocks as B
from quadpost.operators import corpus, index, search
from quadpost.sources import tables
from quadpost.sources.shared import written

FAMILY = tuple(f"ql_{cg}_{ld}" for cg, ld in quad_length.WAYS)


def sequences(spark: SparkSession, sf_dir: str, source: str, seq: str = "gaps", sampled: bool = False) -> DataFrame:
    """(term, values) blocks of a collection's long lists; ``sampled``: only of terms that the benchmark's queries ask."""
    found = corpus.postings(tables.collection(spark, sf_dir, source))
    if sampled:
        n = found.select("doc_id").distinct().count()
        asked = search.query_terms(tables.table(spark, sf_dir, "benchmark"), corpus.dictionary(found), n)
        found = found.join(asked.select("term").distinct(), "term", "left_semi")
    return corpus.blocks(corpus.gaps(corpus.long_lists(found))).select("term", F.col(seq).alias("values"))


def codec_sweep(spark, sf_dir, source="documents", seq="gaps", names=None, backends=("lanes", "scalar"), runs=10, sampled=True) -> DataFrame:
    """(codec, backend, n, encode_mis, decode_mis, bits_per_int): the speed and size tables of one sequence kind."""
    names = list(names or codec_names())
    held = written(sequences(spark, sf_dir, source, seq, sampled), "sequences")
    size = B.sizes(held, names).groupBy("codec").agg((F.sum("bits") / F.sum("n")).alias("bits_per_int"))
    return B.timings(held, names, backends, runs=runs).join(size, "codec")


def index_sizes(spark, sf_dir, source="documents", names=None) -> DataFrame:
    """(codec, postings, gap_bits, tf_bits, skip_bits, bits) of whole indexes, short lists by variable byte codes."""
    return index.index_sizes(corpus.postings(tables.collection(spark, sf_dir, source)), tuple(names or codec_names()))


def query_rates(spark, sf_dir, names, source="documents", modes=("and",), runs=3) -> list[dict]:
    """Queries per second over the whole query set: [{codec, mode, queries, build_seconds, seconds, rate, decode_share}].

    The index is a written table, built and timed apart; each mode runs once to warm up.
    ``decode_share`` (of "and") is the time inside the codecs for the blocks that the
    queries read, over the queries' time on all task slots; what a task waits counts too.
    """
    out, found = [], written(corpus.postings(tables.collection(spark, sf_dir, source)), "postings")
    lengths = written(found.groupBy("doc_id").agg(F.sum("tf").alias("len")), "lengths")
    asked = written(search.query_terms(tables.table(spark, sf_dir, "benchmark"), corpus.dictionary(found), lengths.count()), "asked")
    n = asked.select("query_id").distinct().count()

    def seconds(make, times: int) -> float:
        began = perf_counter()
        for _ in range(times):
            make().write.format("noop").mode("overwrite").save()
        return (perf_counter() - began) / times

    for name in names:
        began = perf_counter()
        held = written(index.build_index(found, name), "index")
        build = perf_counter() - began
        searcher = search.Searcher(held, lengths)
        for mode in modes:
            ask = {"and": searcher.and_topk, "or": searcher.or_topk, "wand": searcher.or_wand, "maxscore": searcher.or_maxscore}[mode]
            seconds(lambda ask=ask: ask(asked), 1)
            took, share = seconds(lambda ask=ask: ask(asked), runs), None
            if mode == "and":
                touched = written(searcher.skipped_blocks(asked, searcher.candidates(asked)), "touched")
                spent = index.decode_ns(touched).agg(F.sum("ns")).first()[0] or 0
                share = spent / 1e9 / (took * spark.sparkContext.defaultParallelism)
            out.append({"codec": name, "mode": mode, "queries": n, "build_seconds": build, "seconds": took, "rate": n / took, "decode_share": share})
    return out


def _mis(f, n: int, runs: int) -> float:
    began = perf_counter()
    for _ in range(runs):
        f()
    return n * runs / (perf_counter() - began) / 1e6


def ablations(values: np.ndarray, runs: int = 20) -> list[dict]:
    """[{what, on_mis, off_mis, gain}]: each idea switched on and off on one array."""
    n, x = len(values), values.astype(np.uint64)
    s, m = quad_selector.QUAD_SELECTOR, quad_selector.QUAD_SELECTOR_MAX
    sb = s.encode(values)
    rows = [
        ("pseudo maximum, encode", lambda: s.encode(values), lambda: m.encode(values)),
        ("quads instead of integers in selection", lambda: quad_selector.select(lanes.quad_or(x)), lambda: quad_selector.select(x)),
        ("one routine per selector, decode", lambda: s.decode(sb), lambda: lanes.unpack(sb.data, *quad_selector._slots(quad_selector.read_selectors(sb), -(-n // 4)))),
    ]
    for cg, ld in quad_length.WAYS:
        c = quad_length.quad_length(cg, ld)
        b = c.encode(values)
        rows.append((f"table of control units, {c.name}", lambda b=b, cg=cg, ld=ld: quad_length.read_descriptors(b, cg, ld), lambda b=b, cg=cg, ld=ld: quad_length.read_descriptors(b, cg, ld, "bits")))
        rows.append((f"all units at once, {c.name}", lambda b=b, c=c: c.decode(b), lambda b=b, cg=cg, ld=ld: quad_length.decode_by_unit(b, cg, ld)))
    out = []
    for what, on, off in rows:
        a, z = _mis(on, n, runs), _mis(off, n, max(1, runs // 5))
        out.append({"what": what, "on_mis": a, "off_mis": z, "gain": a / z - 1})
    return out
