"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

Beside the seconds of each query: million integers a second of the codecs' kernels
(one core, mean of the runs) on the gaps of the long lists, and bits per integer; the
same on frequencies; query rates with the index built and timed
apart, and the share of decoding in them; gains of single ideas.
"""

from __future__ import annotations

import json
import os
import time

import numpy as np

from quadpost.plans import registry, workloads
from quadpost.session import local_session

QUERIES = ("q_df", "q_dgap", "q_blocks512", "q_rt_quad_selector", "q_rt_ql_8_iu", "q_rt_quad_pfor", "q_rt_quad_bp128", "q_ratio_table_gap", "q_size_expr", "q_merge_segments", "q_and_topk", "q_or_topk", "q_or_maxscore", "q_or_wand")
CODECS = ("rice", "gamma", "ql_1_cu", "vbyte", "gvb", "g8iu", "g8cu", "ql_8_iu", "simple9", "simple16", "quad_selector", "packed_binary", "pfor", "afor", "fastpfor", "quad_fastpfor", "quad_bp128", "quad_afor", "quad_pfor")

#: Swept on frequencies.
SWEPT = ("rice", *workloads.FAMILY, "vbyte", "quad_selector", "quad_bp128", "quad_afor", "quad_pfor")
#: AND queries on an index that stands.
RATED = ("quad_bp128", "vbyte")


def main() -> None:
    sf_dir, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    spark = local_session(cpus, "16g", 16)
    every = registry.queries()
    every["q_df"](spark, sf_dir).write.format("noop").mode("overwrite").save()  # warm-up
    seconds = {}
    for name in QUERIES:
        began = time.perf_counter()
        every[name](spark, sf_dir).write.format("noop").mode("overwrite").save()
        seconds[name] = round(time.perf_counter() - began, 3)
    speeds = {}
    for r in workloads.codec_sweep(spark, sf_dir, names=CODECS, runs=2).collect():
        speeds.setdefault(r["codec"], {"bits": round(r["bits_per_int"], 3)})[r["backend"]] = {"decode": round(r["decode_mis"], 2), "encode": round(r["encode_mis"], 2)}
    def compact(rows: list[dict]) -> list[dict]:
        return [{k: round(v, 3) if isinstance(v, float) else v for k, v in r.items()} for r in rows]

    more = {}
    for source, seq in (("documents", "tfs"),):
        rows = workloads.codec_sweep(spark, sf_dir, source, seq, SWEPT, ("lanes",), runs=1).collect()
        more[f"{source}_{seq}"] = {r["codec"]: {"bits": round(r["bits_per_int"], 3), "decode": round(r["decode_mis"], 2), "encode": round(r["encode_mis"], 2)} for r in rows}
    rates = workloads.query_rates(spark, sf_dir, RATED, runs=1)
    values = np.random.default_rng(1).geometric(0.05, 1 << 16)
    extra = {"more_codecs": more, "query_rates": compact(rates), "ablations": compact(workloads.ablations(values, 5))}
    print(json.dumps({"metric": "headline queries", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": sf_dir.rstrip("/").rsplit("sf", 1)[-1], "codecs": speeds, **extra}), flush=True)
    spark.stop()


if __name__ == "__main__":
    main()
