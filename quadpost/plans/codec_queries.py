"""Queries over codecs: what they decide, their sizes, their round trips and reports."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql import Window as W

from quadpost.codecs import frames
from quadpost.codecs.base import Codec
from quadpost.codecs.base import names as codec_names
from quadpost.codecs.quad_selector import SELECTORS
from quadpost.functions import expressions as E
from quadpost.operators import blocks as B
from quadpost.operators import corpus
from quadpost.operators.index import index_sizes
from quadpost.plans import sql
from quadpost.plans.index_queries import long_gaps, s1
from quadpost.plans.size_sql import BLK, FORMS, lane_frame_form, lane_plan_form, measured, threshold_form
from quadpost.sources import tables

QUERIES, ORACLES = {}, {}


def query(name: str, oracle: str | None = None):
    def add(f):
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f

    return add


def gap_blocks(spark, d, col: str = "gaps"):
    """(term, block, values) of the long lists of documents."""
    return corpus.blocks(long_gaps(spark, d)).select("term", "block", F.col(col).alias("values"))


@query("q_effective_bits", sql.gaps() + " SELECT length(bin(gap)) AS bits, count(*) AS gaps FROM gaps GROUP BY ALL")
def q_effective_bits(spark, d):
    return long_gaps(spark, d).groupBy(E.effective_bits(F.col("gap")).cast("long").alias("bits")).agg(F.count("*").alias("gaps"))


_GAP_ROWS = sql.ROWS.format(values="gap")


@query("q_quad_max", sql.gaps("documents", _GAP_ROWS, sql.QUADS) + " SELECT term, block, list(m ORDER BY q) AS maxima FROM quad GROUP BY ALL")
def q_quad_max(spark, d):
    return gap_blocks(spark, d).select("term", "block", E.quad_max(F.col("values")).alias("maxima"))


@query("q_quad_or", sql.gaps("documents", _GAP_ROWS, sql.QUADS) + " SELECT term, block, q, o AS pseudo, length(bin(m)) = length(bin(o)) AS same_bits FROM quad")
def q_quad_or(spark, d):
    """The pseudo maximum of each quad, as rows: a bitwise aggregate with a partial sum on the map side."""
    rows = long_gaps(spark, d).select("term", F.floor(F.col("pos") / corpus.BLOCK).alias("block"), F.floor(F.col("pos") % corpus.BLOCK / 4).alias("q"), "gap")
    o = rows.groupBy("term", "block", "q").agg(F.bit_or("gap").alias("pseudo"), F.max("gap").alias("m"))
    return o.select("term", "block", "q", "pseudo", (E.effective_bits(F.col("m")) == E.effective_bits(F.col("pseudo"))).alias("same_bits"))


_SELECTOR_WALK = sql.walk([(n, b) for _, n, b in SELECTORS], sql.QUAD_NEED)


@query("q_selector_modes", sql.blocks("gap", "documents", _SELECTOR_WALK) + " SELECT term, block, list(cast(sel AS INT) ORDER BY ofs) AS modes FROM steps GROUP BY ALL")
def q_selector_modes(spark, d):
    return gap_blocks(spark, d).select("term", "block", E.selector_modes(F.col("values")).alias("modes"))


@query("q_selector_bits", sql.blocks("gap", "documents", _SELECTOR_WALK) + " SELECT term, block, 132 * count(*) AS bits FROM steps GROUP BY ALL")
def q_selector_bits(spark, d):
    """From the encoder itself; the modes above come from the expression."""
    return B.sizes(gap_blocks(spark, d), ["quad_selector"]).select("term", "block", "bits")


@query("q_lane_components", sql.gaps("documents", _GAP_ROWS) + " SELECT term, block, i % 4 AS lane, list(x ORDER BY i) AS members FROM rows GROUP BY ALL")
def q_lane_components(spark, d):
    rows = long_gaps(spark, d).select("term", F.floor(F.col("pos") / corpus.BLOCK).alias("block"), F.pmod("pos", F.lit(4)).alias("lane"), "pos", "gap")
    held = F.sort_array(F.collect_list(F.struct("pos", "gap")))
    return rows.groupBy("term", "block", "lane").agg(held.alias("h")).select("term", "block", "lane", F.col("h.gap").alias("members"))


_WAYS = [(cg, c) for cg in (1, 2, 4, 8) for c in ("b", "cu")]


@query(
    "q_ld_values",
    sql.gaps("documents", _GAP_ROWS, sql.QUADS)
    + " SELECT cg, coding, stored, width, count(*) AS quads FROM ("
    + " UNION ALL ".join(f"SELECT {cg} AS cg, '{c}' AS coding, cast(ceil(length(bin(m)) / {cg}) AS BIGINT) - {int(c == 'b')} AS stored, cast({cg} * ceil(length(bin(m)) / {cg}) AS BIGINT) AS width FROM quad" for cg, c in _WAYS)
    + ") GROUP BY ALL",
)
def q_ld_values(spark, d):
    """What the control area stores per granularity and coding, and the width that a reader makes of it."""
    maxima = gap_blocks(spark, d).select(F.explode(E.quad_max(F.col("values"))).alias("m"))
    per = maxima.groupBy("m").agg(F.count("*").alias("quads"))
    ways = F.explode(F.array(*[F.struct(F.lit(cg).alias("cg"), F.lit(c).alias("coding"), E.stored_descriptor(F.col("m"), cg, c).alias("stored"), E.width_of(E.stored_descriptor(F.col("m"), cg, c), cg, c).alias("width")) for cg, c in _WAYS]))
    return per.select("quads", ways.alias("w")).groupBy("w.cg", "w.coding", "w.stored", "w.width").agg(F.sum("quads").alias("quads"))


@query(
    "q_ld_ctrl_bits",
    sql.gaps("documents", _GAP_ROWS, sql.QUADS)
    + " SELECT term, block, codec, cast(bits AS BIGINT) AS ctrl_bits FROM ("
    + " UNION ALL ".join(
        [f"SELECT term, block, 'ql_{cg}_b' AS codec, {sql._UNIT[cg][0]} * ceil(count(*) / {sql._UNIT[cg][1]}) AS bits FROM quad GROUP BY ALL" for cg in (1, 2, 4, 8)]
        + [f"SELECT term, block, 'ql_{cg}_cu' AS codec, 8 * ceil(sum(ceil(length(bin(m)) / {cg})) / 8) AS bits FROM quad GROUP BY ALL" for cg in (1, 2, 4, 8)]
    )
    + ")",
)
def q_ld_ctrl_bits(spark, d):
    return B.sizes(gap_blocks(spark, d), [f"ql_{cg}_{c}" for cg, c in _WAYS]).select("term", "block", "codec", "ctrl_bits")


def _iu_sql(cg: int) -> str:
    unit = f"list_transform({sql.QUAD_NEED}, lambda b: cast(ceil(b / {cg}) AS BIGINT))"
    return sql.blocks("gap", "documents", sql.fill(unit, 8)) + f" SELECT term, block, 'ql_{cg}_iu' AS codec, 8 * max(groups) AS ctrl_bits FROM fills GROUP BY ALL"


@query("q_iu_ctrl_bits", f"SELECT * FROM ({_iu_sql(4)}) UNION ALL SELECT * FROM ({_iu_sql(8)})")
def q_iu_ctrl_bits(spark, d):
    return B.sizes(gap_blocks(spark, d), ["ql_4_iu", "ql_8_iu"]).select("term", "block", "codec", F.col("ctrl_bits").cast("long").alias("ctrl_bits"))


@query("q_bit_offsets", sql.gaps("documents", _GAP_ROWS, sql.QUADS) + " SELECT term, block, q, ofs // 32 AS component, ofs % 32 AS bit, ofs % 32 + w > 32 AS split FROM (SELECT term, block, q, w, coalesce(sum(w) OVER (PARTITION BY term, block ORDER BY q ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS ofs FROM (SELECT term, block, q, length(bin(m)) AS w FROM quad))")
def q_bit_offsets(spark, d):
    """Where each quad of the granularity-1 codec stands in its lanes: a running sum of widths."""
    rows = long_gaps(spark, d).select("term", F.floor(F.col("pos") / corpus.BLOCK).alias("block"), F.floor(F.col("pos") % corpus.BLOCK / 4).alias("q"), "gap")
    width = rows.groupBy("term", "block", "q").agg(E.effective_bits(F.max("gap")).alias("w"))
    before = W.partitionBy("term", "block").orderBy("q").rowsBetween(W.unboundedPreceding, -1)
    at = width.withColumn("at", F.coalesce(F.sum("w").over(before), F.lit(0)).cast("long"))
    return at.select("term", "block", "q", F.floor(F.col("at") / 32).alias("component"), F.pmod("at", F.lit(32)).alias("bit"), (F.pmod("at", F.lit(32)) + F.col("w") > 32).alias("split"))


@query("q_afor_partition", sql.blocks("gap", "documents", sql.frames(sql.QUAD_NEED, 8, (8, 16, 32), 4)) + " SELECT term, block, best[1] AS cost FROM plan WHERE done = len(c)")
def q_afor_partition(spark, d):
    """The least cost of an adaptive partition over quads: header and lane bits of the frames that the encoder chose."""
    from quadpost.codecs.base import codec

    @F.pandas_udf(T.LongType())
    def cost(values):
        import numpy as np

        from quadpost.codecs.frames import _lane_partition
        from quadpost.codecs.bits import bitlen
        from quadpost.codecs.lanes import quad_or

        scheme = codec("quad_afor").options["scheme"]
        out = []
        for v in values:
            lengths, widths = _lane_partition(bitlen(quad_or(np.asarray(v).astype(np.uint64))), scheme.frames)
            out.append(int((8 + 4 * lengths * widths).sum()))
        import pandas as pd

        return pd.Series(out)

    return gap_blocks(spark, d).select("term", "block", cost("values").alias("cost"))


_PFOR = f"""pq AS (SELECT term, block, q // 32 AS frame, length(bin(m)) AS w FROM quad),
  cand AS (SELECT term, block, frame, b, count(*) FILTER (WHERE w > b) AS over, count(*) AS quads FROM pq, (SELECT unnest(range(1, 33)) AS b) GROUP BY ALL),
  fw AS (SELECT term, block, frame, min(b) AS width FROM cand WHERE over < 0.1 * quads GROUP BY ALL)"""


@query("q_pfor_width", sql.gaps("documents", _GAP_ROWS, sql.QUADS, _PFOR) + " SELECT term, block, frame, width FROM fw")
def q_pfor_width(spark, d):
    """The width of each frame of 32 quads: the least that leaves less than a tenth of the maxima as exceptions."""
    q = gap_blocks(spark, d).select("term", "block", F.posexplode(E.quad_max(F.col("values"))).alias("q", "m"))
    frame = q.select("term", "block", F.floor(F.col("q") / 32).alias("frame"), E.effective_bits(F.col("m")).alias("w"))
    hist = frame.groupBy("term", "block", "frame", "w").agg(F.count("*").alias("c"))
    above = W.partitionBy("term", "block", "frame").orderBy(F.desc("w")).rowsBetween(W.unboundedPreceding, -1)
    every = W.partitionBy("term", "block", "frame")
    cum = hist.withColumn("over", F.coalesce(F.sum("c").over(above), F.lit(0))).withColumn("quads", F.sum("c").over(every))
    return cum.where("over < 0.1 * quads").groupBy("term", "block", "frame").agg(F.min("w").cast("long").alias("width"))


@query(
    "q_exception_counts",
    sql.gaps("documents", _GAP_ROWS, sql.QUADS, _PFOR)
    + " SELECT term, block, frame, cast(count(*) FILTER (WHERE length(bin(x)) > width) AS BIGINT) AS exceptions, count(*) AS members FROM (SELECT term, block, i // 128 AS frame, x FROM rows) JOIN fw USING (term, block, frame) GROUP BY ALL",
)
def q_exception_counts(spark, d):
    """Integers beyond the width that their frame got from the quads' maxima."""
    width = q_pfor_width(spark, d)
    rows = long_gaps(spark, d).select("term", F.floor(F.col("pos") / corpus.BLOCK).alias("block"), F.floor(F.col("pos") % corpus.BLOCK / 128).alias("frame"), "gap")
    return rows.join(width, ["term", "block", "frame"]).groupBy("term", "block", "frame").agg(F.count_if(E.effective_bits(F.col("gap")) > F.col("width")).alias("exceptions"), F.count("*").alias("members"))


@query(
    "q_exceptions",
    sql.gaps("documents", _GAP_ROWS, sql.QUADS, _PFOR) + " SELECT term, block, i, x AS value, width FROM (SELECT term, block, i, i // 128 AS frame, x FROM rows) JOIN fw USING (term, block, frame) WHERE length(bin(x)) > width",
)
def q_exceptions(spark, d):
    width = q_pfor_width(spark, d)
    i = F.pmod("pos", F.lit(corpus.BLOCK))
    rows = long_gaps(spark, d).select("term", F.floor(F.col("pos") / corpus.BLOCK).alias("block"), i.alias("i"), F.floor(i / 128).alias("frame"), F.col("gap").alias("value"))
    return rows.join(width, ["term", "block", "frame"]).where(E.effective_bits(F.col("value")) > F.col("width")).select("term", "block", "i", "value", "width")


@query("q_bp128_width", sql.gaps("documents", _GAP_ROWS) + " SELECT term, block, i // 128 AS frame, length(bin(max(x))) AS width FROM rows GROUP BY ALL")
def q_bp128_width(spark, d):
    rows = long_gaps(spark, d).select("term", F.floor(F.col("pos") / corpus.BLOCK).alias("block"), F.floor(F.col("pos") % corpus.BLOCK / 128).alias("frame"), "gap")
    return rows.groupBy("term", "block", "frame").agg(E.effective_bits(F.max("gap")).cast("long").alias("width"))


@query("q_width_map", sql.gaps("documents", _GAP_ROWS) + " SELECT term, block, list(w || ':' || c ORDER BY w) AS widths FROM (SELECT term, block, length(bin(x)) AS w, count(*) AS c FROM rows GROUP BY ALL) GROUP BY ALL")
def q_width_map(spark, d):
    """A map from width to count for each block, shown as its sorted entries."""
    rows = long_gaps(spark, d).select("term", F.floor(F.col("pos") / corpus.BLOCK).alias("block"), E.effective_bits(F.col("gap")).alias("w"))
    hist = rows.groupBy("term", "block", "w").agg(F.count("*").alias("c")).groupBy("term", "block").agg(F.map_from_entries(F.collect_list(F.struct("w", "c"))).alias("m"))
    entries = F.array_sort(F.map_entries(F.transform_values("m", lambda k, v: v.cast("string"))))
    return hist.select("term", "block", F.transform(entries, lambda e: F.concat_ws(":", e["key"].cast("string"), e["value"])).alias("widths"))


@query("q_bitlen_hist", sql.gaps("documents", _GAP_ROWS) + " SELECT term, quantile_disc(length(bin(x)), 0.5) AS median_bits, cast(max(length(bin(x))) AS BIGINT) AS most_bits FROM rows GROUP BY ALL")
def q_bitlen_hist(spark, d):
    g = long_gaps(spark, d).select("term", E.effective_bits(F.col("gap")).cast("long").alias("w"))
    return g.groupBy("term").agg(F.expr("percentile_disc(0.5) WITHIN GROUP (ORDER BY w)").cast("long").alias("median_bits"), F.max("w").alias("most_bits"))


# --- round trips ---------------------------------------------------------------------------------------------------

_RT = {values: sql.gaps() + f" SELECT term, pos, {column} AS value FROM gaps" for values, column in (("gaps", "gap"), ("tfs", "tf"))}


def _roundtrip(name: str, col: str, backend: str = "lanes"):
    def run(spark, d):
        back = B.roundtrip(gap_blocks(spark, d, col), name, backend=backend)
        return back.select("term", "block", F.posexplode("values").alias("i", "value")).select("term", (F.col("block") * corpus.BLOCK + F.col("i")).alias("pos"), "value")

    run.__doc__ = f"Every value of the long lists ({col}), written and read by {name}."
    return run


#: The codecs that the paper's comparison keeps; these get a frequency round trip too.
KEPT = ("ql_1_cu", "ql_8_iu", "quad_selector", "quad_afor", "quad_pfor", "quad_bp128", "rice", "gamma", "vbyte", "gvb", "g8iu", "g8cu", "simple9", "simple16", "packed_binary", "pfor", "afor", "fastpfor")
for _name in codec_names():
    query(f"q_rt_{_name}", _RT["gaps"])(_roundtrip(_name, "gaps"))
for _name in KEPT:
    query(f"q_rt_tf_{_name}", _RT["tfs"])(_roundtrip(_name, "tfs"))
for _name in ("quad_selector", "ql_8_iu", "quad_pfor"):
    query(f"q_rt_scalar_{_name}", _RT["gaps"])(_roundtrip(_name, "gaps", "scalar"))

# --- sizes ---------------------------------------------------------------------------------------------------------


def _sizes(name: str):
    def run(spark, d):
        return B.sizes(gap_blocks(spark, d), [name]).select("term", "block", "n", "bits")

    run.__doc__ = f"Bits of every gap block under {name}, as the encoder counts them."
    return run


for _name in codec_names():
    query(f"q_bits_{_name}", measured({_name: FORMS[_name]}) + " SELECT term, block, n, bits FROM sizes")(_sizes(_name))

_ALL = {v: sql.all_sizes(sql.CLOSED, v) for v in ("gap", "tf")}


def _measured(spark, d, col="gaps"):
    return B.sizes(gap_blocks(spark, d, col), list(sql.CLOSED))


def _ratio(col):
    def run(spark, d):
        """Bits per integer: over all integers, and the mean over terms."""
        per = _measured(spark, d, col).groupBy("codec", "term").agg(F.sum("n").alias("n"), F.sum("bits").alias("bits"))
        return per.groupBy("codec").agg(F.sum("n").alias("n"), F.sum("bits").alias("bits"), F.round(F.sum("bits") / F.sum("n"), 6).alias("micro"), F.round(F.avg(F.col("bits") / F.col("n")), 6).alias("macro"))

    return run


for _label, _col, _val in (("gap", "gaps", "gap"), ("tf", "tfs", "tf")):
    query(
        f"q_ratio_table_{_label}",
        _ALL[_val]
        + " SELECT codec, cast(sum(n) AS BIGINT) AS n, cast(sum(bits) AS BIGINT) AS bits, round(sum(bits) / sum(n), 6) AS micro, round(avg(bits / n), 6) AS macro FROM (SELECT codec, term, sum(n) AS n, sum(bits) AS bits FROM sizes GROUP BY ALL) GROUP BY codec",
    )(_ratio(_col))


def _ratio_all(collection: str, col: str):
    def run(spark, d):
        held = corpus.blocks(corpus.gaps(corpus.long_lists(corpus.postings(tables.collection(spark, d, collection)))))
        per = B.sizes(held.select("term", "block", F.col(col).alias("values")), codec_names()).groupBy("codec", "term").agg(F.sum("n").alias("n"), F.sum("bits").alias("bits"))
        return per.groupBy("codec").agg(F.sum("n").alias("n"), F.sum("bits").alias("bits"), F.round(F.sum("bits") / F.sum("n"), 6).alias("micro"), F.round(F.avg(F.col("bits") / F.col("n")), 6).alias("macro"))

    run.__doc__ = f"Bits per integer of every codec on the {col} of {collection}: over all integers, and the mean over terms."
    return run


for _coll in tables.COLLECTIONS:
    for _label, _col, _val in (("gap", "gaps", "gap"), ("tf", "tfs", "tf")):
        query(
            f"q_ratio_{_coll}_{_label}",
            measured(FORMS, _val, _coll)
            + " SELECT codec, cast(sum(n) AS BIGINT) AS n, cast(sum(bits) AS BIGINT) AS bits, round(sum(bits) / sum(n), 6) AS micro, round(avg(bits / n), 6) AS macro FROM (SELECT codec, term, sum(n) AS n, sum(bits) AS bits FROM sizes GROUP BY ALL) GROUP BY codec",
        )(_ratio_all(_coll, _col))


@query("q_size_expr", _ALL["gap"] + " SELECT codec, cast(sum(bits) AS BIGINT) AS bits FROM sizes WHERE codec <> 'golomb' GROUP BY codec UNION ALL SELECT 'quad_selector', cast(132 * count(*) AS BIGINT) FROM (" + sql.blocks("gap", "documents", _SELECTOR_WALK) + " SELECT * FROM steps)")
def q_size_expr(spark, d):
    """The same totals from expressions alone: no value leaves the JVM."""
    names = [n for n in sql.CLOSED if n != "golomb"] + ["quad_selector"]
    g = gap_blocks(spark, d).withColumn("b", E.value_bits(F.col("values"))).withColumn("q", E.quad_bits(F.col("b")))
    each = F.explode(F.array(*[F.struct(F.lit(n).alias("codec"), E.size_expr(n, F.col("values"), F.col("b"), F.col("q")).cast("long").alias("bits")) for n in names]))
    return g.select(each.alias("x")).groupBy("x.codec").agg(F.sum("x.bits").alias("bits"))


_FAMILY = [f"ql_{cg}_{c}" for cg, c in _WAYS] + ["ql_4_iu", "ql_8_iu"]


@query("q_family_bits", measured({n: FORMS[n] for n in _FAMILY}) + " SELECT codec, cast(substr(codec, 4, 1) AS INT) AS cg, substr(codec, 6) AS coding, cast(sum(bits) AS BIGINT) AS bits, round(sum(bits) / sum(n), 6) AS micro FROM sizes GROUP BY codec")
def q_family_bits(spark, d):
    """All ten members of the family by granularity and coding."""
    m = B.sizes(gap_blocks(spark, d), _FAMILY)
    return m.groupBy("codec").agg(F.sum("bits").alias("bits"), F.round(F.sum("bits") / F.sum("n"), 6).alias("micro")).select("codec", F.substring("codec", 4, 1).cast("int").alias("cg"), F.substring("codec", 6, 9).alias("coding"), "bits", "micro")


def _both(spark, d):
    return _measured(spark, d, "gaps").withColumn("seq", F.lit("gap")).unionByName(_measured(spark, d, "tfs").withColumn("seq", F.lit("tf")))


_BOTH = f"(SELECT 'gap' AS seq, * FROM ({_ALL['gap']} SELECT * FROM sizes) UNION ALL SELECT 'tf', * FROM ({_ALL['tf']} SELECT * FROM sizes))"


@query("q_bits_rollup", f"SELECT seq, codec, cast(sum(bits) AS BIGINT) AS bits, cast(sum(n) AS BIGINT) AS n FROM {_BOTH} GROUP BY ROLLUP (seq, codec)")
def q_bits_rollup(spark, d):
    return _both(spark, d).rollup("seq", "codec").agg(F.sum("bits").alias("bits"), F.sum("n").alias("n"))


@query("q_bits_cube", f"SELECT seq, codec, cast(sum(bits) AS BIGINT) AS bits FROM {_BOTH} GROUP BY CUBE (seq, codec)")
def q_bits_cube(spark, d):
    return _both(spark, d).cube("seq", "codec").agg(F.sum("bits").alias("bits"))


@query("q_bits_pivot", f"SELECT codec, cast(sum(bits) FILTER (WHERE seq = 'gap') AS BIGINT) AS gap, cast(sum(bits) FILTER (WHERE seq = 'tf') AS BIGINT) AS tf FROM {_BOTH} GROUP BY codec")
def q_bits_pivot(spark, d):
    return _both(spark, d).groupBy("codec").pivot("seq", ["gap", "tf"]).agg(F.sum("bits"))


@query("q_codec_rank", _ALL["gap"] + " SELECT codec, cast(dense_rank() OVER (ORDER BY bits) AS INT) AS rank FROM (SELECT codec, sum(bits) AS bits FROM sizes GROUP BY codec)")
def q_codec_rank(spark, d):
    total = _measured(spark, d).groupBy("codec").agg(F.sum("bits").alias("bits"))  # one row per codec
    return total.select("codec", F.dense_rank().over(W.orderBy("bits")).alias("rank"))


@query("q_choose_codec", _ALL["gap"] + " SELECT term, block, list_min(list({'bits': bits, 'codec': codec})).codec AS chosen FROM sizes WHERE codec IN ('vbyte', 'gamma', 'packed_binary', 'quad_bp128', 'ql_1_cu', 'rice') GROUP BY ALL")
def q_choose_codec(spark, d):
    """The smallest of a choice of codecs for each block, from size expressions."""
    from quadpost.operators.choose import choose_codec

    return choose_codec(gap_blocks(spark, d), ("vbyte", "gamma", "packed_binary", "quad_bp128", "ql_1_cu", "rice")).select("term", "block", "chosen")


@query("q_ctrl_data_bits")
def q_ctrl_data_bits(spark, d):
    """How the bits of each codec divide into control, data, exceptions and headers."""
    m = B.sizes(gap_blocks(spark, d), [n for n in codec_names()])
    return m.groupBy("codec").agg(*[F.sum(c).alias(c) for c in ("n", "bits", "ctrl_bits", "data_bits", "exc_bits", "head_bits")])


def _index_size_sql(collection: str) -> str:
    """Long lists by each codec, short ones by variable byte codes, two 64-bit ids a block; a block's first gap counts as 1."""
    local = f"lg AS (SELECT term, df, pos, CASE WHEN pos % {corpus.BLOCK} = 0 THEN 1 ELSE gap END AS gap, tf FROM gaps JOIN dict USING (term))"
    pieces = []
    for values in ("gap", "tf"):
        rows = f"rows AS (SELECT term, pos // {corpus.BLOCK} AS block, pos % {corpus.BLOCK} AS i, {values} AS x FROM lg WHERE df >= {corpus.SHORT_LIST})"
        blk = BLK.format(values=values, source=f"(SELECT * FROM lg WHERE df >= {corpus.SHORT_LIST})")
        short = f"(SELECT coalesce(sum(8 * ceil({sql.bits_of(values)} / 7)), 0) FROM lg WHERE df < {corpus.SHORT_LIST})"
        skip = f"(SELECT 128 * count(*) FROM (SELECT DISTINCT term, pos // {corpus.BLOCK} FROM lg))"
        each = " UNION ALL ".join(f"SELECT '{n}' AS codec, '{values}' AS seq, (SELECT coalesce(sum(bits), 0) FROM {FORMS[n]}) + {short} AS bits, {skip} AS skip, (SELECT count(*) FROM lg) AS postings" for n in KEPT_INDEXES)
        pieces.append(f"SELECT * FROM ({sql.postings(collection, sql.DICTIONARY, sql.GAPS.format(source='tf'), local, rows, sql.QUADS, blk)} {each})")
    total = "cast(max(postings) AS BIGINT) AS postings, cast(sum(bits) FILTER (WHERE seq = 'gap') AS BIGINT) AS gap_bits, cast(sum(bits) FILTER (WHERE seq = 'tf') AS BIGINT) AS tf_bits, cast(max(skip) AS BIGINT) AS skip_bits, cast(sum(bits) + max(skip) AS BIGINT) AS bits"
    return f"SELECT codec, {total} FROM ({' UNION ALL '.join(pieces)}) GROUP BY codec"


#: The codecs whose indexes are compared: those kept above, and no coding at all.
KEPT_INDEXES = (*KEPT, "uncompressed")


def _index_size(collection: str):
    def run(spark, d):
        return index_sizes(corpus.postings(tables.collection(spark, d, collection)), KEPT_INDEXES)

    run.__doc__ = f"Bits of whole indexes of {collection}: short lists by variable byte codes, skip pointers, and all together."
    return run


for _coll in tables.COLLECTIONS:
    query("q_index_size" if _coll == "documents" else f"q_index_size_{_coll}", _index_size_sql(_coll))(_index_size(_coll))


_RELATION_SIZES = ("gamma", "vbyte", "gvb", "g8cu", "packed_binary", "quad_bp128", "ql_1_cu", "ql_8_b")


@query(
    "q_rel_postings_bits",
    " UNION ALL ".join(
        f"SELECT '{name}' AS relation, codec, cast(sum(bits) AS BIGINT) AS bits FROM (WITH tf AS (SELECT DISTINCT cast({key} AS VARCHAR) || ':' || {member} // {corpus.SHARD_DOCS} AS term, {member} % {corpus.SHARD_DOCS} AS doc_id, 1 AS tf FROM {source}), {sql.GAPS.format(source='tf')}, {_GAP_ROWS}, {sql.QUADS} "
        + " UNION ALL ".join(f"SELECT '{n}' AS codec, bits FROM {sql.sizes_of(n)}" for n in _RELATION_SIZES)
        + ") GROUP BY codec"
        for name, (source, key, member) in tables.RELATIONS.items()
    ),
)
def q_rel_postings_bits(spark, d):
    """Sizes on relational postings, where gaps are wide; gaps start again in every shard."""
    out = None
    for name in tables.RELATIONS:
        g = corpus.blocks(corpus.gaps(tables.relation(spark, d, name))).select("term", "block", F.col("gaps").alias("values"))
        row = B.sizes(g, list(_RELATION_SIZES)).groupBy("codec").agg(F.sum("bits").alias("bits")).select(F.lit(name).alias("relation"), "codec", "bits")
        out = row if out is None else out.unionByName(row)
    return out


_ZETAS = (0.02, 0.05, 0.1, 0.2, 0.3)


@query(
    "q_zeta_sweep",
    sql.gaps("documents", _GAP_ROWS, sql.QUADS)
    + f", pq AS (SELECT term, block, q // 32 AS frame, length(bin(m)) AS w FROM quad), cand AS (SELECT term, block, frame, b, count(*) FILTER (WHERE w > b) AS over, count(*) AS quads FROM pq, (SELECT unnest(range(1, 33)) AS b) GROUP BY ALL), z AS (SELECT unnest({list(_ZETAS)}) AS zeta), fw AS (SELECT zeta, term, block, frame, min(b) AS width FROM cand, z WHERE over < zeta * quads GROUP BY ALL)"
    + " SELECT cast(zeta AS DOUBLE) AS zeta, count(*) AS frames, cast(sum(width) AS BIGINT) AS widths FROM fw GROUP BY zeta",
)
def q_zeta_sweep(spark, d):
    """How the exception threshold moves the frames' widths: a broadcast grid of parameters."""
    q = gap_blocks(spark, d).select("term", "block", F.posexplode(E.quad_max(F.col("values"))).alias("q", "m"))
    hist = q.select("term", "block", F.floor(F.col("q") / 32).alias("frame"), E.effective_bits(F.col("m")).alias("w")).groupBy("term", "block", "frame", "w").agg(F.count("*").alias("c"))
    key = ["term", "block", "frame"]
    above = W.partitionBy(*key).orderBy(F.desc("w")).rowsBetween(W.unboundedPreceding, -1)
    cum = hist.withColumn("over", F.coalesce(F.sum("c").over(above), F.lit(0))).withColumn("quads", F.sum("c").over(W.partitionBy(*key)))
    grid = spark.createDataFrame([(z,) for z in _ZETAS], "zeta double")
    return cum.crossJoin(F.broadcast(grid)).where(F.col("over") < F.col("zeta") * F.col("quads")).groupBy("zeta", *key).agg(F.min("w").alias("w")).groupBy("zeta").agg(F.count("*").alias("frames"), F.sum("w").cast("long").alias("widths"))


_FRAMES = (32, 64, 128, 256, 512)


@query("q_frame_sweep", " UNION ALL ".join(f"SELECT {f} AS frame, cast(sum(8 + c * w) AS BIGINT) AS bits FROM ({sql.gaps('documents', _GAP_ROWS)} SELECT count(*) AS c, length(bin(max(x))) AS w FROM rows GROUP BY term, block, i // {f})" for f in _FRAMES))
def q_frame_sweep(spark, d):
    """Plain frames of growing size: fewer headers, wider values."""
    rows = long_gaps(spark, d).select("term", F.floor(F.col("pos") / corpus.BLOCK).alias("block"), F.pmod("pos", F.lit(corpus.BLOCK)).alias("i"), "gap")
    each = rows.select("*", F.explode(F.array(*map(F.lit, _FRAMES))).alias("frame"))
    per = each.groupBy("frame", "term", "block", F.floor(F.col("i") / F.col("frame")).alias("f")).agg(F.count("*").alias("c"), E.effective_bits(F.max("gap")).alias("w"))
    return per.groupBy("frame").agg(F.sum(8 + F.col("c") * F.col("w")).alias("bits"))


_LANE_FRAMES = {f"frames of {f}": lane_frame_form(f) for f in _FRAMES}
_PLANS = {"frames of " + " or ".join(map(str, p)): p for p in ((16, 32, 64), (32, 64), (32, 64, 128), (64, 128), (32, 64, 128, 256))}
_SHARES = {f"share below {z}": z for z in _ZETAS}
_TOTAL = " SELECT codec AS setting, cast(sum(bits) AS BIGINT) AS bits, round(sum(bits) / sum(n), 6) AS bits_per_int FROM sizes GROUP BY codec"


def _sweep(made: dict[str, Codec]):
    def run(spark, d):
        m = B.sizes(gap_blocks(spark, d), list(made), codecs=made)
        return m.groupBy(F.col("codec").alias("setting")).agg(F.sum("bits").alias("bits"), F.round(F.sum("bits") / F.sum("n"), 6).alias("bits_per_int"))

    return run


@query("q_sweep_quad_frames", measured(_LANE_FRAMES) + _TOTAL)
def q_sweep_quad_frames(spark, d):
    """Fixed frames in four lanes, by their length."""
    return _sweep({f"frames of {f}": frames.lift(frames.PACKED_BINARY, f"frames of {f}", (f,)) for f in _FRAMES})(spark, d)


@query("q_sweep_quad_afor", measured({n: lane_plan_form(p) for n, p in _PLANS.items()}) + _TOTAL)
def q_sweep_quad_afor(spark, d):
    """Adaptive frames in four lanes, by the lengths that the partition may choose from."""
    return _sweep({n: frames.lift(frames.AFOR, n, p) for n, p in _PLANS.items()})(spark, d)


@query("q_sweep_quad_pfor", measured({n: threshold_form(True, zeta=z) for n, z in _SHARES.items()}) + _TOTAL)
def q_sweep_quad_pfor(spark, d):
    """Patched frames in four lanes, by the share of exceptions that their width may leave."""
    return _sweep({n: frames.build(replace(frames.PFOR.options["scheme"], name=n, laned=True, zeta=z)) for n, z in _SHARES.items()})(spark, d)
