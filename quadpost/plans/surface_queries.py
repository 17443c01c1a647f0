"""The surface around the methods: events, windows, functions for SQL, and segments."""

from __future__ import annotations

from pyspark.sql import functions as F

from quadpost.functions.registered import bits_of_group, register
from quadpost.operators import blocks as B
from quadpost.operators import corpus
from quadpost.operators.index import decode_postings, merge_segments
from quadpost.plans import sql
from quadpost.plans.codec_queries import gap_blocks
from quadpost.sources import tables

QUERIES, ORACLES = {}, {}


def query(name: str, oracle: str | None = None):
    def add(f):
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f

    return add


@query("q_events_json", "SELECT event_type, count(*) AS events, count(props) AS with_props, cast(sum(length(props)) AS BIGINT) AS chars, count(json_extract_string(props, '$.k')) AS keyed FROM events GROUP BY event_type")
def q_events_json(spark, d):
    e = tables.table(spark, d, "events")
    return e.groupBy("event_type").agg(F.count("*").alias("events"), F.count("props").alias("with_props"), F.sum(F.char_length("props")).alias("chars"), F.count(F.get_json_object("props", "$.k")).alias("keyed"))


@query("q_event_gaps", "SELECT event_type, event_id, coalesce(s - lag(s) OVER (PARTITION BY event_type ORDER BY s, event_id), 0) AS gap FROM (SELECT event_type, event_id, cast(floor(epoch(ts)) AS BIGINT) AS s FROM events)")
def q_event_gaps(spark, d):
    """Seconds between neighbouring events of a type."""
    from pyspark.sql import Window as W

    e = tables.table(spark, d, "events").select("event_type", "event_id", F.unix_seconds(F.col("ts").cast("timestamp")).alias("s"))
    return e.select("event_type", "event_id", F.coalesce(F.col("s") - F.lag("s").over(W.partitionBy("event_type").orderBy("s", "event_id")), F.lit(0)).alias("gap"))


@query("q_win_tumbling", "SELECT cast(epoch(date_trunc('hour', ts)) AS BIGINT) AS start, event_type, count(*) AS events, count(DISTINCT user_id) AS users FROM events GROUP BY ALL")
def q_win_tumbling(spark, d):
    w = tables.table(spark, d, "events").groupBy(F.window("ts", "1 hour").alias("w"), "event_type").agg(F.count("*").alias("events"), F.count_distinct("user_id").alias("users"))
    return w.select(F.unix_seconds(F.col("w.start").cast("timestamp")).alias("start"), "event_type", "events", "users")


@query(
    "q_win_sliding",
    "SELECT start, count(*) AS events FROM (SELECT unnest([s - s % 900, s - s % 900 - 900, s - s % 900 - 1800, s - s % 900 - 2700]) AS start FROM (SELECT cast(floor(epoch(ts)) AS BIGINT) AS s FROM events)) GROUP BY start",
)
def q_win_sliding(spark, d):
    w = tables.table(spark, d, "events").groupBy(F.window("ts", "1 hour", "15 minutes").alias("w")).agg(F.count("*").alias("events"))
    return w.select(F.unix_seconds(F.col("w.start").cast("timestamp")).alias("start"), "events")


@query(
    "q_win_session",
    """WITH e AS (SELECT user_id, epoch_us(ts) AS t FROM events), m AS (SELECT *, CASE WHEN t - lag(t) OVER (PARTITION BY user_id ORDER BY t) < 7200000000 THEN 0 ELSE 1 END AS fresh FROM e),
    s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY t ROWS UNBOUNDED PRECEDING) AS k FROM m) SELECT user_id, cast(min(t) AS BIGINT) AS start, count(*) AS events FROM s GROUP BY user_id, k""",
)
def q_win_session(spark, d):
    w = tables.table(spark, d, "events").groupBy(F.session_window("ts", "2 hours").alias("w"), "user_id").agg(F.count("*").alias("events"))
    return w.select("user_id", F.unix_micros(F.col("w.start").cast("timestamp")).alias("start"), "events")


_GAP_ROWS = sql.ROWS.format(values="gap")


@query("q_bits_udaf", sql.gaps("documents", _GAP_ROWS) + " SELECT term, round(cast(sum(8 * ceil(length(bin(x)) / 7)) AS DOUBLE) / count(*), 6) AS bits_per_int FROM rows GROUP BY term")
def q_bits_udaf(spark, d):
    """Bits per integer of each term, by a grouped aggregate function over its blocks."""
    return gap_blocks(spark, d).groupBy("term").agg(F.round(bits_of_group("vbyte")(F.col("values")), 6).alias("bits_per_int"))


@query("q_decode_udtf", sql.gaps() + " SELECT term, pos // 512 AS block, pos % 512 AS pos, gap AS value FROM gaps")
def q_decode_udtf(spark, d):
    """Encoded blocks decoded by a table function in a lateral join."""
    register(spark)
    coded = B.encode_blocks(gap_blocks(spark, d), "quad_selector").select("term", "block", "codec", "n", "ctrl", "data", "exc")
    coded.createOrReplaceTempView("_quadpost_coded")
    return spark.sql("SELECT c.term, c.block, v.pos, v.value FROM _quadpost_coded c, LATERAL quadpost_decode(c.codec, c.n, c.ctrl, c.data, c.exc) v")


@query("q_sql_surface", sql.gaps("documents", _GAP_ROWS) + " SELECT term, block, cast(sum(8 * ceil(length(bin(x)) / 7)) AS BIGINT) AS vbyte, cast(sum(2 * length(bin(x)) - 1) AS BIGINT) AS gamma FROM rows GROUP BY ALL")
def q_sql_surface(spark, d):
    register(spark)
    gap_blocks(spark, d).createOrReplaceTempView("_quadpost_blocks")
    return spark.sql("SELECT term, block, quadpost_bits('vbyte', `values`) AS vbyte, quadpost_bits('gamma', `values`) AS gamma FROM _quadpost_blocks")


@query("q_merge_segments", sql.postings() + " SELECT term, doc_id, tf FROM tf")
def q_merge_segments(spark, d):
    """Local segments by document range, merged into one index and read back."""
    docs = tables.collection(spark, d, "documents")
    segments = corpus.postings(docs).withColumn("seg", F.floor(F.col("doc_id") / 300))
    return decode_postings(merge_segments(segments))
