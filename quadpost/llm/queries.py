"""The registered queries of the training-data operators, each over whole tables with production parameters."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from quadpost.llm import chat, decontamination, html, language, lines, neighbours, packing, sharding, simhash, substrings
from quadpost.llm.staging import written

#: Bytes of text in a shard of op6_sharding.
SHARD_BYTES = 1 << 20
TEST_CONVERSATION = -7
TEST_TEXT = "</s>[INST] ok [/INST]"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html.extract(table(spark, sf_dir, "pages"))


def op2_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontamination.contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op3_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    kept = lines.dedup_lines(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return kept.select("doc_id", "n_lines", "n_removed", F.sha2(F.coalesce("text", F.lit("")), 256).alias("kept_sha256"))


def op4_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.classes(table(spark, sf_dir, "documents"))
    return found.select("doc_id", simhash.hex_digits(F.col("fp")).alias("fingerprint"), "component_id")


def op5_nearest_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neighbours.nearest(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 20 == 0)


def op6_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", F.octet_length("text").alias("_bytes"))
    return sharding.assign_shards(docs, "doc_id", F.col("_bytes"), SHARD_BYTES).select("doc_id", "shard", "depth", "page", "n_bytes", "shard_bytes", "oversize")


def op7_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substrings.dedup_substrings(table(spark, sf_dir, "documents")).select("doc_id", "n_words", "n_removed", "kept_sha256")


def op8_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"))


def op9_chat_formatting(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    extra = spark.range(2).select(
        F.lit(TEST_CONVERSATION).cast("long").alias("conv_id"), F.col("id").alias("turn"), F.when(F.col("id") == 0, F.lit("user")).otherwise(F.lit("assistant")).alias("role"), F.lit(TEST_TEXT).alias("text")
    )
    messages = written(chat.chain_messages(turns.unionByName(extra)), "conversation-messages")
    made = chat.format_paths(messages, chat.reply_paths(messages)).withColumn("turns", chat.read_turns(F.col("formatted"))).withColumn("loss", chat.read_loss(F.col("formatted"), F.col("loss_spans")))
    digest = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    return made.select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(digest, 256).alias("turns_sha256"),
        F.char_length("loss").cast("long").alias("loss_chars"),
        F.sha2("loss", 256).alias("loss_sha256"),
        F.char_length("formatted").cast("long").alias("formatted_chars"),
    )


def op10_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    found = language.predict(docs, language.fit(docs))
    return found.select("doc_id", language.held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score")


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

_OP2 = rf"""
WITH w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM documents),
b AS (SELECT cast(item_id AS VARCHAR) AS item_id, regexp_extract_all(translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM benchmark WHERE item_id IS NOT NULL),
bw AS (SELECT DISTINCT item_id, least(13, len(ws)) AS n, array_to_string(ws[i:i + least(13, len(ws)) - 1], ' ') AS g
       FROM (SELECT item_id, ws, unnest(range(1, greatest(1, len(ws) - 12) + 1)) AS i FROM b WHERE len(ws) > 0)),
sizes AS (SELECT DISTINCT n FROM bw),
dw AS (SELECT doc_id, n, i, array_to_string(ws[i:i + n - 1], ' ') AS g
       FROM (SELECT doc_id, ws, n, unnest(range(1, len(ws) - n + 2)) AS i FROM w, sizes WHERE len(ws) >= n)),
m AS (SELECT dw.doc_id, dw.n, dw.i, bw.item_id FROM dw JOIN bw USING (n, g)),
hits AS (SELECT doc_id, count(*) AS n_hit FROM (SELECT DISTINCT doc_id, unnest(range(i, i + n)) AS p FROM m) GROUP BY doc_id),
its AS (SELECT doc_id, count(*) AS n_items, string_agg(item_id, ',' ORDER BY item_id) AS ids FROM (SELECT DISTINCT doc_id, item_id FROM m) GROUP BY doc_id)
SELECT w.doc_id, cast(len(ws) AS BIGINT) AS n_words, cast(coalesce(n_hit, 0) AS BIGINT) AS n_hit, cast(coalesce(n_items, 0) AS BIGINT) AS n_items,
  sha256(coalesce(ids, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(ws) AS contaminated
FROM w LEFT JOIN hits USING (doc_id) LEFT JOIN its USING (doc_id)
"""

_OP3 = r"""
WITH l AS (SELECT doc_id, text IS NULL AS none, unnest(range(0, len(string_split(text, chr(10))))) AS pos, unnest(string_split(text, chr(10))) AS line FROM documents),
f AS (SELECT *, regexp_matches(line, '\S') AS solid, len(regexp_extract_all(line, '\S+')) AS words FROM l),
p AS (SELECT *, lead(line) OVER d AS next, lead(solid) OVER d AS next_solid FROM f WINDOW d AS (PARTITION BY doc_id ORDER BY pos)),
r AS (SELECT *, row_number() OVER (PARTITION BY solid, line ORDER BY doc_id, pos) AS k1,
        CASE WHEN solid AND next_solid THEN row_number() OVER (PARTITION BY solid AND coalesce(next_solid, FALSE), line, next ORDER BY doc_id, pos) ELSE 1 END AS k2 FROM p),
c AS (SELECT *, solid AND ((words >= 5 AND k1 > 1) OR k2 > 1 OR coalesce(lag(k2) OVER (PARTITION BY doc_id ORDER BY pos), 1) > 1) AS cut FROM r),
g AS (SELECT doc_id, count(*) AS n_lines, count(*) FILTER (WHERE cut) AS n_removed, string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT cut) AS kept FROM c GROUP BY doc_id)
SELECT d.doc_id, cast(coalesce(n_lines, 0) AS BIGINT) AS n_lines, cast(coalesce(n_removed, 0) AS BIGINT) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256
FROM documents d LEFT JOIN g USING (doc_id)
"""

_OP6 = f"""
WITH r AS (SELECT doc_id, coalesce(strlen(text), 0) AS n_bytes, cast('0x' || substr(md5(coalesce(cast(doc_id AS VARCHAR), '')), 1, 15) AS BIGINT) AS h FROM documents),
d AS (SELECT unnest(range(0, 61)) AS depth),
s AS (SELECT depth, h >> (60 - depth) AS prefix, sum(n_bytes) AS shard_bytes, min(h) = max(h) AS one FROM r, d GROUP BY ALL),
leaf AS (SELECT r.doc_id, r.h, r.n_bytes, min(s.depth) AS depth FROM r JOIN s ON s.prefix = r.h >> (60 - s.depth) WHERE s.shard_bytes <= {SHARD_BYTES} OR s.one GROUP BY ALL)
SELECT leaf.doc_id, CASE WHEN leaf.depth = 0 THEN '' ELSE lpad(bin(s.prefix), leaf.depth::INT, '0') END AS shard, cast(leaf.depth AS INT) AS depth, 0 AS page,
  cast(leaf.n_bytes AS BIGINT) AS n_bytes, cast(s.shard_bytes AS BIGINT) AS shard_bytes, s.shard_bytes > {SHARD_BYTES} AS oversize
FROM leaf JOIN s ON s.depth = leaf.depth AND s.prefix = leaf.h >> (60 - leaf.depth)
"""

_OP7 = r"""
WITH w AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS ws FROM documents),
g AS (SELECT doc_id, i, array_to_string(ws[i:i + 49], ' ') AS s FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 48)) AS i FROM w WHERE len(ws) >= 50)),
f AS (SELECT doc_id, i, min(doc_id) OVER (PARTITION BY s) < doc_id AS cut FROM g),
c AS (SELECT DISTINCT doc_id, unnest(range(i, i + 50)) AS p FROM f WHERE cut),
n AS (SELECT doc_id, list(p) AS ps FROM c GROUP BY doc_id),
k AS (SELECT w.doc_id, len(ws) AS n_words, coalesce(len(ps), 0) AS n_removed, CASE WHEN ps IS NULL THEN ws ELSE list_filter(ws, lambda x, i: NOT list_contains(ps, i)) END AS kept FROM w LEFT JOIN n USING (doc_id))
SELECT doc_id, cast(n_words AS BIGINT) AS n_words, cast(n_removed AS BIGINT) AS n_removed, sha256(coalesce(array_to_string(kept, ' '), '')) AS kept_sha256 FROM k
"""


def _escaped_length(column: str) -> str:
    text = f"replace(coalesce({column}, ''), '\\', '\\\\')"
    for mark in chat.CONTROL:
        text = f"replace({text}, '{mark}', '{mark[0]}\\{mark[1:]}')"
    return f"length({text})"


_OP9 = f"""
WITH t AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '{TEST_TEXT}' UNION ALL SELECT -7, 1, 'assistant', '{TEST_TEXT}'),
g AS (SELECT conv_id, count(*) AS n_turns, string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn) AS whole,
  coalesce(string_agg(text, '' ORDER BY turn) FILTER (WHERE role = 'assistant'), '') AS loss,
  sum({len(chat.START + chat.TEXT + chat.END)} + {_escaped_length("role")} + {_escaped_length("text")}) AS formatted_chars FROM t GROUP BY conv_id)
SELECT conv_id, cast(n_turns AS BIGINT) AS n_turns, sha256(whole) AS turns_sha256, cast(length(loss) AS BIGINT) AS loss_chars, sha256(loss) AS loss_sha256, cast(formatted_chars AS BIGINT) AS formatted_chars FROM g
"""


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        f.__name__: f
        for f in (op1_html_extraction, op2_decontamination, op3_line_dedup, op4_simhash, op5_nearest_neighbours, op6_sharding, op7_substring_dedup, op8_packing, op9_chat_formatting, op10_language_id, pipeline)
    }


def oracle_sql() -> dict[str, str]:
    return {"op2_decontamination": _OP2, "op3_line_dedup": _OP3, "op6_sharding": _OP6, "op7_substring_dedup": _OP7, "op9_chat_formatting": _OP9}
