"""Queries over postings: from texts and relations to gaps, blocks and skip pointers."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql import Window as W

from quadpost.operators import corpus
from quadpost.operators.corpus import BLOCK, SHORT_LIST
from quadpost.operators.index import build_index, decode_postings
from quadpost.plans import sql
from quadpost.sources import tables

QUERIES, ORACLES = {}, {}


def query(name: str, oracle: str | None = None):
    def add(f):
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f

    return add


def s1(spark, d):
    return corpus.postings(tables.collection(spark, d, "documents"))


def long_gaps(spark, d):
    return corpus.gaps(corpus.long_lists(s1(spark, d)))


@query("q_tokens", sql.postings() + " SELECT doc_id, count(*) AS tokens, count(DISTINCT term) AS terms, max(length(term)) AS longest FROM tok GROUP BY doc_id")
def q_tokens(spark, d):
    t = corpus.tokens(tables.collection(spark, d, "documents"))
    return t.groupBy("doc_id").agg(F.count("*").alias("tokens"), F.count_distinct("term").alias("terms"), F.max(F.char_length("term")).cast("long").alias("longest"))


@query("q_tf", sql.postings() + " SELECT term, doc_id, tf FROM tf")
def q_tf(spark, d):
    return s1(spark, d)


@query("q_df", sql.postings("documents", sql.DICTIONARY) + " SELECT term, df, cf, n_blocks FROM dict")
def q_df(spark, d):
    return corpus.dictionary(s1(spark, d))


@query("q_doc_len", sql.postings("documents", sql.LENGTHS) + " SELECT doc_id, len FROM lens")
def q_doc_len(spark, d):
    return corpus.doc_lengths(tables.collection(spark, d, "documents"))


def _stats_sql() -> str:
    one = lambda c: f"SELECT '{c}' AS dataset, (SELECT count(*) FROM ({sql.COLLECTIONS[c]})) AS documents, count(DISTINCT term) AS terms, count(*) AS postings, cast(sum(tf) AS BIGINT) AS tokens FROM ({sql.postings(c)} SELECT * FROM tf)"
    return " UNION ALL ".join(map(one, tables.COLLECTIONS))


@query("q_dataset_stats", _stats_sql())
def q_dataset_stats(spark, d):
    """Documents, terms, postings and tokens of the four text collections."""
    out = None
    for name in tables.COLLECTIONS:
        docs = tables.collection(spark, d, name)
        t = corpus.postings(docs).groupBy("term").agg(F.count("*").alias("p"), F.sum("tf").alias("c")).agg(F.count("*").alias("terms"), F.sum("p").alias("postings"), F.sum("c").alias("tokens"))
        row = docs.agg(F.count("*").alias("documents")).crossJoin(F.broadcast(t)).select(F.lit(name).alias("dataset"), "documents", "terms", "postings", "tokens")
        out = row if out is None else out.unionByName(row)
    return out


@query("q_dgap", sql.gaps() + " SELECT term, pos, doc_id, gap FROM gaps")
def q_dgap(spark, d):
    return long_gaps(spark, d).select("term", "pos", "doc_id", "gap")


@query("q_tf_seq", sql.blocks("tf") + " SELECT term, block, n, v AS tfs FROM blk")
def q_tf_seq(spark, d):
    return corpus.blocks(long_gaps(spark, d)).select("term", "block", F.col("n").cast("long").alias("n"), "tfs")


@query(
    "q_fit8_share",
    " UNION ALL ".join(
        f"SELECT '{c}' AS dataset, round(avg(CASE WHEN gap < 256 THEN 1.0 ELSE 0.0 END), 6) AS gap_share, round(avg(CASE WHEN tf < 256 THEN 1.0 ELSE 0.0 END), 6) AS tf_share FROM ({sql.gaps(c)} SELECT * FROM gaps)"
        for c in tables.COLLECTIONS
    ),
)
def q_fit8_share(spark, d):
    """The share of gaps and frequencies that one byte holds."""
    out = None
    for name in tables.COLLECTIONS:
        g = corpus.gaps(corpus.long_lists(corpus.postings(tables.collection(spark, d, name))))
        fits = lambda c: F.round(F.avg(F.when(F.col(c) < 256, 1.0).otherwise(0.0)), 6)
        row = g.agg(fits("gap").alias("gap_share"), fits("tf").alias("tf_share")).select(F.lit(name).alias("dataset"), "gap_share", "tf_share")
        out = row if out is None else out.unionByName(row)
    return out


_BLOCKS = f"SELECT term, pos // {BLOCK} AS block, count(*) AS n, min(doc_id) AS first_doc, max(doc_id) AS last_doc FROM gaps GROUP BY ALL"


@query("q_blocks512", sql.gaps() + f" {_BLOCKS}")
def q_blocks512(spark, d):
    return corpus.blocks(long_gaps(spark, d)).select("term", "block", F.col("n").cast("long").alias("n"), "first_doc", "last_doc")


def probes(found, count: int):
    """``count`` documents evenly spaced from 0 to the largest: one aggregated row, spread out."""
    top = found.agg(F.coalesce(F.max("doc_id"), F.lit(0)).alias("top"))
    return top.select(F.explode(F.sequence(F.lit(0), F.lit(count - 1))).alias("k"), "top").select(F.floor(F.col("k") * F.col("top") / (count - 1)).alias("doc_id")).distinct()


def _probes(count: int, name: str = "probe") -> str:
    return f"{name} AS (SELECT DISTINCT k * top // {count - 1} AS doc_id FROM (SELECT coalesce(max(doc_id), 0) AS top FROM tf), (SELECT unnest(range(0, {count})) AS k))"


@query("q_skip_blocks", sql.gaps("documents", f"b AS ({_BLOCKS})", _probes(11)) + " SELECT term, block, doc_id FROM b JOIN probe ON probe.doc_id BETWEEN first_doc AND last_doc")
def q_skip_blocks(spark, d):
    """Which blocks may hold given documents: by document range first, then by the exact bounds; nothing is decoded."""
    width = 4096
    found = s1(spark, d)
    probe = probes(found, 11).withColumn("range", F.floor(F.col("doc_id") / width))
    b = corpus.blocks(corpus.gaps(corpus.long_lists(found))).withColumn("range", F.explode(F.sequence(F.floor(F.col("first_doc") / width), F.floor(F.col("last_doc") / width))))
    return b.join(F.broadcast(probe), "range").where("doc_id BETWEEN first_doc AND last_doc").select("term", "block", "doc_id")


@query("q_seek_asof", sql.gaps("documents", f"b AS ({_BLOCKS})", _probes(6, "spot"), "probe AS (SELECT DISTINCT term, spot.doc_id FROM b, spot)") + " SELECT term, doc_id, (SELECT min(block) FROM b WHERE b.term = probe.term AND b.last_doc >= probe.doc_id) AS block FROM probe")
def q_seek_asof(spark, d):
    """The block in which a cursor stops that seeks a document: the first whose last document is not smaller."""
    found = s1(spark, d)
    b = corpus.blocks(corpus.gaps(corpus.long_lists(found))).select("term", "block", "last_doc")
    probe = b.select("term").distinct().crossJoin(F.broadcast(probes(found, 6)))
    both = b.select("term", F.col("last_doc").alias("at"), F.lit(1).alias("kind"), "block").unionByName(probe.select("term", F.col("doc_id").alias("at"), F.lit(0).alias("kind"), F.lit(None).cast("long").alias("block")))
    ahead = W.partitionBy("term").orderBy("at", "kind").rowsBetween(W.currentRow, W.unboundedFollowing)
    return both.withColumn("found", F.first("block", ignorenulls=True).over(ahead)).where("kind = 0").select("term", F.col("at").alias("doc_id"), F.col("found").alias("block"))


@query("q_long_lists", sql.postings() + f" SELECT term, count(*) AS df FROM tf GROUP BY term HAVING count(*) >= {SHORT_LIST}")
def q_long_lists(spark, d):
    return s1(spark, d).groupBy("term").agg(F.count("*").alias("df")).where(F.col("df") >= SHORT_LIST)


@query("q_pages_fields", sql.PAGE_FIELDS)
def q_pages_fields(spark, d):
    return tables.page_fields(tables.table(spark, d, "pages"))


@query("q_user_docs", sql.COLLECTIONS["conversations"])
def q_user_docs(spark, d):
    return tables.collection(spark, d, "conversations")


@query("q_docid_recovery", sql.gaps() + " SELECT term, pos, doc_id FROM gaps")
def q_docid_recovery(spark, d):
    return corpus.doc_ids(long_gaps(spark, d)).select("term", "pos", "doc_id")


@query("q_dense_ids", "SELECT doc_id, text, lang, source, n_chars, row_number() OVER (ORDER BY doc_id) - 1 AS dense_id FROM documents")
def q_dense_ids(spark, d):
    """Every document with all its columns and its place in the order of ids."""
    return corpus.dense_doc_ids(tables.table(spark, d, "documents"), "doc_id")


@query("q_index_postings", sql.postings() + " SELECT term, doc_id, tf FROM tf")
def q_index_postings(spark, d):
    """Every posting read back from the compressed index, short lists included."""
    return decode_postings(build_index(s1(spark, d), "quad_pfor"))


_REL = " UNION ALL ".join(
    f"SELECT '{name}' AS relation, count(DISTINCT term) AS lists, count(*) AS postings, cast(max(gap) AS BIGINT) AS widest, round(avg(CASE WHEN gap < 256 THEN 1.0 ELSE 0.0 END), 6) AS fit8 FROM (SELECT term, doc_id - lag(doc_id, 1, shard * {corpus.SHARD_DOCS} - 1) OVER (PARTITION BY term, shard ORDER BY doc_id) AS gap FROM (SELECT DISTINCT cast({key} AS VARCHAR) AS term, {member} AS doc_id, {member} // {corpus.SHARD_DOCS} AS shard FROM {source}))"
    for name, (source, key, member) in tables.RELATIONS.items()
)


@query("q_relation_gaps", _REL)
def q_relation_gaps(spark, d):
    """Relational postings: lists, postings, the widest gap of a shard and how many gaps a byte holds."""
    out = None
    for name in tables.RELATIONS:
        g = corpus.gaps(tables.relation(spark, d, name))
        row = g.agg(F.count_distinct("term").alias("lists"), F.count("*").alias("postings"), F.max("gap").alias("widest"), F.round(F.avg(F.when(F.col("gap") < 256, 1.0).otherwise(0.0)), 6).alias("fit8")).select(F.lit(name).alias("relation"), "*")
        out = row if out is None else out.unionByName(row)
    return out
