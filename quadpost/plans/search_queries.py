"""Ranked retrieval over the compressed index of documents (and of pages)."""

from __future__ import annotations

from pyspark.sql import functions as F

from quadpost.operators import corpus, search
from quadpost.operators.index import build_index
from quadpost.plans import sql
from quadpost.plans.codec_queries import KEPT_INDEXES
from quadpost.sources import tables
from quadpost.sources.shared import written

QUERIES, ORACLES = {}, {}


def query(name: str, oracle: str | None = None):
    def add(f):
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f

    return add


def prepared(spark, d, codec: str = "quad_selector", collection: str = "documents"):
    """(searcher, asked terms) over a collection. The index, the lengths and the asked terms are tables, as a search engine has them."""
    docs = tables.collection(spark, d, collection)
    lengths = written(corpus.doc_lengths(docs), "lengths")
    index = written(build_index(corpus.sharded_postings(docs), codec), "index")
    searcher = search.Searcher(index, lengths)
    asked = search.query_terms(tables.table(spark, d, "benchmark"), index.select("term", "df").distinct(), searcher.n_docs)
    return searcher, written(asked, "asked")


@query("q_query_terms", sql.search() + " SELECT query_id, term, df FROM asked")
def q_query_terms(spark, d):
    return prepared(spark, d)[1]


@query("q_query_terms_df", sql.search() + " SELECT query_id, count(*) AS terms, min(df) AS rarest, max(df) AS commonest FROM asked GROUP BY query_id")
def q_query_terms_df(spark, d):
    return prepared(spark, d)[1].groupBy("query_id").agg(F.count("*").alias("terms"), F.min("df").alias("rarest"), F.max("df").alias("commonest"))


@query("q_terms_no_stop", sql.search() + f" SELECT term, df FROM dict WHERE df <= {search.STOP_SHARE} * (SELECT n FROM st)")
def q_terms_no_stop(spark, d):
    found = corpus.postings(tables.collection(spark, d, "documents"))
    words, n = corpus.dictionary(found), found.select("doc_id").distinct().count()
    return words.join(words.where(F.col("df") > search.STOP_SHARE * n).select("term"), "term", "left_anti").select("term", "df")


@query("q_and_docs", sql.search(sql.AND_SCORES) + " SELECT query_id, doc_id FROM scores")
def q_and_docs(spark, d):
    searcher, asked = prepared(spark, d)
    return searcher.and_documents(asked).select("query_id", "doc_id").distinct()


def _and(codec: str, collection: str = "documents"):
    def run(spark, d):
        """Documents with all terms, best ten by BM25; blocks without a candidate are never decoded."""
        searcher, asked = prepared(spark, d, codec, collection)
        return searcher.and_topk(asked)

    return run


_AND_SQL = sql.search(sql.AND_SCORES) + " " + sql.TOP
query("q_and_topk", _AND_SQL)(_and("quad_selector"))
for _name in (n for n in KEPT_INDEXES if n != "quad_selector"):
    query(f"q_and_topk_{_name}", _AND_SQL)(_and(_name))
query("q_and_topk_pages", sql.search(sql.AND_SCORES, collection="pages") + " " + sql.TOP)(_and("quad_bp128", "pages"))

_OR_SQL = sql.search(sql.OR_SCORES) + " " + sql.TOP


@query("q_or_topk", _OR_SQL)
def q_or_topk(spark, d):
    searcher, asked = prepared(spark, d)
    return searcher.or_topk(asked)


@query("q_or_maxscore", _OR_SQL)
def q_or_maxscore(spark, d):
    searcher, asked = prepared(spark, d)
    return searcher.or_maxscore(asked)


@query("q_or_wand", _OR_SQL)
def q_or_wand(spark, d):
    searcher, asked = prepared(spark, d)
    return searcher.or_wand(asked)


@query("q_bm25_or_scores", sql.search(sql.OR_SCORES) + " SELECT query_id, count(*) AS docs, round(max(score), 6) AS best, round(sum(score), 4) AS total FROM scores GROUP BY query_id")
def q_bm25_or_scores(spark, d):
    searcher, asked = prepared(spark, d)
    scores = searcher.parts(asked).groupBy("query_id", "doc_id").agg(F.sum("part").alias("score"))
    return scores.groupBy("query_id").agg(F.count("*").alias("docs"), F.round(F.max("score"), 6).alias("best"), F.round(F.sum("score"), 4).alias("total"))


_PAIR = "pair AS (SELECT query_id, min(term) AS a, max(term) AS b FROM asked GROUP BY query_id HAVING count(*) > 1)"


def _sides(spark, d):
    searcher, asked = prepared(spark, d)
    pair = asked.groupBy("query_id").agg(F.min("term").alias("a"), F.max("term").alias("b"), F.count("*").alias("n")).where("n > 1")
    hits = corpus.postings(tables.collection(spark, d, "documents")).select("term", "doc_id")
    side = lambda c: pair.select("query_id", F.col(c).alias("term")).join(hits, "term").select("query_id", "doc_id")
    return side("a"), side("b")


def _set_sql(op: str) -> str:
    side = lambda c: f"SELECT query_id, doc_id FROM pair JOIN tf ON tf.term = pair.{c}"
    return sql.search(_PAIR) + f" {side('a')} {op} {side('b')}"


@query("q_set_and", _set_sql("INTERSECT"))
def q_set_and(spark, d):
    a, b = _sides(spark, d)
    return a.intersect(b)


@query("q_set_or", _set_sql("UNION"))
def q_set_or(spark, d):
    a, b = _sides(spark, d)
    return a.union(b).distinct()


@query("q_set_not", _set_sql("EXCEPT"))
def q_set_not(spark, d):
    a, b = _sides(spark, d)
    return a.exceptAll(b)
