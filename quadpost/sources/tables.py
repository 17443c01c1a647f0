"""Reading the given tables, and the text collections that stand on them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from quadpost.schemas import TABLES


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One given table; with its schema known, nothing is inferred and only used columns are read."""
    reader = spark.read.schema(TABLES[name]) if name in TABLES else spark.read
    return reader.parquet(f"{sf_dir}/{name}.parquet")


def page_fields(pages: DataFrame) -> DataFrame:
    """(doc_id, title, body) of raw pages: scripts, styles, comments and tags cut out, a few references decoded."""
    title = F.regexp_extract("html", "(?is)<title[^>]*>(.*?)</title>", 1)
    body = F.regexp_replace("html", "(?is)<head[^>]*>.*?</head>|<script[^>]*>.*?</script>|<style[^>]*>.*?</style>|<!--.*?-->", " ")
    body = F.regexp_replace(body, "(?s)<[^>]*>", " ")

    def tidy(col):
        for name, mark in (("&quot;", '"'), ("&lt;", "<"), ("&gt;", ">"), ("&copy;", "©"), ("&middot;", "·"), ("&amp;", "&")):
            col = F.replace(col, F.lit(name), F.lit(mark))
        return F.trim(F.regexp_replace(col, "[ \\t\\r\\n]+", " "))

    return pages.select(F.col("page_id").alias("doc_id"), tidy(title).alias("title"), tidy(body).alias("body"))


def user_documents(conversations: DataFrame) -> DataFrame:
    """(doc_id, text): all turns of a conversation, in order, as one document."""
    turns = F.sort_array(F.collect_list(F.struct("turn", "text")))
    return conversations.groupBy("conv_id").agg(turns.alias("t")).select(F.col("conv_id").alias("doc_id"), F.concat_ws(" ", "t.text").alias("text"))


def collection(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """(doc_id, text) of S1 documents, S2 pages, S3 documents of good quality, S4 user documents."""
    if name == "documents":
        return table(spark, sf_dir, "documents").select("doc_id", "text")
    if name == "pages":
        fields = page_fields(table(spark, sf_dir, "pages"))
        return fields.select("doc_id", F.concat_ws(" ", "title", "body").alias("text"))
    if name == "quality":
        good = table(spark, sf_dir, "labels").where("quality = 1").select("doc_id").distinct()
        return table(spark, sf_dir, "documents").select("doc_id", "text").join(good, "doc_id", "left_semi")
    if name == "conversations":
        return user_documents(table(spark, sf_dir, "conversations"))
    raise KeyError(name)


COLLECTIONS = ("documents", "pages", "quality", "conversations")

#: Relational postings: list key and member key of each.
RELATIONS = {
    "lineitem_supplier": ("lineitem", "l_suppkey", "l_orderkey"),
    "lineitem_flag": ("lineitem", "l_returnflag", "l_orderkey"),
    "orders_customer": ("orders", "o_custkey", "o_orderkey"),
    "events_user": ("events", "user_id", "event_id"),
    "events_type": ("events", "event_type", "event_id"),
    "embeddings_label": ("embeddings", "label", "vec_id"),
}


def relation(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Postings (term, doc_id, tf) of a relation: which members each key has, and how often."""
    source, key, member = RELATIONS[name]
    return table(spark, sf_dir, source).groupBy(F.col(key).cast("string").alias("term"), F.col(member).cast("long").alias("doc_id")).agg(F.count("*").alias("tf"))


def read_texts(spark: SparkSession, path: str, kind: str, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, text) of files of kind parquet, orc, json, csv or text; nothing is inferred.

    A text file's lines have no ids: they get dense ones in the order of their content.
    """
    if kind == "text":
        from quadpost.operators.corpus import dense_doc_ids

        return dense_doc_ids(spark.read.text(path), "value").select(F.col("dense_id").alias("doc_id"), F.col("value").alias("text"))
    reader = spark.read.schema(f"`{key}` bigint, `{text}` string")
    found = reader.option("header", "true").option("multiLine", "true").csv(path) if kind == "csv" else reader.format(kind).load(path)
    return found.select(F.col(key).alias("doc_id"), F.col(text).alias("text"))
