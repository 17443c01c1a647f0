"""Reply trees to chat strings, in DataFrame operations only.

Iterative self-joins walk from each message towards its root: a round knows the
message twice as far up, and the score of all between. Branches are ranked by score.
Only the chosen leaves' paths are listed, by the same rounds from the last to the
first: each doubles the messages that a path has. A path becomes one string:

    <|start|>ROLE<|text|>TEXT<|end|><|start|>...

Control strings inside roles and texts are made harmless reversibly: every
backslash is doubled, and a backslash goes after the first character of every
control string. Reading back undoes both.

Defined cases: null role or text is empty; a message whose parent is null or
missing is a root; messages with equal ids in one conversation keep the least
(role, text); messages on a cycle of parents belong to no root and give no
path; ties between branches go to the smaller leaf id; an empty table gives no
rows; other columns are ignored.
"""

from __future__ import annotations

from math import ceil, log2

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from quadpost.llm.staging import written

START, TEXT, END = "<|start|>", "<|text|>", "<|end|>"
#: What a text may not contain as it is: our own marks, and those of common chat templates.
CONTROL = ("<|", "</s>", "<s>", "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>")
LEARNED_ROLE = "assistant"


def escape(col: Column) -> Column:
    out = F.replace(col, F.lit("\\"), F.lit("\\\\"))
    for mark in CONTROL:
        out = F.replace(out, F.lit(mark), F.lit(f"{mark[0]}\\{mark[1:]}"))
    return out


def unescape(col: Column) -> Column:
    for mark in reversed(CONTROL):
        col = F.replace(col, F.lit(f"{mark[0]}\\{mark[1:]}"), F.lit(mark))
    return F.replace(col, F.lit("\\\\"), F.lit("\\"))


def chain_messages(turns: DataFrame) -> DataFrame:
    """Rows (conv_id, turn, role, text) as trees of one branch: each turn answers the one before it."""
    order = W.partitionBy("conv_id").orderBy(F.col("turn").asc_nulls_first(), "role", "text")
    numbered = turns.select("conv_id", "role", "text", F.row_number().over(order).cast("long").alias("msg_id"))
    return numbered.select("conv_id", "msg_id", F.when(F.col("msg_id") > 1, F.col("msg_id") - 1).alias("parent_id"), "role", "text", F.lit(0.0).alias("score"))


def reply_paths(messages: DataFrame, best: int = 1) -> DataFrame:
    """(conv_id, rank, path array of msg_id from root to leaf, score): the ``best`` branches of each conversation.

    Every round of joins is a table of its own, so plans stay small however deep the trees are.
    """
    links = messages.groupBy("conv_id", "msg_id").agg(F.min("parent_id").alias("parent_id"), F.max(F.coalesce("score", F.lit(0.0))).alias("score"))
    here = F.struct(F.col("conv_id").isNull().alias("no"), F.coalesce(F.col("conv_id"), F.lit(0)).alias("id"))
    nodes = written(links.select(here.alias("conv"), "msg_id", "parent_id", "score"), "messages")
    most = nodes.groupBy("conv").count().agg(F.max("count")).first()[0] or 1
    parents = nodes.select("conv", F.col("parent_id").alias("msg_id")).where("msg_id IS NOT NULL").distinct()
    leaves = nodes.select("conv", "msg_id").join(parents, ["conv", "msg_id"], "left_anti").select("conv", F.col("msg_id").alias("leaf"))
    real = nodes.select("conv", F.col("msg_id").alias("top"), F.lit(True).alias("known"))
    part = nodes.withColumnRenamed("parent_id", "top").join(real, ["conv", "top"], "left").select("conv", "msg_id", F.when(F.col("known"), F.col("top")).alias("top"), "score")
    part = written(part, "ancestors")
    # settled messages have no ancestor that far up and leave; the others ask all for the next round
    ups, settled = [part.where("top IS NOT NULL")], part.where("top IS NULL")
    for _ in range(ceil(log2(max(most, 1)))):
        if ups[-1].isEmpty():
            break
        above = settled.unionByName(ups[-1]).select("conv", F.col("msg_id").alias("top"), F.col("top").alias("next"), F.col("score").alias("add"))
        further = ups[-1].join(above, ["conv", "top"]).select("conv", "msg_id", F.col("next").alias("top"), (F.col("score") + F.col("add")).alias("score"))
        part = written(further, "ancestors")
        settled = settled.unionByName(part.where("top IS NULL"))
        ups.append(part.where("top IS NOT NULL"))  # of round k: the message 2^k steps up
    branches = settled.join(leaves.withColumnRenamed("leaf", "msg_id"), ["conv", "msg_id"], "left_semi")
    if best == 1:
        top = branches.groupBy("conv").agg(F.max_by(F.struct("msg_id", "score"), F.struct("score", -F.col("msg_id"))).alias("b"))
        chosen = top.select("conv", F.lit(1).alias("rank"), "b.score", "b.msg_id")
    else:
        order = W.partitionBy("conv").orderBy(F.desc("score"), "msg_id")
        chosen = branches.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= best).select("conv", "rank", "score", "msg_id")
    listed = written(chosen.withColumn("steps", F.lit(0)), "paths")
    for k in reversed(range(len(ups))):
        up = ups[k].select("conv", "msg_id", "top")
        more = listed.join(up, ["conv", "msg_id"]).select("conv", "rank", "score", F.col("top").alias("msg_id"), (F.col("steps") + (1 << k)).alias("steps"))
        listed = written(listed.unionByName(more), "paths")
    path = F.reverse(F.sort_array(F.collect_list(F.struct("steps", "msg_id"))))["msg_id"]
    conv = F.when(~F.col("conv.no"), F.col("conv.id")).alias("conv_id")
    return listed.groupBy("conv", "rank", "score").agg(path.alias("path")).select(conv, "rank", "path", "score")


def format_paths(messages: DataFrame, paths: DataFrame) -> DataFrame:
    """(conv_id, rank, formatted, loss_spans): one string per path, and where in it (code points) the learned texts are."""
    texts = messages.groupBy("conv_id", "msg_id").agg(F.min(F.struct(F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))).alias("m"))
    steps = paths.select("conv_id", "rank", F.posexplode("path").alias("pos", "msg_id"))
    same = steps["conv_id"].eqNullSafe(texts["conv_id"]) & (steps["msg_id"] == texts["msg_id"])
    turns = steps.join(texts, same).select(steps["conv_id"], "rank", "pos", F.col("m.role").alias("role"), F.col("m.text").alias("text"))
    head = turns.select("*", F.concat(F.lit(START), escape(F.col("role")), F.lit(TEXT)).alias("head"), escape(F.col("text")).alias("body"))
    by = W.partitionBy("conv_id", "rank").orderBy("pos")
    length = F.char_length("head") + F.char_length("body") + len(END)
    placed = head.withColumn("at", F.coalesce(F.sum(length).over(by.rowsBetween(W.unboundedPreceding, -1)), F.lit(0)) + F.char_length("head"))
    span = F.when(F.col("role") == LEARNED_ROLE, F.struct(F.col("at").cast("int").alias("start"), F.char_length("body").alias("length")))
    whole = placed.groupBy("conv_id", "rank").agg(F.sort_array(F.collect_list(F.struct("pos", F.concat("head", "body", F.lit(END)).alias("turn"), span.alias("span")))).alias("t"))
    return whole.select("conv_id", "rank", F.array_join("t.turn", "").alias("formatted"), F.filter("t.span", lambda s: s.isNotNull()).alias("loss_spans"))


def read_turns(formatted: Column) -> Column:
    """The turns of a formatted string again: array of struct(role, text)."""
    parts = F.split(formatted, r"<\|start\|>")
    pieces = F.transform(F.slice(parts, 2, F.size(parts)), lambda p: F.split(p, r"<\|text\|>"))
    return F.transform(pieces, lambda p: F.struct(unescape(p[0]).alias("role"), unescape(F.replace(p[1], F.lit(END), F.lit(""))).alias("text")))


def read_loss(formatted: Column, spans: Column) -> Column:
    """All text under the loss mask, unescaped, joined without anything between."""
    return F.array_join(F.transform(spans, lambda s: unescape(F.substring(formatted, s["start"] + 1, s["length"]))), "")
