"""Operator 6 [native]: reply trees to formatted conversations.

Leaves walk up to the root by iterative self-joins whose step doubles (the table of ancestors is joined with itself), so
a tree of depth d takes log2(d) rounds and its paths as many rows as they have turns. Each tree's paths are
ranked by their summed score, and every chosen path becomes one text with the spans of the loss mask.

Template: a turn is <s>[INST]role[/INST]text</s>. Inside role and text '&' and the four control strings are
written as entities, which makes reading back exact. Only DataFrame expressions run.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from vertexalg.llm import common as C

#: Control strings and the entities that stand for them inside texts.
BEGIN, END, OPEN, CLOSE = "<s>", "</s>", "[INST]", "[/INST]"
ENTITIES = ((BEGIN, "&bos;"), (END, "&eos;"), (OPEN, "&open;"), (CLOSE, "&close;"))


def escape(x: Column) -> Column:
    return reduce(lambda c, e: F.replace(c, F.lit(e[0]), F.lit(e[1])), ENTITIES, F.replace(x, F.lit("&"), F.lit("&amp;")))


def unescape(x: Column) -> Column:
    return F.replace(reduce(lambda c, e: F.replace(c, F.lit(e[1]), F.lit(e[0])), ENTITIES, x), F.lit("&amp;"), F.lit("&"))


def paths(nodes: DataFrame) -> DataFrame:
    """(tree, leaf, node, up) of nodes (tree, node, parent): every node on the way from each leaf, up steps above it.

    (tree, node) is unique and not null; a parent that is null or missing makes a root. A circle of
    parents raises an error."""
    links = nodes.select("tree", "node", "parent")
    ids = links.select("tree", F.col("node").alias("parent"))
    jump = C.materialise(links.where("parent is not null").join(ids, ["tree", "parent"]).select("tree", "node", F.col("parent").alias("above")), "jump")
    leaves = links.join(jump.select("tree", F.col("above").alias("node")).distinct(), ["tree", "node"], "left_anti")
    walk = C.materialise(leaves.select("tree", F.col("node").alias("leaf"), "node", F.lit(0).cast("long").alias("up")), "walk")
    step, most = 1, None
    while (left := jump.count()) > 0:
        most = left if most is None else most
        if step > most:
            raise ValueError("the replies form a circle")
        more = walk.join(jump, ["tree", "node"]).select("tree", "leaf", F.col("above").alias("node"), (F.col("up") + step).alias("up"))
        shorter, walk = walk, C.materialise(walk.union(more), "walk")
        C.discard(shorter)
        far = jump.withColumnRenamed("above", "middle").join(jump.withColumnRenamed("node", "middle"), ["tree", "middle"])
        shorter, jump, step = jump, C.materialise(far.select("tree", "node", "above"), "jump"), step * 2
        C.discard(shorter)
    return walk


def format_trees(messages: DataFrame, keep: int = 1) -> DataFrame:
    """Conversations (tree, leaf, score, n, formatted, loss) of messages (tree, node, parent, role, text, score): the keep
    best paths of each tree by summed score (null counts 0), ties to the smaller leaf.

    loss: spans of assistant texts in formatted, in code points, end exclusive. Null roles and texts are empty."""
    walk = paths(messages)
    score = F.coalesce(F.col("score").cast("double"), F.lit(0.0))
    turns = walk.join(messages.select("tree", "node", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"), score.alias("score")), ["tree", "node"])
    if keep:
        ranked = turns.groupBy("tree", "leaf").agg(F.sum("score").alias("total")).withColumn("r", F.row_number().over(W.partitionBy("tree").orderBy(F.desc("total"), "leaf")))
        turns = turns.join(ranked.where(F.col("r") <= keep).select("tree", "leaf"), ["tree", "leaf"], "left_semi")
    head, tail = F.concat(F.lit(BEGIN + OPEN), escape(F.col("role")), F.lit(CLOSE)), F.lit(END)
    written = turns.select("tree", "leaf", "score", "up", (F.col("role") == "assistant").alias("learn"), head.alias("head"), escape(F.col("text")).alias("body"))
    joined = written.groupBy("tree", "leaf").agg(F.sum("score").alias("score"), F.array_sort(F.collect_list(F.struct((-F.col("up")).alias("order"), "head", "body", "learn"))).alias("turns"))
    formatted = F.array_join(F.transform("turns", lambda t: F.concat(t["head"], t["body"], tail)), "")
    begin = F.struct(F.lit(0).alias("at"), F.expr("cast(array() as array<struct<start: int, end: int>>)").alias("out"))

    def step(acc: Column, t: Column) -> Column:
        start = acc["at"] + F.length(t["head"])
        end = start + F.length(t["body"])
        span = F.struct(start.alias("start"), end.alias("end"))
        return F.struct((end + len(END)).alias("at"), F.when(t["learn"], F.array_append(acc["out"], span)).otherwise(acc["out"]).alias("out"))

    loss = F.aggregate("turns", begin, step, lambda acc: acc["out"])
    return joined.select("tree", "leaf", "score", F.size("turns").alias("n"), formatted.alias("formatted"), loss.alias("loss"))


def read_back(formatted: DataFrame) -> DataFrame:
    """Adds turns (role, text) and learned (all text under the loss mask), read from formatted and loss alone."""
    parts = F.split("formatted", END, -1)
    whole = F.slice(parts, 1, F.size(parts) - 1)
    turn = lambda p: F.struct(unescape(F.substring_index(F.substr(p, F.lit(len(BEGIN + OPEN) + 1), F.length(p)), CLOSE, 1)).alias("role"), unescape(F.substring_index(p, CLOSE, -1)).alias("text"))
    masked = F.transform("loss", lambda s: unescape(F.substr("formatted", s["start"] + 1, s["end"] - s["start"])))
    return formatted.withColumn("turns", F.transform(whole, turn)).withColumn("learned", F.array_join(masked, ""))


def reply_chain(conversations: DataFrame) -> DataFrame:
    """Rows (conv_id, turn, role, text) as reply trees: each row answers the one before it in its conversation (by
    turn, then role and text where turns repeat; a null turn first)."""
    order = W.partitionBy("tree").orderBy("turn", "role", "text")
    rows = conversations.select(C.known_id("conv_id").alias("tree"), "turn", "role", "text").withColumn("node", F.row_number().over(order).cast("long"))
    parent = F.when(F.col("node") > 1, F.col("node") - 1)
    return C.materialise(rows.select("tree", "node", parent.alias("parent"), "role", "text", F.lit(1.0).alias("score")), "replies")


def op6_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All conversations and one of control strings, each a chain of replies. Null texts and roles are empty; turns that
    repeat are ordered by role and text; a null conv_id is a conversation of its own and comes back as null; an empty
    table leaves the one conversation that is added."""
    rows = C.table(spark, sf_dir, "conversations").select(F.col("conv_id").cast("long"), F.col("turn").cast("long"), "role", "text")
    extra = spark.range(2).select(F.lit(-7).cast("long").alias("conv_id"), F.col("id").alias("turn"), F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"), F.lit("</s>[INST] ok [/INST]").alias("text"))
    found = read_back(format_trees(reply_chain(rows.union(extra))))
    whole = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    return found.select(C.original_id("tree").alias("conv_id"), F.size("turns").cast("long").alias("n_turns"), F.sha2(whole, 256).alias("turns_sha256"), F.length("learned").cast("long").alias("loss_chars"), F.sha2("learned", 256).alias("loss_sha256"), F.length("formatted").cast("long").alias("formatted_chars"))


def _sql_escape(x: str) -> str:
    return reduce(lambda c, e: f"replace({c}, '{e[0]}', '{e[1]}')", ENTITIES, f"replace({x}, '&', '&amp;')")


OP6_SQL = f"""with r as (select conv_id, turn, coalesce(role, '') as role, coalesce(text, '') as text from conversations
 union all values (-7, 0, 'user', '</s>[INST] ok [/INST]'), (-7, 1, 'assistant', '</s>[INST] ok [/INST]')),
g as (select conv_id, count(*) as n, string_agg(role || chr(10) || text || chr(10), '' order by turn, role, text) as whole,
 coalesce(string_agg(text, '' order by turn, role, text) filter (role = 'assistant'), '') as learned,
 sum({len(BEGIN + OPEN + CLOSE + END)} + length({_sql_escape("role")}) + length({_sql_escape("text")})) as size from r group by conv_id)
select conv_id, n as n_turns, sha256(whole) as turns_sha256, length(learned) as loss_chars, sha256(learned) as loss_sha256, cast(size as bigint) as formatted_chars from g"""
