"""Chat formatting of reply trees (operator 2, native).

Messages name the message they answer. Self-joins that double their reach each round give every message its distance to the
root and the score of its whole branch; the best leaves of each tree are chosen; the rounds' tables, read from the widest
step down, then list all messages of each chosen path. A tree of depth d takes about log2(d) rounds, and every table holds one row a message.

The template marks turns with ``<|turn|>role<|text|>`` and ``<|end|>``. Control strings inside texts and roles get a backslash after their first
character, and backslashes are doubled, so formatted text never holds a control string but the template's and can be read back.

Defined cases: null texts and roles are empty; a null tree id is a tree of its own; a parent that is missing, null or the
message itself makes a root; repeated message ids are told apart by the caller; messages on a reply cycle have no root and
are on no path; an empty table gives no rows. One formatted conversation is one row, whatever its length.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import Scratch

TURN, TEXT, END = "<|turn|>", "<|text|>", "<|end|>"
#: Fixed strings that other templates give a meaning; they are escaped inside texts as well.
CONTROL = r"<\||</?s>|\[/?INST\]|<</?SYS>>"


def escape(value: Column) -> Column:
    return F.regexp_replace(F.replace(value, F.lit("\\"), F.lit("\\\\")), f"(?={CONTROL})(.)", r"$1\\")


def unescape(value: Column) -> Column:
    return F.regexp_replace(value, r"(?s)\\(.)", "$1")


def jump_tables(messages: DataFrame, scratch: Scratch) -> tuple[list[DataFrame], DataFrame]:
    """Self-joins that double their reach: table r maps a message to the one 2**r steps above it.

    Also gives (tree, msg, depth, total) of all messages that hang on a root: steps to the root and the branch's score.
    ``messages`` has tree, msg, parent, score; tree and msg are never null.
    """
    ids = messages.select("tree", F.col("msg").alias("parent"), F.lit(True).alias("there"))
    linked = messages.join(ids, ["tree", "parent"], "left").select(
        "tree", "msg", F.when(F.col("there") & (F.col("parent") != F.col("msg")), F.col("parent")).alias("up"), F.lit(0).cast("long").alias("depth"), F.col("score").alias("total")
    )
    longest = messages.count()
    now = scratch.write(linked.withColumn("depth", F.when(F.col("up").isNull(), 0).otherwise(1).cast("long")), "jump0")
    tables, done = [], now.filter(F.col("up").isNull())
    for r in range(longest.bit_length() + 1):  # a chain of all messages needs no more; what is left then hangs on a cycle
        climbing = now.filter(F.col("up").isNotNull())
        if climbing.isEmpty():
            break
        tables.append(climbing.select("tree", "msg", "up"))
        # only messages that have not reached their root are joined again
        above = done.unionByName(climbing).select("tree", F.col("msg").alias("up"), F.col("up").alias("next"), F.col("depth").alias("more"), F.col("total").alias("plus"))
        step = climbing.join(above, ["tree", "up"], "left").select(
            "tree", "msg", F.col("next").alias("up"), (F.col("depth") + F.coalesce("more", F.lit(0))).alias("depth"), (F.col("total") + F.coalesce("plus", F.lit(0.0))).alias("total")
        )
        now = scratch.write(step, f"jump{r + 1}")
        done = done.unionByName(now.filter(F.col("up").isNull()))
    return tables, done.drop("up")


def best_paths(messages: DataFrame, per_tree: int = 1) -> DataFrame:
    """(tree, path, rank, total, msg, place): messages of the ``per_tree`` best root-to-leaf paths, place 0 at the root.

    Branches are ranked by their summed score, then depth, then the smaller leaf id.
    """
    scratch = Scratch(messages.sparkSession, "replies")
    plain = scratch.write(messages.select("tree", "msg", "parent", F.col("score").cast("double").alias("score")), "messages")
    tables, rooted = jump_tables(plain, scratch)
    answered = plain.filter(F.col("parent").isNotNull() & (F.col("parent") != F.col("msg"))).select("tree", F.col("parent").alias("msg")).distinct()
    leaves = rooted.join(answered, ["tree", "msg"], "left_anti")
    order = W.partitionBy("tree").orderBy(F.desc("total"), F.desc("depth"), "msg")
    chosen = leaves.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= per_tree)
    paths = scratch.write(chosen.select("tree", F.col("msg").alias("path"), "rank", "total", "msg", F.col("depth").alias("place")), "paths")
    for r in reversed(range(len(tables))):
        up = paths.join(tables[r], ["tree", "msg"]).select("tree", "path", "rank", "total", F.col("up").alias("msg"), (F.col("place") - F.lit(1 << r)).alias("place"))
        paths = scratch.write(paths.unionByName(up), f"paths{r}")
    return paths


def formatted(turns: DataFrame) -> DataFrame:
    """(tree, path, formatted) from rows of (tree, path, place, role, text)."""
    part = F.concat(F.lit(TURN), escape(F.coalesce("role", F.lit(""))), F.lit(TEXT), escape(F.coalesce("text", F.lit(""))), F.lit(END))
    rows = turns.groupBy("tree", "path").agg(F.sort_array(F.collect_list(F.struct("place", part.alias("part")))).alias("parts"))
    return rows.select("tree", "path", F.array_join(F.transform("parts", lambda p: p["part"]), "").alias("formatted"))


def read_back(column: Column) -> Column:
    """Array of (role, text) of a formatted conversation."""
    parts = F.filter(F.split(column, r"<\|end\|>", -1), lambda p: p != "")
    fields = lambda p: F.split(F.substring(p, len(TURN) + 1, 1 << 30), r"<\|text\|>", -1)
    return F.transform(parts, lambda p: F.struct(unescape(F.get(fields(p), F.lit(0))).alias("role"), unescape(F.get(fields(p), F.lit(1))).alias("text")))


def conversations(messages: DataFrame, per_tree: int = 1) -> DataFrame:
    """Formatted best paths of reply trees: messages has tree, msg, parent, role, text, score."""
    paths = best_paths(messages, per_tree)
    return formatted(paths.join(messages.select("tree", "msg", "role", "text"), ["tree", "msg"]))


def as_tree(rows: DataFrame) -> DataFrame:
    """A table of turns as reply trees: each turn answers the one before it. Repeated turns follow one another."""
    order = W.partitionBy("conv_id").orderBy("turn", "role", "text")
    numbered = rows.withColumn("msg", F.row_number().over(order).cast("long"))
    return numbered.select(
        F.col("conv_id").alias("tree"), "msg", F.when(F.col("msg") > 1, F.col("msg") - 1).alias("parent"), "role", "text", F.lit(1.0).alias("score")
    )


def op2_reply_trees(spark: SparkSession, sf_dir: str) -> DataFrame:
    given = spark.read.parquet(f"{sf_dir}/conversations.parquet").select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), "role", "text")
    said = "</s>[INST] ok [/INST]"
    extra = spark.range(2).select(F.lit(-7).cast("long").alias("conv_id"), F.col("id").alias("turn"), F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"), F.lit(said).alias("text"))
    trees = Scratch(spark, "turns").write(as_tree(given.unionByName(extra)), "tree")
    # a null id is a tree of its own
    out = conversations(trees.withColumn("tree", F.struct(F.col("tree").isNull().alias("no"), F.coalesce("tree", F.lit(0)).alias("id"))))
    turns = out.withColumn("turns", read_back(F.col("formatted")))
    assistant = F.array_join(F.transform(F.filter("turns", lambda t: t["role"] == "assistant"), lambda t: t["text"]), "")
    every = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    return turns.select(
        F.when(~F.col("tree.no"), F.col("tree.id")).alias("conv_id"),
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(every, 256).alias("turns_sha256"),
        F.length(assistant).cast("long").alias("loss_chars"),
        F.sha2(assistant, 256).alias("loss_sha256"),
        F.length("formatted").cast("long").alias("formatted_chars"),
    )


OP2_SQL = r"""
WITH c AS (SELECT CAST(conv_id AS BIGINT) AS conv_id, CAST(turn AS BIGINT) AS turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '</s>[INST] ok [/INST]' UNION ALL SELECT -7, 1, 'assistant', '</s>[INST] ok [/INST]'),
e AS (SELECT *, length(role) + length(text)
  + (length(role || text) - length(replace(role || text, '\', '')))
  + len(regexp_extract_all(role, '<\||</?s>|\[/?INST\]|<</?SYS>>')) + len(regexp_extract_all(text, '<\||</?s>|\[/?INST\]|<</?SYS>>')) + 23 AS chars FROM c)
SELECT conv_id, count(*) AS n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
  CAST(sum(CASE WHEN role = 'assistant' THEN length(text) ELSE 0 END) AS BIGINT) AS loss_chars,
  sha256(coalesce(string_agg(CASE WHEN role = 'assistant' THEN text ELSE '' END, '' ORDER BY turn, role, text), '')) AS loss_sha256,
  CAST(sum(chars) AS BIGINT) AS formatted_chars
FROM e GROUP BY conv_id
"""
