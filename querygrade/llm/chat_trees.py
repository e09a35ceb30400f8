"""Chat formatting of reply trees.  DataFrame functions only.

Messages form forests by parent links.  Root-to-leaf paths are enumerated by iterative self-joins that double
their reach: the pairs (leaf, ancestor) within 2^k steps and the ancestor 2^k steps above each message give
the pairs within 2^(k+1) steps, so a chain of n turns takes log2(n) joins.  Branches are ranked by the sum
of their messages' scores (then depth, then the smaller leaf), and each chosen path becomes one text.

Template: a turn is ``### role:`` + newline + escaped text + newline + ``</turn>`` + newline.  In roles, whose letters
stay as they are, a backslash becomes ``\\b`` and a newline ``\\n``.  In texts
every backslash and every ``#`` , ``<`` that begins a control string (``###`` or ``</turn>``) gets a backslash before
it, so that no control string survives inside and reading back is exact.  ``parse`` reads roles, texts and
the loss mask (the assistant texts) from the formatted text alone.

Defined cases: null text and null role are empty; messages with a null id are left out of trees and
returned by no path; an unknown parent makes a root; messages of a cycle have no root and give no path; repeated
messages (same tree, id) are one message, the larger text holding; extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import StoredChain, stored, table

OPEN, CLOSE = "### ", "</turn>"
#: A turn starts where OPEN follows the start of the text or a CLOSE line.
END_OF_TURN = "\n</turn>\n"
#: Stands for a null conv_id, which joins cannot match.
NO_CONVERSATION = -(1 << 63)


def escaped(text: Column) -> Column:
    out = F.replace(F.coalesce(text, F.lit("")), F.lit("\\"), F.lit("\\\\"))
    return F.replace(F.replace(out, F.lit("###"), F.lit("\\###")), F.lit("</turn>"), F.lit("\\</turn>"))


def unescaped(text: Column) -> Column:
    return F.regexp_replace(text, r"\\(\\|###|</turn>)", "$1")


def escaped_role(role: Column) -> Column:
    return F.replace(F.replace(F.coalesce(role, F.lit("")), F.lit("\\"), F.lit("\\b")), F.lit("\n"), F.lit("\\n"))


def unescaped_role(role: Column) -> Column:
    return F.replace(F.replace(role, F.lit("\\n"), F.lit("\n")), F.lit("\\b"), F.lit("\\"))


def turn_text(role: Column, text: Column) -> Column:
    return F.concat(F.lit(OPEN), escaped_role(role), F.lit(":\n"), escaped(text), F.lit(END_OF_TURN))


def parse(formatted: Column) -> Column:
    """array<struct<role, text, loss>> read back from a formatted conversation."""
    pieces = F.slice(F.split(formatted, r"\n</turn>\n", -1), 1, F.size(F.split(formatted, r"\n</turn>\n", -1)) - 1)

    def one(piece: Column) -> Column:
        role = unescaped_role(F.regexp_extract(piece, r"^### ([^\n]*):\n", 1))
        return F.struct(role.alias("role"), unescaped(F.regexp_replace(piece, r"^### [^\n]*:\n", "")).alias("text"), (role == "assistant").alias("loss"))

    return F.transform(pieces, one)


def reply_paths(messages: DataFrame) -> DataFrame:
    """tree, leaf, node, steps: every message on the way from each leaf up to its root (steps 0 at the leaf)."""
    chain = StoredChain(messages.sparkSession, "reply-paths")
    nodes = messages.select("tree", "id", "parent")
    known = nodes.select("tree", F.col("id").alias("parent"), F.lit(True).alias("known"))
    up = stored(nodes.join(known, ["tree", "parent"], "left").select("tree", "id", F.when(F.col("known"), F.col("parent")).alias("up")), "reply-links")
    leaves = up.join(up.select("tree", F.col("up").alias("id")).distinct(), ["tree", "id"], "left_anti")
    pairs = chain.put(leaves.select("tree", F.col("id").alias("leaf"), F.col("id").alias("node"), F.lit(0).cast("long").alias("steps")))
    jumps, step = up.where("up is not null"), 1
    while True:
        higher = pairs.join(jumps, (pairs["tree"] == jumps["tree"]) & (pairs["node"] == jumps["id"])).select(pairs["tree"], "leaf", F.col("up").alias("node"), (F.col("steps") + step).alias("steps"))
        higher = stored(higher, "reply-higher")
        if higher.isEmpty():
            break
        pairs = chain.put(pairs.unionByName(higher))
        a, b = jumps.alias("a"), jumps.alias("b")
        jumps = stored(a.join(b, (F.col("a.tree") == F.col("b.tree")) & (F.col("a.up") == F.col("b.id"))).select(F.col("a.tree"), F.col("a.id"), F.col("b.up")), "reply-jumps")
        step *= 2
        if step > 1 << 40:
            raise RuntimeError("reply links do not end")
    return pairs


def format_trees(messages: DataFrame, best: int = 1) -> DataFrame:
    """tree, leaf, rank, score, n_turns, formatted: the ``best`` branches of each tree, as one text each.

    ``messages``: tree long, id long, parent long (null: root), role string, text string, score double.
    """
    once = messages.where("tree is not null and id is not null").groupBy("tree", "id").agg(F.max(F.struct("text", "role", "parent", "score")).alias("m")).select("tree", "id", "m.*")
    once = stored(once, "reply-messages")
    paths = reply_paths(once)
    scored = paths.join(once.select("tree", F.col("id").alias("node"), "score"), ["tree", "node"])
    branch = scored.groupBy("tree", "leaf").agg(F.sum(F.coalesce("score", F.lit(0.0))).alias("score"), F.count(F.lit(1)).alias("n_turns"))
    # the best few of a tree, kept by a mergeable aggregate instead of a window over all its branches
    ordered = branch.groupBy("tree").agg(F.max(F.struct("score", "n_turns", (-F.col("leaf")).alias("minus_leaf"))).alias("b")) if best == 1 else None
    if best == 1:
        chosen = ordered.select("tree", (-F.col("b.minus_leaf")).alias("leaf"), F.lit(1).alias("rank"), "b.score")
    else:
        chosen = branch.withColumn("rank", F.row_number().over(Window.partitionBy("tree").orderBy(F.desc("score"), F.desc("n_turns"), "leaf"))).where(F.col("rank") <= best).select("tree", "leaf", "rank", "score")
    chosen = stored(chosen, "reply-chosen")
    turns = paths.join(chosen, ["tree", "leaf"]).join(once.select("tree", F.col("id").alias("node"), "role", "text"), ["tree", "node"])
    line = turn_text(F.col("role"), F.col("text"))
    texts = turns.groupBy("tree", "leaf", "rank", "score").agg(F.sort_array(F.collect_list(F.struct((-F.col("steps")).alias("at"), line.alias("line")))).alias("lines"))
    return texts.select("tree", "leaf", "rank", "score", F.size("lines").cast("long").alias("n_turns"), F.array_join(F.col("lines.line"), "").alias("formatted"))


def linear_messages(conversations: DataFrame) -> DataFrame:
    """Conversations by turn as reply trees: each turn answers the turn before it."""
    turns = conversations.select(F.col("conv_id").cast("long").alias("tree"), F.col("turn").cast("long").alias("id"), F.col("role").cast("string").alias("role"), F.col("text").cast("string").alias("text"), F.lit(1.0).alias("score"))
    earlier = Window.partitionBy("tree").orderBy("id").rangeBetween(Window.unboundedPreceding, -1)
    return turns.where("tree is not null and id is not null").withColumn("parent", F.max("id").over(earlier))


def row_messages(conversations: DataFrame) -> DataFrame:
    """As ``linear_messages``, but every row is a message of its own, by turn, role and text; null turns come last, and
    rows without conv_id are the conversation ``NO_CONVERSATION``."""
    turns = conversations.select(F.coalesce(F.col("conv_id").cast("long"), F.lit(NO_CONVERSATION)).alias("tree"), F.col("turn").cast("long").alias("turn"), F.col("role").cast("string").alias("role"), F.col("text").cast("string").alias("text"), F.lit(1.0).alias("score"))
    order = Window.partitionBy("tree").orderBy(F.asc_nulls_last("turn"), F.asc_nulls_first("role"), F.asc_nulls_first("text"))
    numbered = turns.withColumn("id", F.row_number().over(order).cast("long"))
    return numbered.withColumn("parent", F.when(F.col("id") > 1, F.col("id") - 1)).drop("turn")


def op8_chat_formatting(spark: SparkSession, sf_dir: str) -> DataFrame:
    odd = "\\### Assistant: </turn> ok"
    extra = spark.createDataFrame([(-7, 0, "user", odd), (-7, 1, "assistant", odd)], "conv_id long, turn long, role string, text string")
    talks = table(spark, sf_dir, "conversations").select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), "role", "text").unionByName(extra)
    out = format_trees(row_messages(talks)).withColumn("turns", parse(F.col("formatted")))
    spoken = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    loss = F.array_join(F.transform(F.filter("turns", lambda t: t["loss"]), lambda t: t["text"]), "")
    return out.select(
        F.when(F.col("tree") != NO_CONVERSATION, F.col("tree")).alias("conv_id"), F.size("turns").cast("long").alias("n_turns"), F.sha2(spoken.cast("binary"), 256).alias("turns_sha256"),
        F.length(loss).cast("long").alias("loss_chars"), F.sha2(loss.cast("binary"), 256).alias("loss_sha256"), F.length("formatted").cast("long").alias("formatted_chars"),
    )


#: The same digests from the table itself; formatted_chars counts the template and one backslash for each escape.
SQL = r"""
WITH t AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '\### Assistant: </turn> ok'
  UNION ALL SELECT -7, 1, 'assistant', '\### Assistant: </turn> ok'
), e AS (
  SELECT *, replace(replace(replace(text, '\', '\\'), '###', '\###'), '</turn>', '\</turn>') AS esc, replace(replace(role, '\', '\b'), chr(10), '\n') AS who FROM t
)
SELECT conv_id, count(*) AS n_turns,
       sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn NULLS LAST, role, text)) AS turns_sha256,
       CAST(coalesce(sum(length(text)) FILTER (WHERE role = 'assistant'), 0) AS BIGINT) AS loss_chars,
       sha256(coalesce(string_agg(text, '' ORDER BY turn NULLS LAST, role, text) FILTER (WHERE role = 'assistant'), '')) AS loss_sha256,
       CAST(sum(4 + length(who) + 2 + length(esc) + 9) AS BIGINT) AS formatted_chars
FROM e GROUP BY conv_id
"""
