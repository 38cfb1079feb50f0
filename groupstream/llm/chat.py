r"""Chat formatting of reply trees (DataFrame operators only).

Messages point to the message they answer. Leaves are found by an anti join, and self-joins that double their reach
enumerate each leaf's ancestors: after k rounds every ancestor less than 2**k replies away is known, so a thread of n
messages takes log2(n) rounds. Jumps are doubled first, one row for each message, which finds the messages that never come
to a root before any path is written. Branches are ranked inside their tree by the mean score of their messages, and each chosen
path is formatted as one conversation with the character spans of the assistant's texts.

Template: `<|im_start|>role`, newline, text, `<|im_end|>`, newline for each turn. A backslash in a role or text is
doubled, and one is put after the first character of every control string, so no text can open or close a turn, and before
every newline of a role, which would end it; removing the backslash before any character undoes all three.

Cases: null roles and texts are empty; null scores count 0; a parent that does not exist makes its message a root; of
several messages with one id the smallest (parent, role, text) counts; messages on a cycle of replies belong to no path
from a root and give none; null trees form one tree; an empty table gives an empty result; other columns are dropped.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import cut

START, END = "<|im_start|>", "<|im_end|>"
#: Control strings of common chat templates.
CONTROLS = ("<|im_start|>", "<|im_end|>", "<|endoftext|>", "<s>", "</s>", "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>")


def escape(text: Column) -> Column:
    text = F.replace(F.coalesce(text, F.lit("")), F.lit("\\"), F.lit("\\\\"))
    return reduce(lambda t, c: F.replace(t, F.lit(c), F.lit(f"{c[0]}\\{c[1:]}")), CONTROLS, text)


def escape_role(role: Column) -> Column:
    return F.replace(escape(role), F.lit("\n"), F.lit("\\\n"))


def unescape(text: Column) -> Column:
    return F.regexp_replace(text, r"\\([\s\S])", "$1")


def _same(a: str, b: str) -> Column:
    return F.col(a).eqNullSafe(F.col(b))


def paths(messages: DataFrame) -> DataFrame:
    """(tree, msg, parent) -> (tree, leaf, node, up): every leaf's messages, up replies above it."""
    known = messages.select(F.col("tree").alias("t2"), F.col("msg").alias("m2"))
    linked = messages.join(known, _same("tree", "t2") & (F.col("parent") == F.col("m2")), "left").select("tree", "msg", F.col("m2").alias("parent"))
    links = cut(linked, "chat-links")
    # jumps[k]: from each message to the one 2**k replies above it. A chain from a root has a message of just that height,
    # whose jump is the last, so a round after which as many are left as before has messages on or behind a cycle only.
    jumps = [links.where("parent is not null").select("tree", "msg", F.col("parent").alias("jump"))]
    left, before = jumps[0].count(), -1
    while left and left != before:
        step = jumps[-1].select(F.col("tree").alias("t2"), F.col("msg").alias("m2"), F.col("jump").alias("j2"))
        jumps.append(cut(jumps[-1].join(step, _same("tree", "t2") & (F.col("jump") == F.col("m2"))).select("tree", "msg", F.col("j2").alias("jump")), "chat-jumps"))
        left, before = jumps[-1].count(), left
    parents = links.where("parent is not null").select(F.col("tree").alias("t2"), F.col("parent").alias("m2")).distinct()
    leaves = links.join(parents, _same("tree", "t2") & (F.col("msg") == F.col("m2")), "left_anti").select("tree", "msg")
    if left:
        endless = jumps[-1].select(F.col("tree").alias("t2"), F.col("msg").alias("m2"))
        leaves = leaves.join(endless, _same("tree", "t2") & (F.col("msg") == F.col("m2")), "left_anti")
    found = cut(leaves.select("tree", F.col("msg").alias("leaf"), F.col("msg").alias("node"), F.lit(0).cast("long").alias("up")), "chat-reach")
    for k, jump in enumerate(jumps[:-1]):
        step = jump.select(F.col("tree").alias("t2"), F.col("msg").alias("m2"), F.col("jump").alias("j2"))
        above = found.join(step, _same("tree", "t2") & (F.col("node") == F.col("m2"))).select("tree", "leaf", F.col("j2").alias("node"), (F.col("up") + (1 << k)).alias("up"))
        found = found.unionByName(cut(above, "chat-reach"))
    return found


def format_trees(messages: DataFrame, branches: int | None = None, loss_role: str = "assistant") -> DataFrame:
    """(tree, msg, parent, role, text[, score]) -> (tree, leaf, branch, score, n_turns, formatted, loss_spans).

    loss_spans: array of (start, length) in characters of formatted, one for each text of loss_role. branches: how many of
    a tree's paths to keep, best first; None keeps all.
    """
    score = F.coalesce(F.col("score"), F.lit(0.0)).cast("double") if "score" in messages.columns else F.lit(0.0)
    rows = messages.select("tree", "msg", "parent", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"), score.alias("score")).where("msg is not null")
    rows = rows.groupBy("tree", "msg").agg(F.min(F.struct("parent", "role", "text", "score")).alias("m")).select("tree", "msg", "m.*")
    on_path = paths(rows.select("tree", "msg", "parent"))
    body = rows.select(F.col("tree").alias("t2"), F.col("msg").alias("m2"), "role", "text", "score")
    turns = on_path.join(body, _same("tree", "t2") & (F.col("node") == F.col("m2"))).drop("t2", "m2")
    if branches is not None:
        means = turns.groupBy("tree", "leaf").agg(F.avg("score").alias("mean"))
        best = means.withColumn("n", F.row_number().over(Window.partitionBy("tree").orderBy(F.desc("mean"), "leaf"))).where(F.col("n") <= branches)
        turns = turns.join(best.select(F.col("tree").alias("t2"), F.col("leaf").alias("l2")), _same("tree", "t2") & (F.col("leaf") == F.col("l2")), "left_semi")
    head, tail = F.concat(F.lit(START), escape_role(F.col("role")), F.lit("\n")), f"{END}\n"
    turns = turns.withColumns({"head": head, "body": escape(F.col("text"))})
    turns = turns.withColumn("chars", F.char_length("head") + F.char_length("body") + len(tail))
    before = Window.partitionBy("tree", "leaf").orderBy(F.desc("up")).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    turns = turns.withColumn("start", F.sum("chars").over(before) - F.col("chars") + F.char_length("head"))
    part = F.struct((-F.col("up")).alias("at"), F.concat("head", "body", F.lit(tail)).alias("turn"), "start", F.char_length("body").cast("long").alias("length"), (F.col("role") == loss_role).alias("loss"))
    made = turns.groupBy("tree", "leaf").agg(F.sort_array(F.collect_list(part)).alias("parts"), F.avg("score").alias("score"))
    made = made.withColumn("branch", F.row_number().over(Window.partitionBy("tree").orderBy(F.desc("score"), "leaf")))
    spans = F.transform(F.filter("parts", lambda p: p["loss"]), lambda p: F.struct(p["start"].alias("start"), p["length"].alias("length")))
    return made.select("tree", "leaf", "branch", "score", F.size("parts").cast("long").alias("n_turns"), F.array_join(F.transform("parts", lambda p: p["turn"]), "").alias("formatted"), spans.alias("loss_spans"))


def read_back(formatted: DataFrame) -> DataFrame:
    """The formatted conversations with turns (array of role, text) and loss_text, both parsed from the output."""
    pieces = F.filter(F.split("formatted", r"<\|im_end\|>\n", -1), lambda p: p != "")
    line = r"^<\|im_start\|>((?:[^\\\n]|\\[\s\S])*)\n([\s\S]*)$"
    turns = F.transform(pieces, lambda p: F.struct(unescape(F.regexp_extract(p, line, 1)).alias("role"), unescape(F.regexp_extract(p, line, 2)).alias("text")))
    loss = F.array_join(F.transform("loss_spans", lambda s: unescape(F.substring(F.col("formatted"), (s["start"] + 1).cast("int"), s["length"].cast("int")))), "")
    return formatted.withColumns({"turns": turns, "loss_text": loss})


def threads(conversations: DataFrame) -> DataFrame:
    """Linear conversations as reply trees: every row answers the row before it, by turn."""
    order = Window.partitionBy("conv_id").orderBy("turn", "role", "text")
    numbered = conversations.select("conv_id", "role", "text", F.row_number().over(order).cast("long").alias("msg"))
    return numbered.select(F.col("conv_id").alias("tree"), "msg", F.when(F.col("msg") > 1, F.col("msg") - 1).alias("parent"), "role", "text")


#: Fixed value: the extra conversation of the query, whose texts hold control strings.
EXTRA = "</s>[INST] ok [/INST]"


def query(spark, sf_dir):
    from .common import table

    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    extra = spark.range(2).select(F.lit(-1).cast("long").alias("conv_id"), F.col("id").alias("turn"), F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"), F.lit(EXTRA).alias("text"))
    back = read_back(format_trees(threads(rows.unionByName(extra))))
    said = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    return back.select(
        F.col("tree").alias("conv_id"),
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(said, 256).alias("turns_sha256"),
        F.char_length("loss_text").cast("long").alias("loss_chars"),
        F.sha2("loss_text", 256).alias("loss_sha256"),
        F.char_length("formatted").cast("long").alias("formatted_chars"),
    )


def _sql_escape(column: str) -> str:
    made = f"replace(coalesce({column}, ''), '\\', '\\\\')"
    for c in CONTROLS:
        made = f"replace({made}, '{c}', '{c[0]}\\{c[1:]}')"
    return made


SQL = rf"""
WITH c AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -1, 0, 'user', '{EXTRA}' UNION ALL SELECT -1, 1, 'assistant', '{EXTRA}')
SELECT conv_id, count(*) AS n_turns,
       sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
       coalesce(sum(length(text)) FILTER (role = 'assistant'), 0)::BIGINT AS loss_chars,
       sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (role = 'assistant'), '')) AS loss_sha256,
       sum({len(START) + len(END) + 2} + length(replace({_sql_escape("role")}, chr(10), chr(92) || chr(10))) + length({_sql_escape("text")}))::BIGINT AS formatted_chars
FROM c GROUP BY conv_id
"""
