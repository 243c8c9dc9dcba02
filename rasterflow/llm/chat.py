"""Chat formatting of reply trees, in DataFrame functions only.

Iterated self-joins double how far each node can see upwards, and then enumerate every root-to-leaf path from its leaf
(the work follows the size of the result, also for long chains).  Branches of a tree are ranked by the mean score of
their nodes, and each chosen path becomes one conversation.  Texts are escaped so that no text can hold a control
string: a backslash is doubled, and one is put inside `<|` and `|>`.

Null text or role: empty.  Null score: 0.  Null tree: a tree of its own.  A parent that isn't there makes its child a
root.  Ties between branches go to the smaller leaf.  Repeated rows of a linear conversation are turns of their own,
ordered by turn, role and text.  An empty table gives no rows.  Other columns are ignored.  A cycle is an error.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window as W, functions as F

from .common import written

END = "<|end|>\n"


def escape(c: Column) -> Column:
    c = F.replace(c, F.lit("\\"), F.lit("\\\\"))
    c = F.replace(c, F.lit("<|"), F.lit("<\\|"))
    return F.replace(c, F.lit("|>"), F.lit("|\\>"))


def unescape(c: Column) -> Column:
    c = F.replace(c, F.lit("|\\>"), F.lit("|>"))
    c = F.replace(c, F.lit("<\\|"), F.lit("<|"))
    return F.replace(c, F.lit("\\\\"), F.lit("\\"))


def linear(turns: DataFrame, tree: str = "conv_id", order: str = "turn", role: str = "role", text: str = "text") -> DataFrame:
    """Nodes (tree, node, parent, role, text, score) of conversations without branches: each turn answers the one before."""
    place = F.row_number().over(W.partitionBy(tree).orderBy(order, role, text))
    rows = turns.select(F.col(tree).alias("tree"), place.cast("long").alias("node"), F.col(role).alias("role"), F.col(text).alias("text"))
    return rows.select("tree", "node", F.when(F.col("node") > 1, F.col("node") - 1).alias("parent"), "role", "text", F.lit(0.0).alias("score"))


def paths(nodes: DataFrame) -> DataFrame:
    """Rows (tree_key, leaf, node, up): the nodes of every root-to-leaf path; `up` counts steps above the leaf."""
    ids = written(nodes.select(F.coalesce(F.col("tree").cast("string"), F.lit("")).alias("tree_key"), "node", "parent").distinct())
    there = ids.select("tree_key", F.col("node").alias("parent")).distinct()
    jump = written(ids.join(there, ["tree_key", "parent"], "left_semi").select("tree_key", "node", F.col("parent").alias("above")))
    leaves = ids.join(jump.select("tree_key", F.col("above").alias("node")).distinct(), ["tree_key", "node"], "left_anti").select("tree_key", F.col("node").alias("leaf"), "node", F.lit(0).cast("long").alias("up")).distinct()
    jumps, n = [], ids.count()
    while not jump.isEmpty():
        if 1 << len(jumps) > 2 * n:
            raise ValueError("the replies have a cycle")
        jumps.append(jump)
        jump = written(jump.join(jump.select("tree_key", F.col("node").alias("above"), F.col("above").alias("over")), ["tree_key", "above"]).select("tree_key", "node", F.col("over").alias("above")))
    out = leaves
    for k in reversed(range(len(jumps))):
        out = written(out)  # else each step would double the plan
        out = out.unionByName(out.join(jumps[k], ["tree_key", "node"]).select("tree_key", "leaf", F.col("above").alias("node"), (F.col("up") + (1 << k)).alias("up")))
    return out


def conversations(nodes: DataFrame, best: int | None = None) -> DataFrame:
    """Rows (tree, leaf, branch_rank, branch_score, n_turns, formatted, loss) for the `best` paths of each tree (None: all).

    formatted: every turn as <|role|>, a newline, the escaped text and <|end|>, a newline.
    loss: array of (start, length) in code points of `formatted`, the assistant's escaped texts.
    """
    keyed = nodes.select(F.coalesce(F.col("tree").cast("string"), F.lit("")).alias("tree_key"), "tree", "node", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"), F.coalesce("score", F.lit(0.0)).alias("score"))
    steps = paths(nodes).join(keyed, ["tree_key", "node"])
    head = F.concat(F.lit("<|"), escape(F.col("role")), F.lit("|>\n"))
    steps = steps.withColumn("head", head).withColumn("body", escape(F.col("text")))
    earlier = W.partitionBy("tree_key", "leaf").orderBy(F.desc("up")).rowsBetween(W.unboundedPreceding, -1)
    length = F.char_length("head") + F.char_length("body") + len(END)
    steps = steps.withColumn("start", (F.coalesce(F.sum(length).over(earlier), F.lit(0)) + F.char_length("head")).cast("long"))
    turn = F.struct((-F.col("up")).alias("place"), F.concat("head", "body", F.lit(END)).alias("piece"), (F.col("role") == "assistant").alias("learn"), "start", F.char_length("body").cast("long").alias("length"))
    grouped = steps.groupBy("tree_key", "leaf").agg(F.first("tree").alias("tree"), F.avg("score").alias("branch_score"), F.count("*").alias("n_turns"), F.sort_array(F.collect_list(turn)).alias("turns"))
    ranked = grouped.withColumn("branch_rank", F.row_number().over(W.partitionBy("tree_key").orderBy(F.desc("branch_score"), "leaf")))
    if best is not None:
        ranked = ranked.where(F.col("branch_rank") <= best)
    mask = F.transform(F.filter("turns", lambda t: t["learn"]), lambda t: F.struct(t["start"].alias("start"), t["length"].alias("length")))
    return ranked.select("tree", "leaf", "branch_rank", "branch_score", "n_turns", F.array_join(F.transform("turns", lambda t: t["piece"]), "").alias("formatted"), mask.alias("loss"))


def parsed(formatted: Column) -> Column:
    """Turns read back from a formatted conversation: array of (role, text)."""
    pieces = F.split(formatted, r"<\|end\|>\n", -1)
    pieces = F.slice(pieces, 1, F.size(pieces) - 1)
    role = lambda p: F.substring_index(F.substr(p, F.lit(3)), "|>\n", 1)
    return F.transform(pieces, lambda p: F.struct(unescape(role(p)).alias("role"), unescape(F.substr(p, F.char_length(role(p)) + 6)).alias("text")))


def digests(formatted: DataFrame) -> DataFrame:
    """What op4 returns, all read back from the output."""
    turns = formatted.withColumn("back", parsed(F.col("formatted")))
    said = F.array_join(F.transform("back", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    learnt = F.array_join(F.transform("loss", lambda m: unescape(F.substr(F.col("formatted"), (m["start"] + 1).cast("int"), m["length"].cast("int")))), "")
    turns = turns.select("tree", "formatted", "back", said.alias("said"), learnt.alias("learnt"))
    return turns.select(
        F.col("tree").alias("conv_id"),
        F.size("back").cast("long").alias("n_turns"),
        F.sha2("said", 256).alias("turns_sha256"),
        F.char_length("learnt").cast("long").alias("loss_chars"),
        F.sha2("learnt", 256).alias("loss_sha256"),
        F.char_length("formatted").cast("long").alias("formatted_chars"),
    )


#: Fixed value: the conversation that op4 adds.
PROBE = r"\### Assistant: </turn> ok"

ORACLE = r"""
WITH c AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '\### Assistant: </turn> ok' UNION ALL SELECT -7, 1, 'assistant', '\### Assistant: </turn> ok'),
e AS (SELECT *, replace(replace(replace(role, '\', '\\'), '<|', '<\|'), '|>', '|\>') AS r, replace(replace(replace(text, '\', '\\'), '<|', '<\|'), '|>', '|\>') AS x FROM c)
SELECT conv_id, count(*)::BIGINT AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
  coalesce(sum(CASE WHEN role = 'assistant' THEN length(text) END), 0)::BIGINT AS loss_chars,
  sha256(coalesce(string_agg(CASE WHEN role = 'assistant' THEN text ELSE '' END, '' ORDER BY turn, role, text), '')) AS loss_sha256,
  sum(length(r) + length(x) + 13)::BIGINT AS formatted_chars
FROM e GROUP BY conv_id
"""
