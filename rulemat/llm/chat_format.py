"""Chat formatting of reply trees, in DataFrame functions only.

Nodes reply to a parent node of their conversation.  Iterative self-joins double the distance
that a pointer spans (1, 2, 4, ... replies up) and give every leaf its ancestors after
log2(depth) rounds; the rows are the (leaf, ancestor) pairs, never whole paths per node.
Branches are ranked by the sum of their nodes' scores (ties: smaller leaf), and each chosen
path is formatted as one conversation with a loss mask over its assistant texts.

Template: every turn is ``<|`` role ``|>`` text ``</s>`` and a line feed.  In roles and texts
``~``, ``<`` and ``[`` are escaped as ``~0``, ``~1`` and ``~2`` (and a line feed or ``|`` in a
role as ``~3`` and ``~4``), so that no control string can occur; unescaping gives them back.

Defined cases: null text or role is empty; a null conversation is a conversation of its own;
a node whose parent is missing is a root; replies in a circle have their smallest node as root;
equal rows each stay; an empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import discard, persisted

# Marks of the template, and the escapes in the order in which they are applied.
OPEN, CLOSE, STOP = "<|", "|>", "</s>\n"
ESCAPES = (("~", "~0"), ("<", "~1"), ("[", "~2"))
ROLE_ESCAPES = (*ESCAPES, ("\n", "~3"), ("|", "~4"))


def escape(text: Column, table: tuple[tuple[str, str], ...] = ESCAPES) -> Column:
    for a, b in table:
        text = F.replace(text, F.lit(a), F.lit(b))
    return text


def unescape(text: Column, table: tuple[tuple[str, str], ...] = ESCAPES) -> Column:
    for a, b in reversed(table):
        text = F.replace(text, F.lit(b), F.lit(a))
    return text


def _replies(nodes: DataFrame) -> DataFrame:
    """(conv, node, above): the replies whose parent is there."""
    ids = nodes.select("conv", F.col("node").alias("above"))
    jump = nodes.where(F.col("parent").isNotNull()).select("conv", "node", F.col("parent").alias("above"))
    return jump.join(ids, ["conv", "above"], "left_semi").select("conv", "node", "above")


def _doubled(jump: DataFrame, carry: str | None = None) -> DataFrame:
    """Pointers twice as far; ``carry`` is a column whose least value along the way is kept."""
    upper = jump.select("conv", F.col("node").alias("above"), F.col("above").alias("top"), *([F.col(carry).alias("other")] if carry else []))
    kept = [F.least(carry, "other").alias(carry)] if carry else []
    return persisted(jump.join(upper, ["conv", "above"]).select("conv", "node", F.col("top").alias("above"), *kept), "replies")


def opened(nodes: DataFrame, jump: DataFrame, longest: int) -> DataFrame:
    """``nodes`` with every cycle of replies opened at its smallest node, which becomes a root.
    ``jump`` points further than any path without a cycle is long, so it ends on cycles."""
    on = jump.select("conv", F.col("above").alias("node")).distinct()
    ring = persisted(_replies(nodes).join(on, ["conv", "node"], "left_semi").withColumn("low", F.col("node")), "ring")
    span = 1
    while span < longest:
        ring, old, span = _doubled(ring, "low"), ring, 2 * span
        discard(old)
    roots = ring.where(F.col("node") == F.col("low")).select("conv", "node", F.lit(True).alias("opens"))
    return persisted(nodes.join(roots, ["conv", "node"], "left").withColumn("parent", F.when(F.col("opens").isNull(), F.col("parent"))).select(*nodes.columns), "nodes")


def leaf_paths(nodes: DataFrame) -> DataFrame:
    """(conv, leaf, node, up): every leaf's ancestors, ``up`` replies above it."""
    ids = nodes.select("conv", "node")
    jump = persisted(_replies(nodes), "replies")
    leaves = ids.join(jump.select("conv", F.col("above").alias("node")), ["conv", "node"], "left_anti")
    paths = persisted(leaves.select("conv", F.col("node").alias("leaf"), "node", F.lit(0).cast("long").alias("up")), "paths")
    longest = ids.groupBy("conv").count().agg(F.max("count")).first()[0] or 0
    span = 1
    while not jump.isEmpty():
        if span >= longest:  # further than any path reaches: replies go in circles
            return leaf_paths(opened(nodes, jump, longest))
        further = paths.join(jump, ["conv", "node"]).select("conv", "leaf", F.col("above").alias("node"), (F.col("up") + span).alias("up"))
        paths, old = persisted(paths.unionByName(further), "paths"), paths
        discard(old)
        jump, old, span = _doubled(jump), jump, 2 * span
        discard(old)
    return paths


def best_paths(nodes: DataFrame, keep: int = 1) -> DataFrame:
    """The ``keep`` best branches of every conversation: (conv, leaf, rank, node, pos)."""
    paths = leaf_paths(nodes)
    scored = paths.join(nodes.select("conv", "node", "score"), ["conv", "node"])
    branch = scored.groupBy("conv", "leaf").agg(F.sum(F.coalesce("score", F.lit(0.0))).alias("score"), F.max("up").alias("depth"))
    if keep == 1:  # one row per conversation without gathering its branches
        best = branch.groupBy("conv").agg(F.max(F.struct("score", (-F.col("leaf")).alias("order"), "depth")).alias("b"))
        chosen = best.select("conv", (-F.col("b.order")).alias("leaf"), F.lit(1).alias("rank"), F.col("b.depth").alias("depth"))
    else:
        order = Window.partitionBy("conv").orderBy(F.desc("score"), "leaf")
        chosen = branch.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= keep).select("conv", "leaf", "rank", "depth")
    return paths.join(chosen, ["conv", "leaf"]).select("conv", "leaf", "rank", "node", (F.col("depth") - F.col("up")).alias("pos"))


def format_paths(nodes: DataFrame, keep: int = 1) -> DataFrame:
    """(conv, leaf, rank, formatted, loss): one formatted conversation per chosen path, and
    the code point ranges of its assistant texts."""
    picked = best_paths(nodes, keep).join(nodes.select("conv", "node", "role", "text"), ["conv", "node"])
    role, text = F.coalesce("role", F.lit("")), F.coalesce("text", F.lit(""))
    head = F.concat(F.lit(OPEN), escape(role, ROLE_ESCAPES), F.lit(CLOSE))
    turn = picked.select("conv", "leaf", "rank", "pos", (role == "assistant").alias("learn"), head.alias("head"), escape(text).alias("body"))
    turn = turn.withColumn("piece", F.concat("head", "body", F.lit(STOP)))
    so_far = Window.partitionBy("conv", "leaf").orderBy("pos").rowsBetween(Window.unboundedPreceding, -1)
    placed = turn.withColumn("at", F.coalesce(F.sum(F.length("piece")).over(so_far), F.lit(0)) + F.length("head"))
    one = F.struct("pos", "piece", "learn", "at", (F.col("at") + F.length("body")).alias("stop"))
    gathered = placed.groupBy("conv", "leaf", "rank").agg(F.array_sort(F.collect_list(one)).alias("t"))
    loss = F.transform(F.filter("t", lambda x: x["learn"]), lambda x: F.struct(x["at"].alias("start"), x["stop"].alias("stop")))
    return gathered.select("conv", "leaf", "rank", F.array_join(F.transform("t", lambda x: x["piece"]), "").alias("formatted"), loss.alias("loss"))


def parse_formatted(text: Column) -> Column:
    """Array of (role, text) read from a formatted conversation."""
    pieces = F.split(text, r"</s>\n", -1)
    pieces = F.slice(pieces, 1, F.size(pieces) - 1)
    return F.transform(pieces, lambda p: F.struct(unescape(F.substring_index(p.substr(F.lit(len(OPEN) + 1), F.length(p)), CLOSE, 1), ROLE_ESCAPES).alias("role"), unescape(p.substr(F.locate(CLOSE, p) + len(CLOSE), F.length(p))).alias("text")))


def as_tree(conversations: DataFrame) -> DataFrame:
    """Rows by turn as a chain of replies; ties go by role and text, and equal rows stay."""
    order = Window.partitionBy("conv").orderBy("turn", "role", "text")
    lowest = F.lit(-(2**63)).cast("long")
    rows = conversations.select(F.coalesce(F.col("conv_id").cast("long"), lowest).alias("conv"), "turn", "role", "text")
    return rows.withColumn("node", F.row_number().over(order).cast("long")).select("conv", "node", F.when(F.col("node") > 1, F.col("node") - 1).alias("parent"), "role", "text", F.lit(0.0).alias("score"))


def chat_digests(spark: SparkSession, conversations: DataFrame) -> DataFrame:
    sample = "</s>[INST] ok [/INST]"
    extra = spark.createDataFrame([(-7, 0, "user", sample), (-7, 1, "assistant", sample)], "conv_id long, turn long, role string, text string")
    nodes = persisted(as_tree(conversations.select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), "role", "text").unionByName(extra)), "nodes")
    done = format_paths(nodes)
    turns = parse_formatted(F.col("formatted"))
    learned = F.array_join(F.transform("loss", lambda x: unescape(F.col("formatted").substr(x["start"].cast("int") + 1, (x["stop"] - x["start"]).cast("int")))), "")
    read = done.select("conv", F.length("formatted").cast("long").alias("formatted_chars"), turns.alias("turns"), learned.alias("learned"))
    whole = F.array_join(F.transform("turns", lambda x: F.concat(x["role"], F.lit("\n"), x["text"], F.lit("\n"))), "")
    return read.select(
        F.when(F.col("conv") != -(2**63), F.col("conv")).alias("conv_id"),
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(whole.cast("binary"), 256).alias("turns_sha256"),
        F.length("learned").cast("long").alias("loss_chars"),
        F.sha2(F.col("learned").cast("binary"), 256).alias("loss_sha256"),
        "formatted_chars",
    )


ORACLE_SQL = r"""
WITH r AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text, role AS r0, text AS t0 FROM conversations
           UNION ALL SELECT -7, 0, 'user', '</s>[INST] ok [/INST]', 'user', '</s>[INST] ok [/INST]'
           UNION ALL SELECT -7, 1, 'assistant', '</s>[INST] ok [/INST]', 'assistant', '</s>[INST] ok [/INST]'),
n AS (SELECT *, row_number() OVER (PARTITION BY conv_id ORDER BY turn NULLS FIRST, r0 NULLS FIRST, t0 NULLS FIRST) AS k,
             length(text) + length(regexp_replace(text, '[^~<\[]', '', 'g')) + length(role) + length(regexp_replace(role, '[^~<\[\n|]', '', 'g')) + 9 AS chars FROM r)
SELECT conv_id, count(*) AS n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY k)) AS turns_sha256,
       CAST(coalesce(sum(length(text)) FILTER (WHERE role = 'assistant'), 0) AS BIGINT) AS loss_chars,
       sha256(coalesce(string_agg(text, '' ORDER BY k) FILTER (WHERE role = 'assistant'), '')) AS loss_sha256,
       CAST(sum(chars) AS BIGINT) AS formatted_chars
FROM n GROUP BY conv_id
"""
