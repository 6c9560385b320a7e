"""Reply trees: root-to-leaf paths, branches ranked by score, each chosen path formatted as one conversation."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import Workspace, table

#: One turn: TURN role ROLE_END text END. Every control string begins with < or [ and has no backslash after it.
TURN, ROLE_END, END = "<s>[TURN]", "[/TURN]", "</s>"


def escape(text: Column) -> Column:
    """A backslash goes after each < and [, so that no control string can stand in the result; reversible."""
    return F.replace(F.replace(text, F.lit("<"), F.lit("<\\")), F.lit("["), F.lit("[\\"))


def unescape(text: Column) -> Column:
    return F.replace(F.replace(text, F.lit("<\\"), F.lit("<")), F.lit("[\\"), F.lit("["))


def render(role: Column, text: Column) -> Column:
    return F.concat(F.lit(TURN), escape(role), F.lit(ROLE_END), escape(text), F.lit(END))


def parse(formatted: Column) -> Column:
    """The turns of a formatted conversation: array of (role, text), both unescaped."""
    turns = F.filter(F.split(formatted, "</s>"), lambda x: x.startswith(TURN))
    cut = lambda x: F.struct(
        unescape(F.substring_index(F.substr(x, F.lit(len(TURN) + 1)), ROLE_END, 1)).alias("role"),
        unescape(F.substr(x, F.instr(x, ROLE_END) + F.lit(len(ROLE_END)))).alias("text"),
    )
    return F.transform(turns, cut)


def _jumps(nodes: DataFrame, ws: Workspace, most: int) -> tuple[list[DataFrame], DataFrame | None]:
    """Tables of (tree, node, to), the k-th with each node's ancestor 2^k above, until nobody has one; and, where some
    node has an ancestor more than ``most`` above, so that its way up never ends, the nodes of those cycles."""
    here = nodes.select("tree", F.col("node").alias("to"))
    jumps = nodes.where("parent is not null").select("tree", "node", F.col("parent").alias("to")).join(here, ["tree", "to"], "left_semi")
    tables = [ws.save(jumps.select("tree", "node", "to"), "jumps0")]
    while not tables[-1].isEmpty():
        if 1 << (len(tables) - 1) > most:
            return tables, ws.save(tables[-1].select("tree", F.col("to").alias("node")).distinct(), "cycles")
        last = tables[-1]
        twice = last.join(last.select("tree", F.col("node").alias("to"), F.col("to").alias("far")), ["tree", "to"])
        tables.append(ws.save(twice.select("tree", "node", F.col("far").alias("to")), f"jumps{len(tables)}"))
    return tables[:-1], None


def paths(nodes: DataFrame, ws: Workspace) -> DataFrame:
    """(tree, leaf, node, up): each leaf with every node on its way to the root, ``up`` steps above it.

    ``nodes``: tree, node, parent (null at a root), distinct by (tree, node) and none of them null. Self-joins double
    the jumps: after k rounds a table holds each node's ancestor 2^k above. Each distance is one sum of distinct powers
    of two, so walking the tables once gives every ancestor exactly once, with about as many rounds as the depth has
    bits. A parent that is missing ends the path. A node on a cycle of replies has no parent: it is a root.
    """
    most = nodes.groupBy("tree").agg(F.count(F.lit(1)).alias("n")).agg(F.max("n")).first()[0] or 0
    tables, cycles = _jumps(nodes, ws, most)
    if cycles is not None:
        on_cycle = nodes.join(cycles, ["tree", "node"], "left_semi").withColumn("parent", F.lit(None).cast(nodes.schema["parent"].dataType))
        nodes = ws.save(nodes.join(cycles, ["tree", "node"], "left_anti").unionByName(on_cycle), "cut")
        tables, _ = _jumps(nodes, ws, most)
    here = nodes.select("tree", "node")
    leaves = here.join(tables[0].select("tree", F.col("to").alias("node")).distinct(), ["tree", "node"], "left_anti") if tables else here
    on_path = leaves.select("tree", F.col("node").alias("leaf"), "node", F.lit(0).cast("long").alias("up"))
    for k, step in enumerate(tables):
        more = on_path.join(step, ["tree", "node"]).select("tree", "leaf", F.col("to").alias("node"), (F.col("up") + (1 << k)).alias("up"))
        on_path = ws.save(on_path.unionByName(more), f"paths{k}")
    return on_path


def format_trees(nodes: DataFrame, best: int | None = None, unique: bool = False) -> DataFrame:
    """Per chosen path: tree, leaf, rank, score, n_turns, formatted, loss_spans.

    ``nodes``: tree, node, parent, role, text, score (null scores count as 0; null roles and texts as empty).
    A branch's score is the sum of its nodes' scores; branches of a tree rank by score, then by leaf. ``best``
    keeps so many branches of each tree, None all of them. ``loss_spans``: (start, end) in characters of the
    formatted text, around each assistant text. Paths are gathered by (tree, leaf): a conversation is one row.
    A null tree is a tree like any other, a null node a node to which nothing replies. Rows that repeat (tree, node)
    count as one: the least by parent, role, text and score; ``unique`` says that there are none. An empty table gives
    no rows.
    """
    ws = Workspace(nodes.sparkSession, "chat")
    # Keys stand in structs, which equal each other where their fields are null.
    said = (F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"), F.coalesce("score", F.lit(0.0)).alias("score"))
    parent = F.when(F.col("parent").isNotNull(), F.struct(F.col("parent").alias("id"))).alias("parent")
    nodes = nodes.select(F.struct(F.col("tree").alias("id")).alias("tree"), F.struct(F.col("node").alias("id")).alias("node"), parent, *said)
    if not unique:
        nodes = nodes.groupBy("tree", "node").agg(F.min(F.struct("parent", "role", "text", "score")).alias("x")).select("tree", "node", "x.*")
    nodes = ws.save(nodes, "nodes")
    on_path = paths(nodes, ws)
    if best is not None:
        scored = on_path.join(nodes.select("tree", "node", "score"), ["tree", "node"]).groupBy("tree", "leaf").agg(F.sum("score").alias("score"))
        ranked = scored.withColumn("rank", F.row_number().over(Window.partitionBy("tree").orderBy(F.desc("score"), "leaf"))).where(F.col("rank") <= best)
        on_path = on_path.join(ranked.select("tree", "leaf"), ["tree", "leaf"], "left_semi")
    turns = on_path.join(nodes, ["tree", "node"]).groupBy("tree", "leaf").agg(F.array_sort(F.collect_list(F.struct((-F.col("up")).alias("at"), "role", "text"))).alias("turns"), F.sum("score").alias("score"))
    rank = F.row_number().over(Window.partitionBy("tree").orderBy(F.desc("score"), "leaf"))
    turns = turns.withColumn("rank", rank)
    shown = turns.withColumn("pieces", F.transform("turns", lambda x: render(x["role"], x["text"])))
    lengths = F.transform("turns", lambda x: F.struct(F.length(render(x["role"], x["text"])).cast("long").alias("n"), (F.length(F.lit(TURN + ROLE_END)) + F.length(escape(x["role"]))).cast("long").alias("head"), (x["role"] == "assistant").alias("own")))
    # The turns' places by a running sum: (characters so far, spans).
    walk = F.reduce(
        lengths,
        F.struct(F.lit(0).cast("long").alias("at"), F.array().cast("array<struct<start:bigint,end:bigint>>").alias("spans")),
        lambda a, x: F.struct((a["at"] + x["n"]).alias("at"), F.when(x["own"], F.concat(a["spans"], F.array(F.struct((a["at"] + x["head"]).alias("start"), (a["at"] + x["n"] - len(END)).alias("end"))))).otherwise(a["spans"]).alias("spans")),
    )
    return shown.select(F.col("tree.id").alias("tree"), F.col("leaf.id").alias("leaf"), "rank", "score", F.size("turns").cast("long").alias("n_turns"), F.array_join("pieces", "").alias("formatted"), walk["spans"].alias("loss_spans"))


def linear_trees(conversations: DataFrame) -> DataFrame:
    """Conversations (conv_id, turn, role, text) as reply trees: each row answers the one before it.

    Rows go by turn, nulls first; equal turns by role, then text. Repeated rows stay turns of their own.
    """
    order = Window.partitionBy("tree").orderBy("turn", "role", "text")
    rows = conversations.select(F.col("conv_id").cast("long").alias("tree"), F.col("turn").cast("long").alias("turn"), F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    placed = rows.withColumn("node", F.row_number().over(order).cast("long"))
    return placed.select("tree", "node", F.when(F.col("node") > 1, F.col("node") - 1).alias("parent"), "role", "text", F.lit(0.0).alias("score"))


def op1_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All ``conversations`` and conversation -1, formatted and read back: the digests of what was read."""
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    tricky = spark.range(2).select(F.lit(-1).cast("long").alias("conv_id"), F.col("id").alias("turn"), F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"), F.lit("</s>[INST] ok [/INST]").alias("text"))
    out = format_trees(linear_trees(rows.unionByName(tricky)), unique=True)
    back = out.withColumn("back", parse(F.col("formatted")))
    masked = F.transform("loss_spans", lambda x: unescape(F.substr("formatted", (x["start"] + 1).cast("int"), (x["end"] - x["start"]).cast("int"))))
    back = back.withColumn("masked", F.array_join(masked, ""))
    said = F.array_join(F.transform("back", lambda x: F.concat(x["role"], F.lit("\n"), x["text"], F.lit("\n"))), "")
    return back.select(
        F.col("tree").alias("conv_id"), F.size("back").cast("long").alias("n_turns"), F.sha2(said, 256).alias("turns_sha256"), F.length("masked").cast("long").alias("loss_chars"),
        F.sha2("masked", 256).alias("loss_sha256"), F.length("formatted").cast("long").alias("formatted_chars"),
    )


OP1_SQL = r"""
WITH t AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -1, 0, 'user', '</s>[INST] ok [/INST]' UNION ALL SELECT -1, 1, 'assistant', '</s>[INST] ok [/INST]'
), o AS (SELECT *, row_number() OVER (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role, text) AS k FROM t)
SELECT conv_id, count(*) AS n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY k)) AS turns_sha256,
       coalesce(sum(length(text)) FILTER (role = 'assistant'), 0)::BIGINT AS loss_chars,
       sha256(coalesce(string_agg(text, '' ORDER BY k) FILTER (role = 'assistant'), '')) AS loss_sha256,
       sum(20 + length(replace(replace(role || text, '<', '<<'), '[', '[[')))::BIGINT AS formatted_chars
FROM o GROUP BY conv_id
"""
