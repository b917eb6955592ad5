"""Conversations from reply trees, in DataFrame operations only.

Root-to-leaf paths come from iterative self-joins: every message points at its
parent, and each round joins the pointers with themselves, so a round doubles
how far a pointer reaches and carries the scores passed on the way; a tree of
depth d takes log2(d) rounds and every row keeps a constant size.  Leaves are
ranked by the score of their whole path, and the messages of the chosen paths are
gathered by walking the same pointers back, longest first.  Each chosen path is
formatted as one conversation, with a mask over what the model should learn.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .lineage import settle

#: Control strings of the template (fixed values).
START, END = "<|im_start|>", "<|im_end|>"
ROUNDS = 48


def escape(c: Column) -> Column:
    """No control string is left: a backslash is doubled, one goes into each ``<|``."""
    return F.replace(F.replace(c, F.lit("\\"), F.lit("\\\\")), F.lit("<|"), F.lit("<\\|"))


def unescape(c: Column) -> Column:
    return F.replace(F.replace(c, F.lit("<\\|"), F.lit("<|")), F.lit("\\\\"), F.lit("\\"))


def _escape_role(c: Column) -> Column:
    return F.replace(escape(c), F.lit("\n"), F.lit("<\\n"))


def _unescape_role(c: Column) -> Column:
    return unescape(F.replace(c, F.lit("<\\n"), F.lit("\n")))


def chosen_paths(nodes: DataFrame, branches: int = 1) -> DataFrame:
    """``tree, leaf, place, depth, node`` of the best ``branches`` paths of each tree.

    ``nodes`` has ``tree, node, parent, score``; a message whose parent is null
    or missing is a root.  ``place`` ranks the paths of a tree by the sum of
    their scores (null counts 0), ties by the smaller leaf; ``depth`` starts at
    0.  A cycle of parents raises an error.
    """
    base = nodes.select("tree", "node", "parent", F.coalesce(F.col("score").cast("double"), F.lit(0.0)).alias("gain"))
    real = nodes.select(F.col("tree").alias("t"), F.col("node").alias("n"))
    known = base.join(real, F.col("tree").eqNullSafe(F.col("t")) & (F.col("parent") == F.col("n")), "left")
    up = settle(known.select("tree", "node", F.col("n").alias("up"), "gain", F.lit(1).cast("long").alias("steps")))
    levels = [up]
    while not up.where("up is not null").isEmpty():
        if len(levels) > ROUNDS:
            raise ValueError("the parents of some messages form a cycle")
        far = up.select(F.col("tree").alias("t"), F.col("node").alias("n"), F.col("up").alias("far"), F.col("gain").alias("more"), F.col("steps").alias("on"))
        # pointers that have reached a root are done; only the others are joined again
        step = up.where("up is not null").join(far, F.col("tree").eqNullSafe(F.col("t")) & (F.col("up") == F.col("n")), "left")
        moved = step.select("tree", "node", F.col("far").alias("up"), (F.col("gain") + F.coalesce("more", F.lit(0.0))).alias("gain"), (F.col("steps") + F.coalesce("on", F.lit(0))).alias("steps"))
        up = settle(moved.unionAll(up.where("up is null")))
        levels.append(up)
    parents = levels[0].where("up is not null").select(F.col("tree").alias("t"), F.col("up").alias("n")).distinct()
    leaves = up.join(parents, F.col("tree").eqNullSafe(F.col("t")) & (F.col("node") == F.col("n")), "left_anti")
    order = W.partitionBy("tree").orderBy(F.desc("gain"), "node")
    best = leaves.withColumn("place", F.row_number().over(order)).where(F.col("place") <= branches)
    path = best.select("tree", F.col("node").alias("leaf"), "place", (F.col("steps") - 1).alias("depth"), "node")
    for k in range(len(levels) - 1, -1, -1):
        jump = levels[k].where("up is not null").select(F.col("tree").alias("t"), F.col("node").alias("n"), "up")
        more = path.join(jump, F.col("tree").eqNullSafe(F.col("t")) & (F.col("node") == F.col("n"))).select("tree", "leaf", "place", (F.col("depth") - (1 << k)).alias("depth"), F.col("up").alias("node"))
        path = settle(path.unionAll(more))
    return path


def format_turns(turns: DataFrame, learn: str = "assistant") -> DataFrame:
    """``conv_id, formatted, loss`` from ``conv_id, place, depth, role, text``.

    A turn is the start mark, its role, a line break, its text and the end mark
    with a line break.  ``loss`` lists ``start, n`` in code points of the texts of
    ``learn`` as they stand in ``formatted``.  Null roles and texts are empty.
    """
    role, text = _escape_role(F.coalesce("role", F.lit(""))), escape(F.coalesce("text", F.lit("")))
    piece = turns.select("conv_id", "place", "depth", (F.coalesce("role", F.lit("")) == learn).alias("learnt"), F.concat(F.lit(START), role, F.lit("\n")).alias("head"), text.alias("body"))
    before = W.partitionBy("conv_id", "place").orderBy("depth")
    long = F.length("head") + F.length("body") + len(END) + 1
    placed = piece.withColumn("end", F.sum(long).over(before)).withColumn("at", F.col("end") - len(END) - 1 - F.length("body"))
    item = F.struct("depth", F.concat("head", "body", F.lit(END + "\n")).alias("piece"), "learnt", F.col("at").alias("start"), F.length("body").cast("long").alias("n"))
    whole = placed.groupBy("conv_id", "place").agg(F.sort_array(F.collect_list(item)).alias("items"))
    return whole.select(
        "conv_id",
        "place",
        F.array_join(F.transform("items", lambda x: x["piece"]), "").alias("formatted"),
        F.transform(F.filter("items", lambda x: x["learnt"]), lambda x: F.struct(x["start"].alias("start"), x["n"].alias("n"))).alias("loss"),
    )


def read_back(formatted: Column) -> Column:
    """The ``role, text`` turns of a formatted conversation."""
    parts = F.slice(F.split(formatted, r"<\|im_start\|>"), 2, 1 << 30)

    def turn(part: Column) -> Column:
        head = F.substring_index(part, "\n", 1)
        body = F.substring(part, F.length(head) + 2, F.length(part) - F.length(head) - 2 - len(END))
        return F.struct(_unescape_role(head).alias("role"), unescape(body).alias("text"))

    return F.transform(parts, turn)


def learnt_text(formatted: Column, loss: Column) -> Column:
    """All text under the loss mask, unescaped, nothing between."""
    return F.array_join(F.transform(loss, lambda x: unescape(F.substring(formatted, x["start"].cast("int") + 1, x["n"].cast("int")))), "")


def conversation_nodes(rows: DataFrame) -> DataFrame:
    """A table of turns as reply trees: each row answers the one before it.

    Order is ``turn``, ties by role and text; every row is a message of its own.
    """
    order = W.partitionBy("conv_id").orderBy("turn", "role", "text")
    return rows.select("conv_id", "turn", "role", "text").withColumn("node", F.row_number().over(order).cast("long"))


def format_conversations(rows: DataFrame) -> DataFrame:
    """Every conversation of a table of ``conv_id, turn, role, text`` as one string.

    Columns ``conv_id, formatted, loss``.  A null conv_id is a conversation too.
    """
    nodes = settle(conversation_nodes(rows))
    tree = nodes.select(F.col("conv_id").alias("tree"), "node", F.when(F.col("node") > 1, F.col("node") - 1).alias("parent"), F.lit(0.0).alias("score"))
    path = chosen_paths(tree)
    own = nodes.select(F.col("conv_id").alias("c"), F.col("node").alias("n"), "role", "text")
    turns = path.join(own, F.col("tree").eqNullSafe(F.col("c")) & (F.col("node") == F.col("n"))).select(F.col("tree").alias("conv_id"), "place", "depth", "role", "text")
    return format_turns(turns).drop("place")
