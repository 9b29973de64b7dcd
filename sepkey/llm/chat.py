"""Chat formatting of reply trees.

A tree is a set of rows (tree_id, node_id, parent_id, role, text, score). Iterative self-joins enumerate its root-to-leaf paths: runs of single
replies are first contracted to chains by pointer doubling, then paths grow from the roots by one chain a round. Branches of a tree are
ranked by the sum of their scores (ties: the longer, then the smaller path) and each chosen branch becomes one formatted conversation.

The template writes a turn as ``<|im_start|>role\\ntext<|im_end|>\\n``. Inside roles and texts a backslash becomes two and ``<|`` becomes
``<\\|``, so no text can open or close a turn, and ``parse`` gives the exact texts back.

Texts stay out of these joins: paths carry ids, and texts are attached to the chosen branches alone.

Null texts and roles are empty; a null score is 0; a null parent, or one that is not in the tree, makes a root; rows without tree or node
id are left out; of rows with one node id the smallest (parent, role, text, score) stays. Nodes on a cycle are reached from no root and give no
branch. Extra columns are ignored.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import common

START, END = "<|im_start|>", "<|im_end|>"


def escape(text: Column) -> Column:
    return F.replace(F.replace(F.coalesce(text, F.lit("")), F.lit("\\"), F.lit("\\\\")), F.lit("<|"), F.lit("<\\|"))


def escape_role(role: Column) -> Column:
    return F.replace(escape(role), F.lit("\n"), F.lit("\\n"))


def unescape(text: str) -> str:
    out, i = [], 0
    while i < len(text):
        j = text.find("\\", i)
        if j < 0 or j + 1 >= len(text):
            out.append(text[i:])
            break
        out.append(text[i:j])
        out.append("\n" if text[j + 1] == "n" else text[j + 1])
        i = j + 2
    return "".join(out)


def parse(formatted: str) -> list[tuple[str, str]]:
    """(role, text) of each turn of a formatted conversation."""
    turns = []
    for part in formatted.split(START)[1:]:
        role, _, rest = part.partition("\n")
        if not rest.endswith(END + "\n"):
            raise ValueError("a turn is not closed")
        turns.append((unescape(role), unescape(rest[: -len(END) - 1])))
    return turns


def turns_as_tree(rows: DataFrame) -> DataFrame:
    """conversations (conv_id, turn, role, text) as chains: each row replies to the one before it by (turn, role, text). A null turn
    comes first. Numbering within a conversation gives repeated turns nodes of their own."""
    order = Window.partitionBy("conv_id").orderBy("turn", "role", "text")
    node = F.row_number().over(order).cast("long")
    return rows.select(F.col("conv_id").alias("tree_id"), node.alias("node_id"), F.when(node > 1, node - 1).alias("parent_id"), "role", "text", F.lit(0.0).alias("score"))


def chains(tree: DataFrame) -> DataFrame:
    """(tree_id, node_id, chain, pos, before, last, score): each node's chain, named by its first node, and its place in it. A chain runs
    as long as each node has one reply. ``before`` is the node that the chain's first node replies to (null: a root), ``last`` marks a leaf.

    Pointers double: after round r a node knows the one 2^r replies up, so a thread of 1000 turns takes 10 self-joins. Nodes on a cycle
    find no first node and are left out."""
    links = tree.where("tree_id is not null and node_id is not null").select("tree_id", "node_id", "parent_id", F.coalesce("score", F.lit(0.0)).cast("double").alias("score"))
    links = common.durable(links.groupBy("tree_id", "node_id").agg(F.min(F.struct("parent_id", "score")).alias("s")).select("tree_id", "node_id", "s.parent_id", "s.score"), "links")
    replies = links.where("parent_id is not null").groupBy("tree_id", "parent_id").agg(F.count("*").alias("replies"))
    known = links.select("tree_id", F.col("node_id").alias("parent_id"), F.lit(True).alias("known"))
    nodes = links.join(known, ["tree_id", "parent_id"], "left").withColumn("parent_id", F.when(F.col("known"), F.col("parent_id"))).drop("known")
    mine = replies.select("tree_id", F.col("parent_id").alias("node_id"), F.col("replies").alias("own"))
    nodes = nodes.join(replies, ["tree_id", "parent_id"], "left").join(mine, ["tree_id", "node_id"], "left")
    # the only reply to its parent continues the parent's chain
    goes_on = F.col("parent_id").isNotNull() & (F.col("replies") == 1)
    nodes = nodes.select("tree_id", "node_id", "score", "parent_id", F.col("own").isNull().alias("last"), goes_on.alias("open"), F.when(goes_on, F.col("parent_id")).otherwise(F.col("node_id")).alias("up"), F.when(goes_on, 1).otherwise(0).cast("long").alias("pos"))
    nodes = common.durable(nodes, "chains")
    left = nodes.where("open").count()
    while left:
        target = nodes.select("tree_id", F.col("node_id").alias("up"), F.col("up").alias("next"), F.col("pos").alias("more"), F.col("open").alias("still"))
        moved = nodes.where("open").join(target, ["tree_id", "up"]).select("tree_id", "node_id", "score", "parent_id", "last", F.col("still").alias("open"), F.col("next").alias("up"), (F.col("pos") + F.col("more")).alias("pos"))
        nodes = common.durable(nodes.where("not open").unionByName(moved), "chains")
        was, left = left, nodes.where("open").count()
        if left == was:
            break
    first = nodes.where("not open and pos = 0").select("tree_id", F.col("node_id").alias("chain"), F.col("parent_id").alias("before"))
    found = nodes.where("not open").select("tree_id", "node_id", F.col("up").alias("chain"), "pos", "last", "score")
    return common.durable(found.join(first, ["tree_id", "chain"]), "chains")


def branches(found: DataFrame) -> DataFrame:
    """(tree_id, path, total, turns) from the result of ``chains``: every root-to-leaf path as an array of chains, the sum of its scores and its
    length. One self-join for each level of branching; only paths that still grow take part."""
    whole = found.groupBy("tree_id", "chain").agg(F.first("before").alias("before"), F.max("last").alias("leaf"), F.sum("score").alias("score"), F.count("*").alias("n"))
    of_node = found.select("tree_id", F.col("node_id").alias("before"), F.col("chain").alias("above"))
    whole = common.durable(whole.join(of_node, ["tree_id", "before"], "left"), "whole")
    replies = whole.where("above is not null").select("tree_id", F.col("above").alias("end"), F.col("chain").alias("next"), F.col("leaf").alias("next_leaf"), F.col("score").alias("more"), F.col("n").alias("longer"))
    growing = whole.where("before is null").select("tree_id", F.col("chain").alias("end"), F.array("chain").alias("path"), F.col("score").alias("total"), F.col("n").alias("turns"), "leaf")
    done = growing.where("leaf").drop("leaf", "end")
    growing = growing.where("not leaf").drop("leaf")
    while not growing.isEmpty():
        step = growing.join(replies, ["tree_id", "end"]).select("tree_id", F.col("next").alias("end"), F.array_append("path", F.col("next")).alias("path"), (F.col("total") + F.col("more")).alias("total"), (F.col("turns") + F.col("longer")).alias("turns"), F.col("next_leaf").alias("leaf"))
        step = common.durable(step, "paths")
        done = done.unionByName(step.where("leaf").drop("leaf", "end"))
        growing = step.where("not leaf").drop("leaf")
    return done


def ranked(paths: DataFrame, top: int | None) -> DataFrame:
    order = Window.partitionBy("tree_id").orderBy(F.desc("total"), F.desc("turns"), F.col("path"))
    out = paths.withColumn("rank", F.row_number().over(order))
    return out if top is None else out.where(F.col("rank") <= top)


def format_trees(tree: DataFrame, top: int | None = None, learn_role: str = "assistant") -> DataFrame:
    """One row for each chosen branch: tree_id, rank, total, formatted, and ``loss``, the code-point spans [start, end) of the escaped
    texts of ``learn_role``, in order. ``top=None`` chooses every branch."""
    found = chains(tree)
    chosen = ranked(branches(found), top).select("tree_id", "rank", "total", F.posexplode("path").alias("part", "chain"))
    chosen = chosen.join(found.select("tree_id", "chain", "node_id", "pos"), ["tree_id", "chain"])
    said = tree.where("tree_id is not null and node_id is not null").groupBy("tree_id", "node_id").agg(F.min(F.struct("parent_id", "role", "text")).alias("s")).select("tree_id", "node_id", F.coalesce("s.role", F.lit("")).alias("role"), F.col("s.text").alias("text"))
    turn = chosen.join(said, ["tree_id", "node_id"]).select("tree_id", "rank", "total", F.struct("part", "pos", (F.col("role") == learn_role).alias("learn"), F.concat(F.lit(START), escape_role(F.col("role")), F.lit("\n")).alias("head"), escape(F.col("text")).alias("body")).alias("t"))
    whole = turn.groupBy("tree_id", "rank", "total").agg(F.array_sort(F.collect_list("t")).alias("t"))
    tail = END + "\n"
    piece = lambda t: F.concat(t["head"], t["body"], F.lit(tail))
    spans = F.aggregate(
        "t",
        F.struct(F.lit(0).alias("at"), F.array().cast("array<struct<start:int,end:int>>").alias("out")),
        lambda acc, t: F.struct(
            (acc["at"] + F.length(piece(t))).alias("at"),
            F.when(t["learn"], F.array_append(acc["out"], F.struct((acc["at"] + F.length(t["head"])).alias("start"), (acc["at"] + F.length(t["head"]) + F.length(t["body"])).alias("end")))).otherwise(acc["out"]).alias("out"),
        ),
    )["out"]
    return whole.select("tree_id", "rank", "total", F.array_join(F.transform("t", piece), "").alias("formatted"), spans.alias("loss"))


def digest(formatted: str, loss) -> tuple[int, str, int, str, int]:
    """What a reader of the output finds: turns and their hash, characters and hash under the loss mask (unescaped), characters in all."""
    turns = parse(formatted)
    said = hashlib.sha256("".join(f"{role}\n{text}\n" for role, text in turns).encode("utf-8", "surrogatepass")).hexdigest()
    learned = "".join(unescape(formatted[a:b]) for a, b in loss)
    return len(turns), said, len(learned), hashlib.sha256(learned.encode("utf-8", "surrogatepass")).hexdigest(), len(formatted)
