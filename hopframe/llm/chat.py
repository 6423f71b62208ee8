"""Chat formatting of reply trees.

Root-to-leaf paths come from self-joins that double in reach: after k rounds every leaf knows its ancestors nearer
than 2**k, and every message its ancestor 2**k steps up. Branches are ranked by their mean message score; each
chosen path becomes one conversation under a template that marks turns, escapes control strings inside texts
reversibly, and comes with the spans of assistant text that a loss is taken on.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from hopframe.llm.common import staged

#: self-joins at most; paths may be 2**ROUNDS messages long
ROUNDS = 24
SALT = 32
LOSS_ROLE = "assistant"

# fixed values of the template
OPEN, CLOSE, END = "<|", "|>\n", "<|end|>\n"

_MARKED = re.compile(r"([<\[|])\\")
_TURN = re.compile(r"<\|(.*?)\|>\n(.*?)<\|end\|>\n", re.DOTALL)


def escaped(text: str) -> str:
    """``text`` without any control string: a backslash follows each ``<``, ``[`` and ``|`` and is itself doubled."""
    return re.sub(r"([<\[|])", r"\1\\", text.replace("\\", "\\\\"))


def unescaped(text: str) -> str:
    return _MARKED.sub(r"\1", text).replace("\\\\", "\\")


def formatted(turns: list[tuple[str, str]]) -> tuple[str, list[tuple[int, int]]]:
    """The conversation of (role, text) turns, and the spans (in characters) of its assistant texts."""
    out, spans, at = [], [], 0
    for role, text in turns:
        head, body = f"{OPEN}{escaped(role)}{CLOSE}", escaped(text)
        out += [head, body, END]
        if role == LOSS_ROLE:
            spans.append((at + len(head), at + len(head) + len(body)))
        at += len(head) + len(body) + len(END)
    return "".join(out), spans


def parsed(conversation: str) -> list[tuple[str, str]]:
    """The (role, text) turns of a formatted conversation."""
    return [(unescaped(role), unescaped(text)) for role, text in _TURN.findall(conversation)]


def reply_paths(messages: DataFrame) -> DataFrame:
    """(tree, leaf, node, up) for every message on every root-to-leaf path of (tree, node, parent).

    Trees must not be null. A null parent, or one that is not in the tree, makes a root. A path of 2**24 messages or more, or a cycle below
    some leaf, raises ValueError; messages on a cycle without a leaf are on no path.
    """
    nodes = messages.select("tree", "node", "parent")
    known = nodes.select("tree", F.col("node").alias("parent")).distinct()
    step = staged(nodes.where("parent is not null").join(known, ["tree", "parent"], "left_semi").select("tree", "node", F.col("parent").alias("above")))
    answered = step.select("tree", F.col("above").alias("node")).distinct()
    paths = staged(nodes.join(answered, ["tree", "node"], "left_anti").select("tree", F.col("node").alias("leaf"), "node", F.lit(0).cast("long").alias("up")))
    for k in range(ROUNDS):
        more = staged(paths.join(step, ["tree", "node"]).select("tree", "leaf", F.col("above").alias("node"), (F.col("up") + (1 << k)).alias("up")))
        if more.isEmpty():
            return paths
        paths = staged(paths.unionByName(more))
        step = staged(step.join(step.select("tree", F.col("node").alias("above"), F.col("above").alias("further")), ["tree", "above"]).select("tree", "node", F.col("further").alias("above")))
    raise ValueError("a reply path is too long or runs in a circle")


def ranked_branches(paths: DataFrame, messages: DataFrame, branches: int) -> DataFrame:
    """The best ``branches`` leaves of each tree by mean score (null counts as 0), ties to the smaller leaf."""
    scored = paths.join(messages.select("tree", "node", F.coalesce("score", F.lit(0.0)).alias("score")), ["tree", "node"])
    leaves = scored.groupBy("tree", "leaf").agg((F.sum("score") / F.count("*")).alias("score")).withColumn("salt", F.pmod(F.xxhash64("leaf"), F.lit(SALT)))
    for keys in (["tree", "salt"], ["tree"]):  # a tree of very many leaves is thinned out in parts first
        leaves = leaves.withColumn("rank", F.row_number().over(W.partitionBy(*keys).orderBy(F.desc("score"), "leaf"))).where(F.col("rank") <= branches)
    return leaves.select("tree", "leaf", "rank", "score")


def conversations_of(messages: DataFrame, branches: int = 1) -> DataFrame:
    """tree, leaf, rank, score, conversation and loss spans of the chosen paths.

    ``messages`` has tree, node, parent, role, text and score; (tree, node) is a key. Null roles and texts count as
    empty, and the rows without a tree are one tree. Other columns are ignored. An empty table gives an empty result.
    """
    kind = messages.schema["tree"].dataType
    key = F.coalesce(F.concat(F.lit("="), F.col("tree").cast("string")), F.lit(""))  # joins see it, pandas keeps it exact
    slim = staged(messages.select(key.alias("tree"), "node", "parent", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"), F.col("score").cast("double").alias("score")))
    paths = reply_paths(slim)
    chosen = ranked_branches(paths, slim, branches)
    rows = paths.join(chosen, ["tree", "leaf"]).join(slim.select("tree", "node", "role", "text"), ["tree", "node"])
    turns = rows.groupBy("tree", "leaf", "rank", "score").agg(F.sort_array(F.collect_list(F.struct((-F.col("up")).alias("at"), "role", "text"))).alias("turns"))

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            made = [formatted([(t["role"], t["text"]) for t in turns]) for turns in frame["turns"]]
            yield frame.drop(columns="turns").assign(conversation=[m[0] for m in made], loss=[[{"first": a, "stop": b} for a, b in m[1]] for m in made])

    made = turns.mapInPandas(run, f"tree string, leaf {slim.schema['node'].dataType.simpleString()}, rank int, score double, conversation string, loss array<struct<first:long,stop:long>>")
    return made.withColumn("tree", F.when(F.col("tree") != "", F.expr("substr(tree, 2)")).cast(kind))


def chain(turns: DataFrame, tree: str = "conv_id", order: str = "turn") -> DataFrame:
    """Messages of plain conversations: each row answers the one before it by turn, role and text.

    The rows of a null id are one conversation.
    """
    rows = turns.select(F.col(tree).alias("tree"), F.col(order).alias("at"), "role", "text")
    place = W.partitionBy("tree").orderBy("at", "role", "text")
    numbered = rows.withColumn("node", F.row_number().over(place).cast("long"))
    return numbered.select("tree", "node", F.when(F.col("node") > 1, F.col("node") - 1).alias("parent"), "role", "text", F.lit(None).cast("double").alias("score"))


def read_back(conversations: DataFrame) -> DataFrame:
    """What a reader gets out of each formatted conversation: turns, their digest, and the text under the loss."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            out = []
            for tree, text, loss in zip(frame["tree"], frame["conversation"], frame["loss"]):
                turns = parsed(text)
                told = "".join(f"{role}\n{body}\n" for role, body in turns)
                under = "".join(unescaped(text[s["first"] : s["stop"]]) for s in loss)
                out.append((tree, len(turns), hashlib.sha256(told.encode()).hexdigest(), len(under), hashlib.sha256(under.encode()).hexdigest(), len(text)))
            yield pd.DataFrame(out, columns=["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"])

    told = conversations.select(F.col("tree").cast("string").alias("tree"), "conversation", "loss")  # pandas would make floats of ids beside nulls
    return told.mapInPandas(run, "conv_id string, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long").withColumn("conv_id", F.col("conv_id").cast("long"))
