"""Operator 5: chat formatting of reply trees.

Root-to-leaf paths are enumerated by self-joins that double the distance each round (a tree of depth
d takes log2(d) joins), branches are ranked by the sum of their scores, and each chosen path becomes
one conversation. Rows of a linear conversation form a tree without branches: each turn replies to
the one before.

The template marks turns with control strings; where a text holds a control string (ours or one of
other common templates) a backslash is put behind its first character, one more if backslashes stand
there already, so the escape is undone exactly.

Null text or role is empty. Turns of equal number stand in order of role and text. Rows without
conv_id form one conversation without id. One conversation is one output row, whatever its length.
Other columns are ignored.
"""

from __future__ import annotations

import re

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from relmodel.llm._common import drop_written, text_of, written

#: Our control strings, then those of other templates.
OPEN, SAYS, END = "<|turn|>", "<|says|>", "<|end|>"
CONTROLS = (OPEN, SAYS, END, "<s>", "</s>", "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>", "<|im_start|>", "<|im_end|>", "<|endoftext|>")

_rest = "|".join(re.escape(c[1:]) for c in sorted(CONTROLS, key=len, reverse=True))
_plain = re.compile(rf"([<\[])(\\*)({_rest})")
_escaped = re.compile(rf"([<\[])\\(\\*)({_rest})")
_turn = re.compile(f"{re.escape(OPEN)}(.*?){re.escape(SAYS)}(.*?){re.escape(END)}", re.S)


def escape(text: str) -> str:
    return _plain.sub(r"\1\\\2\3", text)


def unescape(text: str) -> str:
    return _escaped.sub(r"\1\2\3", text)


def render(turns: list[tuple[str, str]], speaks: str = "assistant") -> tuple[str, list[tuple[int, int]]]:
    """The conversation as one text, and the spans of it that the loss counts."""
    out, spans, at = [], [], 0
    for role, text in turns:
        head, body = f"{OPEN}{escape(role)}{SAYS}", escape(text)
        if role == speaks:
            spans.append((at + len(head), at + len(head) + len(body)))
        out += [head, body, END]
        at += len(head) + len(body) + len(END)
    return "".join(out), spans


def parse(text: str) -> list[tuple[str, str]]:
    return [(unescape(r), unescape(t)) for r, t in _turn.findall(text)]


def paths(nodes: DataFrame) -> DataFrame:
    """(leaf, node, up) for every root-to-leaf path of (node, parent); ``up`` counts steps from the
    leaf. A cycle of parents raises ValueError."""
    jump = written(nodes.where("parent IS NOT NULL").select("node", F.col("parent").alias("to")))
    inner = jump.select(F.col("to").alias("node")).distinct()
    found = written(nodes.join(inner, "node", "left_anti").select(F.col("node").alias("leaf"), "node", F.lit(0).cast("long").alias("up")))
    count, step = nodes.count(), 1
    while not jump.isEmpty():
        if step > count:
            raise ValueError("replies form a cycle")
        more = found.join(jump, "node").select("leaf", F.col("to").alias("node"), (F.col("up") + step).alias("up"))
        hop = jump.select(F.col("node").alias("to"), F.col("to").alias("far"))
        longer, grown = written(jump.join(hop, "to").select("node", F.col("far").alias("to"))), written(found.union(more))
        drop_written(jump, found)
        jump, found, step = longer, grown, 2 * step
    return found


def format_trees(nodes: DataFrame, branches: int | None = 1) -> DataFrame:
    """tree, leaf, score, formatted, loss_spans: the ``branches`` best paths of each tree (None: all).
    ``nodes`` has tree, node (unique), parent, role, text, score."""
    own = written(nodes.select("tree", "node", "parent", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"), F.coalesce("score", F.lit(0.0)).alias("score")))
    way = paths(own.select("node", "parent"))
    ranked = way.join(own.select("tree", "node", "score"), "node").groupBy("leaf").agg(F.sum("score").alias("total"), F.max("tree").alias("tree"))
    if branches == 1:
        best = ranked.groupBy("tree").agg(F.max(F.struct("total", (-F.col("leaf")).alias("leaf"))).alias("b")).select((-F.col("b.leaf")).alias("leaf"), F.col("b.total").alias("total"))
    else:
        place = F.row_number().over(Window.partitionBy("tree").orderBy(F.desc("total"), "leaf"))
        best = ranked.withColumn("place", place).where(F.lit(True) if branches is None else F.col("place") <= branches).select("leaf", "total")
    turns = way.join(best, "leaf").join(own.select("tree", "node", "role", "text"), "node")
    whole = turns.groupBy("leaf").agg(F.max("tree").alias("tree"), F.max("total").alias("score"), F.sort_array(F.collect_list(F.struct((-F.col("up")).alias("at"), "role", "text"))).alias("turns"))

    def run(batches):
        for b in batches:
            made = [render([(t["role"], t["text"]) for t in turns]) for turns in b.column("turns").to_pylist()]
            spans = pa.array([[{"start": s, "end": e} for s, e in x] for _, x in made], pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())])))
            yield pa.RecordBatch.from_arrays([b.column("tree"), b.column("leaf"), b.column("score"), pa.array([x for x, _ in made], pa.string()), spans], names=["tree", "leaf", "score", "formatted", "loss_spans"])

    return whole.select("tree", "leaf", "score", "turns").mapInArrow(run, "tree long, leaf long, score double, formatted string, loss_spans array<struct<start:long,end:long>>")


def conversations_as_trees(rows: DataFrame) -> DataFrame:
    """Turns of linear conversations as tree nodes."""
    own = rows.select(F.col("conv_id").cast("long").alias("tree"), F.col("turn").cast("long").alias("turn"), text_of("role").alias("role"), text_of("text").alias("text"))
    own = written(own.withColumn("node", F.monotonically_increasing_id()))
    order = Window.partitionBy("tree").orderBy("turn", "role", "text", "node")
    return own.select("tree", "node", F.lag("node").over(order).alias("parent"), "role", "text", F.lit(0.0).alias("score"))


def format_conversations(rows: DataFrame) -> DataFrame:
    """conv_id, formatted, loss_spans per conversation of (conv_id, turn, role, text)."""
    return format_trees(conversations_as_trees(rows)).select(F.col("tree").alias("conv_id"), "formatted", "loss_spans")
