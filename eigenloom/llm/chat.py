"""Chat formatting of reply trees.

`ancestry` joins the tree with itself, doubling the known path length each round, `best_branches` ranks the root-to-leaf paths by score and walks the chosen
ones up the same jump tables, and `formatted` renders each chosen path as one conversation with a loss mask over the assistant's texts.
The template marks turns with control strings; those inside texts or roles gain one backslash after their first character
(more for each one already there), which `parse` takes away again, so the output reads back exactly.

Null texts and roles count as empty; a null conversation id is a conversation of its own; rows with equal turns are ordered by role and text; repeated rows are
turns of their own; nodes on a cycle have no root and no path; extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import re
from functools import reduce

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import stored

#: The template's control strings.
BEGIN, END, ROLE, ROLE_END = "<s>", "</s>", "[ROLE]", "[/ROLE]"
CONTROLS = (BEGIN, END, ROLE, ROLE_END, "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>", "<unk>", "<pad>")
_TAILS = {c: "|".join(re.escape(x[1:]) for x in CONTROLS if x[0] == c) for c in "<["}
_ESCAPE = re.compile("|".join(rf"{re.escape(c)}\\*(?:{t})" for c, t in _TAILS.items()))
_TURN = re.compile(re.escape(BEGIN + ROLE) + "(.*?)" + re.escape(ROLE_END) + "(.*?)" + re.escape(END), re.S)


def escape(text: str) -> str:
    return _ESCAPE.sub(lambda m: m[0][0] + "\\" + m[0][1:], text)


def unescape(text: str) -> str:
    return _ESCAPE.sub(lambda m: m[0][0] + m[0][2:], text)


def render(turns: list[tuple[str, str]]) -> tuple[str, list[tuple[int, int]]]:
    """The formatted conversation, and the [begin, end) code points under the loss mask."""
    out, spans, at = [], [], 0
    for role, text in turns:
        head, body = BEGIN + ROLE + escape(role) + ROLE_END, escape(text)
        if role == "assistant":
            spans.append((at + len(head), at + len(head) + len(body)))
        out += [head, body, END]
        at += len(head) + len(body) + len(END)
    return "".join(out), spans


def parse(formatted: str) -> list[tuple[str, str]]:
    return [(unescape(m[1]), unescape(m[2])) for m in _TURN.finditer(formatted)]


def reply_nodes(conversations: DataFrame) -> DataFrame:
    """(conv, conv_id, node, parent, role, text, score) of linear conversations: each row replies to the one before it."""
    key = F.coalesce(F.col("conv_id").cast("string"), F.lit("null"))
    order = F.row_number().over(Window.partitionBy("conv").orderBy("turn", "role", "text"))
    text = F.coalesce("text", F.lit(""))
    rows = conversations.select(key.alias("conv"), "conv_id", "turn", F.coalesce("role", F.lit("")).alias("role"), text.alias("text")).withColumn("node", order.cast("long"))
    return rows.select("conv", "conv_id", "node", F.when(F.col("node") > 1, F.col("node") - 1).alias("parent"), "role", "text", F.lit(0.0).alias("score"))


def ancestry(nodes: DataFrame) -> tuple[DataFrame, list[DataFrame]]:
    """Depths and summed scores (conv, node, depth, score) of all nodes below a root, and jump tables (conv, node, above), whose k-th leads 2^k nodes up.

    A node whose parent is missing is a root. Each round joins the unfinished nodes with the table itself and doubles the known part of their paths;
    rows stay narrow, and only nodes at least 2^k deep are in round k. The rest of a table that a round leaves as large as it was lies on or below cycles.
    """
    ids = nodes.select("conv", F.col("node").alias("parent"), F.lit(True).alias("known"))
    first = nodes.select("conv", "node", "parent", F.coalesce("score", F.lit(0.0)).cast("double").alias("score")).join(ids, ["conv", "parent"], "left")
    state = first.select("conv", "node", F.when(F.col("known"), F.col("parent")).alias("above"), F.col("known").isNotNull().cast("long").alias("depth"), "score")
    done, jumps, before = [], [], -1
    while True:
        state = stored(state.withColumn("going", F.col("above").isNotNull()), "ancestry", "going")
        going = state.filter("going").drop("going")
        done.append(state.filter("not going").drop("going"))
        left = going.count()
        if left in (0, before):
            break
        jumps.append(going.select("conv", "node", "above"))
        upper = reduce(DataFrame.unionByName, [*done, going]).select("conv", F.col("node").alias("above"), F.col("above").alias("next"), F.col("depth").alias("more"), F.col("score").alias("gain"))
        state = going.join(upper, ["conv", "above"]).select("conv", "node", F.col("next").alias("above"), (F.col("depth") + F.col("more")).alias("depth"), (F.col("score") + F.col("gain")).alias("score"))
        before = left
    return reduce(DataFrame.unionByName, done).drop("above"), jumps


def path_nodes(ends: DataFrame, jumps: list[DataFrame]) -> DataFrame:
    """(conv, branch, place, node) of the nodes from the root to each of ends (conv, branch, depth, node): every jump, the longest first, adds the nodes it reaches."""
    found = ends.select("conv", "branch", F.col("depth").alias("place"), "node")
    for k in reversed(range(len(jumps))):
        both = F.array_compact(F.array(F.struct("place", "node"), F.when(F.col("above").isNotNull(), F.struct((F.col("place") - (1 << k)).alias("place"), F.col("above").alias("node")))))
        found = found.join(jumps[k], ["conv", "node"], "left").select("conv", "branch", F.inline(both))
    return found


def _gathered(found: DataFrame, *keys: str) -> DataFrame:
    return found.groupBy("conv", *keys).agg(F.transform(F.sort_array(F.collect_list(F.struct("place", "node"))), lambda x: x["node"]).alias("path"))


def root_paths(nodes: DataFrame) -> DataFrame:
    """(conv, node, path, score): the nodes from the root to each node, and the sum of their scores."""
    reach, jumps = ancestry(nodes)
    paths = _gathered(path_nodes(reach.withColumn("branch", F.col("node")), jumps), "branch").withColumnRenamed("branch", "node")
    return paths.join(reach, ["conv", "node"]).select("conv", "node", "path", "score")


def _best_leaves(nodes: DataFrame, reach: DataFrame, branches: int) -> DataFrame:
    """(conv, branch, node, depth, score): the leaves with the highest scores, ties to the lower leaf."""
    parents = nodes.filter("parent is not null").select("conv", F.col("parent").alias("node")).distinct()
    leaves = reach.join(parents, ["conv", "node"], "left_anti")
    if branches == 1:
        best = leaves.groupBy("conv").agg(F.max_by(F.struct("node", "depth", "score"), F.struct("score", -F.col("node"))).alias("best"))
        return best.select("conv", F.lit(1).alias("branch"), "best.*")
    rank = F.row_number().over(Window.partitionBy("conv").orderBy(F.desc("score"), "node"))
    return leaves.withColumn("branch", rank).filter(F.col("branch") <= branches).select("conv", "branch", "node", "depth", "score")


def best_branches(nodes: DataFrame, branches: int = 1) -> DataFrame:
    """(conv, branch, path, score): the paths to the leaves with the highest scores."""
    reach, jumps = ancestry(nodes)
    ends = _best_leaves(nodes, reach, branches)
    return _gathered(path_nodes(ends, jumps), "branch").join(ends, ["conv", "branch"]).select("conv", "branch", "path", "score")


def formatted(nodes: DataFrame, branches: int = 1) -> DataFrame:
    """(conv_id, branch, formatted, loss_spans): one row per chosen path. nodes is read several times, so store it first."""
    reach, jumps = ancestry(nodes)
    chosen = path_nodes(_best_leaves(nodes, reach, branches), jumps)
    turns = chosen.join(nodes.select("conv", "conv_id", "node", "role", "text"), ["conv", "node"])
    grouped = turns.groupBy("conv", "branch").agg(F.first("conv_id").alias("conv_id"), F.collect_list(F.struct("place", "role", "text")).alias("turns"))

    def run(batches):
        for batch in batches:
            made = [render([(t["role"], t["text"]) for t in sorted(turns, key=lambda t: t["place"])]) for turns in batch.column(2).to_pylist()]
            spans = pa.array([[{"begin": b, "end": e} for b, e in m[1]] for m in made], pa.list_(pa.struct([("begin", pa.int32()), ("end", pa.int32())])))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([m[0] for m in made], pa.string()), spans], ["conv_id", "branch", "formatted", "loss_spans"])

    return grouped.select(F.col("conv_id").cast("long").alias("conv_id"), "branch", "turns").mapInArrow(run, "conv_id long, branch int, formatted string, loss_spans array<struct<begin:int,end:int>>")


def read_back(rows: DataFrame) -> DataFrame:
    """Digests taken from the formatted strings alone."""

    def run(batches):
        for batch in batches:
            out = []
            for conv_id, text, spans in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2).to_pylist()):
                turns = parse(text)
                loss = "".join(unescape(text[s["begin"] : s["end"]]) for s in spans)
                digest = hashlib.sha256("".join(f"{r}\n{t}\n" for r, t in turns).encode()).hexdigest()
                out.append((conv_id, len(turns), digest, len(loss), hashlib.sha256(loss.encode()).hexdigest(), len(text)))
            kinds = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in out], kinds[k]) for k in range(6)], ["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"])

    return rows.select("conv_id", "formatted", "loss_spans").mapInArrow(run, "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")
