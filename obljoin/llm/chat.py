"""Chat formatting of reply trees.

Messages point at the message they answer. Pointer doubling (self-joins, one per power of two) gives every
message its depth and the score of its path; the leaves of a tree are ranked by it; the chosen
root-to-leaf paths are unfolded by the same jump tables, one self-join per power of two; each path becomes one
conversation, formatted in a single streaming pass over its sorted messages.

The template marks turns and escapes control strings inside texts with a backslash, so that a formatted
conversation reads back to the same turns.

Defined results: a message whose parent is missing is a root; messages on a cycle lead to no root and are
left out; a null text or role counts as empty; ties of a score fall to the smaller leaf; repeated rows of a turn are
ordered by role and text; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from obljoin.llm.common import saved, trimmed

#: The control strings of the template.
CONTROLS = ("<s>", "</s>", "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>", "[ROLE]", "[/ROLE]")
#: What stands before and after the text of a turn; other roles are written out.
AROUND = {"user": ("<s>[INST]", "[/INST]"), "system": ("<<SYS>>", "<</SYS>>"), "assistant": ("", "</s>")}

#: Stands for a null conversation id inside, as null keys do not join.
NO_ID = -(1 << 63)

_MARK = re.compile("|".join(re.escape(x) for x in ("\\", *CONTROLS)))
_TOKEN = re.compile("\\\\.|" + "|".join(re.escape(x) for x in CONTROLS), re.DOTALL)
_ESCAPED = re.compile(r"\\(.)", re.DOTALL)


def escape(text: str) -> str:
    return _MARK.sub(lambda m: "\\" + m[0], text)


def unescape(text: str) -> str:
    return _ESCAPED.sub(r"\1", text)


def format_turn(role: str, text: str) -> tuple[str, int, int]:
    """The formatted turn, and where its text lies in it."""
    before, after = AROUND.get(role) or (f"[ROLE]{escape(role)}[/ROLE]", "</s>")
    body = escape(text)
    return before + body + after, len(before), len(before) + len(body)


def parse(formatted: str) -> Iterator[tuple[str, str, int, int]]:
    """Role, text, and the place of the text of each turn."""
    at = 0

    def until(mark: str, start: int) -> int:
        for m in _TOKEN.finditer(formatted, start):
            if m[0] == mark:
                return m.start()
        raise ValueError("an unfinished turn")

    while at < len(formatted):
        if formatted.startswith("[ROLE]", at):
            end = until("[/ROLE]", at + 6)
            role, start, after = unescape(formatted[at + 6 : end]), end + 7, "</s>"
        else:
            role = next((r for r, (before, _) in AROUND.items() if before and formatted.startswith(before, at)), "assistant")
            start, after = at + len(AROUND[role][0]), AROUND[role][1]
        end = until(after, start)
        yield role, unescape(formatted[start:end]), start, end
        at = end + len(after)


def jump_tables(nodes: DataFrame) -> tuple[list[DataFrame], DataFrame]:
    """Jump tables (tree, node, up), up being the 2**j-th ancestor, and (tree, node, score, depth) summed up to the root.

    A round joins only the messages whose path is not summed to its root yet.
    """
    known = nodes.select("tree", F.col("node").alias("parent"), F.lit(True).alias("known"))
    start = nodes.join(known, ["tree", "parent"], "left").select("tree", "node", F.when(F.col("known"), F.col("parent")).alias("up"), F.col("score").cast("double"), F.lit(1).cast("long").alias("depth"))
    now = saved(start)
    total, jumps = now.count(), []
    while (1 << len(jumps)) <= total and now.where("up is not null").head(1):
        open_ = now.where("up is not null")
        jumps.append(open_.select("tree", "node", "up"))
        above = now.select("tree", F.col("node").alias("up"), F.col("up").alias("next"), F.col("score").alias("more"), F.col("depth").alias("far"))
        moved = open_.join(above, ["tree", "up"]).select("tree", "node", F.col("next").alias("up"), (F.col("score") + F.col("more")).alias("score"), (F.col("depth") + F.col("far")).alias("depth"))
        now = saved(now.where("up is null").unionByName(moved))
    return jumps, now.where("up is null").drop("up")  # what is left with an up lies on or below a cycle


def best_paths(nodes: DataFrame, branches: int = 1, mean: bool = True) -> DataFrame:
    """(tree, leaf, rank, path_score, node, depth) for the ``branches`` best leaves of every tree.

    ``nodes`` has tree, node (unique in its tree), parent and score.
    """
    jumps, rooted = jump_tables(nodes)
    inner = nodes.where("parent is not null").select("tree", F.col("parent").alias("node")).distinct()
    leaves = rooted.join(inner, ["tree", "node"], "left_anti")
    score = F.col("score") / F.col("depth") if mean else F.col("score")
    order = Window.partitionBy("tree").orderBy(F.desc("path_score"), "node")
    ranked = leaves.withColumn("path_score", score).withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= branches)
    paths = ranked.select("tree", F.col("node").alias("leaf"), "rank", "path_score", "node")
    for jump in reversed(jumps):
        paths = saved(paths)
        paths = paths.unionByName(paths.join(jump, ["tree", "node"]).select("tree", "leaf", "rank", "path_score", F.col("up").alias("node")))
    return paths.join(rooted.select("tree", "node", "depth"), ["tree", "node"])


def conversations(messages: DataFrame, branches: int = 1, mean: bool = True) -> DataFrame:
    """One row per chosen path: tree, leaf, rank, path_score, n_turns, formatted, loss_starts, loss_ends.

    ``messages`` has tree long, node long, parent long, role, text, score. The loss mask covers the texts of the assistant;
    its spans count code points of ``formatted``.
    """
    held = saved(messages.select("tree", "node", "parent", "role", "text", "score"))
    paths = best_paths(held.select("tree", "node", "parent", "score"), branches, mean)
    turns = paths.join(held.select("tree", "node", "role", "text"), ["tree", "node"])
    ordered = turns.repartition("tree", "leaf").sortWithinPartitions("tree", "leaf", "depth")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, head, parts, starts, ends, place = None, None, [], [], [], 0

        def done() -> pa.RecordBatch:
            tree, leaf, rank, score = head
            values = [tree, leaf, rank, score, len(parts), "".join(parts), starts, ends]
            kinds = (pa.int64(), pa.int64(), pa.int32(), pa.float64(), pa.int64(), pa.string(), pa.list_(pa.int64()), pa.list_(pa.int64()))
            return pa.RecordBatch.from_arrays([pa.array([v], k) for v, k in zip(values, kinds, strict=True)], names=["tree", "leaf", "rank", "path_score", "n_turns", "formatted", "loss_starts", "loss_ends"])

        for batch in batches:
            for tree, leaf, rank, score, role, text in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if (tree, leaf) != now:
                    if now is not None:
                        yield done()
                    now, head, parts, starts, ends, place = (tree, leaf), (tree, leaf, rank, score), [], [], [], 0
                turn, a, b = format_turn(role or "", text or "")
                if role == "assistant":
                    starts.append(place + a)
                    ends.append(place + b)
                parts.append(turn)
                place += len(turn)
        if now is not None:
            yield done()

    chosen = ordered.select("tree", "leaf", "rank", "path_score", "role", "text")
    return chosen.mapInArrow(trimmed(run), "tree long, leaf long, rank int, path_score double, n_turns long, formatted string, loss_starts array<long>, loss_ends array<long>")


def from_turns(table: DataFrame, conv_id: str = "conv_id", turn: str = "turn") -> DataFrame:
    """A conversation as a tree in which every row answers the row before it."""
    at = F.row_number().over(Window.partitionBy("tree").orderBy("turn", "role", "text")).cast("long")
    rows = table.select(F.coalesce(F.col(conv_id).cast("long"), F.lit(NO_ID)).alias("tree"), F.col(turn).cast("long").alias("turn"), F.col("role").cast("string").alias("role"), F.col("text").cast("string").alias("text"))
    return rows.withColumn("node", at).select("tree", "node", F.when(F.col("node") > 1, F.col("node") - 1).alias("parent"), "role", "text", F.lit(1.0).alias("score"))


def read_back(formatted: DataFrame) -> DataFrame:
    """conv_id, n_turns, turns_sha256, loss_chars, loss_sha256, formatted_chars, all parsed from ``formatted``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for tree, text, starts, ends in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                turns, loss, n, chars = hashlib.sha256(), hashlib.sha256(), 0, 0
                for role, said, _, _ in parse(text):
                    turns.update(f"{role}\n{said}\n".encode())
                    n += 1
                for a, b in zip(starts, ends, strict=True):
                    said = unescape(text[a:b])
                    loss.update(said.encode())
                    chars += len(said)
                out.append((None if tree == NO_ID else tree, n, turns.hexdigest(), chars, loss.hexdigest(), len(text)))
            kinds = (pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64())
            names = ["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"]
            columns = zip(*out, strict=True) if out else [[]] * 6
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=names)

    chosen = formatted.select("tree", "formatted", "loss_starts", "loss_ends")
    return chosen.mapInArrow(trimmed(run), "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")
