"""Reply trees: paths from root to leaf by iterative self-joins, the best branches formatted as conversations.

Messages name their parent. Joining the table of ancestors with itself doubles how far
it looks, so that depth and score of every path are known after a logarithm of the
greatest depth of rounds, each ending in a durable table. The leaves of a tree are
ranked by the mean score of their path; the messages of each chosen path are gathered
by the same tables and formatted as one text.

The template writes ``### role: text</turn>`` and a line end for every message. Inside
roles and texts a backslash stands before every backslash, every sign of a run of
three or more ``#``, and ``</turn>``; in roles also before colons and line ends; reading
takes one backslash away again. The mask lists the character ranges of the
trained role's texts.

Null texts and roles are empty. Texts of any length stay whole. A message whose parent
is null or unknown is a root; messages on a cycle, and replies to them, have no root
and are on no path. One conversation is one row of the result, gathered in one task. Linear tables get parents in the order of turn, role and text, so ties and repeated
rows follow one another. A null conversation is one conversation. Other columns
don't matter; an empty table gives an empty result.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, Window, functions as F

from ..runtime import durable, ship

END = "</turn>\n"
_CONTROL = re.compile(r"\\|#{3,}|</turn>")
_ROLE = re.compile(r"[\\#:\n<]")
_ESCAPED = re.compile(r"\\(.)", re.DOTALL)
_TURN = re.compile(r"### ((?:[^\\:]|\\.)*): ((?:[^\\<]|\\.|<(?!/turn>))*)</turn>\n", re.DOTALL)


def escape(text: str) -> str:
    return _CONTROL.sub(lambda m: "\\" + m[0] if m[0] != "#" * len(m[0]) else "\\#" * len(m[0]), text)


def unescape(text: str) -> str:
    return _ESCAPED.sub(r"\1", text)


def format_turns(turns: list[tuple[str | None, str | None]], trained: str = "assistant") -> tuple[str, list[tuple[int, int]]]:
    """The text of a conversation, and where the trained role's texts stand in it."""
    out, mask, at = [], [], 0
    for role, text in turns:
        head = f"### {_ROLE.sub(lambda m: chr(92) + m[0], role or '')}: "
        body = escape(text or "")
        if role == trained:
            mask.append((at + len(head), at + len(head) + len(body)))
        out += [head, body, END]
        at += len(head) + len(body) + len(END)
    return "".join(out), mask


def read_turns(formatted: str) -> list[tuple[str, str]]:
    """Roles and texts, from a formatted conversation alone."""
    out, at = [], 0
    while at < len(formatted):
        m = _TURN.match(formatted, at)
        if not m:
            raise ValueError(f"no turn at {at}")
        out.append((unescape(m[1]), unescape(m[2])))
        at = m.end()
    return out


def linear(messages: DataFrame, conversation: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text") -> DataFrame:
    """(tree, node, parent, role, text, score) of conversations whose rows follow one another by turn."""
    order = Window.partitionBy(conversation).orderBy(turn, role, text)
    n = F.row_number().over(order).cast("long")
    rows = messages.select(F.col(conversation).alias("tree"), F.col(turn), F.col(role).alias("role"), F.col(text).alias("text"), n.alias("node"))
    return rows.select("tree", "node", F.when(F.col("node") > 1, F.col("node") - 1).alias("parent"), "role", "text", F.lit(0.0).alias("score"))


def paths(tree: DataFrame, best: int = 1) -> DataFrame:
    """(tree, branch, position, node) for the ``best`` leaves of each tree; tree and node name a message."""
    tree = tree.select("tree", "node", "parent", F.coalesce("score", F.lit(0.0)).alias("score"))
    same = lambda a, b, x, y: F.col(a).eqNullSafe(F.col(b)) & (F.col(x) == F.col(y))
    ids = tree.select(F.col("tree").alias("t"), F.col("node").alias("p"))
    # depth and score cover a message and those above it, up to the one that far names; without one they are final
    state = durable(
        tree.join(ids, same("tree", "t", "parent", "p"), "left").select("tree", "node", F.col("p").alias("far"), F.lit(1).cast("long").alias("depth"), "score"), "state"
    )
    parents = state.filter("far is not null").select(F.col("tree").alias("t"), F.col("far").alias("p"))
    nodes = state.count()
    final, jumps = [state.filter("far is null")], []
    onward = state.filter("far is not null")
    while not onward.isEmpty():
        if 1 << len(jumps) > 2 * nodes:  # a path is no longer than that: what is left leads into a cycle
            break
        jumps.append(onward.select("tree", "node", "far"))
        every = onward
        for done in final:
            every = every.unionByName(done)
        above = every.select(F.col("tree").alias("t"), F.col("node").alias("p"), F.col("far").alias("f"), F.col("depth").alias("d"), F.col("score").alias("s"))
        moved = onward.join(above, same("tree", "t", "far", "p")).select("tree", "node", F.col("f").alias("far"), (F.col("depth") + F.col("d")).alias("depth"), (F.col("score") + F.col("s")).alias("score"))
        moved = durable(moved, "state")
        final.append(moved.filter("far is null"))
        onward = moved.filter("far is not null")
    state = final[0]
    for done in final[1:]:
        state = state.unionByName(done)
    leaf = state.join(parents, same("tree", "t", "node", "p"), "left_anti")
    ranked = leaf.withColumn("branch", F.row_number().over(Window.partitionBy("tree").orderBy(F.desc(F.col("score") / F.col("depth")), "node"))).filter(F.col("branch") <= best)
    got = ranked.select("tree", "branch", "node", F.col("depth").alias("position"))
    for k, jump in enumerate(jumps):
        step = jump.select(F.col("tree").alias("t"), F.col("node").alias("p"), "far")
        further = got.join(step, same("tree", "t", "node", "p")).select("tree", "branch", F.col("far").alias("node"), (F.col("position") - (1 << k)).alias("position"))
        got = durable(got.unionByName(further), "path")
    return got


def conversations(tree: DataFrame, best: int = 1, trained: str = "assistant") -> DataFrame:
    """(tree, branch, formatted, mask): each chosen path as one text."""
    spark = tree.sparkSession
    ship(spark)
    tree = durable(tree, "tree")
    chosen = paths(tree, best)
    texts = tree.select(F.col("tree").alias("t"), F.col("node").alias("p"), "role", "text")
    full = chosen.join(texts, F.col("tree").eqNullSafe(F.col("t")) & (F.col("node") == F.col("p")))
    lists = full.groupBy("tree", "branch").agg(F.array_sort(F.collect_list(F.struct("position", "role", "text"))).alias("turns"))

    def formatted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts, masks = [], []
            for turns in b.column(2).to_pylist():
                text, mask = format_turns([(t["role"], t["text"]) for t in turns], trained)
                texts.append(text)
                masks.append([{"from": a, "to": z} for a, z in mask])
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(texts, pa.string()), pa.array(masks, pa.list_(pa.struct([("from", pa.int64()), ("to", pa.int64())])))], names=["tree", "branch", "formatted", "mask"])

    return lists.select("tree", "branch", "turns").mapInArrow(formatted, f"tree {tree.schema['tree'].dataType.simpleString()}, branch int, formatted string, mask array<struct<from: long, to: long>>")


def read_back(formatted: DataFrame) -> DataFrame:
    """What the formatted texts and masks hold, unescaped, as counts and digests."""
    import hashlib

    ship(formatted.sparkSession)

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sha = lambda t: hashlib.sha256(t.encode("utf-8", "surrogatepass")).hexdigest()
        for b in batches:
            rows = []
            for text, mask in zip(b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True):
                turns = read_turns(text)
                loss = "".join(unescape(text[m["from"] : m["to"]]) for m in mask)
                rows.append((len(turns), sha("".join(f"{r}\n{t}\n" for r, t in turns)), len(loss), sha(loss), len(text)))
            n, turns, chars, loss, size = map(list, zip(*rows, strict=True)) if rows else ([], [], [], [], [])
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64()), pa.array(turns, pa.string()), pa.array(chars, pa.int64()), pa.array(loss, pa.string()), pa.array(size, pa.int64())], names=["tree", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"])

    return formatted.select("tree", "formatted", "mask").mapInArrow(read, f"tree {formatted.schema['tree'].dataType.simpleString()}, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")
