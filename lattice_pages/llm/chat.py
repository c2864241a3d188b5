"""Chat formatting of reply trees.

Messages point at their parents. Self-joins double a jump table (the parent, the
grandparent, the fourth ancestor, ...), and each round extends the ancestor lists of
all leaves by one more power of two, so a tree of depth d needs log2(d) rounds and
only root-to-leaf paths are ever held. Branches are ranked by the sum of their message
scores (ties: the smaller leaf), the best ``branches`` of a tree are kept, and each
becomes one conversation string with the spans of its loss mask.

The template marks a turn with control strings that begin with ``<|``. Inside roles and
texts a backslash is doubled and ``<|`` becomes ``<\\|``, so no text can hold a control
string, and dropping the escapes gives the text back exactly.

Defined results: a null text or role counts as empty; messages whose parent is missing
are roots; a path whose scores hold a NaN ranks last; messages of a parent cycle, and branches that hang from one, give no path;
rows that repeat a node are taken once each as siblings; null tree ids form one tree; an empty
table gives an empty table. Only the named columns are read, so others cannot clash.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from lattice_pages.session import drop_path, materialize

_ESCAPED = re.compile(r"\\(.)", re.S)


def escape(text: str) -> str:
    return text.replace("\\", "\\\\").replace("<|", "<\\|")


def unescape(text: str) -> str:
    return _ESCAPED.sub(r"\1", text)


@dataclass(frozen=True)
class Template:
    """Control strings; each must begin with ``<|``. ``learn``: the roles under the loss mask."""

    turn: str = "<|turn|>"
    text: str = "<|text|>"
    end: str = "<|end|>"
    learn: tuple[str, ...] = ("assistant",)

    def render(self, turns: list[tuple[str, str]]) -> tuple[str, list[tuple[int, int]]]:
        """(conversation, code point spans of the loss mask)."""
        out, spans, at = [], [], 0
        for role, text in turns:
            head, body = f"{self.turn}{escape(role)}{self.text}", escape(text)
            if role in self.learn:
                spans.append((at + len(head), at + len(head) + len(body)))
            out += [head, body, self.end]
            at += len(head) + len(body) + len(self.end)
        return "".join(out), spans

    def parse(self, line: str) -> list[tuple[str, str]]:
        """The turns of a rendered conversation."""
        parts = re.split("(" + "|".join(map(re.escape, (self.turn, self.text, self.end))) + ")", line)
        if any(parts[0::6]) or [p for p in parts[1::2]] != [self.turn, self.text, self.end] * (len(parts) // 6):
            raise ValueError("not a rendered conversation")
        return [(unescape(parts[i + 2]), unescape(parts[i + 4])) for i in range(0, len(parts) - 1, 6)]


def chain(rows: DataFrame, tree: str = "conv_id", order: str = "turn", role: str = "role", text: str = "text") -> DataFrame:
    """Linear conversations as trees: ``tree, node, parent, role, text, score``."""
    w = Window.partitionBy(tree).orderBy(order, role, text)
    n = F.row_number().over(w).cast("long")
    return rows.select(F.col(tree).alias("tree"), n.alias("node"), F.when(n > 1, n - 1).alias("parent"), F.col(role).alias("role"), F.col(text).alias("text"), F.lit(0.0).alias("score"))


def paths(messages: DataFrame) -> DataFrame:
    """``tree, leaf, node, up`` for the nodes of every root-to-leaf path; up: steps above the leaf.

    Input: ``tree, node, parent`` with (tree, node) unique.
    """
    up = messages.select("tree", "node", F.col("parent").alias("to")).join(messages.select("tree", F.col("node").alias("to")), ["tree", "to"], "left_semi").select("tree", "node", "to")
    jump = materialize(up, "jump")
    inner = jump.select("tree", F.col("to").alias("node")).distinct()
    got = materialize(messages.select("tree", "node").join(inner, ["tree", "node"], "left_anti").select("tree", F.col("node").alias("leaf"), "node", F.lit(0).cast("long").alias("up")), "paths")
    most = messages.groupBy("tree").agg(F.count(F.lit(1)).alias("n")).agg(F.max("n")).first()[0] or 0
    step = 1
    while step < most and not jump.isEmpty():
        more = got.join(jump, ["tree", "node"]).select("tree", "leaf", F.col("to").alias("node"), (F.col("up") + step).alias("up"))
        got, old = materialize(got.unionByName(more), "paths"), got
        far = jump.select("tree", F.col("node").alias("to"), F.col("to").alias("next"))
        jump, was = materialize(jump.join(far, ["tree", "to"]).select("tree", "node", F.col("next").alias("to")), "jump"), jump
        drop_path(messages.sparkSession, old)
        drop_path(messages.sparkSession, was)
        step *= 2
    return got


def conversations(messages: DataFrame, template: Template = Template(), branches: int = 1, keep_turns: bool = False) -> DataFrame:
    """``tree, branch, formatted, loss`` for the ``branches`` best paths of each tree.

    ``loss``: start and end of each span under the mask, in code points of ``formatted``.
    Input columns: ``tree, node, parent, role, text, score``.
    """
    kind = messages.schema["tree"].dataType.simpleString()
    null = F.lit("\0null")
    again = Window.partitionBy("tree", "node").orderBy("parent", "role", "text", "score")
    rows = messages.select(F.coalesce(F.concat(F.lit("="), F.col("tree").cast("string")), null).alias("tree"), "node", "parent", "role", "text", "score")
    rows = rows.withColumn("again", F.row_number().over(again))
    # a repeated node is a sibling of its own: only the first row has children
    rows = rows.select("tree", F.concat_ws("/", F.lpad(F.col("node").cast("string"), 20, "0"), F.when(F.col("again") > 1, F.lpad(F.col("again").cast("string"), 10, "0"))).alias("node"), F.lpad(F.col("parent").cast("string"), 20, "0").alias("parent"), "role", "text", F.coalesce(F.col("score"), F.lit(0.0)).alias("score"))
    # ids and scores decide; texts are read again for the chosen paths alone
    said = materialize(rows, "messages")
    slim = said.select("tree", "node", "parent", "score")
    steps = paths(slim).join(slim, ["tree", "node"])
    real = slim.select("tree", F.col("node").alias("parent")).withColumn("known", F.lit(True))
    # a path is rooted if its top, the row furthest above the leaf, has no parent among the rows
    tops = steps.groupBy("tree", "leaf").agg(F.sum("score").alias("total"), F.max_by("parent", "up").alias("parent"))
    ranked = tops.join(real, ["tree", "parent"], "left_anti").withColumn("total", F.when(F.isnan("total"), F.lit(None)).otherwise(F.col("total")))
    ranked = ranked.withColumn("branch", F.row_number().over(Window.partitionBy("tree").orderBy(F.desc_nulls_last("total"), "leaf"))).filter(F.col("branch") <= branches)
    chosen = steps.select("tree", "leaf", "node", "up").join(ranked.select("tree", "leaf", "branch"), ["tree", "leaf"])
    chosen = chosen.join(said.select("tree", "node", "role", "text"), ["tree", "node"])
    turn = F.struct((-F.col("up")).alias("at"), F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    lists = chosen.groupBy("tree", "branch").agg(F.sort_array(F.collect_list(turn)).alias("turns"))
    lists = lists.select(F.when(F.col("tree") != null, F.substring("tree", 2, 1 << 30)).cast(kind).alias("tree"), "branch", "turns")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            made = [template.render([(t["role"], t["text"]) for t in turns.as_py()]) for turns in b.column(2)]
            loss = pa.array([[{"start": s, "end": e} for s, e in spans] for _, spans in made], pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())])))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array([m[0] for m in made], pa.string()), loss], ["tree", "branch", "formatted", "loss"])

    return lists.mapInArrow(run, f"tree {kind}, branch int, formatted string, loss array<struct<start:long,end:long>>")


def read_back(formatted: DataFrame, template: Template = Template()) -> DataFrame:
    """Digests of what a reader of the formatted conversations gets: turns and loss text."""
    kind = formatted.schema["tree"].dataType.simpleString()
    names = ["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = []
            for line, loss in zip(b.column(1).to_pylist(), b.column(2).to_pylist()):
                turns = template.parse(line)
                said = hashlib.sha256("".join(f"{r}\n{t}\n" for r, t in turns).encode("utf-8"))
                text = "".join(unescape(line[s["start"] : s["end"]]) for s in loss)
                rows.append((len(turns), said.hexdigest(), len(text), hashlib.sha256(text.encode("utf-8")).hexdigest(), len(line)))
            kinds = [pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64()]
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds))], names)

    return formatted.select("tree", "formatted", "loss").mapInArrow(run, f"conv_id {kind}, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")
