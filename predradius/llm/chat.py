"""Reply trees to training conversations.

Messages point at the message they answer. Self-joins that double their reach each round (every message knows an ancestor
twice as far, its depth and the sum of scores on the way) reach the roots of all trees at once; branches of a tree are ranked by score.
Self-joins with ever narrower jumps then enumerate the root-to-leaf paths that were chosen, one row for each message of a path, and
each path is formatted as one conversation with the texts joined in at the end. Up to there no row grows with the length of a path.

Template: every turn is `<|turn|>role\\n`, the text, `<|end|>`. Inside roles and texts, strings that could be read as
control strings (`<|`, `<s>`, `</s>`, `[INST]`, `[/INST]`, `<SYS>`, `</SYS>`) get a backslash after their first
character, and those that have backslashes there get one more, so `unescape` restores every text. Roles also have their backslashes
doubled and line breaks written as a backslash and an n.

Edge cases: null texts and roles count as empty; messages of a null conversation form one conversation under a null id;
a parent that does not exist makes its child a root; rows equal in all columns stay separate turns; messages on a cycle
or below one have no root and are left out; branches of equal score and length go by their leaf; extra columns are ignored, whatever
their names; an empty table gives no conversations; long texts are whole.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import shared_table

# The strings of the template and the ends of strings that may not occur inside a text.
TURN, END = "<|turn|>", "<|end|>"
CONTROL = r"([<\[])(\\*)(\||/?s>|/?INST\]|/?SYS>)"
UNCONTROL = re.compile(r"([<\[])\\(\\*)(\||/?s>|/?INST\]|/?SYS>)")


def escape(text: Column) -> Column:
    return F.regexp_replace(text, CONTROL, r"$1$2\\$3")


def escape_role(role: Column) -> Column:
    """A role ends at a line break, so it may hold none: backslashes double, and a line break becomes a backslash and an n."""
    return F.replace(F.replace(escape(role), F.lit("\\"), F.lit("\\\\")), F.lit("\n"), F.lit("\\n"))


def unescape_role(role: str) -> str:
    return unescape(re.sub(r"\\(.)", lambda m: "\n" if m[1] == "n" else m[1], role, flags=re.S))


def unescape(text: str) -> str:
    return UNCONTROL.sub(r"\1\2\3", text)


def linear_trees(turns: DataFrame) -> DataFrame:
    """conv_id, turn, role, text rows as trees: each turn answers the one before; rows of one turn go by role and text."""
    order = Window.partitionBy("conv_id").orderBy("turn", "role", "text")
    nodes = turns.select("conv_id", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"), F.row_number().over(order).cast("long").alias("node"))
    return nodes.select("conv_id", "node", F.when(F.col("node") > 1, F.col("node") - 1).alias("parent"), "role", "text", F.lit(0.0).alias("score"))


class Trees:
    """Reply trees climbed by doubling: table i knows each message's ancestor 2^i steps up, and the last one its depth and the score of its path.

    Nothing but identifiers and sums is stored, a row for each message and table, whatever the length of a path.
    """

    def __init__(self, nodes: DataFrame):
        links = nodes.select("conv_id", "node", "parent", "score")
        known = links.select(F.col("conv_id").alias("c"), F.col("node").alias("n")).distinct().withColumn("known", F.lit(True))
        inner = links.filter("parent is not null").select(F.col("conv_id").alias("c"), F.col("parent").alias("n")).distinct().withColumn("inner", F.lit(True))
        a = links.join(known, same_node("conv_id", "parent"), "left").drop("c", "n").join(inner, same_node("conv_id", "node"), "left").drop("c", "n")
        state = shared_table(a.select("conv_id", "node", F.when(F.col("known"), F.col("parent")).alias("up"), F.lit(1).cast("long").alias("depth"), F.col("score").alias("total"), F.col("inner").isNull().alias("leaf")))
        #: jumps[i]: conv_id, node, up of the messages that have an ancestor 2^i steps up.
        self.jumps = [state.filter("up is not null").select("conv_id", "node", "up")]
        # A message that has not reached a root after as many steps as there are messages is on a cycle or below one.
        most = state.count()
        while 1 << (len(self.jumps) - 1) <= most and state.filter("leaf and up is not null").limit(1).count():
            b = state.select(F.col("conv_id").alias("c"), F.col("node").alias("n"), F.col("up").alias("beyond"), F.col("depth").alias("depth2"), F.col("total").alias("total2"))
            both = state.join(b, same_node("conv_id", "up"), "left")
            add = lambda x: (F.col(x) + F.coalesce(f"{x}2", F.lit(0).cast("long" if x == "depth" else "double"))).alias(x)
            state = shared_table(both.select("conv_id", "node", F.col("beyond").alias("up"), add("depth"), add("total"), "leaf"))
            self.jumps.append(state.filter("up is not null").select("conv_id", "node", "up"))
        self.state = state

    def leaves(self) -> DataFrame:
        """conv_id, leaf, length of the path from the root, score (mean over the path)."""
        return self.state.filter("leaf and up is null").select("conv_id", F.col("node").alias("leaf"), F.col("depth").alias("length"), (F.col("total") / F.col("depth")).alias("score"))

    def steps(self, leaves: DataFrame) -> DataFrame:
        """leaves with a row for each message (node) of their paths and its place i, from 0 at the root.

        From the widest jumps to the narrowest, each round adds the message halfway between those known, so rows double up to the length of the paths.
        """
        found = leaves.withColumn("node", F.col("leaf")).withColumn("i", F.col("length") - 1)
        for k in reversed(range(len(self.jumps) - 1)):
            jump = self.jumps[k].select(F.col("conv_id").alias("c"), F.col("node").alias("n"), "up")
            above = found.join(jump, same_node("conv_id", "node")).select(*leaves.columns, F.col("up").alias("node"), (F.col("i") - (1 << k)).alias("i"))
            found = shared_table(found.unionByName(above))
        return found


def same_node(conv: str, node: str) -> Column:
    return F.col(conv).eqNullSafe(F.col("c")) & (F.col(node) == F.col("n"))


def root_to_leaf_paths(nodes: DataFrame) -> DataFrame:
    """conv_id, leaf, path (node ids from the root to the leaf), length, score (mean over the path) of every leaf."""
    trees = Trees(nodes)
    steps = trees.steps(trees.leaves())
    path = F.transform(F.sort_array(F.collect_list(F.struct("i", "node"))), lambda s: s["node"])
    return steps.groupBy("conv_id", "leaf", "length", "score").agg(path.alias("path"))


def rank_branches(paths: DataFrame, best: int | None = 1) -> DataFrame:
    """The `best` branches (leaves, or whole paths) of each tree by score, longer paths and then smaller leaves first; None keeps all."""
    order = Window.partitionBy("conv_id").orderBy(F.desc("score"), F.desc("length"), "leaf")
    ranked = paths.withColumn("branch", F.row_number().over(order))
    return ranked if best is None else ranked.filter(F.col("branch") <= best)


def format_paths(nodes: DataFrame, paths: DataFrame, learn: str = "assistant") -> DataFrame:
    """conv_id, branch, n_turns, formatted, loss_spans: code point ranges [from, to) of the texts to learn."""
    return format_steps(nodes, paths.select("conv_id", "branch", F.posexplode("path").alias("i", "node")), learn)


def format_steps(nodes: DataFrame, steps: DataFrame, learn: str = "assistant") -> DataFrame:
    """The same from one row (conv_id, branch, i, node) for each message of a path."""
    steps = steps.select(F.col("conv_id").alias("c"), "branch", "i", F.col("node").alias("n"))
    own = nodes.select("conv_id", "node", "role", "text").join(steps, same_node("conv_id", "node"))
    turns = own.select("conv_id", "branch", "i", F.concat(F.lit(TURN), escape_role(F.col("role")), F.lit("\n")).alias("head"), escape("text").alias("body"), (F.col("role") == learn).alias("learned"))
    whole = turns.groupBy("conv_id", "branch").agg(F.sort_array(F.collect_list(F.struct("i", "head", "body", "learned"))).alias("t"))
    start = F.struct(F.lit(0).cast("int").alias("at"), F.array().cast("array<struct<from:int,to:int>>").alias("spans"))

    def step(acc, t):
        a = acc["at"] + F.length(t["head"])
        z = a + F.length(t["body"])
        span = F.array(F.struct(a.alias("from"), z.alias("to")))
        return F.struct((z + F.lit(len(END))).alias("at"), F.when(t["learned"], F.concat(acc["spans"], span)).otherwise(acc["spans"]).alias("spans"))

    text = F.array_join(F.transform("t", lambda t: F.concat(t["head"], t["body"], F.lit(END))), "")
    return whole.select("conv_id", "branch", F.size("t").cast("long").alias("n_turns"), text.alias("formatted"), F.aggregate("t", start, step, lambda acc: acc["spans"]).alias("loss_spans"))


def parse_formatted(formatted: str) -> list[tuple[str, str]]:
    """(role, text) of each turn, read back from the formatted conversation."""
    turns = []
    for part in formatted.split(END)[:-1]:
        role, _, text = part.removeprefix(TURN).partition("\n")
        turns.append((unescape_role(role), unescape(text)))
    return turns


def read_back(conversations: DataFrame) -> DataFrame:
    """Digests of the turns and of the text under the loss mask, from the formatted text alone."""
    schema = "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long"

    def digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for conv_id, text, spans in zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True):
                turns = parse_formatted(text)
                said = "".join(f"{r}\n{t}\n" for r, t in turns).encode()
                loss = "".join(unescape(text[s["from"] : s["to"]]) for s in spans)
                rows.append((conv_id, len(turns), hashlib.sha256(said).hexdigest(), len(loss), hashlib.sha256(loss.encode()).hexdigest(), len(text)))
            names = [x.split()[0] for x in schema.split(", ")]
            kinds = [pa.string() if "sha256" in n else pa.int64() for n in names]
            yield pa.RecordBatch.from_arrays([pa.array([r[j] for r in rows], k) for j, k in enumerate(kinds)], names)

    return conversations.select(F.col("conv_id").cast("long"), "formatted", "loss_spans").mapInArrow(digest, schema)


def format_conversations(turns: DataFrame, best: int = 1, learn: str = "assistant") -> DataFrame:
    nodes = shared_table(linear_trees(turns))
    trees = Trees(nodes)
    return format_steps(nodes, trees.steps(rank_branches(trees.leaves(), best)), learn)
