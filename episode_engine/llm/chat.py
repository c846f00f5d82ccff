"""Chat formatting over reply trees, with DataFrame functions only.

Messages name their parent. Iterative self-joins double the distance that every leaf has looked up its
branch, so that a path of d messages takes log2(d) rounds; branches are ranked by score, and each chosen
path becomes one string with a loss mask.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import discard, written

START, TEXT, END = "<|start|>", "<|text|>", "<|end|>\n"
#: What is never left as it is inside a role or text: this template's marks and those of common others.
CONTROL = r"<(?=\||/?s>)|\[(?=/?(?:INST|SYS)\])|<(?=</?SYS>>)"
MAX_ROUNDS = 40


def escape(text: Column) -> Column:
    r"""Every backslash is doubled, then one is put after the first character of each control string."""
    return F.regexp_replace(F.regexp_replace(text, r"\\", r"\\\\"), CONTROL, r"$0\\")


def unescape(text: Column) -> Column:
    return F.regexp_replace(text, r"(?s)\\(.)", "$1")


def _join(left: DataFrame, right: DataFrame, keys: list[str], how: str = "inner") -> DataFrame:
    """left join right on keys, as with their names, but a null conv_id is equal to a null conv_id."""
    theirs = {k: f"_right_{k}" for k in keys}
    equal = [F.col(k).eqNullSafe(F.col(r)) if k == "conv_id" else F.col(k) == F.col(r) for k, r in theirs.items()]
    return left.join(right.withColumnsRenamed(theirs), reduce(Column.__and__, equal), how).drop(*theirs.values())


def as_chains(conversations: DataFrame) -> DataFrame:
    """conversations(conv_id, turn, role, text, ...) -> messages, each the reply to the one before it.

    Equal turns of one conversation are put in order by role and text, and all kept; null roles and texts become empty.
    Rows with a null conv_id are one conversation.
    """
    rows = conversations.select("conv_id", "turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    node = F.row_number().over(W.partitionBy("conv_id").orderBy("turn", "role", "text")).cast("long")
    rows = rows.withColumn("node", node)
    return rows.select("conv_id", "node", F.when(F.col("node") > 1, F.col("node") - 1).alias("parent"), "role", "text", F.lit(0.0).alias("score"))


def branches(messages: DataFrame) -> DataFrame:
    """messages(conv_id, node, parent, ...) -> conv_id, leaf, node, up (steps from the leaf): every root-to-leaf path.

    A message whose parent is null or missing is a root. Messages on a cycle have no leaf and are on no path.
    """
    key = ["conv_id", "node"]
    ids = messages.select(*key, "parent")
    up = written(_join(ids, ids.select("conv_id", F.col("node").alias("parent")), ["conv_id", "parent"]).select(*key, F.col("parent").alias("to")), "jumps")
    leaves = _join(ids, up.select("conv_id", F.col("to").alias("node")), key, "left_anti")
    paths = leaves.select("conv_id", F.col("node").alias("leaf"), "node", F.lit(0).cast("long").alias("up"))
    paths = written(paths, "paths")
    for k in range(MAX_ROUNDS):
        if up.isEmpty():
            return paths
        further = _join(paths, up, key).select("conv_id", "leaf", F.col("to").alias("node"), (F.col("up") + F.lit(2**k)).alias("up"))
        longer = written(paths.unionByName(further), "paths")
        twice = _join(up, up.select("conv_id", F.col("node").alias("to"), F.col("to").alias("to2")), ["conv_id", "to"])
        twice = written(twice.select(*key, F.col("to2").alias("to")), "jumps")
        discard(paths, up)
        paths, up = longer, twice
    # What still has an ancestor 2 ** MAX_ROUNDS steps up is below a cycle.
    return _join(paths, up.select("conv_id", F.col("node").alias("leaf")).distinct(), ["conv_id", "leaf"], "left_anti")


def format_trees(messages: DataFrame, top_k: int = 1, loss_roles: tuple[str, ...] = ("assistant",)) -> DataFrame:
    """messages(conv_id, node, parent, role, text, score) -> one row for each chosen path.

    conv_id, leaf, branch_rank (1 is best: the highest sum of scores, then the longest path, then the smallest leaf),
    n_turns, formatted, loss_spans (array of start and length in UTF-8 bytes of `formatted`; they cover the texts of
    `loss_roles`, escaped). (conv_id, node) must be unique. Null scores count 0, null roles and texts as empty.
    Messages with a null conv_id are one conversation; a message with a null node is on no path and left out.
    An empty table gives no rows; extra columns are ignored.
    """
    rows = messages.select("conv_id", "node", "parent", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"), F.coalesce("score", F.lit(0.0)).alias("score"))
    paths = branches(rows)
    scored = _join(paths, rows.select("conv_id", "node", "score"), ["conv_id", "node"])
    ranked = scored.groupBy("conv_id", "leaf").agg(F.sum("score").alias("total"), F.count("*").alias("n_turns"))
    best = F.row_number().over(W.partitionBy("conv_id").orderBy(F.desc("total"), F.desc("n_turns"), "leaf"))
    chosen = ranked.withColumn("branch_rank", best.cast("long")).filter(F.col("branch_rank") <= top_k).drop("total")
    head, text = F.concat(F.lit(START), escape(F.col("role")), F.lit(TEXT)), escape(F.col("text"))
    pieces = rows.select("conv_id", "node", F.col("role").isin(*loss_roles).alias("loss"), head.alias("head"), text.alias("body"))
    on_path = _join(_join(paths, chosen, ["conv_id", "leaf"]), pieces, ["conv_id", "node"])
    piece = F.concat("head", "body", F.lit(END))
    before = W.partitionBy("conv_id", "leaf").orderBy(F.desc("up")).rowsBetween(W.unboundedPreceding, -1)
    at = F.coalesce(F.sum(F.octet_length(piece)).over(before), F.lit(0)) + F.octet_length("head")
    placed = on_path.select("conv_id", "leaf", "branch_rank", "n_turns", "loss", piece.alias("piece"), at.alias("start"), F.octet_length("body").cast("long").alias("length"))
    gathered = placed.groupBy("conv_id", "leaf", "branch_rank", "n_turns").agg(F.sort_array(F.collect_list(F.struct("start", "length", "loss", "piece"))).alias("p"))
    return gathered.select(
        "conv_id", "leaf", "branch_rank", "n_turns",
        F.array_join(F.transform("p", lambda x: x["piece"]), "").alias("formatted"),
        F.transform(F.filter("p", lambda x: x["loss"]), lambda x: F.struct(x["start"].alias("start"), x["length"].alias("length"))).alias("loss_spans"),
    )


def read_turns(formatted: Column) -> Column:
    """The turns of a formatted string, as an array of role and text."""
    parts = F.filter(F.split(formatted, r"<\|start\|>"), lambda x: x != "")

    def turn(x: Column) -> Column:
        role = F.substring_index(x, TEXT, 1)
        body = F.regexp_replace(F.regexp_replace(x, r"(?s)^.*?<\|text\|>", ""), r"<\|end\|>\n$", "")
        return F.struct(unescape(role).alias("role"), unescape(body).alias("text"))

    return F.transform(parts, turn)


def read_loss(formatted: Column, spans: Column) -> Column:
    """The texts under the loss mask, unescaped."""
    raw = formatted.cast("binary")
    return F.transform(spans, lambda s: unescape(F.substring(raw, (s["start"] + 1).cast("int"), s["length"].cast("int")).cast("string")))
