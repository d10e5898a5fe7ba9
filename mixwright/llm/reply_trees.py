"""Chat formatting from reply trees, with DataFrame functions only.

Messages form trees by their parent links. Pointer doubling (self-joins of the link table, as many as the logarithm of
the greatest depth) gives every leaf the summed score of its branch; branches are ranked within their tree; the chosen
leaves are expanded to whole paths by the same doubled links; and each path becomes one formatted conversation.

The template writes a turn as ``<s>[INST]role[/INST]text</s>``. Control strings inside roles and texts get one
backslash after their first character, one more if they have some already, and lose it again when read back, so
escaping is reversible for every text.

Each doubling round is written to the shared folder and reread. Rows of one round are linear in the messages, and the
expanded paths are as many as the turns that come out. One conversation is one row of the result, by definition.

Defined results: null roles and texts count as empty; a message whose parent is missing is a root; messages on a
cycle of parent links have no root and belong to no path; a tree may have a null id; node ids must be unique within
their tree (``chains`` makes such ids from turn numbers, ties and repeated rows included, each kept as a turn); an empty
table gives an empty result; other columns of the input are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .shared import stored

OPEN, MID, CLOSE = "<s>[INST]", "[/INST]", "</s>"
CONTROL = r"([<\[])(\\*)(/?(?:s>|INST\]))"
ESCAPED = r"([<\[])\\(\\*)(/?(?:s>|INST\]))"


def escape(text: Column) -> Column:
    return F.regexp_replace(text, CONTROL, r"$1\\$2$3")


def unescape(text: Column) -> Column:
    return F.regexp_replace(text, ESCAPED, "$1$2$3")


def chains(df: DataFrame, tree: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text") -> DataFrame:
    """Linear conversations as reply trees: each row answers the row before it, by turn, role and text."""
    w = Window.partitionBy(tree).orderBy(turn, role, text)
    return df.select(F.col(tree).alias("tree"), F.row_number().over(w).cast("long").alias("node"), F.col(role).alias("role"), F.col(text).alias("text")).select(
        "tree", "node", F.when(F.col("node") > 1, F.col("node") - 1).alias("parent"), "role", "text", F.lit(1.0).alias("score")
    )


def _at(a: str, b: str, left: str, right: str) -> Column:
    return F.col(f"{a}.tree").eqNullSafe(F.col(f"{b}.tree")) & (F.col(f"{a}.{left}") == F.col(f"{b}.{right}"))


def branch_paths(nodes: DataFrame, per_tree: int = 1, score: Column | None = None) -> DataFrame:
    """(tree, leaf, rank, depth, node) of the ``per_tree`` best branches of each tree, roots at depth 0.

    A branch's score is the sum of ``score`` over its messages; ties go to the deeper branch, then the smaller leaf.
    """
    links = nodes.select("tree", "node", "parent", (F.col("score") if score is None else score).cast("double").alias("score"))
    known = nodes.select("tree", "node", F.lit(True).alias("there"))
    links = links.alias("n").join(known.alias("k"), _at("n", "k", "parent", "node"), "left")
    links = links.select("n.tree", "n.node", F.when(F.col("there"), F.col("parent")).alias("up"), F.coalesce("score", F.lit(0.0)).alias("score"), F.lit(1).cast("long").alias("hops"))
    parents = nodes.select("tree", F.col("parent").alias("node")).filter("node is not null").distinct()
    leaf = links.alias("n").join(parents.alias("p"), _at("n", "p", "node", "node"), "left_anti").select("n.tree", "n.node")
    start = stored(links, "reply-links")
    limit = max(1, start.count()).bit_length() + 1
    # A message that has reached its root is done and joins no more; what is left of a round is its live links.
    live, done = start.filter("up is not null"), start.filter("up is null")
    jumps = []
    while len(jumps) <= limit and not live.isEmpty():
        jumps.append(live)
        a, b = live.alias("a"), live.unionByName(done).alias("b")
        step = stored(
            a.join(b, _at("a", "b", "up", "node")).select("a.tree", "a.node", F.col("b.up").alias("up"), (F.col("a.score") + F.col("b.score")).alias("score"), (F.col("a.hops") + F.col("b.hops")).alias("hops")),
            "reply-links",
        )
        live, done = step.filter("up is not null"), done.unionByName(step.filter("up is null"))
    whole = leaf.alias("l").join(done.alias("j"), _at("l", "j", "node", "node")).select("l.tree", F.col("l.node").alias("leaf"), "j.score", "j.hops")
    rank = F.row_number().over(Window.partitionBy("tree").orderBy(F.col("score").desc(), F.col("hops").desc(), "leaf"))
    chosen = whole.withColumn("rank", rank).filter(F.col("rank") <= per_tree)
    # Members at distance d from the leaf: each stored jump of 2^k doubles the distances reached.
    paths = chosen.select("tree", "leaf", "rank", "hops", F.col("leaf").alias("node"), F.lit(0).cast("long").alias("back"))
    for k, jump in enumerate(jumps):
        j = jump.alias("j")
        paths = stored(
            paths.unionByName(paths.alias("p").join(j, _at("p", "j", "node", "node")).select("p.tree", "leaf", "rank", "p.hops", F.col("j.up").alias("node"), (F.col("back") + (1 << k)).alias("back"))),
            "reply-paths",
        )
    return paths.select("tree", "leaf", "rank", (F.col("hops") - 1 - F.col("back")).alias("depth"), "node")


def format_paths(nodes: DataFrame, paths: DataFrame, loss_role: str = "assistant") -> DataFrame:
    """(tree, leaf, rank, n_turns, formatted, loss): ``loss`` lists the (start, length) spans in code points of the escaped texts to learn from."""
    empty = lambda c: F.coalesce(F.col(c), F.lit(""))
    turns = paths.alias("p").join(nodes.alias("n"), _at("p", "n", "node", "node")).select("p.tree", "leaf", "rank", "depth", empty("role").alias("role"), empty("text").alias("text"))
    head = F.concat(F.lit(OPEN), escape(F.col("role")), F.lit(MID))
    body = escape(F.col("text"))
    w = Window.partitionBy("tree", "leaf").orderBy("depth").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    turns = turns.select("tree", "leaf", "rank", "depth", (F.col("role") == loss_role).alias("learn"), head.alias("head"), body.alias("body"))
    turns = turns.withColumn("upto", F.sum(F.length("head") + F.length("body") + len(CLOSE)).over(w))
    span = F.struct((F.col("upto") - len(CLOSE) - F.length("body")).alias("start"), F.length("body").alias("length"))
    rows = turns.groupBy("tree", "leaf", "rank").agg(F.array_sort(F.collect_list(F.struct("depth", F.concat("head", "body", F.lit(CLOSE)).alias("turn"), F.when(F.col("learn"), span).alias("span")))).alias("turns"))
    return rows.select(
        "tree", "leaf", "rank", F.size("turns").cast("long").alias("n_turns"), F.array_join(F.col("turns.turn"), "").alias("formatted"), F.filter(F.col("turns.span"), lambda s: s.isNotNull()).alias("loss")
    )


def read_back(formatted: Column) -> Column:
    """Array of (role, text) from a formatted conversation."""
    parts = F.split(formatted, CLOSE)
    turns = F.filter(parts, lambda t: t != "")
    role = lambda t: F.substring_index(t, MID, 1)
    return F.transform(
        turns,
        lambda t: F.struct(unescape(F.substring(role(t), F.lit(len(OPEN) + 1), F.length(t))).alias("role"), unescape(F.substring(t, F.length(role(t)) + len(MID) + 1, F.length(t))).alias("text")),
    )


def read_loss(formatted: Column, loss: Column) -> Column:
    """Array of the unescaped texts under the loss spans."""
    return F.transform(loss, lambda s: unescape(F.substring(formatted, (s["start"] + 1).cast("int"), s["length"])))
