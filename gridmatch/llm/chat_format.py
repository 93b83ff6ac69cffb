"""Chat formatting of reply trees, with DataFrame functions only.

Messages form trees by parent.  Branches are found by self-joins of ids whose jumps
double each time, so a tree of depth d takes log2(d) joins and no text moves; the branches of a
conversation are ranked by score, the jumps mark the nodes of the chosen paths, and the texts
meet their marks in one exchange by conversation.

Each turn is written as ``<s>role\\ntext</s>\\n``.  A control string inside a text gets one more
backslash after its first character (``</s>`` becomes ``<\\/s>``), whatever number it has, so no
text can close a turn and the way back is exact.  The loss mask is a list of character spans.

Null texts and roles are empty.  A null turn comes first, a null conversation is one of its own.
Rows that share a turn are one node and stand in order of role and text; repeated rows stay.
A reply whose parent is missing starts a tree; messages on a cycle of parents, or below one,
have no root and are left out.  An empty table gives no conversations.  Extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import cut, table

#: The template's control strings.
CONTROL = r"([<\[])(\\*)(/?(?:s>|INST\]))"
ESCAPED = r"([<\[])\\(\\*)(/?(?:s>|INST\]))"
OPEN, CLOSE = "<s>", "</s>\n"
NONE = -(1 << 63)  # stands for a null key inside joins


def escape(text: Column) -> Column:
    return F.regexp_replace(text, CONTROL, r"$1\\$2$3")


def unescape(text: Column) -> Column:
    return F.regexp_replace(text, ESCAPED, "$1$2$3")


def _escape_role(role: Column) -> Column:
    return F.replace(F.replace(escape(role), F.lit("|"), F.lit("||")), F.lit("\n"), F.lit("|n"))


def _unescape_role(role: Column) -> Column:
    marked = F.replace(F.replace(role, F.lit("||"), F.lit("|p")), F.lit("|n"), F.lit("\n"))
    return unescape(F.replace(marked, F.lit("|p"), F.lit("|")))


def linear_nodes(messages: DataFrame) -> DataFrame:
    """Nodes of conversations whose rows are simply numbered by `turn`: each replies to the one before."""
    ids = messages.select(F.coalesce("conv_id", F.lit(NONE)).alias("conv"), F.coalesce("turn", F.lit(NONE)).alias("node")).distinct()
    return ids.withColumn("parent", F.lag("node").over(Window.partitionBy("conv").orderBy("node"))).withColumn("score", F.lit(0.0))


def branches(nodes: DataFrame) -> tuple[DataFrame, list[DataFrame]]:
    """Leaves of `nodes` (conv, node, parent, score) with their path's length and score, and the
    jumps (conv, node, up) over 1, 2, 4, ... parents that found them."""
    nodes = cut(nodes)
    jumps: list[DataFrame] = []
    state = nodes.select("conv", "node", F.col("parent").alias("up"), F.lit(1).cast("long").alias("depth"), "score")
    n = None
    while True:
        open_ = state.filter("up IS NOT NULL")
        if open_.isEmpty():
            break
        n = nodes.count() if n is None else n
        if 1 << len(jumps) > 2 * n:  # longer than any path: what is left runs in circles
            state = state.filter("up IS NULL")
            break
        jumps.append(open_.select("conv", "node", "up"))
        b = state.select("conv", F.col("node").alias("up"), F.col("up").alias("up2"), F.col("depth").alias("d2"), F.col("score").alias("s2"))
        on = open_.join(b, ["conv", "up"], "left").select("conv", "node", F.col("up2").alias("up"), (F.col("depth") + F.coalesce("d2", F.lit(0))).alias("depth"), (F.col("score") + F.coalesce("s2", F.lit(0.0))).alias("score"))
        state = cut(state.filter("up IS NULL").union(on))
    inner = nodes.filter("parent IS NOT NULL").select("conv", F.col("parent").alias("node")).distinct()
    return state.join(inner, ["conv", "node"], "left_anti").select("conv", "node", "depth", "score"), jumps


def ranked(leaves: DataFrame, keep: int | None = 1) -> DataFrame:
    """The `keep` best leaves of each conversation (all for None), with their rank."""
    if keep == 1:
        best = F.min(F.struct((-F.col("score")).alias("s"), "node", "depth")).alias("b")
        return leaves.groupBy("conv").agg(best).select("conv", "b.node", "b.depth", F.lit(1).alias("rank"))
    rows = leaves.withColumn("rank", F.row_number().over(Window.partitionBy("conv").orderBy(F.desc("score"), "node")))
    return (rows if keep is None else rows.filter(F.col("rank") <= keep)).select("conv", "node", "depth", "rank")


def path_marks(leaves: DataFrame, jumps: list[DataFrame]) -> DataFrame:
    """Every node of the leaves' paths: conv, node, rank, depth.  Jumps from the longest to the
    shortest reach each ancestor once, so the rows are as many as the paths' nodes."""
    marks = cut(leaves.select("conv", "node", "rank", "depth"))
    for i in range(len(jumps) - 1, -1, -1):
        up = marks.join(jumps[i], ["conv", "node"]).select("conv", F.col("up").alias("node"), "rank", (F.col("depth") - (1 << i)).alias("depth"))
        marks = cut(marks.union(up.filter("depth > 0")))
    return marks


def format_paths(messages: DataFrame, marks: DataFrame) -> DataFrame:
    """conv_id, rank, formatted, loss (spans of the assistant's texts: start, len)."""
    texts = messages.select(F.coalesce("conv_id", F.lit(NONE)).alias("conv"), F.coalesce("turn", F.lit(NONE)).alias("node"), F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    mark = F.struct("rank", F.col("depth").alias("pos"))
    both = texts.withColumn("mark", F.expr("CAST(NULL AS STRUCT<rank: INT, pos: BIGINT>)")).unionByName(marks.select("conv", "node", F.lit(None).cast("string").alias("role"), F.lit(None).cast("string").alias("text"), mark.alias("mark")))
    # one exchange by conversation serves marks, texts and the turns' list
    met = both.repartition("conv").withColumn("marks", F.collect_list("mark").over(Window.partitionBy("conv", "node")))
    placed = met.filter("role IS NOT NULL").select("conv", "role", "text", F.explode("marks").alias("m"))
    turns = placed.groupBy("conv", F.col("m.rank").alias("rank")).agg(F.array_sort(F.collect_list(F.struct("m.pos", "role", "text"))).alias("turns"))
    pieces = F.transform("turns", lambda t: F.struct(t["role"].alias("role"), F.concat(F.lit(OPEN), _escape_role(t["role"]), F.lit("\n")).alias("head"), escape(t["text"]).alias("body")))
    out = turns.select("conv", "rank", pieces.alias("p"))
    step = lambda acc, t: F.struct(
        (acc["at"] + F.length(t["head"]) + F.length(t["body"]) + len(CLOSE)).cast("int").alias("at"),
        F.when(t["role"] == "assistant", F.concat(acc["spans"], F.array(F.struct((acc["at"] + F.length(t["head"])).alias("start"), F.length(t["body"]).alias("len"))))).otherwise(acc["spans"]).alias("spans"),
    )
    empty = F.struct(F.lit(0).alias("at"), F.expr("CAST(array() AS ARRAY<STRUCT<start: INT, len: INT>>)").alias("spans"))
    return out.select(
        F.when(F.col("conv") != NONE, F.col("conv")).alias("conv_id"),
        "rank",
        F.array_join(F.transform("p", lambda t: F.concat(t["head"], t["body"], F.lit(CLOSE))), "").alias("formatted"),
        F.aggregate("p", empty, step)["spans"].alias("loss"),
    )


def read_back(formatted: DataFrame) -> DataFrame:
    """Adds `turns` (role, text) and `loss_text`, taken from the formatted string alone."""
    parts = F.split("formatted", CLOSE, -1)
    df = formatted.withColumn("_parts", F.slice(parts, 1, F.size(parts) - 1))
    heads = lambda p: F.substring_index(p, "\n", 1)
    turns = F.transform("_parts", lambda p: F.struct(_unescape_role(F.substr(heads(p), F.lit(len(OPEN) + 1))).alias("role"), unescape(F.substr(p, F.length(heads(p)) + 2)).alias("text")))
    loss = F.array_join(F.transform("loss", lambda s: unescape(F.substr(F.col("formatted"), s["start"] + 1, s["len"]))), "")
    return df.withColumn("turns", turns).withColumn("loss_text", loss).drop("_parts")


def format_conversations(messages: DataFrame, nodes: DataFrame | None = None, keep: int | None = 1) -> DataFrame:
    """Format the best branches of every tree; without `nodes`, rows follow each other by turn."""
    leaves, jumps = branches(nodes if nodes is not None else linear_nodes(messages))
    return format_paths(messages, path_marks(ranked(leaves, keep), jumps))


def op5_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    odd = "'</s>[INST] ok [/INST]'"
    extra = spark.sql(f"SELECT * FROM VALUES (-1L, 0L, 'user', {odd}), (-1L, 1L, 'assistant', {odd}) AS t(conv_id, turn, role, text)")
    messages = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text").union(extra)
    back = read_back(format_conversations(messages))
    digest = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    return back.select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(digest, 256).alias("turns_sha256"),
        F.length("loss_text").cast("long").alias("loss_chars"),
        F.sha2("loss_text", 256).alias("loss_sha256"),
        F.length("formatted").cast("long").alias("formatted_chars"),
    )


ORACLE = r"""
WITH m AS (
  SELECT conv_id, turn, coalesce(role, '') role, coalesce(text, '') t FROM conversations
  UNION ALL SELECT -1, 0, 'user', '</s>[INST] ok [/INST]' UNION ALL SELECT -1, 1, 'assistant', '</s>[INST] ok [/INST]'),
e AS (SELECT *, length(regexp_replace(t, '([<\[])(\\*)(/?(?:s>|INST\]))', '\1\\\2\3', 'g')) + length(role) + 9 n FROM m)
SELECT CAST(conv_id AS BIGINT) conv_id, count(*) n_turns,
  sha256(string_agg(role || chr(10) || t || chr(10), '' ORDER BY turn, role, t)) turns_sha256,
  CAST(coalesce(sum(length(t)) FILTER (role = 'assistant'), 0) AS BIGINT) loss_chars,
  sha256(coalesce(string_agg(t, '' ORDER BY turn, role, t) FILTER (role = 'assistant'), '')) loss_sha256,
  CAST(sum(n) AS BIGINT) formatted_chars
FROM e GROUP BY conv_id
"""

QUERIES = {"op5_chat_format": op5_chat_format}
ORACLES = {"op5_chat_format": ORACLE}
