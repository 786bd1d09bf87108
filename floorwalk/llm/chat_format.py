"""Chat formatting of reply trees.

Messages point to their parents. Ancestor tables that double their reach by self-joins give every message its depth
and root and every leaf its whole path; leaves are ranked in their tree by the mean score of their branch, and each chosen path
is written as one conversation between control strings. Control strings inside texts and roles are escaped reversibly.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from floorwalk.llm.runtime import materialize

# The control strings of the template and those of other common templates, which texts may hold.
OPEN, MIDDLE, CLOSE = "<|turn|>", "<|text|>", "<|end|>"
CONTROL = ("<|", "|>", "<s>", "</s>", "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>")
ESCAPE = "\\"
_parse = re.compile(re.escape(OPEN) + r"(.*?)" + re.escape(MIDDLE) + r"(.*?)" + re.escape(CLOSE), re.DOTALL)
_unescape = re.compile(r"\\(.)", re.DOTALL)


def escaped(text: F.Column) -> F.Column:
    """An escape character is doubled; every control string gets one behind its first character."""
    out = F.replace(text, F.lit(ESCAPE), F.lit(ESCAPE * 2))
    for mark in CONTROL:
        out = F.replace(out, F.lit(mark), F.lit(mark[0] + ESCAPE + mark[1:]))
    return out


def unescape(text: str) -> str:
    return _unescape.sub(r"\1", text)


def ancestors(messages: DataFrame) -> DataFrame:
    """(node, ancestor, distance) of every leaf and each message on its path to the root, itself at distance 0.

    Round k joins all pairs found so far with the table of ancestors 2**k up, and that table with itself, so a tree of
    depth d takes about log2(d) rounds. A parent that is missing, null or the message itself makes a root; messages on a
    cycle, and those whose path up runs into one, have no root and are left out.
    """
    present = messages.select(F.col("node").alias("up"))
    jump = materialize(messages.where("parent is not null and parent <> node").join(present, messages["parent"] == present["up"], "left_semi").select("node", F.col("parent").alias("up")))
    leaves = messages.select("node").join(messages.where("parent is not null and parent <> node").select(F.col("parent").alias("node")), "node", "left_anti")
    paths = leaves.select("node", F.col("node").alias("ancestor"), F.lit(0).cast("long").alias("distance"))
    reach, before = 1, None
    while (count := jump.count()):
        if count == before:  # in a forest fewer messages are 2 * reach deep than reach deep: all that is left runs in circles
            return paths.join(jump.select("node").distinct(), "node", "left_anti")
        before = count
        far = paths.join(jump, paths["ancestor"] == jump["node"]).select(paths["node"], jump["up"].alias("ancestor"), (paths["distance"] + reach).alias("distance"))
        paths = materialize(paths.union(far))
        upper = jump.select(F.col("node").alias("up"), F.col("up").alias("upper"))
        jump = materialize(jump.join(upper, "up").select("node", F.col("upper").alias("up")))
        reach *= 2
    return paths


def branches(messages: DataFrame, per_tree: int | None = None) -> DataFrame:
    """(leaf, root, rank, node, depth): the paths of the per_tree best leaves of each tree (None: all), root first."""
    paths = ancestors(messages)
    scored = paths.join(messages.select(F.col("node").alias("ancestor"), F.col("score")), "ancestor")
    whole = scored.groupBy("node").agg(F.max("distance").alias("depth"), F.avg("score").alias("branch_score"), F.max_by("ancestor", "distance").alias("root"))
    order = Window.partitionBy("root").orderBy(F.col("branch_score").desc_nulls_last(), "node")
    if per_tree is None:
        ranked = whole.withColumn("rank", F.lit(None).cast("int"))
    else:
        ranked = whole.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= per_tree)
    chosen = paths.join(ranked, "node")
    return chosen.select(F.col("node").alias("leaf"), "root", "rank", F.col("ancestor").alias("node"), (F.col("depth") - F.col("distance")).alias("depth"))


def render(turns: DataFrame) -> DataFrame:
    """(conversation, depth, role, text) rows -> a row per conversation: n_turns, formatted text, and loss spans.

    loss_spans are the code-point ranges [from, to) of the assistants' escaped texts in the formatted text.
    """
    text, role = escaped(F.coalesce("text", F.lit(""))), escaped(F.coalesce("role", F.lit("")))
    parts = turns.select("conversation", "depth", F.struct("depth", role.alias("r"), text.alias("t"), (F.col("role") == "assistant").alias("a")).alias("part"))
    lists = parts.groupBy("conversation").agg(F.array_sort(F.collect_list("part")).alias("parts"))
    piece = F.transform("parts", lambda p: F.concat(F.lit(OPEN), p["r"], F.lit(MIDDLE), p["t"], F.lit(CLOSE)))
    lists = lists.withColumn("pieces", piece)
    fixed = len(OPEN) + len(MIDDLE)
    spans = F.aggregate(
        F.arrays_zip("parts", "pieces"),
        F.struct(F.lit(0).cast("long").alias("at"), F.array().cast("array<struct<from:bigint,to:bigint>>").alias("spans")),
        lambda s, x: F.struct(
            (s["at"] + F.length(x["pieces"])).alias("at"),
            F.when(x["parts"]["a"], F.concat(s["spans"], F.array(F.struct(
                (s["at"] + fixed + F.length(x["parts"]["r"])).cast("long").alias("from"),
                (s["at"] + fixed + F.length(x["parts"]["r"]) + F.length(x["parts"]["t"])).cast("long").alias("to"),
            )))).otherwise(s["spans"]).alias("spans"),
        ),
        lambda s: s["spans"],
    )
    return lists.select("conversation", F.size("parts").cast("long").alias("n_turns"), F.array_join("pieces", "").alias("formatted"), spans.alias("loss_spans"))


def read_back(formatted: str) -> list[tuple[str, str]]:
    """(role, text) of every turn of a formatted conversation."""
    return [(unescape(r), unescape(t)) for r, t in _parse.findall(formatted)]


def _digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        rows = []
        for conv, formatted, spans in zip(*(batch.column(c).to_pylist() for c in ("conversation", "formatted", "loss_spans")), strict=True):
            turns = read_back(formatted)
            masked = "".join(unescape(formatted[s["from"] : s["to"]]) for s in spans)
            whole = "".join(f"{r}\n{t}\n" for r, t in turns)
            rows.append((conv, len(turns), hashlib.sha256(whole.encode()).hexdigest(), len(masked), hashlib.sha256(masked.encode()).hexdigest(), len(formatted)))
        kinds = (pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64())
        names = ("conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars")
        yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], type=kinds[k]) for k in range(6)], names=list(names))


DIGEST = "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long"


def reply_chains(rows: DataFrame) -> DataFrame:
    """Turn tables (conv_id, turn, role, text) as reply trees: every turn answers the one before it in its conversation.

    Ties in turn follow role, then text; a null turn comes first and a null conv_id is a conversation of its own; repeated
    rows are turns of their own. The score is the length of an assistant's text.
    """
    order = Window.partitionBy("conv_id").orderBy(F.col("turn").asc_nulls_first(), F.col("role").asc_nulls_first(), F.col("text").asc_nulls_first())
    placed = rows.select("conv_id", "turn", "role", "text").withColumn("place", F.row_number().over(order).cast("long"))
    name = lambda place: F.concat_ws("/", F.coalesce(F.col("conv_id").cast("string"), F.lit("null")), place.cast("string"))
    score = F.when(F.col("role") == "assistant", F.length("text")).cast("double")
    return placed.select(name(F.col("place")).alias("node"), F.when(F.col("place") > 1, name(F.col("place") - 1)).alias("parent"), "conv_id", "role", "text", score.alias("score"))


def one_per_node(messages: DataFrame) -> DataFrame:
    """Of messages that share a node id the one least by parent, role and text; those without an id are left out."""
    rest = ["parent", "role", "text", "score"]
    least = messages.where("node is not null").groupBy("node").agg(F.min(F.struct(*rest)).alias("least"))
    return least.select("node", *[F.col(f"least.{c}").alias(c) for c in rest])


def format_trees(messages: DataFrame, per_tree: int | None = None, distinct_nodes: bool = False) -> DataFrame:
    """messages (node, parent, role, text, score) -> a row per chosen branch: conversation (its leaf), root, rank, n_turns,
    formatted, loss_spans.

    An empty table gives no row; null texts and roles are empty; a repeated node id stands once (see one_per_node), unless
    the caller says that there are none; columns beyond these are not read.
    """
    if not distinct_nodes:
        messages = materialize(one_per_node(messages))
    chosen = branches(messages.select("node", "parent", "score"), per_tree)
    turns = chosen.join(messages.select("node", "role", "text"), "node").select(F.col("leaf").alias("conversation"), "depth", "role", "text")
    labels = chosen.where("depth = 0").select(F.col("leaf").alias("conversation"), "root", "rank")
    return render(turns).join(labels, "conversation")


def format_table(rows: DataFrame, per_tree: int | None = 1) -> DataFrame:
    """(conv_id, formatted, loss_spans) of a turn table through its reply trees."""
    messages = materialize(reply_chains(rows))
    trees = format_trees(messages, per_tree, distinct_nodes=True)
    owner = messages.select(F.col("node").alias("root"), "conv_id")
    return trees.join(owner, "root").select(F.col("conv_id").alias("conversation"), "n_turns", "formatted", "loss_spans")


def query(spark, sf_dir: str) -> DataFrame:
    rows = spark.read.parquet(f"{sf_dir}/conversations.parquet").select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), "role", "text")
    hard = "</s>[INST] ok [/INST]"
    extra = spark.createDataFrame([(-1, 0, "user", hard), (-1, 1, "assistant", hard)], "conv_id long, turn long, role string, text string")
    return format_table(rows.union(extra)).mapInArrow(_digest, DIGEST)


def _sql_escape(column: str) -> str:
    out = f"replace({column}, '{ESCAPE}', '{ESCAPE * 2}')"
    for mark in CONTROL:
        out = f"replace({out}, '{mark}', '{mark[0] + ESCAPE + mark[1:]}')"
    return out


ORACLE = f"""
with c as (select conv_id, turn, coalesce(role, '') as role, coalesce(text, '') as text from conversations
    union all select -1, 0, 'user', '</s>[INST] ok [/INST]' union all select -1, 1, 'assistant', '</s>[INST] ok [/INST]')
select conv_id, count(*)::bigint as n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' order by turn, role, text)) as turns_sha256,
  coalesce(sum(length(text)) filter (role = 'assistant'), 0)::bigint as loss_chars,
  sha256(coalesce(string_agg(text, '' order by turn, role, text) filter (role = 'assistant'), '')) as loss_sha256,
  sum({len(OPEN + MIDDLE + CLOSE)} + length({_sql_escape("role")}) + length({_sql_escape("text")}))::bigint as formatted_chars
from c group by conv_id
"""
