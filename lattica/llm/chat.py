"""Chat formatting from reply trees, with DataFrame functions only.

``reply_paths`` lists every root-to-leaf path by doubling self-joins (a path of
length L needs about log2 L rounds), ``rank_paths`` orders the branches of a tree
by score, ``format_paths`` writes each path as one conversation with a loss mask
over the assistant texts, ``read_back`` parses the written form again.

Defined results: null texts and roles are empty strings; a message whose parent
is null or absent is a root; equal positions are ordered by role, then text;
messages on a parent cycle have no root and so lie on no path; an empty table
gives an empty table; further columns of the input are ignored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import materialize, release, table

OPEN, CLOSE = "<|im_start|>", "<|im_end|>\n"
GUARD = "⁣"
#: Strings that chat templates treat as control marks.
CONTROL = r"</?s>|\[/?INST\]|<</?SYS>>|<\|[A-Za-z_]+\|>"


def escape(text):
    """Double each guard character, then put one inside every control string."""
    text = F.replace(text, F.lit(GUARD), F.lit(GUARD * 2))
    return F.regexp_replace(text, rf"([<\[])(?=(?<=<)/?s>|(?<=\[)/?INST\]|(?<=<)</?SYS>>|(?<=<)\|[A-Za-z_]+\|>)", f"$1{GUARD}")


def unescape(text):
    text = F.regexp_replace(text, rf"([<\[]){GUARD}(?!{GUARD})", "$1")
    return F.replace(text, F.lit(GUARD * 2), F.lit(GUARD))


def as_tree(rows: DataFrame) -> DataFrame:
    """Conversations stored by turn as messages (tree, msg, parent, role, text, score): each turn answers the one before."""
    order = W.partitionBy("conv_id").orderBy(F.col("turn").asc_nulls_first(), "role", "text")
    return rows.select("conv_id", "turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text")).select(F.col("conv_id").alias("tree"), F.row_number().over(order).cast("long").alias("msg"), "role", "text").withColumns({"parent": F.when(F.col("msg") > 1, F.col("msg") - 1), "score": F.lit(0.0)})


def reply_paths(messages: DataFrame) -> DataFrame:
    """Rows (tree, leaf, msg, up): every ancestor msg of every leaf, `up` steps above it."""
    keys = messages.select("tree", "msg", "parent")
    known = keys.select("tree", F.col("msg").alias("parent"))
    jump = materialize(keys.where("parent is not null").join(known, ["tree", "parent"], "left_semi").select("tree", "msg", F.col("parent").alias("above")), "chat-jump")
    leaves = keys.join(keys.select("tree", F.col("parent").alias("msg")), ["tree", "msg"], "left_anti")
    reach = materialize(leaves.select("tree", F.col("msg").alias("leaf"), "msg", F.lit(0).cast("long").alias("up")), "chat-reach")
    step, most = 1, max(1, keys.count())
    while step <= most and not jump.isEmpty():
        grown = reach.unionByName(reach.join(jump, ["tree", "msg"]).select("tree", "leaf", F.col("above").alias("msg"), (F.col("up") + step).alias("up")))
        further = jump.join(jump.select("tree", F.col("msg").alias("above"), F.col("above").alias("top")), ["tree", "above"]).select("tree", "msg", F.col("top").alias("above"))
        old = (reach, jump)
        reach, jump = materialize(grown, "chat-reach"), materialize(further, "chat-jump")
        release(*old)
        step *= 2
    if not jump.isEmpty():  # cycles: their members have ancestors without end
        reach = reach.join(jump.select("tree", "msg").distinct(), ["tree", "msg"], "left_anti")
    return reach


def rank_paths(paths: DataFrame, messages: DataFrame) -> DataFrame:
    """One row per path: its turns from the root, its mean score and its rank among the tree's branches."""
    full = paths.join(messages.select("tree", "msg", "role", "text", "score"), ["tree", "msg"])
    whole = full.groupBy("tree", "leaf").agg(F.array_sort(F.collect_list(F.struct((-F.col("up")).alias("pos"), "role", "text"))).alias("turns"), F.avg("score").alias("score"))
    return whole.withColumn("rank", F.row_number().over(W.partitionBy("tree").orderBy(F.desc_nulls_last("score"), "leaf")))


def format_paths(ranked: DataFrame, best: int | None = None) -> DataFrame:
    """Adds `formatted` and `loss_spans` (start and length in code points of each assistant text, still escaped)."""
    kept = ranked if best is None else ranked.where(F.col("rank") <= best)
    parts = F.transform("turns", lambda t: F.struct(F.concat(F.lit(OPEN), F.url_encode(t["role"]), F.lit("\n")).alias("head"), escape(t["text"]).alias("body"), (t["role"] == "assistant").alias("own")))
    start = F.struct(F.lit(0).alias("at"), F.array().cast("array<struct<start:int,len:int>>").alias("spans"))

    def walk(acc, p):
        begin = acc["at"] + F.length(p["head"])
        size = F.length(p["body"])
        own = F.array(F.struct((begin + 1).alias("start"), size.alias("len")))
        return F.struct((begin + size + F.lit(len(CLOSE))).alias("at"), F.when(p["own"], F.concat(acc["spans"], own)).otherwise(acc["spans"]).alias("spans"))

    kept = kept.withColumn("parts", parts)
    return kept.withColumn("formatted", F.array_join(F.transform("parts", lambda p: F.concat(p["head"], p["body"], F.lit(CLOSE))), "")).withColumn("loss_spans", F.aggregate("parts", start, walk)["spans"]).drop("parts")


def read_back(formatted: DataFrame) -> DataFrame:
    """Parses the written form: `read_turns` (role, text) and `loss_text` (all text under the mask, unescaped)."""
    pieces = F.filter(F.split("formatted", r"<\|im_end\|>\n"), lambda x: F.length(x) > 0)
    bare = F.transform(pieces, lambda x: F.substr(x, F.lit(len(OPEN) + 1)))
    turns = F.transform(bare, lambda x: F.struct(F.url_decode(F.substring_index(x, "\n", 1)).alias("role"), unescape(F.substr(x, F.instr(x, F.lit("\n")) + 1)).alias("text")))
    loss = F.transform("loss_spans", lambda s: unescape(F.substr("formatted", s["start"], s["len"])))
    return formatted.withColumn("read_turns", turns).withColumn("loss_text", F.array_join(loss, ""))


def op7_chat_format(spark, sf_dir) -> DataFrame:
    rows = table(spark, sf_dir, "conversations", "conv_id", "turn", "role", "text")
    sample = "</s>[INST] ok [/INST]"
    extra = spark.sql(f"select cast(-7 as bigint) conv_id, cast(turn as bigint) turn, role, '{sample}' text from values (0, 'user'), (1, 'assistant') as t(turn, role)")
    messages = materialize(as_tree(rows.unionByName(extra)), "chat-messages")
    out = read_back(format_paths(rank_paths(reply_paths(messages), messages), best=1))
    said = F.array_join(F.transform("read_turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    return out.select(F.col("tree").alias("conv_id"), F.size("read_turns").cast("long").alias("n_turns"), F.sha2(said, 256).alias("turns_sha256"), F.length("loss_text").cast("long").alias("loss_chars"), F.sha2("loss_text", 256).alias("loss_sha256"), F.length("formatted").cast("long").alias("formatted_chars"))


OP7_SQL = """
with rows as (
  select conv_id, turn, coalesce(role, '') as role, coalesce(text, '') as text from conversations
  union all select -7, 0, 'user', '</s>[INST] ok [/INST]'
  union all select -7, 1, 'assistant', '</s>[INST] ok [/INST]'),
marked as (
  select *, row_number() over (partition by conv_id order by turn nulls first, role, text) as pos,
    length(regexp_replace(regexp_replace(text, '⁣', '⁣⁣', 'g'), '(</?s>|\\[/?INST\\]|<</?SYS>>|<\\|[A-Za-z_]+\\|>)', '#\\1', 'g')) as size
  from rows)
select conv_id, count(*) as n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' order by pos)) as turns_sha256,
  coalesce(sum(length(text)) filter (where role = 'assistant'), 0)::bigint as loss_chars,
  sha256(coalesce(string_agg(text, '' order by pos) filter (where role = 'assistant'), '')) as loss_sha256,
  sum(12 + length(url_encode(role)) + 1 + size + 11)::bigint as formatted_chars
from marked group by conv_id
"""
