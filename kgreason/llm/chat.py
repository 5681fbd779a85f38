"""Chat formatting with Spark expressions only (no Python on the executors).

``format_conversations`` sorts the turns of a conversation, merges adjacent turns of one role into
one block, escapes the control strings in roles and texts reversibly, and concatenates.  It returns
``conv_id, formatted, loss_spans``; ``read_back`` parses such a string into the original turns.

Defined results: null text and null role are the empty string; null turns sort first; ties of
``turn`` are ordered by role, then text, both as they are and not as they are escaped; repeated rows are repeated
turns; a row with a null ``conv_id`` is a conversation of its own, as nothing says which others it belongs to; an empty
table gives an empty table; further columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table

TURN, TEXT, PART, END = "<|turn|>", "<|text|>", "<|part|>", "<|end|>\n"

#: Where a control string of this or another common template begins; a backslash goes in behind.
_CONTROL = r"<(?=\||/?(?:s|SYS)>)|\[(?=/?INST\])"
_ESCAPED = r"([<\[])\\(?=\||/?(?:s|SYS)>|/?INST\])"


def escape(text: Column) -> Column:
    """Doubles backslashes and puts a single one behind the first sign of each control string."""
    return F.regexp_replace(F.replace(text, F.lit("\\"), F.lit("\\\\")), _CONTROL, "$0\\\\")


def unescape(text: Column) -> Column:
    """Inverse of escape: behind ``<`` or ``[`` runs of backslashes are even but for those added."""
    return F.replace(F.regexp_replace(text, _ESCAPED, "$1"), F.lit("\\\\"), F.lit("\\"))


def _blocks(df: DataFrame) -> DataFrame:
    """(conv_id, blocks) of (conv_id, turns): adjacent turns of a role share a block (role, parts).

    A block is the slice from the place of its first turn to that of the next block's, so that each turn is copied once.
    """
    starts = F.filter(F.sequence(F.lit(0), F.size("turns") - 1), lambda i: (i == 0) | (F.get("turns", i)["role"] != F.get("turns", i - 1)["role"]))
    blocks = F.transform(
        "starts",  # a column of its own: spelt out, it would be worked out again for every block
        lambda first, i: F.struct(
            F.get("turns", first)["role"].alias("role"),
            F.slice("turns", first + 1, F.coalesce(F.get("starts", i + 1), F.size("turns")) - first)["text"].alias("parts"),
        ),
    )
    return df.withColumn("starts", starts).select("conv_id", blocks.alias("blocks"))


CHUNK = 256


def _places(lengths: Column) -> Column:
    """Sums of all numbers before each one.  In chunks, as a list that grows by one is copied at each step."""
    grow = lambda numbers, start: F.aggregate(
        numbers,
        F.struct(start.alias("at"), F.expr("cast(array() as array<bigint>)").alias("before")),
        lambda a, n: F.struct((a["at"] + n).alias("at"), F.concat(a["before"], F.array(a["at"])).alias("before")),
    )["before"]
    chunk = lambda i: F.slice(lengths, i * CHUNK + 1, F.lit(CHUNK))
    chunks = F.sequence(F.lit(0), F.ceil(F.size(lengths) / CHUNK).cast("int") - 1)
    sums = F.transform(chunks, lambda i: F.aggregate(chunk(i), F.lit(0).cast("bigint"), lambda a, n: a + n))
    starts = grow(sums, F.lit(0).cast("bigint"))
    return F.flatten(F.zip_with(chunks, starts, lambda i, start: grow(chunk(i), start)))


def format_conversations(conversations: DataFrame, loss_role: str = "assistant") -> DataFrame:
    """``conv_id, turn, role, text`` to ``conv_id, formatted, loss_spans``.

    loss_spans: array of (first, length), code points of ``formatted``, first counted from 1: the escaped texts of loss_role.
    """
    rows = conversations.select(
        "conv_id",
        F.when(F.col("conv_id").isNull(), F.monotonically_increasing_id()).alias("alone"),
        F.struct(F.col("turn").alias("turn"), F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text")).alias("t"),
    )
    sorted_ = rows.groupBy("conv_id", "alone").agg(F.sort_array(F.collect_list("t")).alias("turns"))
    blocks = _blocks(sorted_)
    # Pieces in the order of output: what stands before a text, then the text.
    pieces = F.flatten(
        F.transform(
            "blocks",
            lambda b: F.transform(
                b["parts"],
                lambda p, i: F.struct(
                    F.when(i == 0, F.concat(F.lit(TURN), escape(b["role"]), F.lit(TEXT))).otherwise(F.lit(PART)).alias("before"),
                    escape(p).alias("text"),
                    F.when(i == F.size(b["parts"]) - 1, F.lit(END)).otherwise(F.lit("")).alias("after"),
                    (b["role"] == loss_role).alias("loss"),
                ),
            ),
        )
    )
    placed = blocks.select("conv_id", pieces.alias("pieces")).withColumn(
        "lengths", F.transform("pieces", lambda p: (F.length(p["before"]) + F.length(p["text"]) + F.length(p["after"])).cast("bigint"))
    )
    placed = placed.withColumn("places", _places(F.col("lengths")))
    spans = F.zip_with(
        "pieces",
        "places",
        lambda p, at: F.when(p["loss"], F.struct((at + 1 + F.length(p["before"])).cast("bigint").alias("first"), F.length(p["text"]).cast("bigint").alias("length"))),
    )
    return placed.select(
        "conv_id",
        F.array_join(F.transform("pieces", lambda p: F.concat(p["before"], p["text"], p["after"])), "").alias("formatted"),
        F.filter(spans, lambda s: s.isNotNull()).alias("loss_spans"),
    )


def read_back(formatted: Column) -> Column:
    """The turns in a formatted string: array of (role, text)."""
    blocks = F.filter(F.split(formatted, r"<\|end\|>\n"), lambda b: b != "")
    return F.flatten(
        F.transform(
            blocks,
            lambda b: F.transform(
                F.split(F.substring_index(b, TEXT, -1), r"<\|part\|>"),
                lambda p: F.struct(
                    unescape(F.substring_index(F.substring_index(b, TURN, -1), TEXT, 1)).alias("role"),
                    unescape(p).alias("text"),
                ),
            ),
        )
    )


def op3_chat_formatting(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Digest of all formatted conversations and of conversation -7, read back from the output."""
    sample = spark.sql(
        "select cast(-7 as bigint) conv_id, cast(t as bigint) turn, r role, '</s>[INST] ok [/INST]' text from values (0, 'user'), (1, 'assistant') v(t, r)"
    )
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text").unionByName(sample)
    out = format_conversations(rows).withColumn("turns", read_back(F.col("formatted")))
    loss = F.transform("loss_spans", lambda s: unescape(F.substring(F.col("formatted"), s["first"].cast("int"), s["length"].cast("int"))))
    return out.withColumn("loss", F.array_join(loss, "")).select(
        "conv_id",
        F.size("turns").cast("bigint").alias("n_turns"),
        F.sha2(F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), ""), 256).alias("turns_sha256"),
        F.length("loss").cast("bigint").alias("loss_chars"),
        F.sha2("loss", 256).alias("loss_sha256"),
        F.length("formatted").cast("bigint").alias("formatted_chars"),
    )


OP3_SQL = r"""
with c as (
  select conv_id, case when conv_id is null then row_number() over () end as alone, turn, coalesce(role, '') as role, coalesce(text, '') as text from conversations
  union all select -7, null, 0, 'user', '</s>[INST] ok [/INST]'
  union all select -7, null, 1, 'assistant', '</s>[INST] ok [/INST]'),
e as (
  select *, replace(text, '\', '\\') as t2, replace(role, '\', '\\') as r2,
         lag(role) over (partition by conv_id, alone order by turn nulls first, role, text) as before
  from c),
f as (
  select *, length(t2) + len(regexp_extract_all(t2, '<\||</?(?:s|SYS)>|\[/?INST\]')) as tl,
         length(r2) + len(regexp_extract_all(r2, '<\||</?(?:s|SYS)>|\[/?INST\]')) as rl
  from e)
select conv_id, count(*) as n_turns,
       sha256(string_agg(role || chr(10) || text || chr(10), '' order by turn nulls first, role, text)) as turns_sha256,
       cast(sum(case when role = 'assistant' then length(text) else 0 end) as bigint) as loss_chars,
       sha256(coalesce(string_agg(text, '' order by turn nulls first, role, text) filter (where role = 'assistant'), '')) as loss_sha256,
       cast(sum(tl + case when before is distinct from role then 8 + rl + 8 + 8 else 8 end) as bigint) as formatted_chars
from f group by conv_id, alone
"""
