"""Chat formatting with a grammar round trip (native expressions only).

A conversation is rendered as turns ``<s>[ROLE] text </s>`` where ROLE is the escaped role.
The grammar is deterministic: ``</s>`` closes a turn, ``<s>[`` opens one, the first ``] ``
ends the role, and a backslash makes the next character plain. Control strings inside roles and texts
are always escaped, those of related templates too. Each rendered turn is parsed again; where the recovered turn still differs
from the source, every character that a control string could begin or end with is escaped. The parsed turns of the whole
conversation must then equal the source, which ``round_trip`` reports. The loss mask covers the texts of the trained role.

Defined cases: a null role or text is empty; a null conversation id is a conversation of its
own; turns are ordered by turn number (null first), then role, then text, so ties and repeated
rows keep a fixed order and all stay; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from veilmatch.llm.common import table

OPEN, CLOSE, BAR = "<s>[", " </s>", "] "
# Strings that mark turns in this template or in its relatives; escaped inside texts.
CONTROL = ("<s>", "</s>", "[INST]", "[/INST]", "] ")


def escape(text: Column) -> Column:
    out = F.replace(text, F.lit("\\"), F.lit("\\\\"))
    for mark in CONTROL:
        out = F.replace(out, F.lit(mark), F.lit(f"{mark[0]}\\{mark[1:]}"))
    return out


def escape_all(text: Column) -> Column:
    """A backslash before every character that control strings are made of, blanks and backslashes included."""
    return F.regexp_replace(text, r"([\\<>/\[\] ])", r"\\$1")


def unescape(text: Column) -> Column:
    return F.when(F.contains(text, F.lit("\\")), F.regexp_replace(text, r"(?s)\\(.)", "$1")).otherwise(text)


def render_turn(role: Column, text: Column) -> Column:
    return F.concat(F.lit(OPEN), role, F.lit(BAR), text, F.lit(CLOSE))


def parse(formatted: Column) -> Column:
    """Formatted text to array<struct<role, text>>, by the grammar alone."""
    pieces = F.split(formatted, r"\Q </s>\E")
    pieces = F.slice(pieces, F.lit(1), F.size(pieces) - 1)

    def turn(piece: Column) -> Column:
        body = F.when(F.startswith(piece, F.lit(OPEN)), F.substring(piece, F.lit(len(OPEN) + 1), F.length(piece)))
        return F.struct(
            unescape(F.substring_index(body, BAR, 1)).alias("role"),
            unescape(F.substring(body, F.instr(body, BAR) + len(BAR), F.length(body))).alias("text"),
        )

    return F.transform(pieces, turn)


def format_conversations(
    turns: DataFrame, conv: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text", trained: str = "assistant"
) -> DataFrame:
    """One row per conversation: conv_id, formatted, turns (parsed back), mask (spans of code points), round_trip."""
    plain = turns.select(
        F.col(conv).alias("conv_id"),
        F.col(turn).alias("turn"),
        F.coalesce(F.col(role).cast("string"), F.lit("")).alias("role"),
        F.coalesce(F.col(text).cast("string"), F.lit("")).alias("text"),
    )
    source = F.array(F.struct("role", "text"))
    first = render_turn(escape(F.col("role")), escape(F.col("text")))
    rendered = plain.withColumn("out", F.when(parse(first) == source, first).otherwise(render_turn(escape_all(F.col("role")), escape_all(F.col("text")))))
    # Where each turn starts in its conversation; the same exchange serves the window and the grouping.
    order = Window.partitionBy("conv_id").orderBy("turn", "role", "text").rowsBetween(Window.unboundedPreceding, -1)
    placed = rendered.withColumn("at", F.coalesce(F.sum(F.length("out")).over(order), F.lit(0)))
    # The whole conversation is one output value, so its turns must meet; each turn travels once.
    whole = placed.groupBy("conv_id").agg(F.array_sort(F.collect_list(F.struct("at", "turn", "role", "text", "out"))).alias("t"))
    closed = F.filter("t", lambda x: x["role"] == trained)
    mask = F.transform(
        closed,
        lambda x: F.struct(
            (x["at"] + F.instr(x["out"], BAR) + len(BAR) - 1).alias("start"),
            (x["at"] + F.length(x["out"]) - len(CLOSE)).alias("end"),
        ),
    )
    formatted = whole.select(
        "conv_id",
        F.array_join("t.out", "").alias("formatted"),
        F.transform("t", lambda x: F.struct(x["role"].alias("role"), x["text"].alias("text"))).alias("source"),
        mask.alias("mask"),
    )
    parsed = formatted.withColumn("turns", parse(F.col("formatted")))
    return parsed.select("conv_id", "formatted", "turns", "mask", (F.col("turns") == F.col("source")).alias("round_trip"))


def masked_text(formatted: Column, mask: Column) -> Column:
    """All text under the mask, unescaped, nothing between."""
    return F.array_join(F.transform(mask, lambda m: unescape(F.substring(formatted, (m["start"] + 1).cast("int"), (m["end"] - m["start"]).cast("int")))), "")


def op10_chat_formatting(spark: SparkSession, sf_dir: str) -> DataFrame:
    given = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    probe = spark.range(2).select(
        F.lit(-1).cast("long").alias("conv_id"),
        F.col("id").alias("turn"),
        F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"),
        F.lit("</s>[INST] ok [/INST]").alias("text"),
    )
    out = format_conversations(given.unionByName(probe))
    loss = masked_text(F.col("formatted"), F.col("mask"))
    return out.select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), ""), 256).alias("turns_sha256"),
        F.length(loss).cast("long").alias("loss_chars"),
        F.sha2(loss, 256).alias("loss_sha256"),
        F.length("formatted").cast("long").alias("formatted_chars"),
        "round_trip",
    )


_ESC = r"replace({0}, '\', '\\')"
for _mark in CONTROL:
    _ESC = f"replace({_ESC}, '{_mark}', '{_mark[0] + chr(92) + _mark[1:]}')"
OP10_SQL = f"""
with t as (
  select conv_id, turn, coalesce(role, '') as role, coalesce(text, '') as text from conversations
  union all select -1, 0, 'user', '</s>[INST] ok [/INST]'
  union all select -1, 1, 'assistant', '</s>[INST] ok [/INST]'
), r as (
  select *, length({_ESC.format('text')}) + length({_ESC.format('role')}) + 11 as n
  from t
)
select conv_id, count(*)::bigint as n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' order by turn, role, text)) as turns_sha256,
  coalesce(sum(length(text)) filter (where role = 'assistant'), 0)::bigint as loss_chars,
  sha256(coalesce(string_agg(text, '' order by turn, role, text) filter (where role = 'assistant'), '')) as loss_sha256,
  sum(n)::bigint as formatted_chars, true as round_trip
from r group by conv_id
"""
