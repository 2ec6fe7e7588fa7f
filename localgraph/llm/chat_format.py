"""Chat formatting with per-segment loss flags, in DataFrame functions only.

A template is data: the open and close strings around a turn, which roles carry loss, and the allowed
transitions of a finite-state machine over roles. Texts are escaped so that none can contain a mark:
the escape sign becomes sign+`b`, every character that begins or ends a mark becomes sign+letter.
`parse` reads a formatted conversation back by splitting at the marks.

A conversation is the unit of output, so its turns (and only its own) meet in one row; rows are
ordered by turn, then role, then text. Defined results: null text or role -> empty string; a null
conv_id or turn is a key like any other (null turns first); repeated rows are separate turns; a
conversation whose roles break the machine is still formatted and has `valid` false; an empty table
gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import table


@dataclass(frozen=True)
class Template:
    """Marks, loss roles and role machine of a chat format."""

    open_left: str = "<s>[INST "
    open_right: str = "]"
    close: str = "</s>"
    escape: str = "\\"
    escaped: tuple[tuple[str, str], ...] = (("<", "l"), ("[", "o"), ("]", "c"))
    loss_roles: tuple[str, ...] = ("assistant",)
    moves: tuple[tuple[str, str], ...] = field(
        default=(("", "system"), ("", "user"), ("system", "user"), ("user", "assistant"), ("assistant", "user"))
    )
    final: tuple[str, ...] = ("assistant",)


def escape(c: Column, t: Template) -> Column:
    c = F.replace(c, F.lit(t.escape), F.lit(t.escape + "b"))
    for sign, letter in t.escaped:
        c = F.replace(c, F.lit(sign), F.lit(t.escape + letter))
    return c


def unescape(c: Column, t: Template) -> Column:
    for sign, letter in t.escaped:
        c = F.replace(c, F.lit(t.escape + letter), F.lit(sign))
    return F.replace(c, F.lit(t.escape + "b"), F.lit(t.escape))


def valid_order(roles: Column, t: Template) -> Column:
    """Run the role machine over an array of roles."""
    moves = F.array(*[F.lit(f"{a}\n{b}") for a, b in t.moves])
    end = F.aggregate(
        roles,
        F.lit(""),
        lambda state, role: F.when(F.array_contains(moves, F.concat(state, F.lit("\n"), role)), role).otherwise(F.lit("\0")),
    )
    return end.isin(*t.final)


def format_chats(rows: DataFrame, t: Template | None = None) -> DataFrame:
    """(conv_id, turn, role, text) -> conv_id, valid, formatted, segments(text, loss)."""
    t = t or Template()
    turns = rows.select("conv_id", F.struct("turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text")).alias("m"))
    convs = turns.groupBy("conv_id").agg(F.sort_array(F.collect_list("m")).alias("ms"))

    def segments(m: Column) -> Column:
        head = F.concat(F.lit(t.open_left), escape(m["role"], t), F.lit(t.open_right))
        loss = m["role"].isin(*t.loss_roles)
        return F.array(
            F.struct(head.alias("text"), F.lit(False).alias("loss")),
            F.struct(escape(m["text"], t).alias("text"), loss.alias("loss")),
            F.struct(F.lit(t.close).alias("text"), F.lit(False).alias("loss")),
        )

    out = convs.select(
        "conv_id",
        valid_order(F.transform("ms", lambda m: m["role"]), t).alias("valid"),
        F.flatten(F.transform("ms", segments)).alias("segments"),
    )
    return out.withColumn("formatted", F.array_join(F.transform("segments", lambda s: s["text"]), ""))


def parse(formatted: Column, t: Template) -> Column:
    """Formatted text -> array of (role, text), unescaped."""
    parts = F.split(formatted, F.lit("\\Q" + t.close + "\\E"), -1)
    heads = F.slice(parts, 1, F.greatest(F.size(parts) - 1, F.lit(0)))

    def turn(p: Column) -> Column:
        body = F.substr(p, F.lit(len(t.open_left) + 1))
        cut = F.instr(body, t.open_right)
        return F.struct(
            unescape(F.substr(body, F.lit(1), cut - 1), t).alias("role"),
            unescape(F.substr(body, cut + len(t.open_right)), t).alias("text"),
        )

    return F.transform(heads, turn)


def op5_chat_formatting(spark, sf_dir: str) -> DataFrame:
    """Digests of all formatted conversations, read back from the formatted text and the loss mask."""
    t = Template()
    extra = spark.range(2).select(
        F.lit(-7).cast("long").alias("conv_id"), F.col("id").alias("turn"),
        F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"), F.lit("</s>[INST] ok [/INST]").alias("text"),
    )
    rows = table(spark, sf_dir, "conversations").select("conv_id", F.col("turn").cast("long").alias("turn"), "role", "text").unionByName(extra)
    done = format_chats(rows, t)
    back = done.select("conv_id", "valid", "formatted", "segments", parse(F.col("formatted"), t).alias("back"))
    loss = F.transform(F.filter("segments", lambda s: s["loss"]), lambda s: unescape(s["text"], t))
    return back.select(
        "conv_id",
        F.size("back").cast("long").alias("n_turns"),
        F.sha2(F.array_join(F.transform("back", lambda m: F.concat(m["role"], F.lit("\n"), m["text"], F.lit("\n"))), ""), 256).alias("turns_sha256"),
        F.length(F.array_join(loss, "")).cast("long").alias("loss_chars"),
        F.sha2(F.array_join(loss, ""), 256).alias("loss_sha256"),
        F.length("formatted").cast("long").alias("formatted_chars"),
        "valid",
    )


OP5_SQL = r"""
WITH r AS (
  SELECT conv_id, CAST(turn AS BIGINT) AS turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '</s>[INST] ok [/INST]' UNION ALL SELECT -7, 1, 'assistant', '</s>[INST] ok [/INST]'),
p AS (
  SELECT *, lag(role, 1, '') OVER (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role, text) AS prev,
    row_number() OVER (PARTITION BY conv_id ORDER BY turn DESC NULLS LAST, role DESC, text DESC) AS from_end,
    length(role || text) + length(regexp_replace(role || text, '[^\\<\[\]]', '', 'g')) AS esc_chars FROM r)
SELECT conv_id, count(*) AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn NULLS FIRST, role, text)) AS turns_sha256,
  CAST(coalesce(sum(length(text)) FILTER (WHERE role = 'assistant'), 0) AS BIGINT) AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn NULLS FIRST, text) FILTER (WHERE role = 'assistant'), '')) AS loss_sha256,
  CAST(sum(esc_chars + 14) AS BIGINT) AS formatted_chars,
  bool_and((prev, role) IN (('', 'system'), ('', 'user'), ('system', 'user'), ('user', 'assistant'), ('assistant', 'user')))
    AND bool_and(from_end > 1 OR role = 'assistant') AS valid
FROM p GROUP BY conv_id
"""
