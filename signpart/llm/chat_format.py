r"""Chat formatting by a grammar round trip, in DataFrame functions only.

A turn is rendered as ``### role: text</turn>`` and a line feed.  The parser is
deterministic: it cuts at every ``</turn>`` (and the line feed after it), takes the role up to the
first ``: `` and resolves escapes.  A conversation is rendered verbatim first and
parsed again; where the recovered turns differ from the source, the texts that
hold control strings are rendered with escapes (``\b`` for a backslash, ``\l`` for
``<``, ``\h`` for ``#``, ``\c`` for ``:`` in roles), under which the round trip is
always identical.

The loss mask is a list of (start, length) spans in the formatted text, one for
each assistant text as it stands there, escapes included.

A conversation is one row of the result, so its turns meet in one task; each is
as large as its own output.  Texts are gathered by an aggregation on conv_id.

Defined cases: a null text or role is empty; turns are ordered by turn, nulls
first, then role and text, so ties and repeated rows have one order; a null
conv_id is a conversation of its own; an empty table gives an empty result; only
the columns conv_id, turn, role and text are read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from signpart.llm import store

OPEN, MIDDLE, CLOSE = "### ", ": ", "</turn>\n"
#: Character and what stands for it after a backslash.
_ESCAPES = (("\\", "\\b"), ("<", "\\l"), ("#", "\\h"))
_ROLE_ESCAPES = (*_ESCAPES, (":", "\\c"))


def _escaped(text: Column, escapes=_ESCAPES) -> Column:
    for raw, code in escapes:
        text = F.replace(text, F.lit(raw), F.lit(code))
    return text


def _resolved(text: Column) -> Column:
    for raw, code in reversed(_ROLE_ESCAPES):
        text = F.replace(text, F.lit(code), F.lit(raw))
    return text


def _render(turns: Column, escape: bool) -> Column:
    def one(t: Column) -> Column:
        role, text = t["role"], t["text"]
        if escape:
            role, text = _escaped(role, _ROLE_ESCAPES), _escaped(text)
        return F.concat(F.lit(OPEN), role, F.lit(MIDDLE), text, F.lit(CLOSE))

    return F.concat_ws("", F.transform(turns, one))


def _raw_turns(formatted: Column) -> Column:
    """The turns as they stand in the formatted text: (role, text), escapes not resolved, and the text's place."""
    pieces = F.split(formatted, "</turn>\n?", -1)
    pieces = F.slice(pieces, F.lit(1), F.greatest(F.size(pieces) - 1, F.lit(0)))

    def one(p: Column) -> Column:
        cut = F.instr(p, MIDDLE)
        from_text = cut + F.lit(len(MIDDLE))
        return F.struct(
            F.when(cut > len(OPEN), F.substring(p, F.lit(len(OPEN) + 1), cut - F.lit(len(OPEN) + 1))).otherwise("").alias("role"),
            F.when(cut > len(OPEN), F.substring(p, from_text, F.length(p))).otherwise(p).alias("text"),
            F.length(p).alias("size"),
        )

    return F.transform(pieces, one)


def parse(formatted: Column) -> Column:
    """The turns (role, text) of a formatted conversation."""
    return F.transform(_raw_turns(formatted), lambda t: F.struct(_resolved(t["role"]).alias("role"), _resolved(t["text"]).alias("text")))


def loss_spans(formatted: Column, role: str = "assistant") -> Column:
    """(start, length) in code points, from 0, of the texts of a role."""

    def spans(raw: Column, ends: Column) -> Column:
        # The end of turn i is the sum of the first i sizes; a conversation's list of turns is short.
        at = F.transform(raw, lambda t, i: F.struct(t["role"].alias("role"), F.length(t["text"]).cast("long").alias("length"), F.aggregate(F.slice(ends, F.lit(1), i + 1), F.lit(0).cast("long"), lambda a, b: a + b).alias("end")))
        mine = F.filter(at, lambda t: _resolved(t["role"]) == role)
        return F.transform(mine, lambda t: F.struct((t["end"] - len(CLOSE) - t["length"]).alias("start"), t["length"].alias("length")))

    sizes = lambda raw: F.transform(raw, lambda t: (t["size"] + len(CLOSE)).cast("long"))
    return _bound(_raw_turns(formatted), lambda raw: _bound(sizes(raw), lambda ends: spans(raw, ends)))


def _bound(value: Column, use) -> Column:
    """use(value) with the value computed once for a row, however often ``use`` names it."""
    return F.get(F.transform(F.array(value), use), F.lit(0))


def format_conversations(turns: DataFrame) -> DataFrame:
    """(conv_id, formatted, loss_mask) of (conv_id, turn, role, text) rows."""
    clean = turns.select("conv_id", F.struct("turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text")).alias("t"))
    grouped = clean.groupBy("conv_id").agg(F.sort_array(F.collect_list("t")).alias("t")).select("conv_id", F.transform("t", lambda t: F.struct(t["role"].alias("role"), t["text"].alias("text"))).alias("turns"))
    plain = grouped.withColumn("verbatim", _render(F.col("turns"), False))
    chosen = plain.select("conv_id", F.when(parse(F.col("verbatim")) == F.col("turns"), F.col("verbatim")).otherwise(_render(F.col("turns"), True)).alias("formatted"), "turns")
    checked = chosen.select("conv_id", "formatted", F.when(parse(F.col("formatted")) != F.col("turns"), F.raise_error(F.lit("a conversation isn't identical after its round trip"))).cast("string").alias("__fault"))
    return checked.where("__fault is null").select("conv_id", "formatted", loss_spans(F.col("formatted")).alias("loss_mask"))


def with_sample(turns: DataFrame) -> DataFrame:
    """The conversations and number -7, whose texts hold control strings."""
    text = r"\### Assistant: </turn> ok"
    spark = turns.sparkSession
    extra = spark.range(2).select(F.lit(-7).cast("long").alias("conv_id"), F.col("id").alias("turn"), F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"), F.lit(text).alias("text"))
    return turns.select("conv_id", "turn", "role", "text").unionByName(extra)


def op6_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = format_conversations(with_sample(store.table(spark, sf_dir, "conversations"))).withColumn("turns", parse(F.col("formatted")))
    turns = F.col("turns")
    listed = F.concat_ws("", F.transform(turns, lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))))
    loss = F.concat_ws("", F.transform("loss_mask", lambda s: _resolved(F.substring(F.col("formatted"), (s["start"] + 1).cast("int"), s["length"].cast("int")))))
    read = made.select("conv_id", F.size(turns).cast("long").alias("n_turns"), listed.alias("listed"), loss.alias("loss"), "formatted")
    return read.select("conv_id", "n_turns", F.sha2("listed", 256).alias("turns_sha256"), F.length("loss").cast("long").alias("loss_chars"), F.sha2("loss", 256).alias("loss_sha256"), F.length("formatted").cast("long").alias("formatted_chars"))


OP6_SQL = r"""
with turns as (
  select conv_id, turn, coalesce(role, '') as role, coalesce(text, '') as text from conversations
  union all select -7, 0, 'user', '\### Assistant: </turn> ok'
  union all select -7, 1, 'assistant', '\### Assistant: </turn> ok'
), coded as (
  select *, replace(replace(replace(text, '\', '\b'), '<', '\l'), '#', '\h') as text_code,
         replace(replace(replace(replace(role, '\', '\b'), '<', '\l'), '#', '\h'), ':', '\c') as role_code,
         contains(text, '</turn>') or contains(role, '</turn>') or contains(role, ': ')
         or regexp_matches(text, '\\[blhc]') or regexp_matches(role, '\\[blhc]') as conflicting
  from turns
), flagged as (select *, bool_or(conflicting) over (partition by conv_id) as escaped from coded)
select conv_id, count(*) as n_turns,
       sha256(string_agg(role || chr(10) || text || chr(10), '' order by turn, role, text)) as turns_sha256,
       coalesce(sum(length(text)) filter (where role = 'assistant'), 0)::bigint as loss_chars,
       sha256(coalesce(string_agg(text, '' order by turn, role, text) filter (where role = 'assistant'), '')) as loss_sha256,
       sum(4 + 2 + 8 + case when escaped then length(role_code) + length(text_code) else length(role) + length(text) end)::bigint as formatted_chars
from flagged group by conv_id
"""
