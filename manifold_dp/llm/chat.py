"""Chat formatting: fold an event log into messages and render them (native).

Events are rows ``(conv_id, turn, seq, kind, role, text)``. Within a turn, in order of
``seq``, ``message`` and ``edit`` set the text, ``delta`` appends to it and
``regenerate`` empties it (deltas that follow make the new text); ``remove`` deletes
the turn unless a later event sets it again. The role is the last one given.

Rendered form, one block per turn::

    ### role:
    escaped text
    </turn>

``\\``, ``#`` and ``<`` inside a text or a role carry a backslash, and so does a line
break inside a role, so neither marker can occur inside a block and ``parse`` restores
every text exactly.

Defined results: null text or role counts as empty; rows with a null conversation form
a conversation of their own; equal rows of a turn table are turns of their own, ties by
turn are ordered by role, then text; null turns come first; columns beyond those named
are ignored; an empty table gives an empty result.

A conversation is rendered into one row by its nature, so one task holds one
conversation; nothing else is gathered by key.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

HEAD, TAIL = "### ", "\n</turn>\n"


def escape(c: Column) -> Column:
    return F.regexp_replace(c, r"([\\#<])", r"\\$1")


def unescape(c: Column) -> Column:
    return F.regexp_replace(c, r"(?s)\\(.)", "$1")


def _numbered(turns: DataFrame) -> DataFrame:
    w = Window.partitionBy("conv_id").orderBy("turn", "role", "text")
    rows = turns.select("conv_id", "turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    return rows.select("conv_id", F.row_number().over(w).cast("long").alias("turn"), "role", "text")


def _event(seq: int, kind: str, role: Column | None, text: Column | None) -> Column:
    none = F.lit(None).cast("string")
    return F.struct(F.lit(seq).cast("long").alias("seq"), F.lit(kind).alias("kind"), (none if role is None else role).alias("role"), (none if text is None else text).alias("text"))


def events_of_turns(turns: DataFrame) -> DataFrame:
    """A table with one row per turn as an event log of ``message`` events."""
    return _numbered(turns).select("conv_id", "turn", F.inline(F.array(_event(0, "message", F.col("role"), F.col("text")))))


def streamed_events(turns: DataFrame) -> DataFrame:
    """The same turns as a server would have logged them, events out of order: turns streamed in
    three deltas, drafts that were regenerated or edited, and turns removed and sent again."""
    role, text = F.col("role"), F.col("text")
    n = F.char_length(text)
    third, rest = F.floor(n / 3).cast("int"), F.floor(2 * n / 3).cast("int")
    deltas = [_event(9, "delta", None, F.substr(text, rest + 1)), _event(7, "delta", None, F.substr(text, F.lit(1), third)), _event(8, "delta", None, F.substr(text, third + 1, rest - third))]
    draft = F.concat(F.lit("draft of "), F.left(text, F.lit(12)))
    logs = [
        F.array(*deltas, _event(0, "message", role, F.lit(""))),
        F.array(*deltas, _event(6, "regenerate", None, None), _event(0, "message", role, draft)),
        F.array(_event(5, "edit", None, text), _event(0, "message", role, draft), _event(1, "delta", None, draft)),
        F.array(_event(4, "message", role, text), _event(3, "remove", None, None), _event(0, "message", role, draft)),
    ]
    kind = F.pmod(F.col("turn"), F.lit(len(logs)))
    log = F.when(kind == 0, logs[0]).when(kind == 1, logs[1]).when(kind == 2, logs[2]).otherwise(logs[3])
    return _numbered(turns).select("conv_id", "turn", F.inline(log))


def fold(events: DataFrame) -> DataFrame:
    """Final messages ``(conv_id, turn, role, text)`` of an event log.

    What counts is the last event that sets or empties the text and the deltas after it,
    so a turn of many deltas is joined once, not appended to again and again.
    """
    e = F.struct("seq", F.coalesce("kind", F.lit("")).alias("kind"), "role", F.coalesce("text", F.lit("")).alias("text"))
    log = events.groupBy("conv_id", "turn").agg(F.sort_array(F.collect_list(e)).alias("log"))
    last = F.array_max(F.transform("log", lambda x, i: F.when(x["kind"].isin("message", "edit", "regenerate", "remove"), i + 1).otherwise(F.lit(0))))
    log = log.select("conv_id", "turn", "log", last.alias("last"))
    base = F.when(F.try_element_at("log", F.nullif("last", F.lit(0)))["kind"].isin("message", "edit"), F.try_element_at("log", F.nullif("last", F.lit(0)))["text"]).otherwise(F.lit(""))
    deltas = F.filter(F.slice("log", F.col("last") + 1, F.size("log")), lambda x: x["kind"] == "delta")
    roles = F.filter(F.transform("log", lambda x: x["role"]), lambda r: r.isNotNull())
    done = log.where(F.element_at("log", -1)["kind"] != "remove")
    return done.select("conv_id", "turn", F.coalesce(F.try_element_at(roles, F.lit(-1)), F.lit("")).alias("role"), F.concat(base, F.array_join(F.transform(deltas, lambda x: x["text"]), "")).alias("text"))


def render(messages: DataFrame, trained_role: str = "assistant") -> DataFrame:
    """``(conv_id, formatted, mask)``; mask: [start, length) of each trained text, in code points of ``formatted``."""
    name = F.regexp_replace(escape(F.col("role")), "\n", "\\\\\n")
    part = messages.select("conv_id", "turn", F.concat(F.lit(HEAD), name, F.lit(":\n")).alias("head"), escape(F.col("text")).alias("body"), (F.col("role") == trained_role).alias("trained"))
    part = part.withColumn("h", F.char_length("head")).withColumn("b", F.char_length("body"))
    before = Window.partitionBy("conv_id").orderBy("turn", "head", "body").rowsBetween(Window.unboundedPreceding, -1)
    part = part.withColumn("at", F.coalesce(F.sum(F.col("h") + F.col("b") + len(TAIL)).over(before), F.lit(0)).cast("int"))
    parts = part.groupBy("conv_id").agg(F.array_sort(F.collect_list(F.struct("turn", "head", "body", "trained", "at", "h", "b"))).alias("p"))
    spans = F.transform(F.filter("p", lambda x: x["trained"]), lambda x: F.struct((x["at"] + x["h"]).alias("start"), x["b"].alias("length")))
    text = F.array_join(F.transform("p", lambda x: F.concat(x["head"], x["body"], F.lit(TAIL))), "")
    return parts.select("conv_id", text.alias("formatted"), spans.alias("mask"))


def parse(formatted: DataFrame) -> DataFrame:
    """Read messages and masked texts back: ``(conv_id, turns, trained, formatted)``."""
    blocks = F.slice(F.split("formatted", TAIL), 1, F.size(F.split("formatted", TAIL)) - 1)

    def block(b):
        cut = F.locate(":\n", b)
        role = F.substr(b, F.lit(len(HEAD) + 1), cut - len(HEAD) - 1)
        return F.struct(unescape(role).alias("role"), unescape(F.substr(b, cut + 2)).alias("text"))

    trained = F.transform("mask", lambda m: unescape(F.substr(F.col("formatted"), m["start"] + 1, m["length"])))
    return formatted.select("conv_id", F.transform(blocks, block).alias("turns"), trained.alias("trained"), "formatted")


def digest(parsed: DataFrame) -> DataFrame:
    loss = F.array_join("trained", "")
    said = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    return parsed.select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(said, 256).alias("turns_sha256"),
        F.char_length(loss).cast("long").alias("loss_chars"),
        F.sha2(loss, 256).alias("loss_sha256"),
        F.char_length("formatted").cast("long").alias("formatted_chars"),
    )


#: The conversation that the query adds: texts made of the template's own control strings.
ODD_TEXT = "\\### Assistant: </turn> ok"


def with_odd_conversation(spark: SparkSession, turns: DataFrame) -> DataFrame:
    odd = spark.range(2).select(F.lit(-7).cast("long").alias("conv_id"), F.col("id").alias("turn"), F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"), F.lit(ODD_TEXT).alias("text"))
    return turns.select("conv_id", "turn", "role", "text").unionByName(odd)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = with_odd_conversation(spark, spark.read.parquet(f"{sf_dir}/conversations.parquet"))
    """Every conversation, reconstructed from a log of deltas, edits, regenerations and removals of its turns."""
    return digest(parse(render(fold(streamed_events(turns)))))


ORACLE = r"""
WITH t AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '\### Assistant: </turn> ok'
  UNION ALL SELECT -7, 1, 'assistant', '\### Assistant: </turn> ok'
)
SELECT conv_id, count(*) AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
  CAST(coalesce(sum(length(text)) FILTER (role = 'assistant'), 0) AS BIGINT) AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (role = 'assistant'), '')) AS loss_sha256,
  CAST(sum(4 + length(regexp_replace(role, '([\\#<\n])', 'xx', 'g')) + 2
      + length(regexp_replace(text, '([\\#<])', 'xx', 'g')) + 9) AS BIGINT) AS formatted_chars
FROM t GROUP BY conv_id
"""
