"""Chat formatting with a grammar round trip, in DataFrame functions only.

A turn is rendered as ``[INST] role``, a line feed, the text and ``</s>``. A deterministic parser reads a rendering back:
it splits at ``</s>``, takes the header up to the first line feed, and the rest as the text. A conversation is rendered, with
those turns escaped that hold a control string, and parsed as a whole; the recovered turns are compared with the source,
and while they differ, the turns that came back otherwise are escaped too (the first one only, if the number of turns
differs), and it is rendered and parsed again. Escaping is
said by ``[INST]\\ `` in place of ``[INST] ``. In escaped text a backslash, ``<``, ``[`` and line feeds of a role are two
characters that begin with a backslash, so no control string is left and unescaping gives the source: the first turn that
differs was not escaped before, so every round escapes one more at least, and there is an end. The results are read from the
last parse.

Defined results: null text or role is empty; a null conversation is a conversation; turns are ordered by (turn, role,
text), nulls first, so repeated turns stay; an empty table leaves the added rows only. A conversation is one string, as
its format demands, so its size is bounded by that of a cell; hot texts and roles need no grouping.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import let

#: Fixed strings of the template.
OPEN, CLOSE, PLAIN, ESCAPED = "[INST]", "</s>", "[INST] ", "[INST]\\ "
CONTROL = ("[INST]", "[/INST]", "<s>", "</s>")
TRAINED = "assistant"
_PAIRS = (("\\", "\\e"), ("<", "\\l"), ("[", "\\b"))
_ROLE_PAIRS = (*_PAIRS, ("\n", "\\n"))


def _escape(c: Column, pairs: tuple) -> Column:
    for plain, code in pairs:
        c = F.replace(c, F.lit(plain), F.lit(code))
    return c


def _unescape(c: Column, pairs: tuple) -> Column:
    for plain, code in (*pairs[1:], pairs[0]):
        c = F.replace(c, F.lit(code), F.lit(plain))
    return c


def parse_turn(one: Column) -> Column:
    """(role, text) of a rendered turn without its close."""
    escaped = F.startswith(one, F.lit(ESCAPED))
    head = F.when(escaped, len(ESCAPED)).otherwise(len(PLAIN))
    line = F.locate("\n", one)
    role = F.substring(one, head + 1, line - 1 - head)
    text = F.substring(one, line + 1, F.length(one))
    return F.struct(F.when(escaped, _unescape(role, _ROLE_PAIRS)).otherwise(role).alias("role"), F.when(escaped, _unescape(text, _PAIRS)).otherwise(text).alias("text"))


def parse(rendered: Column) -> Column:
    """Turns of a rendered conversation, as an array of (role, text)."""
    parts = F.split(rendered, r"\Q</s>\E", -1)
    return F.transform(F.slice(parts, 1, F.greatest(F.size(parts) - 1, F.lit(0))), parse_turn)


def render_turn(turn: Column, escaped: Column) -> Column:
    r, t = turn["role"], turn["text"]
    plain = F.concat(F.lit(PLAIN), r, F.lit("\n"), t, F.lit(CLOSE))
    return F.when(escaped, F.concat(F.lit(ESCAPED), _escape(r, _ROLE_PAIRS), F.lit("\n"), _escape(t, _PAIRS), F.lit(CLOSE))).otherwise(plain)


def conflicts(turn: Column) -> Column:
    """Whether a turn holds a control string."""
    found = F.lit(False)
    for s in CONTROL:
        found = found | F.contains(turn["text"], F.lit(s)) | F.contains(turn["role"], F.lit(s))
    return found


def attempt(source: Column, escaped: Column) -> Column:
    """One round: which turns are escaped, the rendering, what the parser makes of it, whether that is the source."""
    rendered = F.array_join(F.zip_with(source, escaped, render_turn), "")
    read = lambda f: F.struct(escaped.alias("escaped"), f.alias("formatted"), parse(f).alias("turns"))
    return let(let(rendered, read), lambda x: F.struct(x["escaped"], x["formatted"], x["turns"], (x["turns"] == source).alias("same")))


def until_identical(source: Column) -> Column:
    """The first round whose parse gives the source."""
    first = attempt(source, F.transform(source, conflicts))

    def again(state: Column, _: Column) -> Column:
        off = F.transform(source, lambda turn, i: ~F.get(state["turns"], i).eqNullSafe(turn))
        # where the number of turns differs, what comes after the first difference may only have moved
        alone = let(F.array_position(off, F.lit(True)), lambda p: F.transform(off, lambda x, i: i + 1 == p))
        more = F.zip_with(state["escaped"], F.when(F.size(state["turns"]) == F.size(source), off).otherwise(alone), lambda a, b: a | b)
        return F.when(state["same"], state).otherwise(let(more, lambda escaped: attempt(source, escaped)))

    return F.reduce(F.sequence(F.lit(1), F.size(source)), first, again)


def format_chats(conversations: DataFrame) -> DataFrame:
    """One row per conversation: conv_id, formatted, turns as the output gives them, same: whether they are the source."""
    turns = conversations.select("conv_id", F.struct("turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text")).alias("t"))
    whole = turns.groupBy("conv_id").agg(F.sort_array(F.collect_list("t")).alias("_t"))
    source = F.transform("_t", lambda t: F.struct(t["role"].alias("role"), t["text"].alias("text")))
    told = whole.select("conv_id", let(source, until_identical).alias("_r"))
    return told.select("conv_id", "_r.formatted", "_r.turns", "_r.same")


def digests(chats: DataFrame) -> DataFrame:
    loss = F.array_join(F.transform(F.filter("turns", lambda t: t["role"] == TRAINED), lambda t: t["text"]), "")
    told = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    return chats.select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(told.cast("binary"), 256).alias("turns_sha256"),
        F.length(loss).cast("long").alias("loss_chars"),
        F.sha2(loss.cast("binary"), 256).alias("loss_sha256"),
        F.length("formatted").cast("long").alias("formatted_chars"),
    )


PROBE_ID, PROBE_TEXT = -7, "</s>[INST] ok [/INST]"


def with_probe(conversations: DataFrame) -> DataFrame:
    """conversations and one more whose texts look like the template."""
    more = conversations.sparkSession.sql(
        f"SELECT {PROBE_ID}L AS conv_id, turn, role, '{PROBE_TEXT}' AS text FROM VALUES (0L, 'user'), (1L, '{TRAINED}') AS t(turn, role)"
    )
    return conversations.select("conv_id", "turn", "role", "text").unionByName(more)


OP10_SQL = r"""
WITH t AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '</s>[INST] ok [/INST]'
  UNION ALL SELECT -7, 1, 'assistant', '</s>[INST] ok [/INST]'
), c AS (
  SELECT *, contains(role || chr(10) || text, '[INST]') OR contains(role || chr(10) || text, '[/INST]')
            OR contains(role || chr(10) || text, '<s>') OR contains(role || chr(10) || text, '</s>') OR contains(role, chr(10)) AS escaped
  FROM t
), f AS (
  SELECT *, CASE WHEN escaped THEN
      9 + length(role) + length(text) + 4
      + (length(role || text) - length(replace(replace(replace(role || text, '\', ''), '<', ''), '[', '')))
      + (length(role) - length(replace(role, chr(10), '')))
    ELSE 8 + length(role) + length(text) + 4 END AS chars
  FROM c
)
SELECT conv_id, count(*) AS n_turns,
       sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn NULLS FIRST, role, text)) AS turns_sha256,
       CAST(coalesce(sum(length(text)) FILTER (WHERE role = 'assistant'), 0) AS BIGINT) AS loss_chars,
       sha256(coalesce(string_agg(text, '' ORDER BY turn NULLS FIRST, role, text) FILTER (WHERE role = 'assistant'), '')) AS loss_sha256,
       CAST(sum(chars) AS BIGINT) AS formatted_chars
FROM f GROUP BY conv_id
"""
