"""Chat formatting with a grammar round trip, in DataFrame functions only.

Grammar of a rendered conversation (no white space of its own)::

    conversation := turn*
    turn         := "<s>[" flag "]" role "[/INST]" body "</s>"      flag := "INST" (raw) | "ESC" (escaped)

Every turn is first rendered raw and reparsed; if role and text do not come back identically, or if they would not inside
the whole conversation, the turn is rendered with ``~``, ``<`` and ``[`` escaped, a form that always parses back.

Defined results: null role and null text are empty; null ``turn`` sorts first; rows with equal ``turn`` are ordered by role
and text; a null ``conv_id`` is a conversation of its own; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: The control strings of the template (fixed values).
OPEN_RAW, OPEN_ESCAPED, BODY, CLOSE = "<s>[INST]", "<s>[ESC]", "[/INST]", "</s>"
#: Escapes, in the order in which they are applied (fixed values).
ESCAPES = (("~", "~0"), ("<", "~1"), ("[", "~2"))


def escape(c: Column) -> Column:
    for plain, code in ESCAPES:
        c = F.replace(c, F.lit(plain), F.lit(code))
    return c


def unescape(c: Column) -> Column:
    for plain, code in reversed(ESCAPES):
        c = F.replace(c, F.lit(code), F.lit(plain))
    return c


def _raw(role: Column, text: Column) -> Column:
    return F.concat(F.lit(OPEN_RAW), role, F.lit(BODY), text, F.lit(CLOSE))


def _escaped(role: Column, text: Column) -> Column:
    return F.concat(F.lit(OPEN_ESCAPED), escape(role), F.lit(BODY), escape(text), F.lit(CLOSE))


def _from(c: Column, start: Column) -> Column:
    return F.substring(c, start, F.length(c))


def parse_turns(rendered: Column) -> Column:
    """array<struct<role, text, body_chars>> read back from a rendered conversation by the grammar alone.

    ``body_chars`` is the length of the body as it stands in the rendered text (for masks over it). A piece that is not a turn
    of the grammar becomes a null entry.
    """
    pieces = F.split(rendered, r"\Q" + CLOSE + r"\E", -1)
    pieces = F.slice(pieces, 1, F.greatest(F.size(pieces) - 1, F.lit(0)))

    def one(piece: Column) -> Column:
        flagged = F.startswith(piece, F.lit(OPEN_ESCAPED))
        rest = F.when(flagged, _from(piece, F.lit(len(OPEN_ESCAPED) + 1))).when(F.startswith(piece, F.lit(OPEN_RAW)), _from(piece, F.lit(len(OPEN_RAW) + 1)))
        at = F.instr(rest, BODY)
        role, body = F.substring(rest, F.lit(1), at - 1), _from(rest, at + len(BODY))
        return F.when(
            at > 0,
            F.struct(
                F.when(flagged, unescape(role)).otherwise(role).alias("role"),
                F.when(flagged, unescape(body)).otherwise(body).alias("text"),
                F.length(body).cast("long").alias("body_chars"),
                F.length(piece).cast("long").alias("piece_chars"),
            ),
        )

    return F.transform(pieces, one)


def _same(turns: Column, parsed: Column) -> Column:
    plain = lambda a: F.transform(a, lambda t: F.struct(t["role"].alias("role"), t["text"].alias("text")))
    return F.coalesce(plain(turns) == plain(parsed), F.lit(False))


def format_conversations(conversations: DataFrame, trained_role: str = "assistant") -> DataFrame:
    """One row per conversation: ``formatted``, the turns reparsed from it, and the loss spans over it.

    ``loss_spans`` are half-open code point ranges of ``formatted`` that hold the bodies of ``trained_role``; ``loss_text`` is what
    stands there, unescaped. ``escaped_turns`` tells how many turns needed escapes. A conversation is one row of the result, so it is
    the unit that one task must hold.
    """
    turn = F.struct(F.col("turn"), F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    convs = conversations.select("conv_id", turn.alias("t")).groupBy("conv_id").agg(F.array_sort(F.collect_list("t")).alias("turns"))

    def render(t: Column) -> Column:
        raw = _raw(t["role"], t["text"])
        back = parse_turns(raw)
        return F.when(_same(F.array(t), back), raw).otherwise(_escaped(t["role"], t["text"]))

    convs = convs.withColumn("rendered", F.transform("turns", render))
    convs = convs.withColumn("formatted", F.array_join("rendered", ""))
    convs = convs.withColumn("parsed", parse_turns(F.col("formatted"))).withColumn("whole", _same(F.col("turns"), F.col("parsed")))
    all_escaped = F.transform("turns", lambda t: _escaped(t["role"], t["text"]))
    convs = convs.withColumn("rendered", F.when(F.col("whole"), F.col("rendered")).otherwise(all_escaped))
    convs = convs.withColumn("formatted", F.array_join("rendered", "")).withColumn("parsed", parse_turns(F.col("formatted")))
    start = F.struct(F.lit(0).cast("long").alias("at"), F.array().cast("array<struct<from:bigint,to:bigint>>").alias("spans"))

    def step(acc: Column, p: Column) -> Column:
        end = acc["at"] + p["piece_chars"]
        span = F.struct((end - p["body_chars"]).alias("from"), end.alias("to"))
        spans = F.when(p["role"] == trained_role, F.concat(acc["spans"], F.array(span))).otherwise(acc["spans"])
        return F.struct((end + len(CLOSE)).alias("at"), spans.alias("spans"))

    convs = convs.withColumn("loss_spans", F.aggregate("parsed", start, step, lambda a: a["spans"]))
    lost = F.transform(F.filter("parsed", lambda p: p["role"] == trained_role), lambda p: p["text"])
    return convs.select(
        "conv_id",
        "formatted",
        F.transform("parsed", lambda p: F.struct(p["role"].alias("role"), p["text"].alias("text"))).alias("turns"),
        "loss_spans",
        F.array_join(lost, "").alias("loss_text"),
        F.size(F.filter("rendered", lambda r: F.startswith(r, F.lit(OPEN_ESCAPED)))).cast("long").alias("escaped_turns"),
    )


def conversation_digest(formatted: DataFrame) -> DataFrame:
    """Counts and SHA-256 digests of what ``format_conversations`` read back."""
    said = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    return formatted.select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(said.cast("binary"), 256).alias("turns_sha256"),
        F.length("loss_text").cast("long").alias("loss_chars"),
        F.sha2(F.col("loss_text").cast("binary"), 256).alias("loss_sha256"),
        F.length("formatted").cast("long").alias("formatted_chars"),
        "escaped_turns",
    )
