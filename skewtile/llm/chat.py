"""Chat formatting checked by a grammar round trip, in DataFrame functions only.

Grammar of the rendered text: conversation := turn*, turn := START role NL text END NL. The parser
is deterministic: it cuts at START, reads the role up to the first NL and the text up to the first
END, and then asks for exactly NL. A turn is rendered as it is; if parsing gives another turn than
the source, control strings in its text get one more backslash behind their first character, and
parsing takes one away, so any number of backslashes in a source survives. One such round makes every turn come back
identical, as an escaped text holds no control string; round_trip tells it of the whole conversation.

Cases: a null text or role counts as empty; turns of one conversation go by turn (null first), then
role, then text; repeated rows are turns of their own; a null conv_id is a conversation; an empty
table gives no rows; other columns are ignored. One conversation is one output row, so it must fit a row.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

# The control strings of the template.
START, END = "<|im_start|>", "<|im_end|>"
_PLAIN = r"<(\\*\|im_(?:start|end)\|>)"
_ESCAPED = r"<\\(\\*\|im_(?:start|end)\|>)"


def escape(text: Column) -> Column:
    return F.regexp_replace(text, _PLAIN, r"<\\$1")


def unescape(text: Column) -> Column:
    return F.regexp_replace(text, _ESCAPED, r"<$1")


def _role_out(role: Column) -> Column:
    return F.replace(F.replace(F.replace(role, F.lit("\\"), F.lit("\\\\")), F.lit("\n"), F.lit("\\n")), F.lit("<"), F.lit("\\l"))


def _role_in(role: Column) -> Column:
    part = lambda p: F.replace(F.replace(p, F.lit("\\l"), F.lit("<")), F.lit("\\n"), F.lit("\n"))
    return F.array_join(F.transform(F.split(role, r"\\\\"), part), "\\")


def render_turn(role: Column, text: Column) -> Column:
    return F.concat(F.lit(START), _role_out(role), F.lit("\n"), text, F.lit(END + "\n"))


def parse(formatted: Column) -> Column:
    """Array of (role, text, sound) of a rendered conversation; sound is false where the grammar is broken."""
    pieces = F.split(formatted, r"<\|im_start\|>")

    def turn(piece: Column) -> Column:
        role = F.substring_index(piece, "\n", 1)
        rest = F.substring(piece, F.length(role) + 2, F.length(piece))
        text = F.substring_index(rest, END, 1)
        return F.struct(
            _role_in(role).alias("role"),
            unescape(text).alias("text"),
            (rest == F.concat(text, F.lit(END + "\n"))).alias("sound"),
        )

    turns = F.transform(F.slice(pieces, 2, F.greatest(F.size(pieces) - 1, F.lit(0))), turn)
    return F.when(F.element_at(pieces, 1) == "", turns).otherwise(F.array_append(turns, F.struct(F.lit("").alias("role"), F.lit("").alias("text"), F.lit(False).alias("sound"))))


def _same(turns: Column, role: Column, text: Column) -> Column:
    first = F.get(turns, 0)
    return (F.size(turns) == 1) & first["sound"] & (first["role"] == role) & (first["text"] == text)


def format_conversations(turns: DataFrame, trained_roles: tuple[str, ...] = ("assistant",)) -> DataFrame:
    """One row per conversation: conv_id, formatted, loss_spans (start and end code points of the trained texts as
    rendered), turns (parsed back), n_escaped, round_trip (all turns came back as they were)."""
    rows = turns.select(
        "conv_id",
        "turn",
        F.coalesce(F.col("role").cast("string"), F.lit("")).alias("role"),
        F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"),
    )
    kept = _same(parse(render_turn(F.col("role"), F.col("text"))), F.col("role"), F.col("text"))
    rows = rows.withColumn("body", F.when(kept, F.col("text")).otherwise(escape(F.col("text"))))
    rows = rows.withColumn("piece", render_turn(F.col("role"), F.col("body")))
    order = Window.partitionBy("conv_id").orderBy("turn", "role", "text").rowsBetween(Window.unboundedPreceding, 0)
    rows = rows.withColumn("stop", F.sum(F.length("piece").cast("long")).over(order))
    body_stop = F.col("stop") - F.lit(len(END) + 1)
    one = F.struct(
        "stop", "role", "text", "piece",
        (F.col("body") != F.col("text")).alias("escaped"),
        F.struct((body_stop - F.length("body")).alias("start"), body_stop.alias("end")).alias("span"),
    )
    whole = rows.groupBy("conv_id").agg(F.sort_array(F.collect_list(one)).alias("source"))
    whole = whole.select(
        "conv_id",
        "source",
        F.array_join(F.transform("source", lambda t: t["piece"]), "").alias("formatted"),
        F.transform(F.filter("source", lambda t: t["role"].isin(*trained_roles)), lambda t: t["span"]).alias("loss_spans"),
        F.size(F.filter("source", lambda t: t["escaped"])).alias("n_escaped"),
    )
    whole = whole.withColumn("turns", parse(F.col("formatted")))
    back = F.transform("turns", lambda t: F.struct(t["role"], t["text"], t["sound"]))
    there = F.transform("source", lambda t: F.struct(t["role"], t["text"], F.lit(True)))
    return whole.select("conv_id", "formatted", "loss_spans", "turns", "n_escaped", (back == there).alias("round_trip"))


def masked_texts(formatted: Column, loss_spans: Column) -> Column:
    """The texts under the loss mask: its slices of the rendered conversation, unescaped."""
    return F.transform(loss_spans, lambda s: unescape(F.substring(formatted, (s["start"] + 1).cast("int"), (s["end"] - s["start"]).cast("int"))))


def digests(formatted: DataFrame) -> DataFrame:
    """What is read back from the rendered text: counts and hashes of the turns and of the text under the loss mask."""
    told = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    loss = F.array_join(masked_texts(F.col("formatted"), F.col("loss_spans")), "")
    return formatted.select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(told, 256).alias("turns_sha256"),
        F.length(loss).cast("long").alias("loss_chars"),
        F.sha2(loss, 256).alias("loss_sha256"),
        F.length("formatted").cast("long").alias("formatted_chars"),
        "n_escaped",
        "round_trip",
    )
