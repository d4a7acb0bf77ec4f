"""Chat formatting of conversations whose turns have typed content parts.

A visitor flattens the parts of each turn in order: text is escaped, and images, audio and documents become placeholders
that name turn and part; each attachment is recorded with its reference and the number of tokens that it expands to.
The result is a list of segments with a loss flag, whose texts joined are the formatted conversation. Only DataFrame and SQL functions.

Fixed format: each turn is ``<|role|>`` role ``<|text|>`` content ``<|end|>``. In role and text a backslash is doubled and ``<|``
becomes ``<`` backslash ``|``, so no text holds a control string, and ``unescaped`` gives every text back.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Kinds of parts beside text; a part of any other kind is shown as a document.
KINDS = ("image", "audio", "document")
PART = "struct<kind:string,text:string,uri:string,width:int,height:int,seconds:double,pages:int>"
ROLE, TEXT, END = "<|role|>", "<|text|>", "<|end|>"


def escaped(text: Column) -> Column:
    return F.replace(F.replace(text, F.lit("\\"), F.lit("\\\\")), F.lit("<|"), F.lit("<\\|"))


def unescaped(text: Column) -> Column:
    return F.replace(F.replace(text, F.lit("<\\|"), F.lit("<|")), F.lit("\\\\"), F.lit("\\"))


def text_parts(rows: DataFrame) -> DataFrame:
    """conv_id, turn, role and parts, one text part for each row's text (null: empty)."""
    empty = ", ".join(f"cast(null as {kind})" for kind in ("string", "int", "int", "double", "int"))
    parts = F.expr(f"array(cast(struct('text', coalesce(cast(text as string), ''), {empty}) as {PART}))")
    return rows.select("conv_id", "turn", F.coalesce(rows["role"].cast("string"), F.lit("")).alias("role"), parts.alias("parts"))


def expanded_tokens(part: Column, patch: int = 28, audio_rate: int = 25, page_tokens: int = 256) -> Column:
    """Tokens that an attachment stands for: patches of an image, frames of audio, pages of a document; unknown sizes count as one."""
    image = F.ceil(part["width"] / patch) * F.ceil(part["height"] / patch)
    sizes = F.when(part["kind"] == "image", image).when(part["kind"] == "audio", F.ceil(part["seconds"] * audio_rate)).otherwise(part["pages"] * page_tokens)
    return F.greatest(F.coalesce(sizes.cast("long"), F.lit(1)), F.lit(1)).cast("long")


def format_conversations(rows: DataFrame, loss_roles: tuple[str, ...] = ("assistant",)) -> DataFrame:
    """One row per conv_id: n_turns, segments (text, loss), formatted, attachments (turn, part, kind, uri, tokens), expanded_tokens.

    rows: conv_id, turn, role, parts (array of PART). Turns are ordered by turn (nulls first), then role, then parts. Null
    roles and texts are empty; null parts are no parts; a part of unknown kind is shown as a document, so that no kind can
    stand for a control string, while attachments keep the kind as given. A null conv_id is
    a conversation of its own. Repeated rows are repeated turns. No rows give no rows. Further columns are ignored.
    A conversation is one result row, so one row of the largest must fit a task.
    """
    turns = rows.select("conv_id", F.struct("turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("parts", F.expr(f"cast(array() as array<{PART}>)")).alias("parts")).alias("t"))
    grouped = turns.groupBy("conv_id").agg(F.sort_array(F.collect_list("t")).alias("turns"))

    def shown(turn: Column, n: Column) -> Column:
        def visit(part: Column, k: Column) -> Column:
            place = F.concat(F.lit("<|"), F.when(part["kind"].isin(*KINDS), part["kind"]).otherwise("document"), F.lit(" "), n.cast("string"), F.lit("."), k.cast("string"), F.lit("|>"))
            return F.when(part["kind"] == "text", escaped(F.coalesce(part["text"], F.lit("")))).otherwise(place)

        return F.array_join(F.transform(turn["parts"], visit), "")

    def segments(turn: Column, n: Column) -> Column:
        piece = lambda text, loss: F.struct(text.alias("text"), loss.alias("loss"))
        head = F.concat(F.lit(ROLE), escaped(turn["role"]), F.lit(TEXT))
        return F.array(piece(head, F.lit(False)), piece(shown(turn, n), turn["role"].isin(*loss_roles)), piece(F.lit(END), F.lit(False)))

    def attached(turn: Column, n: Column) -> Column:
        found = F.transform(turn["parts"], lambda p, k: F.struct(n.alias("turn"), k.alias("part"), p["kind"].alias("kind"), p["uri"].alias("uri"), expanded_tokens(p).alias("tokens")))
        return F.filter(found, lambda p: F.coalesce(p["kind"], F.lit("document")) != "text")

    flat = grouped.select("conv_id", F.size("turns").cast("long").alias("n_turns"), F.flatten(F.transform("turns", segments)).alias("segments"), F.flatten(F.transform("turns", attached)).alias("attachments"))
    return flat.select("conv_id", "n_turns", "segments", F.array_join(F.transform("segments", lambda s: s["text"]), "").alias("formatted"), "attachments", F.aggregate("attachments", F.lit(0).cast("long"), lambda n, a: n + a["tokens"]).alias("expanded_tokens"))


def parsed_turns(formatted: Column) -> Column:
    """role and text of every turn, read back from a formatted conversation; placeholders stay in the text."""
    turns = F.split(formatted, r"<\|end\|>", -1)

    def one(turn: Column) -> Column:
        # The first TEXT mark ends the role; none can stand in it, nor in the content.
        at = F.locate(TEXT, turn)
        return F.struct(unescaped(F.substring(turn, F.lit(len(ROLE) + 1), at - len(ROLE) - 1)).alias("role"), unescaped(F.substring(turn, at + len(TEXT), F.length(turn))).alias("text"))

    return F.transform(F.slice(turns, 1, F.size(turns) - 1), one)


def loss_text(segments: Column) -> Column:
    """All text under the loss mask, unescaped, in order."""
    return F.array_join(F.transform(F.filter(segments, lambda s: s["loss"]), lambda s: unescaped(s["text"])), "")
