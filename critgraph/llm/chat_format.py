"""Chat formatting: typed content parts, in DataFrame functions alone.

A visitor flattens the parts of a turn (text, image, audio, document) into one string with
numbered placeholders, and records each attachment's reference and the tokens its
placeholder stands for. Turns are then laid out in a template that marks them; control
strings inside roles and texts are escaped reversibly: the backslash becomes backslash-b
and the less-than sign backslash-l, so a bare "<" is always the template's own.

``typed_turns`` makes the parts of plain texts: links to media files become image, audio and document parts, whose
reference is the link as it stood; ``read_back`` puts references back in place of placeholders. The loss mask is a list of
spans of the formatted string (code points), those of the assistant's texts.

Defined results: null texts and roles are empty; turns are ordered by turn (null first),
then escaped role, then flattened text, then attachments; repeated rows are turns each; unknown part types are placeholders of
their name with no tokens; extra columns are not read. A conversation is one string of the
result, as its digest needs; what is gathered per conversation is its own turns.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

OPEN, MID, CLOSE = "<turn ", ">\n", "\n</turn>\n"
#: Tokens that one unit (tile, second, page) of an attachment expands to.
UNIT_TOKENS = {"image": 256, "audio": 25, "document": 512}
LOSS_ROLE = "assistant"
#: Endings of links by the kind of part that they make.
ENDINGS = {"image": "png|jpe?g|gif|webp", "audio": "wav|mp3|ogg|flac", "document": "pdf|docx?"}
MEDIA = r"(?i)https?://[^\x00-\x20<>\"]+?\.(?:%s)" % "|".join(ENDINGS.values())
PARTS = "array<struct<type string, text string, ref string, units bigint>>"


def escaped(s: Column) -> Column:
    return F.replace(F.replace(s, F.lit("\\"), F.lit("\\b")), F.lit("<"), F.lit("\\l"))


def unescaped(s: Column) -> Column:
    return F.replace(F.replace(s, F.lit("\\l"), F.lit("<")), F.lit("\\b"), F.lit("\\"))


def role_escaped(s: Column) -> Column:
    return F.replace(escaped(s), F.lit(">"), F.lit("\\g"))


def role_unescaped(s: Column) -> Column:
    return unescaped(F.replace(s, F.lit("\\g"), F.lit(">")))


def visited(parts: Column) -> tuple[Column, Column, Column]:
    """(flat text with placeholders already escaped, attachments, expanded tokens) of a turn's parts."""
    parts = F.coalesce(parts, F.expr(f"cast(array() as {PARTS})"))
    kind = lambda p: F.coalesce(p["type"], F.lit("text"))
    media = F.filter(parts, lambda p: kind(p) != "text")

    def tokens(p: Column) -> Column:
        rate = F.lit(0)
        for k, n in UNIT_TOKENS.items():
            rate = F.when(p["type"] == k, F.lit(n)).otherwise(rate)
        return (rate * F.coalesce(p["units"], F.lit(1))).cast("bigint")

    attachments = F.transform(media, lambda p, i: F.struct(i.cast("int").alias("place"), p["type"].alias("type"), p["ref"].alias("ref"), tokens(p).alias("tokens")))
    step = lambda acc, p: F.when(
        kind(p) == "text", F.struct(F.concat(acc["s"], escaped(F.coalesce(p["text"], F.lit("")))).alias("s"), acc["n"].alias("n"))
    ).otherwise(F.struct(F.concat(acc["s"], F.lit("<part "), role_escaped(kind(p)), F.lit(":"), acc["n"].cast("string"), F.lit(">")).alias("s"), (acc["n"] + 1).alias("n")))
    flat = F.aggregate(parts, F.struct(F.lit("").alias("s"), F.lit(0).alias("n")), step)["s"]
    return flat, attachments, F.aggregate(attachments, F.lit(0).cast("bigint"), lambda a, x: a + x["tokens"])


def formatted(turns: DataFrame) -> DataFrame:
    """From (conv_id, turn, role, parts): conv_id, formatted, attachments (a list a turn), expanded_tokens, loss_spans.

    A conversation's turns are numbered and measured by a window, and gathered in the same task.
    """
    flat, attachments, tokens = visited(F.col("parts"))
    rows = turns.select("conv_id", "turn", role_escaped(F.coalesce("role", F.lit(""))).alias("role"), F.coalesce("role", F.lit("")).alias("_own"), flat.alias("flat"), attachments.alias("attachments"), tokens.alias("tokens"))
    before = F.length("role") + len(OPEN) + len(MID)
    w = Window.partitionBy("conv_id").orderBy("turn", "role", "flat", "attachments")
    so_far = F.sum((before + F.length("flat") + len(CLOSE)).cast("bigint")).over(w.rowsBetween(Window.unboundedPreceding, Window.currentRow))
    rows = rows.withColumn("n", F.row_number().over(w)).withColumn("end", so_far - len(CLOSE))
    whole = rows.groupBy("conv_id").agg(F.sort_array(F.collect_list(F.struct("n", "role", "_own", "flat", "attachments", "tokens", "end"))).alias("turns"))
    shown = F.transform("turns", lambda t: F.concat(F.lit(OPEN), t["role"], F.lit(MID), t["flat"], F.lit(CLOSE)))
    spoken = F.filter("turns", lambda t: t["_own"] == LOSS_ROLE)
    return whole.select(
        "conv_id", F.array_join(shown, "").alias("formatted"), F.transform("turns", lambda t: t["attachments"]).alias("attachments"),
        F.aggregate("turns", F.lit(0).cast("bigint"), lambda a, t: a + t["tokens"]).alias("expanded_tokens"),
        F.transform(spoken, lambda t: F.struct((t["end"] - F.length(t["flat"])).alias("start"), t["end"].alias("end"))).alias("loss_spans"),
    )


def typed_turns(conversations: DataFrame) -> DataFrame:
    """Plain rows (conv_id, turn, role, text) as turns of typed parts: text, and the media that it links to."""
    own = F.coalesce("text", F.lit(""))
    ending = lambda link: F.lower(F.regexp_extract(link, r"([A-Za-z0-9]+)$", 1))

    def kind(link: Column) -> Column:
        out = F.lit("text")
        for name, endings in ENDINGS.items():
            out = F.when(F.regexp_like(ending(link), F.lit(f"^(?:{endings})$")), F.lit(name)).otherwise(out)
        return out

    def part(name: Column, text: Column | None = None, ref: Column | None = None) -> Column:
        none = F.lit(None).cast("string")
        return F.struct(name.alias("type"), (none if text is None else text).alias("text"), (none if ref is None else ref).alias("ref"), F.lit(None).cast("bigint").alias("units"))

    links = F.transform(F.regexp_extract_all(own, F.lit(MEDIA), F.lit(0)), lambda x: part(kind(x), ref=x))
    texts = F.transform(F.split(own, MEDIA, -1), lambda x: part(F.lit("text"), text=x))
    both = F.flatten(F.zip_with(texts, links, lambda x, y: F.array_compact(F.array(x, y))))
    return conversations.select(F.col("conv_id").cast("bigint"), F.col("turn").cast("bigint"), "role", both.alias("parts"))


def restored(flat: Column, attachments: Column) -> Column:
    """A turn's text from its flattened form: unescaped, references in the places of their parts."""
    texts = F.transform(F.split(flat, "<part [^>]*>", -1), unescaped)
    return F.array_join(F.zip_with(texts, attachments, lambda x, a: F.concat(F.coalesce(x, F.lit("")), F.coalesce(a["ref"], F.lit("")))), "")


def parsed(form: Column, attachments: Column) -> Column:
    """The turns of a formatted conversation: array of (role, text), unescaped."""
    pieces = F.filter(F.split(form, OPEN, -1), lambda p, i: i > 0)
    return F.zip_with(
        pieces, attachments,
        lambda p, own: F.struct(
            role_unescaped(F.substring_index(p, ">", 1)).alias("role"),
            restored(F.substring(p, F.instr(p, MID) + len(MID), F.length(p) - F.instr(p, MID) - len(MID) + 1 - len(CLOSE)), own).alias("text"),
        ),
    )


def masked_text(form: Column, spans: Column) -> Column:
    """The pieces of a formatted string at ``spans``. Places are found in four bytes a sign, not by walking the string for each span."""
    wide = F.encode(form, "UTF-32")
    mark = F.lit(bytearray(b"\x00\x00\xfe\xff"))  # the decoder takes one such mark away: not the text's own
    piece = lambda b, s: F.decode(F.concat(mark, F.substring(b, (4 * s["start"] + 1).cast("int"), (4 * (s["end"] - s["start"])).cast("int"))), "UTF-32")
    start = F.struct(wide.alias("b"), F.expr("cast(array() as array<string>)").alias("out"))
    return F.aggregate(spans, start, lambda acc, s: F.struct(acc["b"].alias("b"), F.concat(acc["out"], F.array(piece(acc["b"], s))).alias("out")))["out"]


def read_back(forms: DataFrame) -> DataFrame:
    """From ``formatted``: conv_id, n_turns, turns_sha256, loss_chars, loss_sha256, formatted_chars, n_attachments, expanded_tokens, loss_spans."""
    d = forms.select("*", parsed(F.col("formatted"), F.col("attachments")).alias("t"))
    said = F.transform("t", lambda x: F.concat(x["role"], F.lit("\n"), x["text"], F.lit("\n")))
    spoken = F.transform(F.filter(F.zip_with("t", "attachments", lambda x, a: F.struct(x["role"].alias("role"), a.alias("a"))), lambda x: x["role"] == LOSS_ROLE), lambda x: x["a"])
    loss = F.array_join(F.zip_with(masked_text(F.col("formatted"), F.col("loss_spans")), spoken, restored), "")
    spans = F.array_join(F.transform("loss_spans", lambda s: F.concat(s["start"].cast("string"), F.lit(":"), s["end"].cast("string"))), ",")
    return d.withColumn("_loss", loss).select(
        "conv_id", F.size("t").cast("bigint").alias("n_turns"), F.sha2(F.array_join(said, ""), 256).alias("turns_sha256"),
        F.length("_loss").cast("bigint").alias("loss_chars"), F.sha2(F.col("_loss"), 256).alias("loss_sha256"),
        F.length("formatted").cast("bigint").alias("formatted_chars"), F.aggregate("attachments", F.lit(0).cast("bigint"), lambda n, a: n + F.size(a)).alias("n_attachments"),
        "expanded_tokens", spans.alias("loss_spans"),
    )
