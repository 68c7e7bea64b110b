"""Chat formatting with typed content parts, a loss mask, and an exact way back.

Template of one turn: ``<role>``, a line end, the content, ``</turn>`` and a line end. Inside roles and
content the backslash, ``<`` and ``>`` are written as ``\\b``, ``\\l`` and ``\\g``, so no control string
can occur there and every ``<`` in the output is a control string's first character.

Defined results: null role, text or part text is empty; a null turn comes first; rows that tie on the
turn stand in the order of role and content; rows with a null conversation form one conversation;
an empty table has no conversations; extra columns are not looked at.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from crowdlink.llm.arrays import let, sums_before

#: Tokens that one placeholder of a kind stands for, if the part gives no size of its own. Fixed values.
PART_TOKENS = {"image": 256, "audio": 128, "document": 512}


def escape(text: Column) -> Column:
    out = F.replace(text, F.lit("\\"), F.lit("\\b"))
    return F.replace(F.replace(out, F.lit("<"), F.lit("\\l")), F.lit(">"), F.lit("\\g"))


def unescape(text: Column) -> Column:
    out = F.replace(F.replace(text, F.lit("\\l"), F.lit("<")), F.lit("\\g"), F.lit(">"))
    return F.replace(out, F.lit("\\b"), F.lit("\\"))


def text_part(text: Column) -> Column:
    """A content of one text part."""
    return F.array(F.struct(F.lit("text").alias("kind"), text.alias("text"), F.lit(None).cast("string").alias("ref"), F.lit(None).cast("int").alias("tokens")))


def visit(parts: Column) -> Column:
    """Content string of an array of parts (kind, text, ref, tokens), in order.

    Text is escaped; every other part becomes ``<kind:n>``, n counting the attachments of the turn.
    A null array, or a null part, is empty text.
    """

    def one(done: Column, part: Column) -> Column:
        is_text = F.coalesce(part["kind"], F.lit("text")) == "text"
        shown = F.when(is_text, escape(F.coalesce(part["text"], F.lit("")))).otherwise(F.concat(F.lit("<"), escape(part["kind"]), F.lit(":"), (done["n"] + 1).cast("string"), F.lit(">")))
        return F.struct(F.concat(done["content"], shown).alias("content"), F.when(is_text, done["n"]).otherwise(done["n"] + 1).alias("n"))

    return F.aggregate(F.coalesce(parts, F.expr("cast(array() as array<struct<kind:string,text:string,ref:string,tokens:int>>)")), F.struct(F.lit("").alias("content"), F.lit(0).alias("n")), one, lambda x: x["content"])


def attachments(parts: Column) -> Column:
    """References and expanded token counts of the parts that are not text, in order."""
    other = F.filter(parts, lambda p: F.coalesce(p["kind"], F.lit("text")) != "text")
    sizes = F.create_map(*[F.lit(x) for kv in PART_TOKENS.items() for x in kv])
    return F.coalesce(
        F.transform(other, lambda p, i: F.struct((i + 1).alias("n"), p["kind"].alias("kind"), p["ref"].alias("ref"), F.coalesce(p["tokens"], F.try_element_at(sizes, p["kind"]), F.lit(0)).alias("tokens"))),
        F.expr("cast(array() as array<struct<n:int,kind:string,ref:string,tokens:int>>)"),
    )


def format_turns(turns: DataFrame, learn: str = "assistant") -> DataFrame:
    """One row per conversation from rows (conv_id, turn, role, parts).

    Gives ``formatted``, ``loss_spans`` (start and length in characters of each content that is learned)
    and ``attachments`` (turn index, number, kind, reference and token count).
    """
    one = turns.select("conv_id", F.struct("turn", F.coalesce("role", F.lit("")).alias("role"), visit(F.col("parts")).alias("content"), attachments(F.col("parts")).alias("files")).alias("row"))
    listed = one.groupBy("conv_id").agg(F.array_sort(F.collect_list("row")).alias("rows"))
    head = lambda r: F.concat(F.lit("<"), escape(r["role"]), F.lit(">\n"))
    framed = F.transform("rows", lambda r: F.struct((r["role"] == learn).alias("learned"), F.length(head(r)).alias("head"), F.length(r["content"]).alias("size"), F.concat(head(r), r["content"], F.lit("</turn>\n")).alias("shown")))

    def place(x: Column, at: Column) -> Column:
        return F.struct((at + x["head"]).alias("start"), x["size"].alias("length"), x["learned"].alias("learned"))

    placed = F.zip_with("framed", sums_before(F.transform("framed", lambda x: F.length(x["shown"]))), place)
    spans = F.transform(F.filter(placed, lambda x: x["learned"]), lambda x: F.struct(x["start"].alias("start"), x["length"].alias("length")))
    files = F.flatten(F.transform("rows", lambda r, i: F.transform(r["files"], lambda f: F.struct(i.alias("turn_index"), f["n"].alias("n"), f["kind"].alias("kind"), f["ref"].alias("ref"), f["tokens"].alias("tokens")))))
    return (
        listed.withColumn("framed", framed)
        .select("conv_id", F.array_join(F.transform("framed", lambda x: x["shown"]), "").alias("formatted"), spans.alias("loss_spans"), files.alias("attachments"))
    )


def read_back(formatted: Column) -> Column:
    """Array of (role, text) of a formatted conversation; placeholders stand in the text as they were written."""
    turns = let(F.split(formatted, "</turn>\n", -1), lambda x: F.slice(x, 1, F.size(x) - 1))

    def one(t: Column) -> Column:
        role = F.substring_index(t, ">\n", 1)
        return F.struct(unescape(F.substr(role, F.lit(2))).alias("role"), unescape(F.substr(t, F.length(role) + 3)).alias("text"))

    return F.transform(turns, one)


def masked_texts(formatted: Column, spans: Column) -> Column:
    """The unescaped texts under the loss mask, in order."""
    return let(formatted, lambda text: F.transform(spans, lambda s: unescape(F.substr(text, s["start"] + 1, s["length"]))))


def digests(chats: DataFrame) -> DataFrame:
    """Counts and digests read back from the output."""
    back = chats.withColumn("turns", read_back(F.col("formatted"))).withColumn("loss", F.array_join(masked_texts(F.col("formatted"), F.col("loss_spans")), ""))
    return back.select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), ""), 256).alias("turns_sha256"),
        F.length("loss").cast("long").alias("loss_chars"),
        F.sha2(F.col("loss"), 256).alias("loss_sha256"),
        F.length("formatted").cast("long").alias("formatted_chars"),
    )
