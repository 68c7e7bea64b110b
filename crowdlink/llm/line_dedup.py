"""Line dedup by a deletion-neighbourhood join: the earliest of equal or nearly equal lines stays.

A line is trimmed of spaces; blank lines always stay and are compared with nothing. Lines stand in the
order of (document id, hash of its text, line number). A line goes if an equal line stands earlier
anywhere, or if it has ``min_words`` words or more and the first place of a line within one edit (one word
replaced, added or left out) stands before its own first place.

Steps, all in built-in functions: equal lines meet by two 64-bit hashes and leave one row with the first
place. Lines that share neither the first nor the last half of their words with another line cannot be
within one edit and leave (each line has four such keys). The others emit every variant with one word
left out, as a hash: with its place (for replaced words), and without it together with the lines' own
hashes (for added words). Per variant only the least places are kept and joined back, so a variant that
millions of lines share costs no pairs. The word edit distance to the partner is verified on the texts.

Defined results: a null text has no lines and stays null; rows of one id and text are treated alike;
a null id is an id of its own that comes first; an empty table gives no rows; extra columns are kept by
``rewrite``; a line of any length is compared whole (its words are rows, so a very long line is shared out
before it is hashed).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from crowdlink.llm.arrays import let
from crowdlink.storage import cut

#: Default of the parameter ``min_words``: one edit in fewer words is no near copy.
MIN_WORDS = 8
#: Seeds of the two hashes.
SEEDS = (1, 2)


def _hashes(*values: Column) -> list[Column]:
    return [F.xxhash64(F.lit(s), *values) for s in SEEDS]


def lines_of(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """Rows ``(place, line)`` of all lines that are not blank; place is (id, text hash, line number)."""
    each = docs.select(F.col(id_col).alias("doc"), F.xxhash64(text_col).alias("th"), F.posexplode(F.split(text_col, "\n")).alias("no", "raw"))
    return each.select(F.struct("doc", "th", "no").alias("place"), F.trim("raw").alias("line")).where("line <> ''")


def _halves(line: Column, n: Column, least: int) -> Column:
    """Keys of the first and last half of the words, for partners of as many words and of one word less."""

    def of(words: Column) -> list[Column]:
        front = F.floor(words / 2).cast("int")
        first = F.call_function("substring_index", line, F.lit(" "), front)
        last = F.call_function("substring_index", line, F.lit(" "), -(words - front))
        return [F.xxhash64(F.lit(side), words, part) for side, part in (("first", first), ("last", last))]

    return F.when(n > least, F.array(*of(n), *of(n - 1))).when(n == least, F.array(*of(n)))


def distinct_lines(lines: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """Rows ``(h1, h2, place, halves)``: each distinct line's first place; halves is null for short lines."""
    h1, h2 = _hashes(F.col("line"))
    n = F.length("line") - F.length(F.replace("line", F.lit(" "), F.lit(""))) + 1
    keyed = lines.select(h1.alias("h1"), h2.alias("h2"), "place", _halves(F.col("line"), n.cast("int"), min_words).alias("halves"))
    return keyed.groupBy("h1", "h2").agg(F.min("place").alias("place"), F.any_value("halves").alias("halves"))


def _survivors(distinct: DataFrame) -> DataFrame:
    """First places of the lines that share half of their words with another line."""
    keys = distinct.where("halves IS NOT NULL").select("h1", "h2", "place", F.explode("halves").alias("key"))
    met = keys.groupBy("key").agg(F.min("h1").alias("a"), F.max("h1").alias("b")).where("a <> b").select("key")
    return keys.join(met, "key", "left_semi").groupBy("h1", "h2").agg(F.any_value("place").alias("place"))


def variants(lines: DataFrame) -> DataFrame:
    """Rows ``(k1, k2, role, place)`` of lines (h1, h2, place, words).

    Role R: a word is left out at a stated place. Role L: a word is left out. Role S: the line itself.
    Words hash with their place, and a line or variant is the exclusive-or of its words, so that all
    variants of a line follow from running sums over its words.
    """
    word = lines.select("h1", "h2", "place", F.size("words").alias("n"), F.posexplode("words").alias("i", "w"))
    here, shifted = _hashes(F.col("w"), F.col("i")), _hashes(F.col("w"), F.col("i") - 1)
    word = word.select("h1", "h2", "place", "n", "i", *(c.alias(f"a{k}") for k, c in enumerate(here)), *(c.alias(f"b{k}") for k, c in enumerate(shifted)))
    line = Window.partitionBy("h1", "h2").orderBy("i")
    before = line.rowsBetween(Window.unboundedPreceding, -1)
    upto = line.rowsBetween(Window.unboundedPreceding, 0)
    whole = Window.partitionBy("h1", "h2")
    none = F.lit(0).cast("long")
    summed = word.select(
        "place", "n", "i",
        *(F.bit_xor(f"a{k}").over(whole).alias(f"t{k}") for k in range(2)),
        *(F.col(f"a{k}") for k in range(2)),
        *(F.coalesce(F.bit_xor(f"a{k}").over(before), none).bitwiseXOR(F.bit_xor(f"b{k}").over(whole)).bitwiseXOR(F.bit_xor(f"b{k}").over(upto)).alias(f"l{k}") for k in range(2)),
    )

    def row(role: str, size: Column, at: Column, sums: list[Column]) -> Column:
        kind = F.lit("replaced" if role == "R" else "added")
        return F.struct(*(F.xxhash64(kind, size, at, s).alias(f"k{k + 1}") for k, s in enumerate(sums)), F.lit(role).alias("role"))

    nowhere = F.lit(-1)
    emitted = F.array(
        row("R", F.col("n"), F.col("i"), [F.col(f"t{k}").bitwiseXOR(F.col(f"a{k}")) for k in range(2)]),
        row("L", F.col("n") - 1, nowhere, [F.col(f"l{k}") for k in range(2)]),
        row("S", F.col("n"), nowhere, [F.col(f"t{k}") for k in range(2)]),
    )
    once = F.when(F.col("i") == 0, emitted).otherwise(F.slice(emitted, 1, 2))
    return summed.select("place", F.explode(once).alias("v")).select("v.k1", "v.k2", "v.role", "place")


def partners(found: DataFrame) -> DataFrame:
    """Rows ``(place, partner)``: an earlier line that shares a variant, by least places only."""
    least = lambda role: F.min(F.when(F.col("role") == role, F.col("place")))
    groups = found.groupBy("k1", "k2").agg(least("R").alias("r"), least("L").alias("l"), least("S").alias("s"), F.count("*").alias("size")).where("size > 1")
    other = F.when(F.col("role") == "R", F.col("r")).when(F.col("role") == "L", F.col("s")).otherwise(F.col("l"))
    joined = found.join(groups, ["k1", "k2"]).select("place", other.alias("partner"))
    return joined.where("partner < place").distinct()


def _same_run(a: Column, b: Column) -> Column:
    """How many leading items of two arrays are equal."""
    step = lambda done, same: F.struct((done["open"] & same).alias("open"), (done["n"] + (done["open"] & same).cast("int")).alias("n"))
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.eqNullSafe(y)), F.struct(F.lit(True).alias("open"), F.lit(0).alias("n")), step, lambda x: x["n"])


def within_one_edit(a: Column, b: Column) -> Column:
    """Whether two arrays of words differ by one replaced, added or missing word at most."""
    alike = _same_run(a, b) + _same_run(F.reverse(a), F.reverse(b))
    return (F.abs(F.size(a) - F.size(b)) <= 1) & (alike >= F.greatest(F.size(a), F.size(b)) - 1)


def near_lines(docs: DataFrame, distinct: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """First places of the distinct lines that an earlier line is within one edit of."""
    survivors = cut(_survivors(distinct), "survivors")
    wanted = survivors.groupBy(F.col("place.doc").alias("doc"), F.col("place.th").alias("th")).agg(F.collect_list(F.struct("place.no", "h1", "h2")).alias("wanted"))
    parts = docs.select(F.col(id_col).alias("doc"), F.xxhash64(text_col).alias("th"), F.col(text_col).alias("text")).alias("d")
    held = parts.join(wanted.alias("w"), F.col("d.doc").eqNullSafe(F.col("w.doc")) & (F.col("d.th") == F.col("w.th")))
    pick = let(F.split("d.text", "\n"), lambda lines: F.transform("w.wanted", lambda x: F.struct(x["h1"].alias("h1"), x["h2"].alias("h2"), x["no"].alias("no"), F.get(lines, x["no"]).alias("raw"))))
    picked = held.select("d.doc", "d.th", F.explode(pick).alias("x"))
    texts = picked.groupBy("x.h1", "x.h2").agg(F.any_value(F.struct("doc", "th", "x.no")).alias("place"), F.any_value(F.split(F.trim("x.raw"), " ")).alias("words"))
    texts = cut(texts, "lines")
    pairs = partners(cut(variants(texts), "variants"))
    own, far = (texts.select(F.col("place").alias(c), F.col("words").alias(f"{c}_words")) for c in ("place", "partner"))
    checked = pairs.join(own, "place").join(far, "partner").where(within_one_edit(F.col("place_words"), F.col("partner_words")))
    return checked.select("place").distinct()


def kept_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_words: int = MIN_WORDS) -> DataFrame:
    """Rows ``(doc, th, kept_lines, n_near)``: numbers of the lines that stay, and of how many a near line went."""
    distinct = cut(distinct_lines(lines_of(docs, id_col, text_col), min_words), "distinct")
    near = near_lines(docs, distinct, id_col, text_col).withColumn("near", F.lit(True))
    judged = distinct.select("place").join(near, "place", "left").select("place.doc", "place.th", "place.no", F.coalesce("near", F.lit(False)).alias("near"))
    return judged.groupBy("doc", "th").agg(F.collect_list(F.when(~F.col("near"), F.col("no"))).alias("kept_lines"), F.count_if("near").alias("n_near"))


def _with_kept(docs: DataFrame, id_col: str, text_col: str, min_words: int) -> DataFrame:
    kept = kept_lines(docs.select(id_col, text_col), id_col, text_col, min_words).select(F.col("doc").alias("__doc"), F.col("th").alias("__th"), F.col("kept_lines").alias("__kept"))
    mine = docs.withColumn("__hash", F.xxhash64(text_col))
    return mine.join(kept, mine[id_col].eqNullSafe(kept["__doc"]) & (mine["__hash"] == kept["__th"]), "left")


def rewrite(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_words: int = MIN_WORDS) -> DataFrame:
    """The documents, their text without the lines that go."""

    def without(lines: Column) -> Column:
        blank = F.filter(F.sequence(F.lit(0), F.size(lines) - 1), lambda i: F.trim(F.get(lines, i)) == "")
        stay = F.array_sort(F.array_union(blank, F.coalesce("__kept", F.expr("cast(array() as array<int>)"))))
        return F.array_join(F.transform(stay, lambda i: F.get(lines, i)), "\n")

    text = let(F.split(text_col, "\n"), without)
    out = _with_kept(docs, id_col, text_col, min_words).withColumn(text_col, F.when(F.col(text_col).isNotNull(), text))
    return out.select(*docs.columns)


def report(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_words: int = MIN_WORDS) -> DataFrame:
    """Counts for each document, and the numbers of the lines that stay, in order and comma-joined."""
    slim = docs.select(id_col, text_col)
    kept = kept_lines(slim, id_col, text_col, min_words)
    lines = F.filter(F.split(text_col, "\n"), lambda x: F.trim(x) != "")
    mine = slim.select(F.col(id_col).alias("doc_id"), F.xxhash64(text_col).alias("text_hash"), F.coalesce(F.size(lines), F.lit(0)).alias("n"))
    met = mine["doc_id"].eqNullSafe(kept["doc"]) & (mine["text_hash"] == kept["th"])
    return mine.join(kept, met, "left").select(
        "doc_id",
        F.greatest("n", F.lit(0)).cast("long").alias("n_lines"),
        F.coalesce(F.size("kept_lines"), F.lit(0)).cast("long").alias("n_kept"),
        F.coalesce("n_near", F.lit(0)).cast("long").alias("n_near"),
        F.coalesce(F.array_join(F.array_sort("kept_lines"), ","), F.lit("")).alias("kept_lines"),
    )
