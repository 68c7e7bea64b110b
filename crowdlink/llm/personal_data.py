"""Personal data: base patterns as seeds, and unseen identifiers found by their contexts.

Base spans are the leftmost matches of four fixed patterns that pass their checks. Every token with a digit
or ``@`` is an occurrence with two lexical patterns: the last word before it with the marks between (as in
``token =``), and the word behind it. Seeds of the fifth kind, secrets, are key-like tokens right behind a
cue word. In rounds, a pattern's confidence in a kind is the share of that kind among its distinct instances,
weighed by how many support it; an instance without a seed gains from each confident pattern (noisy or).
Instances that end above ``ACCEPT`` and look like the kind are personal data wherever they occur.

Spans are in code points, end exclusive. Defined results: a null text is empty; rows of one id and text
share their result; a null id is an id of its own; an empty table gives no rows; extra columns do not
matter; found spans never overlap base spans. All patterns and sums take time linear in the text, so texts
of any length are read whole.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from crowdlink.llm.arrays import let, sums_before
from crowdlink.storage import cut

#: Kinds in the order of reports, and patterns that find the contract's matches without retries.
KINDS = ("email", "ip", "card", "phone")
PATTERNS = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++(?:\.[0-9]++)(?:\.[0-9]++)(?:\.[0-9]++)",
    "card": r"(?<![0-9])(?<![0-9][\x20-])[0-9](?:[\x20-]?[0-9]){12,18}+(?![\x20-]?[0-9])",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
TOKEN = r"(?<!\S)[^\s0-9@]*+[0-9@]\S*+"
#: Shapes that a found instance of a kind must have.
SHAPES = {
    "email": r"^[^@\s]+@[^@\s]+$",
    "ip": r"^[0-9]{1,3}([.:,][0-9]{1,3}){3}$",
    "card": r"^[0-9](?:[.-]?[0-9]){12,18}$",
    "phone": r"^\+?[(]?[0-9](?:[()./-]{0,2}[0-9]){6,14}$",
    "secret": r"^(?=[^0-9]*[0-9])(?=[^a-z]*[a-z])[0-9a-z_+/=-]{16,}$",
}
#: What a text must hold for a base pattern to match at all, and what a seed of a secret is: one of
#: these words before it, and a token of hexadecimal digits or of mixed letters and digits.
GATES = {"email": r"@", "ip": r"[0-9]\.[0-9]++\.[0-9]", "card": r"[0-9](?:[\x20-]?[0-9]){12}", "phone": r"\+[0-9]"}
CUES = ("token", "secret", "password", "passwd", "apikey", "key", "bearer")
KEY_LIKE = r"^(?=[^0-9]*[0-9])(?:(?=[0-9]*[a-f])[0-9a-f]{32,}|(?=[^a-z]*[a-z])(?=[^A-Z]*[A-Z])[0-9A-Za-z_+/=-]{20,})$"
ROUNDS, SUPPORT, CONFIDENT, ACCEPT = 5, 3, 0.8, 0.8
#: Marks between a word and a token that a pattern keeps.
MARKS = 8


NO_SPANS = "cast(array() as array<struct<kind:string,start:int,end:int>>)"


def matches(text: Column, pattern: str) -> Column:
    """Array of (start, end, text, before) of all matches; ``before`` is the text since the match before."""
    found = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    pieces = F.split(text, pattern, -1)

    def place(pairs: Column) -> Column:
        before = sums_before(F.transform(pairs, lambda x: F.length(x["before"]) + F.length(x["text"])))

        def item(x: Column, at: Column) -> Column:
            start = at + F.length(x["before"])
            return F.struct(start.alias("start"), (start + F.length(x["text"])).alias("end"), x["text"].alias("text"), x["before"].alias("before"))

        return F.zip_with(pairs, before, item)

    pairs = let(found, lambda m: F.zip_with(m, F.slice(pieces, 1, F.size(m)), lambda m, s: F.struct(m.alias("text"), s.alias("before"))))
    return let(pairs, place)


def luhn(digits: Column) -> Column:
    """Whether a string of digits passes the check of payment cards."""

    def value(d: Column, i: Column) -> Column:
        n = d.cast("int") * F.when(i % 2 == 1, 2).otherwise(1)
        return n - F.when(n > 9, 9).otherwise(0)

    values = F.transform(F.split(F.reverse(digits), ""), lambda d, i: F.when(d != "", value(F.when(d != "", d).otherwise("0"), i)).otherwise(0))
    return F.aggregate(values, F.lit(0), lambda a, x: a + x) % 10 == 0


def passes(kind: str, text: Column) -> Column:
    digits = F.regexp_replace(text, "[^0-9]", "")
    if kind == "ip":
        return F.forall(F.split(text, "\\."), lambda p: F.length(F.regexp_replace(p, "^0+(?=.)", "")) <= 3) & F.forall(F.split(text, "\\."), lambda p: F.coalesce(F.regexp_substr(F.regexp_replace(p, "^0+(?=.)", ""), F.lit("^[0-9]{1,3}$")).cast("int"), F.lit(999)) <= 255)
    if kind == "card":
        return luhn(digits)
    if kind == "phone":
        return F.length(digits).between(9, 15)
    return F.lit(True)


def base_spans(text: Column) -> Column:
    """Array of (kind, start, end) in the order of kinds and starts."""

    def of(kind: str) -> Column:
        kept = F.filter(matches(text, PATTERNS[kind]), lambda m: passes(kind, m["text"]))
        spans = F.transform(kept, lambda m: F.struct(F.lit(kind).alias("kind"), m["start"].alias("start"), m["end"].alias("end")))
        return F.when(text.rlike(GATES[kind]), spans).otherwise(F.expr(NO_SPANS))

    return F.concat(*map(of, KINDS))


def _first_word(text: Column) -> Column:
    """First word of a text, lower-cased and without marks; null if there is none."""
    flat = F.trim(F.translate(text, "\n\t\r", "   "))
    word = F.regexp_replace(F.lower(F.call_function("substring_index", flat, F.lit(" "), F.lit(1))), r"[^\p{L}\p{N}]+", "")
    return F.when(word != "", word)


def _last_word(text: Column) -> tuple[Column, Column]:
    """Last word of a text as it stands, and the marks behind it without white space; read from the end."""
    back = F.reverse(text)
    end = r"^([^\p{L}\p{N}]*+)([\p{L}\p{N}]*+)"
    return F.reverse(F.regexp_extract(back, end, 2)), F.right(F.regexp_replace(F.reverse(F.regexp_extract(back, end, 1)), r"\s+", ""), F.lit(MARKS))


def occurrences(texts: DataFrame, base: DataFrame) -> DataFrame:
    """Rows ``(doc, th, start, end, value, kind, before, behind)`` of the tokens of rows (doc, th, text).

    ``kind`` is the base kind that begins in the token, or ``secret`` for its seeds; tokens inside a longer
    base span are left out.
    """

    def token(all_: Column, tail: Column, t: Column, i: Column) -> Column:
        lead = F.length(F.regexp_extract(t["text"], r"^[^0-9A-Za-z+@(]*", 0))
        last = F.length(F.regexp_extract(F.reverse(t["text"]), r"^[^0-9A-Za-z]*", 0))
        value = F.substr(t["text"], lead + 1, F.greatest(F.length(t["text"]) - lead - last, F.lit(0)))
        word, marks = _last_word(t["before"])
        before = F.when(word != "", F.concat_ws(" ", F.lower(word), F.when(marks != "", marks))).when(F.trim(t["before"]) == "", F.lower(F.get(all_, i - 1)["text"]))
        behind = _first_word(F.coalesce(F.get(all_, i + 1)["before"], tail))
        cued = word.isin(*CUES) & value.rlike(KEY_LIKE)
        return F.struct((t["start"] + lead).alias("start"), value.alias("value"), before.alias("before"), behind.alias("behind"), F.when(cued, "secret").alias("kind"))

    tail = F.element_at(F.split(F.col("text"), TOKEN, -1), -1)
    tokens = let(F.struct(matches(F.col("text"), TOKEN).alias("all"), tail.alias("tail")), lambda x: F.transform(x["all"], lambda t, i: token(x["all"], x["tail"], t, i)))
    each = texts.where(F.col("text").rlike("[0-9@]")).select("doc", "th", F.explode(tokens).alias("t")).select("doc", "th", "t.*").where("value <> ''")
    each = each.withColumn("end", F.col("start") + F.length("value")).withColumn("token", F.lit(1))
    spans = base.select("doc", "th", F.explode("base").alias("b")).select("doc", "th", "b.*").withColumn("token", F.lit(0))
    both = each.unionByName(spans, allowMissingColumns=True)
    up = Window.partitionBy("doc", "th").orderBy("start", F.desc("token"), "end")
    down = Window.partitionBy("doc", "th").orderBy(F.desc("start"), "token", "end")
    covered = F.max(F.when(F.col("token") == 0, F.col("end"))).over(up.rowsBetween(Window.unboundedPreceding, -1))
    ahead = F.last(F.when(F.col("token") == 0, F.struct("start", "kind")), ignorenulls=True).over(down.rowsBetween(Window.unboundedPreceding, -1))
    both = both.withColumn("covered", covered).withColumn("ahead", ahead).where("token = 1 AND coalesce(covered <= start, true)")
    kind = F.when(F.col("ahead.start") < F.col("end"), F.col("ahead.kind")).otherwise(F.col("kind"))
    return both.select("doc", "th", "start", "end", F.lower("value").alias("value"), kind.alias("kind"), "before", "behind")


def discover(found: DataFrame, rounds: int = ROUNDS) -> DataFrame:
    """Rows ``(value, kind)`` of identifiers that no base pattern shows: rounds over the graph of instances and patterns.

    What one round finds supports the patterns of the next, so identifiers are reached through others that
    have no seed's context themselves. It ends early when a round changes no pattern.
    """
    sides = F.array(F.struct(F.lit("before").alias("side"), F.col("before").alias("word")), F.struct(F.lit("behind").alias("side"), F.col("behind").alias("word")))
    edges = found.select("value", F.explode(sides).alias("p")).where("p.word IS NOT NULL").select("value", "p.side", "p.word").distinct()
    edges = cut(edges, "edges")
    seeds = cut(found.where("kind IS NOT NULL").select("value", "kind").distinct().withColumn("score", F.lit(1.0)), "seeds")
    reach = cut(edges.groupBy("side", "word").agg(F.count("*").alias("instances")).where(F.col("instances") >= SUPPORT), "patterns")
    scores, known = seeds, None
    for _ in range(rounds):
        patterns = edges.join(scores, "value").groupBy("side", "word", "kind").agg(F.sum("score").alias("support")).join(reach, ["side", "word"])
        patterns = patterns.withColumn("confidence", F.round(F.col("support") / F.col("instances"), 9))
        patterns = cut(patterns.where((F.col("support") >= SUPPORT) & (F.col("confidence") >= CONFIDENT)).select("side", "word", "kind", "confidence"), "confident")
        now = patterns.agg(F.count("*"), F.coalesce(F.bit_xor(F.xxhash64("side", "word", "kind", "confidence")), F.lit(0))).first()
        if now[0] == 0 or now == known:
            break
        known = now
        gained = edges.join(patterns, ["side", "word"]).groupBy("value", "kind").agg((1 - F.exp(F.sum(F.log(1.0 - 0.95 * F.col("confidence"))))).alias("score"))
        scores = cut(seeds.unionByName(gained.join(seeds.select("value"), "value", "left_anti")), "scores")
    shape = reduce(lambda a, b: a | b, ((F.col("kind") == k) & F.col("value").rlike(x) for k, x in SHAPES.items()))
    new = scores.where((F.col("score") >= ACCEPT) & shape).join(seeds.select("value"), "value", "left_anti")
    secrets = seeds.where("kind = 'secret'")  # no base span shows them
    return new.unionByName(secrets).groupBy("value").agg(F.max_by("kind", F.struct("score", "kind")).alias("kind"))


def _joined(spans: Column) -> Column:
    order = F.expr("map('email', 0, 'ip', 1, 'card', 2, 'phone', 3, 'secret', 4)")
    ranked = F.array_sort(F.transform(spans, lambda s: F.struct(F.element_at(order, s["kind"]).alias("k"), s["start"].alias("start"), s["end"].alias("end"), s["kind"].alias("kind"))))
    return F.array_join(F.transform(ranked, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def find(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", rounds: int = ROUNDS) -> DataFrame:
    """Rows ``(id, base, found)``: arrays of (kind, start, end) of the base patterns and of the contexts."""
    rows = docs.select(F.col(id_col).alias("doc"), F.coalesce(text_col, F.lit("")).alias("text"))
    rows = rows.withColumn("th", F.xxhash64("text"))
    base = cut(rows.select("doc", "th", base_spans(F.col("text")).alias("base")), "base")
    seen = cut(occurrences(rows, base), "occurrences")
    new = discover(seen, rounds)
    hits = seen.where("kind IS NULL OR kind = 'secret'").drop("kind").join(new, "value").groupBy("doc", "th").agg(F.collect_set(F.struct("kind", "start", "end")).alias("found"))
    met = F.col("b.doc").eqNullSafe(F.col("h.doc")) & (F.col("b.th") == F.col("h.th"))
    return base.alias("b").join(hits.alias("h"), met, "left").select(F.col("b.doc").alias("id"), "base", F.coalesce("found", F.expr(NO_SPANS)).alias("found"))


def report(found: DataFrame) -> DataFrame:
    """Counts of base spans by kind, their digest, all spans, and how many the contexts added."""

    def count(kind: str) -> Column:
        return F.size(F.filter("base", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")

    counts = map(count, KINDS)
    n_secret = F.size(F.filter("found", lambda s: s["kind"] == "secret")).cast("long").alias("n_secret")
    return found.select(F.col("id").alias("doc_id"), *counts, F.sha2(_joined(F.col("base")), 256).alias("base_sha256"), _joined(F.concat("base", "found")).alias("spans"), n_secret, F.size("found").cast("long").alias("n_added"))
