"""URL filters: host-suffix and path-prefix expressions joined with rules on short hash prefixes.

A null URL, or one without ``://``, has an empty host and path and fits no rule. Repeated rows each get
their verdict. Rules of equal length cannot both fit unless they are the same (host, path); then block
wins. Null rule hosts or paths are empty strings; an empty rule host fits no URL. Empty tables give no rows
or no rules; hosts and paths of any length are read whole, in time linear in them for each size that rules
have; extra columns do not matter.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Hexadecimal digits of the digest that the join uses; the rest is confirmed afterwards.
SHORT = 8
#: Rule sets of at most so many rows are broadcast; larger ones are joined by shuffle.
BROADCAST_RULES = 10_000
#: So many tasks share the expressions of one rule of a larger set.
SALTS = 32


def host_and_path(url: Column) -> tuple[Column, Column]:
    """Host with A-Z lowered, and the path up to ``?``, ``#`` or the end."""
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.expr("substring(url, instr(url, '://') + 3)")).otherwise("")
    host = F.regexp_substr(rest, F.lit("^[^/?#]+"))
    path = F.regexp_extract(rest, "^[^/?#]*(/[^?#]*)", 1)
    return F.translate(F.coalesce(host, F.lit("")), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), F.coalesce(path, F.lit(""))


def expressions(host: Column, path: Column, labels: list[int], lengths: list[int]) -> Column:
    """The host suffixes of as many labels as some rule's host has, with the path prefixes of as many characters.

    Only these can equal a rule, so a host of any number of labels gives no more suffixes than rules have sizes.
    """
    own = F.length(host) - F.length(F.translate(host, ".", "")) + 1
    empty = F.expr("cast(array() as array<int>)")
    fits = lambda sizes, most: F.filter(F.array(*map(F.lit, sizes)) if sizes else empty, lambda n: n <= most)
    suffixes = F.transform(fits(labels, own), lambda k: F.call_function("substring_index", host, F.lit("."), -k))
    prefixes = F.transform(fits(lengths, F.length(path)), lambda n: F.substring(path, 1, n))
    return F.flatten(F.transform(suffixes, lambda s: F.transform(prefixes, lambda p: F.struct(s.alias("h"), p.alias("p")))))


def judge(pages: DataFrame, rules: DataFrame, id_col: str = "page_id", url_col: str = "url", default: str = "allow", small: int = BROADCAST_RULES, salts: int = SALTS) -> DataFrame:
    """Rows ``(id, host, path, rule, verdict)``: the longest rule that fits decides, else ``default``.

    ``rules`` has host, path and verdict. Each distinct (host, path) is expanded once, so a host that
    holds a third of all pages costs no more than its distinct paths; URLs without a host join with nothing.
    More than ``small`` rules are joined by shuffle, every rule ``salts`` times, so that the expressions of a
    rule that most pages fit are dealt over as many tasks.
    """
    key = F.concat(F.col("rule_host"), F.col("rule_path"))
    known = rules.select(
        F.coalesce("host", F.lit("")).alias("rule_host"), F.coalesce("path", F.lit("")).alias("rule_path"), F.col("verdict").alias("rule_verdict")
    ).where("rule_host <> ''")
    # the key's parts are hashed with their border, so "a.b" + "/c" differs from "a" + ".b/c"
    known = known.withColumn("digest", F.sha2(F.concat_ws("\n", "rule_host", "rule_path"), 256)).withColumn("short", F.substring("digest", 1, SHORT))
    sized = known.agg(F.collect_set(F.length(F.regexp_replace("rule_host", "[^.]", "")) + 1).alias("labels"), F.collect_set(F.length("rule_path")).alias("lengths"), F.count("*").alias("rules")).first()
    few = sized["rules"] <= small
    known = F.broadcast(known.withColumn("salt", F.lit(0))) if few else known.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    host, path = host_and_path(F.col("url"))
    parsed = pages.select(F.col(id_col).alias("id"), F.col(url_col).alias("url")).select("id", host.alias("host"), path.alias("path"))
    hosted = parsed.where("host <> ''")
    found = (
        hosted.select("host", "path")
        .distinct()
        .withColumn("salt", F.lit(0) if few else F.pmod(F.xxhash64("host", "path"), F.lit(salts)).cast("int"))
        .withColumn("x", F.explode(expressions(F.col("host"), F.col("path"), sorted(sized["labels"]), sorted(sized["lengths"]))))
        .withColumn("full", F.sha2(F.concat_ws("\n", "x.h", "x.p"), 256))
        .withColumn("short", F.substring("full", 1, SHORT))
        .join(known, ["short", "salt"])
        .where("full = digest")
        .groupBy("host", "path")
        .agg(F.max(F.struct(F.length(key).alias("n"), (F.col("rule_verdict") == "block").alias("b"), key.alias("rule"), "rule_verdict")).alias("best"))
    )
    judged = hosted.join(found, ["host", "path"], "left").select(
        "id", "host", "path", F.col("best.rule").alias("rule"), F.coalesce("best.rule_verdict", F.lit(default)).alias("verdict")
    )
    return judged.unionByName(parsed.where("host = ''").select("id", "host", "path", F.lit(None).cast("string").alias("rule"), F.lit(default).alias("verdict")))
