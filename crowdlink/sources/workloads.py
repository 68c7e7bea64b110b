"""The experiment workloads on the given tables: records with gold entities, pools of pairs, simulated votes."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from crowdlink.operators.votes import canonical_votes, unit_hash
from crowdlink.storage import cut


@dataclass(frozen=True)
class Workload:
    table: str
    key: str
    below: int
    entity: str  # SQL expression
    voters: int
    err: float
    initial: int
    batch: int
    pool: float = 1.0  # share of the non-matching pairs that may be asked
    matching: bool = True  # whether all matching pairs may be asked


#: Sizes and settings of the stand-ins.
WORKLOADS = {
    "w1": Workload("part", "p_partkey", 267, "p_name", 10, 0.0567, 2000, 320),
    "w2": Workload("embeddings", "vec_id", 94, "cast(label as string)", 5, 0.1065, 200, 40),
    "w3": Workload("embeddings", "vec_id", 529, "cast(label as string)", 5, 0.0482, 1400, 120, 0.22, False),
    "w4": Workload("part", "p_partkey", 949, "p_name", 5, 0.2777, 2000, 300, 0.05),
    "w4b": Workload("documents", "doc_id", 0, "near copies", 5, 0.05, 200, 50, 0.06),
    "w4d": Workload("part", "p_partkey", 949, "concat(p_name, '/', cast(regexp_extract(p_brand, '[0-9]+', 0) as int) % 3)", 5, 0.2777, 2000, 300, 0.06),
}
SEED = 42


def gold(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Rows ``(rid, entity)``."""
    w = WORKLOADS[name]
    if w.table == "documents":
        return cut(document_gold(spark, sf_dir), "gold")
    t = spark.read.parquet(f"{sf_dir}/{w.table}.parquet")
    return t.where(F.col(w.key) < w.below).select(F.col(w.key).cast("long").alias("rid"), F.expr(w.entity).alias("entity"))


def pool(records: DataFrame, name: str, seed: int = SEED) -> DataFrame:
    """Rows ``(u, w, same)`` of the pairs that may be asked; record sets of experiments are a few hundred rows."""
    w = WORKLOADS[name]
    a, b = (records.select(F.col("rid").alias(c), F.col("entity").alias(f"e{c}")) for c in ("u", "w"))
    pairs = a.join(F.broadcast(b), F.col("u") < F.col("w")).select("u", "w", (F.col("eu") == F.col("ew")).alias("same"))
    if w.pool < 1:
        drawn = unit_hash(seed, F.col("u"), F.col("w"), "pool") < w.pool
        pairs = pairs.where((F.col("same") | drawn) if w.matching else drawn)
    return pairs


def simulate_votes(pairs: DataFrame, voters: int, err: float, seed: int = SEED, hard: bool = False) -> DataFrame:
    """Votes (u, w, worker, yes): wrong with chance ``err``, or with twice that on a hashed half of the pairs if ``hard``."""
    chance = F.when(unit_hash(seed, F.col("u"), F.col("w"), "hard") < 0.5, 2 * err).otherwise(0.0) if hard else F.lit(err)
    each = pairs.select("u", "w", "same", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(voters - 1).cast("long"))).alias("worker"))
    wrong = unit_hash(seed, F.col("u"), F.col("w"), F.col("worker")) < chance
    return each.select("u", "w", "worker", (F.col("same") != wrong).alias("yes"))


def votes(spark: SparkSession, sf_dir: str, name: str, seed: int = SEED, err: float | None = None) -> DataFrame:
    w = WORKLOADS[name]
    return simulate_votes(pool(gold(spark, sf_dir, name), name), w.voters, w.err if err is None else err, seed)


def event_votes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Votes that the event stream carries: k is the pair (k div 10, 10 + k mod 10); an 'error' event is a wrong vote."""
    e = spark.read.parquet(f"{sf_dir}/events.parquet").select("event_id", "ts", "user_id", "event_type", F.get_json_object("props", "$.k").cast("long").alias("k"))
    u, w = F.floor(F.col("k") / 10), 10 + F.col("k") % 10
    rows = e.select("event_id", "ts", u.alias("u"), w.alias("w"), F.col("user_id").alias("worker"), ((u % 5 == w % 5) != (F.col("event_type") == "error")).alias("yes"))
    return canonical_votes(rows, "event_id")


def event_gold(spark: SparkSession) -> DataFrame:
    return spark.range(20).select(F.col("id").alias("rid"), (F.col("id") % 5).cast("string").alias("entity"))


def lineitem_votes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Suppliers of one order are a pair; two lines vote YES if their return flags agree."""
    li = spark.read.parquet(f"{sf_dir}/lineitem.parquet").select("l_orderkey", "l_linenumber", "l_suppkey", "l_returnflag")
    a, b = (li.select("l_orderkey", *(F.col(c).alias(f"{p}{c[2:]}") for c in ("l_linenumber", "l_suppkey", "l_returnflag"))) for p in ("a_", "b_"))
    met = a.join(b, "l_orderkey").where("a_suppkey < b_suppkey AND a_linenumber <> b_linenumber")
    return met.select(F.col("a_suppkey").alias("u"), F.col("b_suppkey").alias("w"), F.col("l_orderkey").alias("worker"), (F.col("a_returnflag") == F.col("b_returnflag")).alias("yes"))


def gold_clusters(records: DataFrame) -> DataFrame:
    least = records.groupBy("entity").agg(F.min("rid").alias("cid"))
    return records.join(least, "entity").select("rid", "cid")


def part_gold(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/part.parquet").select(F.col("p_partkey").cast("long").alias("rid"), F.col("p_name").alias("entity"))


def part_votes(spark: SparkSession, sf_dir: str, voters: int = 5, err: float = 0.05, seed: int = SEED) -> DataFrame:
    """Simulated votes on the parts that stand in one order: a sparse graph that grows with the table."""
    li = spark.read.parquet(f"{sf_dir}/lineitem.parquet").select("l_orderkey", "l_partkey")
    a, b = (li.select("l_orderkey", F.col("l_partkey").alias(c)) for c in ("u", "w"))
    # votes are drawn where the pairs are, so these lie in as many partitions as are asked for
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    pairs = a.join(b, "l_orderkey").where("u < w").select("u", "w").repartition(parts, "u", "w").distinct()
    ends = [part_gold(spark, sf_dir).select(F.col("rid").alias(c), F.col("entity").alias(f"e{c}")) for c in ("u", "w")]
    return simulate_votes(pairs.join(ends[0], "u").join(ends[1], "w").select("u", "w", (F.col("eu") == F.col("ew")).alias("same")), voters, err, seed)


def document_gold(spark: SparkSession, sf_dir: str, least: float = 0.5, width: int = 5) -> DataFrame:
    """Documents that have near copies, with their group as entity: components of pairs of at least that shingle similarity.

    Texts of equal words are one from the start. No pair is left out: similar sets share one of their first shingles
    (``first_shingles``). First the others that share one are compared with the least text of each shingle, which joins
    most groups; then texts of different groups with each other. Similarity is exact on the sets of all shingles.
    """
    from crowdlink.graph import components

    words = F.array(F.filter(F.split(F.lower("text"), r"[^\p{L}\p{N}]+"), lambda w: w != ""))  # computed once
    runs = F.transform(words, lambda w: F.array_distinct(F.transform(F.sequence(F.lit(1), F.greatest(F.size(w) - (width - 1), F.lit(1))), lambda i: F.xxhash64(F.array_join(F.slice(w, i, width), " ")))))[0]
    d = cut(spark.read.parquet(f"{sf_dir}/documents.parquet").where("text IS NOT NULL").select("doc_id", runs.alias("s"), F.xxhash64(F.array_join(words[0], " ")).alias("h")), "shingles")
    one = cut(d.groupBy("h").agg(F.min("doc_id").alias("rid"), F.any_value("s").alias("s")), "texts")
    met = cut(first_shingles(one, least), "first")

    def near(pairs: DataFrame) -> DataFrame:
        both = pairs.join(one.select(F.col("rid").alias("u"), F.col("s").alias("a")), "u").join(one.select(F.col("rid").alias("w"), F.col("s").alias("b")), "w")
        return cut(both.where(F.size(F.array_intersect("a", "b")) >= least * F.size(F.array_union("a", "b"))).select("u", "w"), "near")

    heads = met.groupBy("key").agg(F.min("rid").alias("u"))
    first = near(met.join(heads, "key").where("rid <> u").select("u", F.col("rid").alias("w")).distinct())
    known = components(first).select(F.col("id").alias("rid"), "component")
    parted = met.join(known, "rid", "left").withColumn("part", F.coalesce("component", "rid")).drop("component")
    several = parted.groupBy("key").agg(F.min("part").alias("low"), F.max("part").alias("high")).where("low <> high").select("key")
    parted = cut(parted.join(several, "key", "left_semi"), "parted")
    x, y = (parted.select("key", *(F.col(c).alias(f"{c}_{k}") for c in ("rid", "part", "size", "place"))) for k in "xy")
    left = 1 + F.least(F.col("size_x") - F.col("place_x"), F.col("size_y") - F.col("place_y"))  # most that they share if this is the first
    may = (F.col("part_x") < F.col("part_y")) & (left * (1 + least) >= least * (F.col("size_x") + F.col("size_y")) - 1e-6)
    second = near(x.join(y, "key").where(may).select(F.col("rid_x").alias("u"), F.col("rid_y").alias("w")).distinct())
    copies = d.join(one.select("h", F.col("rid").alias("u")), "h").select("u", F.col("doc_id").alias("w"))
    group = components(first.unionByName(second).unionByName(copies)).groupBy("component").agg(F.collect_list("id").alias("ids")).where(F.size("ids") > 1)
    return group.select(F.explode("ids").alias("rid"), F.col("component").cast("string").alias("entity"))


def first_shingles(one: DataFrame, least: float) -> DataFrame:
    """Rows (key, rid, size, place): of sets (rid, s) the keys by which they can meet, with their places in the set.

    Keys are in the order of how many sets have them. Sets of at least that similarity share more keys than stand
    behind the first ``size - least * size + 1`` of either, so the first that they share is among these in both.
    """
    each = one.select("rid", F.size("s").alias("size"), F.explode("s").alias("key"))
    shared = each.withColumn("n", F.count("*").over(Window.partitionBy("key"))).where("n > 1")  # the others stand before these
    own = shared.groupBy("rid", "size").agg(F.array_sort(F.collect_list(F.struct("n", "key"))).alias("keys"))
    alone = F.col("size") - F.size("keys")
    count = (F.col("size") - F.ceil(least * F.col("size") - 1e-6) + 1).cast("int") - alone
    some = own.where(count > 0).select("rid", "size", alone.alias("alone"), F.posexplode(F.slice("keys", F.lit(1), count)).alias("at", "k"))
    return some.select("k.key", "rid", "size", (F.col("alone") + F.col("at") + 1).alias("place"))
