"""Relational, window, set, function, blocking, user-function, source and streaming operators around the methods."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from crowdlink import graph
from crowdlink.functions import udx
from crowdlink.sources import workloads as W
from crowdlink.storage import cut, new_path
from crowdlink.streaming import answers as S

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


def t(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


@query("SELECT o_orderkey, o_custkey, o_orderstatus FROM orders WHERE o_orderkey BETWEEN 10 AND 5000 AND o_orderstatus IN ('F', 'O') AND o_orderpriority LIKE '1%'")
def scan_project_filter(spark, sf_dir):
    return t(spark, sf_dir, "orders").where(F.col("o_orderkey").between(10, 5000) & F.col("o_orderstatus").isin("F", "O") & F.col("o_orderpriority").like("1%")).select("o_orderkey", "o_custkey", "o_orderstatus")


@query("SELECT n_name, r_name FROM nation JOIN region ON n_regionkey = r_regionkey")
def join_broadcast(spark, sf_dir):
    return t(spark, sf_dir, "nation").join(F.broadcast(t(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey")).select("n_name", "r_name")


@query("SELECT o_orderkey, c_mktsegment FROM orders JOIN customer ON o_custkey = c_custkey")
def join_inner(spark, sf_dir):
    return t(spark, sf_dir, "orders").join(t(spark, sf_dir, "customer"), F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_mktsegment")


@query("SELECT c_custkey, count(o_orderkey) AS n_orders FROM customer LEFT JOIN orders ON o_custkey = c_custkey GROUP BY c_custkey")
def join_left(spark, sf_dir):
    return t(spark, sf_dir, "customer").join(t(spark, sf_dir, "orders"), F.col("o_custkey") == F.col("c_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n_orders"))


@query("SELECT d.doc_id, toxic FROM labels l RIGHT JOIN documents d ON l.doc_id = d.doc_id")
def join_right(spark, sf_dir):
    labels = t(spark, sf_dir, "labels").withColumnRenamed("doc_id", "k")
    return labels.join(t(spark, sf_dir, "documents"), F.col("k") == F.col("doc_id"), "right").select("doc_id", "toxic")


@query("""SELECT coalesce(a.rid, b.rid) AS rid, a.cid AS before, b.cid AS after FROM (SELECT s_suppkey AS rid, s_nationkey AS cid FROM supplier WHERE s_suppkey % 3 <> 0) a
FULL JOIN (SELECT s_suppkey AS rid, s_nationkey % 7 AS cid FROM supplier WHERE s_suppkey % 4 <> 0) b ON a.rid = b.rid WHERE a.cid IS DISTINCT FROM b.cid""")
def join_full_moved_records(spark, sf_dir):
    """Records whose cluster changed, appeared or went, between two clusterings."""
    s = t(spark, sf_dir, "supplier")
    a = s.where("s_suppkey % 3 <> 0").select(F.col("s_suppkey").alias("rid"), F.col("s_nationkey").alias("before"))
    b = s.where("s_suppkey % 4 <> 0").select(F.col("s_suppkey").alias("rid"), (F.col("s_nationkey") % 7).alias("after"))
    return a.join(b, "rid", "full").where(~F.col("before").eqNullSafe(F.col("after")))


@query("SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
def join_semi(spark, sf_dir):
    return t(spark, sf_dir, "documents").select("doc_id").join(t(spark, sf_dir, "labels"), "doc_id", "left_semi")


@query("SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def join_anti(spark, sf_dir):
    return t(spark, sf_dir, "documents").select("doc_id").join(t(spark, sf_dir, "labels"), "doc_id", "left_anti")


@query("SELECT count(*) AS pairs FROM supplier a JOIN supplier b ON a.s_nationkey IS NOT DISTINCT FROM b.s_nationkey AND a.s_suppkey < b.s_suppkey")
def join_null_safe(spark, sf_dir):
    a, b = (t(spark, sf_dir, "supplier").alias(x) for x in "ab")
    return a.join(b, F.col("a.s_nationkey").eqNullSafe(F.col("b.s_nationkey")) & (F.col("a.s_suppkey") < F.col("b.s_suppkey"))).agg(F.count("*").alias("pairs"))


@query("SELECT count(*) AS pairs FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey")
def join_range(spark, sf_dir):
    a, b = (t(spark, sf_dir, "nation").alias(x) for x in "ab")
    return a.join(F.broadcast(b), F.col("a.n_nationkey") < F.col("b.n_nationkey")).agg(F.count("*").alias("pairs"))


@query("""SELECT v.event_id, max(c.event_id) AS clustering FROM events v LEFT JOIN (SELECT * FROM events WHERE event_type = 'purchase') c
ON v.user_id = c.user_id AND c.ts <= v.ts AND c.event_id <= v.event_id GROUP BY v.event_id""")
def join_asof(spark, sf_dir):
    """The latest snapshot at each vote: one pass over the union in time order, no pairs."""
    e = t(spark, sf_dir, "events")
    line = Window.partitionBy("user_id").orderBy("ts", "event_id")
    last = F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(line)
    return e.select("event_id", last.alias("clustering"))


@query("""SELECT q.event_id AS question, count(a.event_id) AS answers FROM events q LEFT JOIN events a ON q.user_id = a.user_id AND a.ts > q.ts AND a.ts <= q.ts + INTERVAL 6 HOUR
WHERE q.event_type = 'click' GROUP BY 1""")
def join_interval(spark, sf_dir):
    e = t(spark, sf_dir, "events").select("event_id", "user_id", "ts", "event_type")
    q, a = e.where("event_type = 'click'").alias("q"), e.alias("a")
    met = (F.col("q.user_id") == F.col("a.user_id")) & (F.col("a.ts") > F.col("q.ts")) & (F.col("a.ts") <= F.col("q.ts") + F.expr("INTERVAL 6 HOURS"))
    return q.join(a, met, "left").groupBy(F.col("q.event_id").alias("question")).agg(F.count("a.event_id").alias("answers"))


@query("SELECT l_returnflag, count(*) AS n, round(sum(l_quantity), 2) AS qty, round(avg(l_discount), 6) AS disc, min(l_tax) AS lo, max(l_tax) AS hi FROM lineitem GROUP BY 1")
def agg_basic(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("qty"), F.round(F.avg("l_discount"), 6).alias("disc"), F.min("l_tax").alias("lo"), F.max("l_tax").alias("hi"))


@query("SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY 1")
def agg_distinct(spark, sf_dir):
    return t(spark, sf_dir, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"))


@query("SELECT s_nationkey, round(product(0.5 + s_acctbal / 40000), 9) AS p FROM supplier GROUP BY 1")
def agg_product(spark, sf_dir):
    return t(spark, sf_dir, "supplier").groupBy("s_nationkey").agg(F.round(F.product(0.5 + F.col("s_acctbal") / 40000), 9).alias("p"))


@query("SELECT s_nationkey, max(s_acctbal) AS most, arg_max(s_suppkey, (s_acctbal, s_suppkey)) AS who FROM supplier GROUP BY 1")
def agg_argmax(spark, sf_dir):
    return t(spark, sf_dir, "supplier").groupBy("s_nationkey").agg(F.max("s_acctbal").alias("most"), F.max_by("s_suppkey", F.struct("s_acctbal", "s_suppkey")).alias("who"))


@query("SELECT round(quantile_cont(value, 0.5), 6) AS median, round(stddev_samp(value), 6) AS sd FROM events")
def agg_percentile(spark, sf_dir):
    return t(spark, sf_dir, "events").agg(F.round(F.percentile("value", F.lit(0.5)), 6).alias("median"), F.round(F.stddev("value"), 6).alias("sd"))


@query("SELECT l_returnflag, l_linestatus, count(*) AS n, grouping_id(l_returnflag, l_linestatus)::BIGINT AS g FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def agg_cube(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.grouping_id().alias("g"))


@query("SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")
def agg_grouping_sets(spark, sf_dir):
    flag, status = F.col("l_returnflag"), F.col("l_linestatus")
    return t(spark, sf_dir, "lineitem").groupingSets([[flag], [status], []], flag, status).agg(F.count("*").alias("n"))


@query("SELECT o_orderstatus, count(*) FILTER (o_orderpriority LIKE '1%') AS urgent, count(*) FILTER (o_orderpriority LIKE '5%') AS low FROM orders GROUP BY 1")
def agg_pivot(spark, sf_dir):
    kind = F.when(F.col("o_orderpriority").like("1%"), "urgent").when(F.col("o_orderpriority").like("5%"), "low")
    return t(spark, sf_dir, "orders").withColumn("kind", kind).groupBy("o_orderstatus").pivot("kind", ["urgent", "low"]).count().na.fill(0)


@query("""SELECT s_suppkey, row_number() OVER w AS rn, rank() OVER (PARTITION BY s_nationkey ORDER BY floor(s_acctbal / 1000)) AS rk, dense_rank() OVER (PARTITION BY s_nationkey ORDER BY floor(s_acctbal / 1000)) AS dr,
ntile(4) OVER w AS q FROM supplier WINDOW w AS (PARTITION BY s_nationkey ORDER BY s_acctbal, s_suppkey)""")
def win_rank(spark, sf_dir):
    w, c = Window.partitionBy("s_nationkey").orderBy("s_acctbal", "s_suppkey"), Window.partitionBy("s_nationkey").orderBy(F.floor(F.col("s_acctbal") / 1000))
    return t(spark, sf_dir, "supplier").select("s_suppkey", F.row_number().over(w).alias("rn"), F.rank().over(c).alias("rk"), F.dense_rank().over(c).alias("dr"), F.ntile(4).over(w).alias("q"))


@query("""SELECT conv_id, turn, lag(role) OVER w AS before, lead(role) OVER w AS after, first(role) OVER w AS opener FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)""")
def win_offset(spark, sf_dir):
    w = Window.partitionBy("conv_id").orderBy("turn")
    return t(spark, sf_dir, "conversations").select("conv_id", "turn", F.lag("role").over(w).alias("before"), F.lead("role").over(w).alias("after"), F.first("role").over(w).alias("opener"))


@query("SELECT event_id, sum(1) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING)::BIGINT AS cost FROM events")
def win_running_cost(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return t(spark, sf_dir, "events").select("event_id", F.sum(F.lit(1)).over(w).alias("cost"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS last_hour FROM events")
def win_range(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("us").rangeBetween(-3_600_000_000, 0)
    return t(spark, sf_dir, "events").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp"))).select("event_id", F.count("*").over(w).alias("last_hour"))


@query("SELECT p_partkey, p_retailprice FROM part ORDER BY p_retailprice DESC, p_partkey LIMIT 20")
def topk_global(spark, sf_dir):
    return t(spark, sf_dir, "part").select("p_partkey", "p_retailprice").orderBy(F.desc("p_retailprice"), "p_partkey").limit(20)


@query("SELECT p_partkey, p_brand FROM part QUALIFY row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) <= 3")
def topk_per_unit(spark, sf_dir):
    w = Window.partitionBy("p_brand").orderBy(F.desc("p_retailprice"), "p_partkey")
    return t(spark, sf_dir, "part").withColumn("rn", F.row_number().over(w)).where("rn <= 3").select("p_partkey", "p_brand")


@query("""SELECT s_suppkey, round(percent_rank() OVER w, 8) AS pr, round(cume_dist() OVER w, 8) AS cd, nth_value(s_suppkey, 2) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second
FROM supplier WINDOW w AS (PARTITION BY s_nationkey ORDER BY s_acctbal, s_suppkey)""")
def win_distribution(spark, sf_dir):
    w = Window.partitionBy("s_nationkey").orderBy("s_acctbal", "s_suppkey")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return t(spark, sf_dir, "supplier").select("s_suppkey", F.round(F.percent_rank().over(w), 8).alias("pr"), F.round(F.cume_dist().over(w), 8).alias("cd"), F.nth_value("s_suppkey", 2).over(whole).alias("second"))


@query("""SELECT o_orderstatus, kind, n FROM (SELECT o_orderstatus, count(*) FILTER (o_orderpriority LIKE '1%') AS urgent, count(*) FILTER (o_orderpriority LIKE '5%') AS low FROM orders GROUP BY 1)
UNPIVOT (n FOR kind IN (urgent, low))""")
def agg_unpivot(spark, sf_dir):
    return agg_pivot(spark, sf_dir).unpivot("o_orderstatus", ["urgent", "low"], "kind", "n")


@query("SELECT n_nationkey AS k FROM nation UNION SELECT s_nationkey FROM supplier")
def set_union(spark, sf_dir):
    return t(spark, sf_dir, "nation").select(F.col("n_nationkey").alias("k")).union(t(spark, sf_dir, "supplier").select("s_nationkey")).distinct()


@query("SELECT n_nationkey AS k FROM nation UNION ALL SELECT s_nationkey FROM supplier")
def set_union_all(spark, sf_dir):
    return t(spark, sf_dir, "nation").select(F.col("n_nationkey").alias("k")).union(t(spark, sf_dir, "supplier").select("s_nationkey"))


@query("SELECT doc_id FROM documents INTERSECT SELECT doc_id FROM labels WHERE toxic = 0")
def set_intersect(spark, sf_dir):
    return t(spark, sf_dir, "documents").select("doc_id").intersect(t(spark, sf_dir, "labels").where("toxic = 0").select("doc_id"))


@query("SELECT s_nationkey AS k FROM supplier EXCEPT ALL SELECT n_nationkey FROM nation")
def set_except(spark, sf_dir):
    return t(spark, sf_dir, "supplier").select(F.col("s_nationkey").alias("k")).exceptAll(t(spark, sf_dir, "nation").select("n_nationkey"))


@query("SELECT s_suppkey, lower(s_name) AS low, length(s_name) AS n, md5(s_name) AS h, levenshtein(s_name, 'Supplier#5')::INT AS d, substr(s_name, 1, 4) AS s, translate(s_name, '#', '-') AS tr FROM supplier")
def fn_string(spark, sf_dir):
    c = F.col("s_name")
    return t(spark, sf_dir, "supplier").select("s_suppkey", F.lower(c).alias("low"), F.length(c).alias("n"), F.md5(c).alias("h"), F.levenshtein(c, F.lit("Supplier#5")).alias("d"), F.substring(c, 1, 4).alias("s"), F.translate(c, "#", "-").alias("tr"))


@query("SELECT event_id, date_trunc('hour', ts) AS h, year(ts)::INT AS y, dayofweek(ts)::INT + 1 AS d FROM events")
def fn_date(spark, sf_dir):
    return t(spark, sf_dir, "events").select("event_id", F.date_trunc("hour", "ts").cast("timestamp_ntz").alias("h"), F.year("ts").alias("y"), F.dayofweek("ts").alias("d"))


@query("SELECT p_partkey, round(log10(p_retailprice), 6) AS l, round(sqrt(p_size), 6) AS r, greatest(p_size, 10) AS g, bit_count(p_partkey)::INT AS b, (p_partkey >> 2) AS s FROM part")
def fn_math(spark, sf_dir):
    return t(spark, sf_dir, "part").select("p_partkey", F.round(F.log10("p_retailprice"), 6).alias("l"), F.round(F.sqrt("p_size"), 6).alias("r"), F.greatest("p_size", F.lit(10)).alias("g"), F.bit_count("p_partkey").alias("b"), F.shiftright("p_partkey", 2).alias("s"))


@query("SELECT vec_id, len(embedding) AS n, round(sqrt(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x))), 6) AS norm FROM embeddings")
def fn_array(spark, sf_dir):
    norm = F.sqrt(F.aggregate(F.transform("embedding", lambda x: x.cast("double") * x), F.lit(0.0), lambda a, x: a + x))
    return t(spark, sf_dir, "embeddings").select("vec_id", F.size("embedding").cast("long").alias("n"), F.round(norm, 6).alias("norm"))


@query("SELECT p_partkey, p_brand AS brand, p_size::VARCHAR AS size FROM part")
def fn_map(spark, sf_dir):
    attrs = F.create_map(F.lit("brand"), F.col("p_brand"), F.lit("size"), F.col("p_size").cast("string"))
    return t(spark, sf_dir, "part").withColumn("attrs", attrs).select("p_partkey", F.element_at("attrs", "brand").alias("brand"), F.element_at("attrs", "size").alias("size"))


@query("SELECT event_id, json_extract_string(props, '$.k')::INT AS k FROM events")
def fn_json(spark, sf_dir):
    return t(spark, sf_dir, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k"))


@query("SELECT p_partkey, '{\"rid\":' || p_partkey || ',\"brand\":\"' || p_brand || '\"}' AS question FROM part")
def fn_to_json(spark, sf_dir):
    return t(spark, sf_dir, "part").select("p_partkey", F.to_json(F.struct(F.col("p_partkey").alias("rid"), F.col("p_brand").alias("brand"))).alias("question"))


@query("SELECT page_id, regexp_extract(html, '<title>([^<]*)</title>', 1) AS title FROM pages")
def fn_html_title(spark, sf_dir):
    return t(spark, sf_dir, "pages").select("page_id", F.regexp_extract("html", "<title>([^<]*)</title>", 1).alias("title"))


@query("SELECT doc_id, sha256(text) AS h FROM documents")
def fn_hash(spark, sf_dir):
    return t(spark, sf_dir, "documents").select("doc_id", F.sha2("text", 256).alias("h"))


@query("SELECT min(doc_id) AS head, count(*) AS n FROM documents GROUP BY text HAVING count(*) > 1")
def block_exact(spark, sf_dir):
    d = t(spark, sf_dir, "documents").select("doc_id", F.sha2("text", 256).alias("h"))
    return d.groupBy("h").agg(F.min("doc_id").alias("head"), F.count("*").alias("n")).where("n > 1").drop("h")


@query("SELECT p_partkey AS u, lead(p_partkey) OVER (PARTITION BY p_brand ORDER BY p_name, p_partkey) AS w FROM part")
def block_sorted_neighbourhood(spark, sf_dir):
    w = Window.partitionBy("p_brand").orderBy("p_name", "p_partkey")
    return t(spark, sf_dir, "part").select(F.col("p_partkey").alias("u"), F.lead("p_partkey").over(w).alias("w"))


@query()
def block_minhash(spark, sf_dir):
    """Buckets of documents that share the least hash of their words' triples, for four hashes."""
    # the split stands in an array of one, so that it is not computed anew for each triple
    words = F.array(F.split(F.lower("text"), r"\s+"))
    triples = F.transform(words, lambda w: F.array_distinct(F.transform(F.sequence(F.lit(1), F.greatest(F.size(w) - 2, F.lit(1))), lambda i: F.array_join(F.slice(w, i, 3), " "))))[0]
    d = t(spark, sf_dir, "documents").select("doc_id", triples.alias("s"))
    keys = F.array(*(F.array_min(F.transform("s", _seeded(k))) for k in range(4)))
    return d.select("doc_id", F.posexplode(keys).alias("table", "key")).groupBy("table", "key").agg(F.min("doc_id").alias("head"), F.count("*").alias("n")).where("n > 1")


def _seeded(k: int):
    return lambda x: F.xxhash64(F.lit(k), x)


@query("SELECT event_id, (SELECT sum(d::INT) FROM (SELECT unnest(string_split(json_extract_string(props, '$.k'), '')) AS d))::INT AS s FROM events")
def udf_scalar(spark, sf_dir):
    return t(spark, sf_dir, "events").select("event_id", udx.digit_sum("props").alias("s"))


@query("SELECT s_nationkey, round(1 - product(1 - (s_acctbal + 1000) / 20000), 9) AS p FROM supplier GROUP BY 1")
def udaf_noisy_or(spark, sf_dir):
    s = t(spark, sf_dir, "supplier").select("s_nationkey", ((F.col("s_acctbal") + 1000) / 20000).alias("x"))
    return s.groupBy("s_nationkey").agg(F.round(udx.noisy_or("x"), 9).alias("p"))


@query("SELECT a.n_nationkey::BIGINT AS u, b.n_nationkey::BIGINT AS w FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
def udtf_pairs(spark, sf_dir):
    udx.register(spark)
    t(spark, sf_dir, "nation").groupBy("n_regionkey").agg(F.collect_list(F.col("n_nationkey").cast("long")).alias("ids")).createOrReplaceTempView("nation_blocks")
    return spark.sql("SELECT p.u, p.w FROM nation_blocks, LATERAL pairs_of(ids) p")


@query("SELECT a.vec_id AS u, b.vec_id AS w, round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 5) AS c FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1")
def vector_cosine(spark, sf_dir):
    a, b = (t(spark, sf_dir, "embeddings").select(F.col("vec_id").alias(k), F.col("embedding").alias(f"e{k}")) for k in ("u", "w"))
    return a.join(b, F.col("w") == F.col("u") + 1).select("u", "w", F.round(udx.cosine(F.col("eu"), F.col("ew")), 5).alias("c"))


@query("SELECT o_orderkey, o_totalprice FROM orders")
def source_round_trips(spark, sf_dir):
    """The same rows through CSV, JSON, ORC and Parquet with a declared schema: what all four give."""
    rows, schema, out = t(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice"), "o_orderkey long, o_totalprice double", None
    for kind in ("csv", "json", "orc", "parquet"):
        path = new_path(spark, f"round-trip-{kind}")
        rows.write.format(kind).save(path)
        back = spark.read.schema(schema).format(kind).load(path)
        out = back if out is None else out.intersectAll(back)
    return out


@query("SELECT o_orderstatus, count(*) AS n, count(*) FILTER (o_orderpriority LIKE '1%') AS urgent FROM orders GROUP BY 1")
def sink_partitioned(spark, sf_dir):
    """Rows written by directories of one column and read with only the directories of a filter."""
    path = new_path(spark, "sink")
    t(spark, sf_dir, "orders").select("o_orderkey", "o_orderpriority", "o_orderstatus").write.partitionBy("o_orderstatus").parquet(path)
    return spark.read.parquet(path).where("o_orderstatus IS NOT NULL").groupBy("o_orderstatus").agg(F.count("*").alias("n"), F.count_if(F.col("o_orderpriority").like("1%")).alias("urgent"))


@query("SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
def sink_bucketed(spark, sf_dir):
    """Two tables in buckets of their join key, which then join without a shuffle of either."""
    names = []
    for name, key, columns in (("orders", "o_custkey", ["o_custkey", "o_orderkey"]), ("customer", "c_custkey", ["c_custkey", "c_mktsegment"])):
        path = new_path(spark, f"bucketed-{name}")
        names.append(path.rsplit("/", 1)[1].replace("-", "_"))
        t(spark, sf_dir, name).select(*columns).write.bucketBy(8, key).sortBy(key).option("path", path).saveAsTable(names[-1])
    o, c = map(spark.table, names)
    return o.join(c, F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n"))


@query("SELECT n_nationkey, n_name FROM nation")
def sink_json(spark, sf_dir):
    """Lines of JSON, as questions go to a crowd, and back."""
    path = new_path(spark, "questions")
    t(spark, sf_dir, "nation").select(F.to_json(F.struct("n_nationkey", "n_name")).alias("value")).write.text(path)
    return spark.read.schema("n_nationkey int, n_name string").json(path)


@query("""WITH RECURSIVE below(k, level) AS (SELECT n_nationkey, 0 FROM nation WHERE n_nationkey = 0 UNION SELECT b.n_nationkey, level + 1 FROM below JOIN nation a ON a.n_nationkey = k JOIN nation b ON b.n_regionkey = a.n_regionkey WHERE level < 2)
SELECT k, min(level) AS level FROM below GROUP BY k""")
def sql_recursive(spark, sf_dir):
    """Reachable nations by recursive SQL, bounded in depth and made distinct outside."""
    t(spark, sf_dir, "nation").createOrReplaceTempView("nation_graph")
    return spark.sql("""WITH RECURSIVE below(k, level) AS (SELECT n_nationkey, 0 FROM nation_graph WHERE n_nationkey = 0 UNION ALL
        SELECT b.n_nationkey, level + 1 FROM below JOIN nation_graph a ON a.n_nationkey = k JOIN nation_graph b ON b.n_regionkey = a.n_regionkey WHERE level < 2)
        SELECT k, min(level) AS level FROM below GROUP BY k""")


LINKS = """WITH RECURSIVE e AS (SELECT DISTINCT l_suppkey AS u, 1000000 + l_orderkey AS w FROM lineitem)
"""


@query(LINKS + "SELECT id, count(*) AS degree FROM (SELECT u AS id FROM e UNION ALL SELECT w FROM e) GROUP BY id")
def graph_degrees(spark, sf_dir):
    return graph.degrees(_links(spark, sf_dir))


@query(LINKS + """, b AS (SELECT u AS x, w AS y FROM e UNION ALL SELECT w, u FROM e), s AS (SELECT min(u) AS id FROM e),
l1 AS (SELECT DISTINCT y AS id FROM b JOIN s ON x = id), l2 AS (SELECT DISTINCT y AS id FROM b JOIN l1 ON x = id WHERE y NOT IN (SELECT id FROM s)),
l3 AS (SELECT DISTINCT y AS id FROM b JOIN l2 ON x = id WHERE y NOT IN (SELECT id FROM l1))
SELECT id, 0 AS level FROM s UNION ALL SELECT id, 1 FROM l1 UNION ALL SELECT id, 2 FROM l2 UNION ALL SELECT id, 3 FROM l3""")
def graph_levels(spark, sf_dir):
    """Three levels breadth first from the first supplier, over the orders."""
    links = _links(spark, sf_dir)
    return graph.levels(links, links.agg(F.min("u").alias("id")), most=3)


def _links(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").select(F.col("l_suppkey").alias("u"), (F.col("l_orderkey") + 1_000_000).alias("w")).distinct()


@query("""WITH e AS (SELECT DISTINCT least(a.l_partkey, b.l_partkey) AS u, greatest(a.l_partkey, b.l_partkey) AS w FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey)
SELECT count(*) AS triangles FROM e a JOIN e b ON b.u = a.w JOIN e c ON c.u = a.u AND c.w = b.w""")
def graph_triangles(spark, sf_dir):
    """Triangles among parts that stand in one order."""
    orders = t(spark, sf_dir, "lineitem").where("l_orderkey IS NOT NULL").groupBy("l_orderkey").agg(F.array_sort(F.collect_set("l_partkey")).alias("parts"))
    ends = orders.select("parts", F.posexplode("parts").alias("at", "u"))
    return graph.count_triangles(ends.select("u", F.explode(F.slice("parts", F.col("at") + 2, F.size("parts"))).alias("w")))


@query("SELECT world, u::BIGINT AS u, w::BIGINT AS w FROM (VALUES (0, 0, 1), (1, 0, 2), (2, 1, 2)) e(bit, u, w), range(8) r(world) WHERE (world >> bit) & 1 = 1")
def udtf_worlds(spark, sf_dir):
    """The chosen edges of each world of a triangle."""
    udx.register(spark)
    return spark.sql("SELECT world, CASE edge WHEN 2 THEN 1L ELSE 0L END AS u, CASE edge WHEN 0 THEN 1L ELSE 2L END AS w FROM possible_worlds(3)")


@query("SELECT n_regionkey AS region, min(range) AS gap FROM range(26), (SELECT DISTINCT n_regionkey FROM nation) r WHERE (range, n_regionkey) NOT IN (SELECT (n_nationkey, n_regionkey) FROM nation) GROUP BY 1")
def udtf_next_gap(spark, sf_dir):
    """The least number that a region's nations leave out."""
    udx.register(spark)
    t(spark, sf_dir, "nation").groupBy("n_regionkey").agg(F.collect_list(F.col("n_nationkey").cast("long")).alias("taken")).createOrReplaceTempView("nation_taken")
    return spark.sql("SELECT n_regionkey AS region, g.gap FROM nation_taken, LATERAL next_gap(taken) g")


@query("SELECT s_nationkey AS k, count(*) AS suppliers, (SELECT count(*) FROM customer WHERE c_nationkey = s_nationkey)::BIGINT AS customers FROM supplier GROUP BY s_nationkey")
def cogroup_counts(spark, sf_dir):
    """Two tables' rows of one key side by side in one call."""
    import pandas as pd

    def both(key, a, b):
        return pd.DataFrame({"k": [key[0]], "suppliers": [len(a)], "customers": [len(b)]})

    a = t(spark, sf_dir, "supplier").select(F.col("s_nationkey").alias("k")).groupBy("k")
    b = t(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("k")).groupBy("k")
    return a.cogroup(b).applyInPandas(both, "k int, suppliers long, customers long").where("suppliers > 0")


@query()
def block_jaccard(spark, sf_dir):
    """Entities of near-copied documents: groups by exact similarity of word shingles."""
    return W.document_gold(spark, sf_dir).groupBy("entity").agg(F.count("*").alias("n"))


@query()
def block_vectors(spark, sf_dir):
    """Buckets of vectors by the signs of eight random projections: candidates for equal labels."""
    import numpy as np

    planes = np.random.default_rng(7).standard_normal((8, 64)).round(6).tolist()
    dot = lambda row: F.aggregate(F.zip_with("embedding", F.array(*map(F.lit, row)), lambda x, y: x * y), F.lit(0.0), lambda a, x: a + x)
    key = sum(((dot(row) > 0).cast("int") * (1 << k) for k, row in enumerate(planes)), F.lit(0))
    return t(spark, sf_dir, "embeddings").select(key.alias("bucket"), "vec_id").groupBy("bucket").agg(F.min("vec_id").alias("head"), F.count("*").alias("n")).where("n > 1")


VOTED = """SELECT u, w, v AS worker, (u % 5 = w % 5) <> (('0x' || substr(md5('42|' || u || '|' || w || '|' || v), 1, 8))::BIGINT / 4294967296.0 < 0.1) AS yes
FROM (SELECT DISTINCT k // 10 AS u, 10 + k % 10 AS w FROM (SELECT json_extract_string(props, '$.k')::BIGINT AS k FROM events)), range(5) c(v) WHERE u < w AND w < 30"""


def _asked(spark, sf_dir):
    """The pairs that the events ask."""
    k = F.get_json_object("props", "$.k").cast("long")
    return t(spark, sf_dir, "events").select(F.floor(k / 10).alias("u"), (10 + k % 10).alias("w")).distinct()


@query(VOTED)
def source_crowd_votes(spark, sf_dir):
    """The vote source's answers on the pairs that the events ask."""
    from crowdlink.sources.crowd import CrowdVotes

    spark.dataSource.register(CrowdVotes)
    votes = spark.read.format("crowd_votes").option("records", 30).option("err", 0.1).load()
    return votes.join(_asked(spark, sf_dir), ["u", "w"], "left_semi")


# streams run to what is there


@query("SELECT u, w, count(*)::INT AS n_votes, sum(yes::INT)::INT AS n_yes FROM (SELECT k // 10 AS u, 10 + k % 10 AS w, ((k // 10) % 5 = (10 + k % 10) % 5) <> (event_type = 'error') AS yes FROM (SELECT *, json_extract_string(props, '$.k')::BIGINT AS k FROM events)) GROUP BY 1, 2")
def stream_edges(spark, sf_dir):
    return S.run_once(S.edge_state(S.vote_stream(spark, sf_dir)), "stream_edges", "complete")


@query("SELECT time_bucket(INTERVAL 6 HOUR, ts) AS start, count(*) AS n_votes, sum((event_type = 'error')::INT)::BIGINT AS n_wrong FROM events GROUP BY 1")
def stream_tumbling(spark, sf_dir):
    return S.run_once(S.windowed(S.vote_stream(spark, sf_dir)), "stream_tumbling", "complete").withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("""SELECT start, count(*) AS n_votes, sum(wrong)::BIGINT AS n_wrong FROM (SELECT unnest([time_bucket(INTERVAL 1 HOUR, ts) - i * INTERVAL 1 HOUR for i in range(6)]) AS start, (event_type = 'error')::INT AS wrong FROM events) GROUP BY 1""")
def stream_sliding(spark, sf_dir):
    return S.run_once(S.windowed(S.vote_stream(spark, sf_dir), "6 hours", "1 hour"), "stream_sliding", "complete").withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("""WITH e AS (SELECT user_id AS worker, ts, CASE WHEN ts - lag(ts) OVER w <= INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT *, sum(fresh) OVER (PARTITION BY worker ORDER BY ts ROWS UNBOUNDED PRECEDING) AS no FROM e)
SELECT worker, min(ts)::TIMESTAMP AS start, (max(ts) + INTERVAL 30 MINUTE)::TIMESTAMP AS "end", count(*) AS n_votes FROM s GROUP BY worker, no""")
def stream_sessions(spark, sf_dir):
    found = S.run_once(S.sittings(S.vote_stream(spark, sf_dir, ended=True)), "stream_sessions", "append")
    return found.withColumns({c: F.col(c).cast("timestamp_ntz") for c in ("start", "end")})


PAIRS = "(SELECT event_id, ts, user_id AS worker, event_type, k // 10 AS u, 10 + k % 10 AS w, ((k // 10) % 5 = (10 + k % 10) % 5) <> (event_type = 'error') AS yes FROM (SELECT *, json_extract_string(props, '$.k')::BIGINT AS k FROM events))"


@query(f"SELECT DISTINCT u, w, worker FROM {PAIRS}")
def stream_dedup(spark, sf_dir):
    """Which worker has voted on which pair, each once."""
    return S.run_once(S.deduplicated(S.vote_stream(spark, sf_dir)).select("u", "w", "worker"), "stream_dedup", "append")


@query(f"""SELECT u, w, count(*) AS n_votes, sum(yes::INT)::BIGINT AS n_yes, true AS "full" FROM (SELECT *, row_number() OVER (PARTITION BY u, w ORDER BY event_id) AS no FROM {PAIRS})
WHERE no <= 5 GROUP BY u, w HAVING count(*) = 5""")
def stream_completed_pairs(spark, sf_dir):
    votes = S.vote_stream(spark, sf_dir).select("ts", "event_id", "u", "w", "yes")
    return S.run_once(S.completed_pairs(votes), "stream_completed", "append").where("full")


@query(f"SELECT q.u, q.w, q.event_id AS question, count(*) AS answers FROM {PAIRS} q JOIN {PAIRS} v ON q.u = v.u AND q.w = v.w AND v.ts >= q.ts AND v.ts <= q.ts + INTERVAL 24 HOUR WHERE q.event_type = 'click' GROUP BY ALL")
def stream_join(spark, sf_dir):
    """Every click opens its pair as a question; the votes that come within a day answer it."""
    votes = S.vote_stream(spark, sf_dir, ended=True)
    asked = S.vote_stream(spark, sf_dir, ended=True).where("event_type = 'click'").select("u", "w", F.col("ts").alias("asked_at"), F.col("event_id").alias("question"))
    return S.run_once(S.answer_counts(asked, votes.select("u", "w", "ts", "worker", "yes")), "stream_join", "append")


@query("""WITH e AS (SELECT ts, ts >= (SELECT quantile_disc(ts, 0.5) FROM events) AS first FROM events), mark AS (SELECT max(ts) - INTERVAL 2 HOUR AS edge FROM events)
SELECT count(*) AS votes, count(*) FILTER (NOT first AND time_bucket(INTERVAL 1 HOUR, ts) + INTERVAL 1 HOUR <= edge) AS late FROM e, mark""")
def stream_late(spark, sf_dir):
    """The later half of the events comes first: what is then behind the watermark is left out and counted."""
    return S.late_votes(spark, sf_dir)


@query(f"""WITH v AS (SELECT u, w, worker, arg_max(yes, event_id) AS yes FROM {PAIRS} GROUP BY u, w, worker) SELECT count(*) AS pairs, sum(n)::BIGINT AS votes, true AS kept_state FROM (SELECT u, w, count(*) AS n FROM v GROUP BY u, w)""")
def stream_agreement(spark, sf_dir):
    """Answers in micro-batches: the clustering is kept while they agree; a batch that comes again changes nothing."""
    step = S.answer_loop(None, W.event_gold(spark))
    votes = W.event_votes(spark, sf_dir)
    for number, part in enumerate(("worker % 2 = 0", "worker % 2 = 1")):
        step(votes.where(part), number)
    before = step.edges().agg(F.sum("n_votes")).first()[0]
    again = S.answer_loop(None, W.event_gold(spark), folder=step.folder)  # a new driver finds the state
    again(votes.where("worker % 2 = 1"), 1)
    return again.edges().agg(F.count("*").alias("pairs"), F.sum("n_votes").cast("long").alias("votes")).withColumn("kept_state", F.col("votes") == F.lit(before))


@query(VOTED)
def stream_crowd_votes(spark, sf_dir):
    """The vote source as a stream of micro-batches, its answers on the pairs that the events ask."""
    from crowdlink.sources.crowd import CrowdVotes

    spark.dataSource.register(CrowdVotes)
    asked = cut(_asked(spark, sf_dir).where("u >= 0 AND u < w AND w < 30"), "asked")  # the source's pairs
    votes = spark.readStream.format("crowd_votes").option("records", 30).option("err", 0.1).option("perBatch", 120).load()
    return S.run_until(votes.join(asked, ["u", "w"], "left_semi"), "stream_crowd", "append", asked.count() * 5)


@query("SELECT event_type, count(*) AS n FROM events GROUP BY 1")
def stream_rate(spark, sf_dir):
    """A source that makes rows on its own, as a load: its numbers call the events up, in three batches or a few more.

    An event answers to one number below the count of events, so each comes once, whatever the ids are.
    """
    events = t(spark, sf_dir, "events").select("event_id", "event_type")
    total = events.count()
    numbered = events.select(F.pmod(F.xxhash64("event_id"), F.lit(max(total, 1))).alias("value"), "event_type")
    rows = spark.readStream.format("rate-micro-batch").option("rowsPerBatch", total // 3 + 1).load().select("value")
    got = rows.join(numbered, "value").groupBy("event_type").agg(F.count("*").alias("n"))
    return S.run_until(got, "stream_rate", "complete", total, measure="sum(n)")


@query("SELECT u, w, same, count(*) AS n FROM (SELECT k // 10 AS u, 10 + k % 10 AS w, (k // 10) % 5 = (10 + k % 10) % 5 AS same FROM (SELECT json_extract_string(props, '$.k')::BIGINT AS k FROM events)) GROUP BY ALL")
def stream_static_gold(spark, sf_dir):
    joined = S.with_gold(S.vote_stream(spark, sf_dir), W.event_gold(spark))
    return S.run_once(joined.groupBy("u", "w", "same").agg(F.count("*").alias("n")), "stream_gold", "complete")
