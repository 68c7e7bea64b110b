"""Every query of the engine by name, with the SQL that it must equal where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from crowdlink.config import Config
from crowdlink.operators import baselines as B
from crowdlink.operators import clustering as C
from crowdlink.operators import measures as M
from crowdlink.operators import questions as Q
from crowdlink.operators import reliability as R
from crowdlink.operators import votes as V
from crowdlink.operators import worlds as P
from crowdlink.plans import experiments as X
from crowdlink.sources import workloads as W
from crowdlink.storage import cut

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


EVENTS = """
WITH ev AS (SELECT event_id, user_id AS worker, event_type, json_extract_string(props, '$.k')::BIGINT AS k FROM events),
raw AS (SELECT event_id, k // 10 AS u, 10 + k % 10 AS w, worker, ((k // 10) % 5 = (10 + k % 10) % 5) <> (event_type = 'error') AS yes FROM ev),
votes AS (SELECT u, w, worker, arg_max(yes, event_id) AS yes FROM raw GROUP BY u, w, worker),
edges AS (SELECT u, w, count(*)::INT AS n_votes, sum(yes::INT)::INT AS n_yes, sum(yes::INT) / count(*) AS p FROM votes GROUP BY u, w),
gold AS (SELECT range AS rid, (range % 5)::VARCHAR AS entity, range % 5 AS cid FROM range(20)),
lab AS (SELECT u, w, p, a.cid AS cu, b.cid AS cw, a.cid = b.cid AS is_yes, CASE WHEN a.cid = b.cid THEN p ELSE 1 - p END AS q
        FROM edges JOIN gold a ON a.rid = u JOIN gold b ON b.rid = w),
disc AS (SELECT least(cu, cw) AS c1, greatest(cu, cw) AS c2, count(*) AS n_edges, 1 - product(p) AS disc FROM lab WHERE NOT is_yes GROUP BY 1, 2)
"""


def simulated(table: str, key: str, entity: str, below: int, voters: int, err: float) -> str:
    return f"""
WITH gold AS (SELECT {key}::BIGINT AS rid, {entity} AS entity FROM {table} WHERE {key} < {below}),
pairs AS (SELECT a.rid AS u, b.rid AS w, a.entity = b.entity AS same FROM gold a JOIN gold b ON a.rid < b.rid),
votes AS (SELECT u, w, v AS worker, same <> (('0x' || substr(md5('42|' || u || '|' || w || '|' || v), 1, 8))::BIGINT / 4294967296.0 < {err}) AS yes
          FROM pairs, (SELECT range AS v FROM range({voters}))),
edges AS (SELECT u, w, count(*)::INT AS n_votes, sum(yes::INT)::INT AS n_yes, sum(yes::INT) / count(*) AS p FROM votes GROUP BY u, w)
"""


W2 = simulated("embeddings", "vec_id", "label::VARCHAR", 94, 5, 0.1065)
W1 = simulated("part", "p_partkey", "p_name", 267, 10, 0.0567)


def recursive(sql: str) -> str:
    return sql.replace("WITH", "WITH RECURSIVE", 1)


def started(sql: str, count: int = 200) -> str:
    """The asked pairs are the first ``count`` in hash order."""
    return sql + f""", asked AS (SELECT * FROM edges ORDER BY ('0x' || substr(md5('42|' || u || '|' || w), 1, 8))::BIGINT, u, w LIMIT {count})
"""


def greedy_sql(records: str, edges: str = "edges") -> str:
    """Greedy merging of the pair of clusters of greatest summed log-odds: found (rid, cid). ``records`` gives the ids."""
    return f""", o AS (SELECT u, w, ln(greatest(least(p, 1 - 1e-9), 1e-9)) - ln(1 - greatest(least(p, 1 - 1e-9), 1e-9)) AS odds FROM {edges}),
greedy AS (SELECT 0 AS step, (SELECT range(max(rid) + 1) FROM {records}) AS label UNION ALL
  SELECT step + 1, list_transform(label, lambda x: CASE WHEN x = b THEN a ELSE x END) FROM (SELECT * FROM (
    SELECT step, label, least(label[u + 1], label[w + 1]) AS a, greatest(label[u + 1], label[w + 1]) AS b, round(sum(odds), 9) AS t
    FROM greedy, o WHERE label[u + 1] <> label[w + 1] GROUP BY ALL) WHERE t > 1e-9 ORDER BY t DESC, a, b LIMIT 1)),
found AS (SELECT rid, label[rid + 1] AS cid FROM {records}, (SELECT label FROM greedy ORDER BY step DESC LIMIT 1))
"""


def first_asked(edges: DataFrame, count: int = 200) -> DataFrame:
    """The part of a vote graph that the first ``count`` pairs in hash order make: a loop's state after its start."""
    return edges.orderBy(V.unit_hash(42, F.col("u"), F.col("w")), "u", "w").limit(count)


def w2_started(spark, sf_dir, mode="ratio", count=200):
    return first_asked(V.build_edges(W.votes(spark, sf_dir, "w2"), mode), count)


def event_edges(spark, sf_dir, mode="ratio"):
    return V.build_edges(W.event_votes(spark, sf_dir), mode)


def event_lab(spark, sf_dir):
    return V.labelled(event_edges(spark, sf_dir), W.gold_clusters(W.event_gold(spark)))


def rounded(df: DataFrame, *names: str, digits: int = 8) -> DataFrame:
    return df.withColumns({n: F.round(n, digits) for n in names})


# votes and graph


@query(W2 + "SELECT u, w, worker, yes FROM votes")
def votes_simulated(spark, sf_dir):
    return W.votes(spark, sf_dir, "w2")


@query(W2.replace("4294967296.0 < 0.1065)", "4294967296.0 < CASE WHEN ('0x' || substr(md5('42|' || u || '|' || w || '|hard'), 1, 8))::BIGINT / 4294967296.0 < 0.5 THEN 0.213 ELSE 0.0 END)") + "SELECT u, w, worker, yes FROM votes")
def votes_hard_pairs(spark, sf_dir):
    """The same mean error, all of it on a hashed half of the pairs."""
    return W.simulate_votes(W.pool(W.gold(spark, sf_dir, "w2"), "w2"), 5, 0.1065, hard=True)


@query(EVENTS + "SELECT u, w, worker, yes FROM votes")
def votes_from_events(spark, sf_dir):
    return W.event_votes(spark, sf_dir)


@query("""SELECT a.l_suppkey AS u, b.l_suppkey AS w, a.l_orderkey AS worker, a.l_returnflag = b.l_returnflag AS yes
FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_suppkey < b.l_suppkey AND a.l_linenumber <> b.l_linenumber""")
def votes_from_lineitem(spark, sf_dir):
    return W.lineitem_votes(spark, sf_dir)


@query(W1 + "SELECT u, w, n_votes, n_yes, round(p, 8) AS p FROM edges")
def edges_ratio(spark, sf_dir):
    return rounded(V.build_edges(W.votes(spark, sf_dir, "w1")), "p")


@query(W2 + "SELECT u, w, n_votes, n_yes, CASE WHEN 2 * n_yes > n_votes THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END AS p FROM edges")
def edges_majority(spark, sf_dir):
    return V.build_edges(W.votes(spark, sf_dir, "w2"), "majority")


@query(W2 + "SELECT u, w, n_votes, n_yes, CASE WHEN 2 * n_yes > n_votes THEN 0.9::DOUBLE ELSE 0.1::DOUBLE END AS p FROM edges")
def edges_fixed_accuracy(spark, sf_dir):
    return V.build_edges(W.votes(spark, sf_dir, "w2"), "fixed_accuracy")


@query("""SELECT u, w, count(*)::INT AS n_votes, sum(yes::INT)::INT AS n_yes, round(sum(yes::INT) / count(*), 8) AS p FROM (
SELECT a.l_suppkey AS u, b.l_suppkey AS w, a.l_returnflag = b.l_returnflag AS yes
FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_suppkey < b.l_suppkey AND a.l_linenumber <> b.l_linenumber) GROUP BY u, w""")
def edges_lineitem(spark, sf_dir):
    return rounded(V.build_edges(W.lineitem_votes(spark, sf_dir)), "p")


@query(W2 + """, wrong AS (SELECT v.u, v.w, avg((v.yes <> p.same)::INT) AS wrong FROM votes v JOIN pairs p USING (u, w) GROUP BY v.u, v.w)
SELECT round(avg(wrong), 8) AS crowd_error, count(*) AS pairs FROM wrong""")
def crowd_error(spark, sf_dir):
    return rounded(V.crowd_error(W.votes(spark, sf_dir, "w2"), W.gold(spark, sf_dir, "w2")), "crowd_error")


@query(W2 + """SELECT same, worker, count(*) AS n, sum((yes <> same)::INT)::BIGINT AS n_wrong, grouping_id(same, worker)::BIGINT AS level
FROM votes JOIN pairs USING (u, w) GROUP BY ROLLUP (same, worker)""")
def crowd_error_by_label_rollup(spark, sf_dir):
    pairs = W.pool(W.gold(spark, sf_dir, "w2"), "w2")
    v = W.votes(spark, sf_dir, "w2").join(pairs, ["u", "w"])
    return v.rollup("same", "worker").agg(F.count("*").alias("n"), F.count_if(F.col("yes") != F.col("same")).alias("n_wrong"), F.grouping_id().alias("level"))


@query("SELECT count(*) AS asked, round(count(*) / (20 * 19 / 2.0), 8)::DOUBLE AS share FROM (" + EVENTS + "SELECT u, w FROM edges)")
def pairs_asked_share(spark, sf_dir):
    return event_edges(spark, sf_dir).agg(F.count("*").alias("asked"), F.round(F.count("*") / F.lit(190.0), 8).alias("share"))


@query(EVENTS + """SELECT CASE WHEN p IS NULL THEN 'unasked' WHEN p = 0 THEN 'refused' WHEN p = 1 THEN 'agreed' ELSE 'uncertain' END AS state, count(*) AS n
FROM (SELECT a.rid AS u, b.rid AS w FROM gold a JOIN gold b ON a.rid < b.rid) LEFT JOIN edges USING (u, w) GROUP BY 1""")
def asked_zero_vs_unasked(spark, sf_dir):
    g = W.event_gold(spark)
    pairs = g.select(F.col("rid").alias("u")).join(g.select(F.col("rid").alias("w")), F.col("u") < F.col("w"))
    state = F.when(F.col("p").isNull(), "unasked").when(F.col("p") == 0, "refused").when(F.col("p") == 1, "agreed").otherwise("uncertain")
    return pairs.join(event_edges(spark, sf_dir), ["u", "w"], "left").groupBy(state.alias("state")).agg(F.count("*").alias("n"))


# worlds and likelihood

TRIANGLE = [(0, 1, 0.8), (0, 2, 0.4), (1, 2, 0.4)]
TRIANGLE_SQL = """WITH e(u, w, bit, p) AS (VALUES (0, 1, 0, 0.8::DOUBLE), (0, 2, 1, 0.4::DOUBLE), (1, 2, 2, 0.4::DOUBLE)),
x AS (SELECT range AS world, u, w, ((range >> bit) & 1) = 1 AS chosen, p FROM range(8), e)
"""


def triangle(spark):
    return spark.createDataFrame(TRIANGLE, "u long, w long, p double")


@query(TRIANGLE_SQL + "SELECT world, round(product(CASE WHEN chosen THEN p ELSE 1 - p END), 8) AS prob FROM x GROUP BY world")
def world_probabilities_triangle(spark, sf_dir):
    return rounded(P.world_probability(P.possible_worlds(triangle(spark))), "prob")


@query(TRIANGLE_SQL + "SELECT world FROM x GROUP BY world HAVING sum(chosen::INT) = 2")
def worlds_not_closed(spark, sf_dir):
    return P.not_closed(P.possible_worlds(triangle(spark)))


#: Label strings where each label is at most one above those before it are the partitions, counted one by one.
@query("""WITH RECURSIVE sizes AS (SELECT n, count(*) AS orders FROM (SELECT count(*) AS n FROM lineitem GROUP BY l_orderkey) GROUP BY n),
grown AS (SELECT 1 AS n, 0 AS top, 1::BIGINT AS ways UNION ALL
SELECT n + 1, greatest(top, l), sum(ways)::BIGINT FROM grown, range(26) t(l), (SELECT max(n) AS most FROM sizes) WHERE l <= top + 1 AND n < most GROUP BY n, greatest(top, l))
SELECT n::INT AS n, orders, partitions FROM sizes JOIN (SELECT n, sum(ways)::BIGINT AS partitions FROM grown GROUP BY n) USING (n)""")
def partition_counts(spark, sf_dir):
    """Orders by the number of their lines, and the partitions that so many records have."""
    lines = spark.read.parquet(f"{sf_dir}/lineitem.parquet").groupBy("l_orderkey").agg(F.count("*").cast("int").alias("n"))
    sizes = cut(lines.groupBy("n").agg(F.count("*").alias("orders")), "sizes")
    most = sizes.agg(F.max("n")).first()[0] or 1
    return sizes.join(P.partition_counts(spark, most), "n").select("n", "orders", "partitions")


@query(EVENTS + "SELECT round(sum(ln(greatest(q, 1e-9))), 6) AS log_likelihood, count(*) AS edges FROM lab")
def loglik_gold(spark, sf_dir):
    return rounded(P.log_likelihood(event_edges(spark, sf_dir), W.gold_clusters(W.event_gold(spark))), "log_likelihood", digits=6)


@query(EVENTS + "SELECT round(sum(ln(greatest(1 - p, 1e-9))), 6) AS log_likelihood, count(*) AS edges FROM edges")
def loglik_vs_singletons(spark, sf_dir):
    alone = W.event_gold(spark).select("rid", F.col("rid").alias("cid"))
    return rounded(P.log_likelihood(event_edges(spark, sf_dir), alone), "log_likelihood", digits=6)


BEST = """, parts AS (SELECT a, b, c FROM range(2) x(a), range(3) y(b), range(4) z(c) WHERE b <= a + 1 AND c <= greatest(a, b) + 1),
place AS (SELECT u, w, p, cu AS block, CASE WHEN u < 5 THEN 1 WHEN u < 10 THEN 2 WHEN u < 15 THEN 3 ELSE 4 END AS i, CASE WHEN w < 5 THEN 1 WHEN w < 10 THEN 2 WHEN w < 15 THEN 3 ELSE 4 END AS j FROM lab WHERE is_yes),
lik AS (SELECT block, a, b, c, product(CASE WHEN ([0, a, b, c])[i] = ([0, a, b, c])[j] THEN p ELSE 1 - p END) AS likelihood FROM place, parts GROUP BY ALL),
top AS (SELECT * FROM lik QUALIFY row_number() OVER (PARTITION BY block ORDER BY round(likelihood, 14) DESC, a, b, c) = 1),
lab4 AS (SELECT block, likelihood, unnest([block, block + 5, block + 10, block + 15]) AS rid, unnest([0, a, b, c]) AS l FROM top)
SELECT block, rid, min(rid) OVER (PARTITION BY block, l) AS cid, round(likelihood, 9) AS likelihood FROM lab4"""


@query(EVENTS + BEST)
def mlc_exact_small(spark, sf_dir):
    """The likeliest of all partitions of each block of four event records."""
    return rounded(P.best_clusterings(event_edges(spark, sf_dir), W.gold_clusters(W.event_gold(spark))), "likelihood", digits=9)


#: A world of a 4-cycle is no clustering only where three of its edges are there.
@query(EVENTS + "SELECT cu::INT AS block, (2 ** count(*))::BIGINT AS worlds, (2 ** count(*) - CASE WHEN count(*) = 4 THEN 4 ELSE 0 END)::BIGINT AS closed FROM lab WHERE is_yes GROUP BY cu")
def worlds_closed_by_block(spark, sf_dir):
    """Worlds of each block of four event records: all of them, and those that are clusterings."""
    lab = event_lab(spark, sf_dir).where("is_yes")
    out = None
    for c in range(5):
        w = P.possible_worlds(lab.where(F.col("cu") == c))
        one = P.closed(w).agg(F.count("*").alias("worlds"), F.count_if("closed").alias("closed")).select(F.lit(c).alias("block"), "worlds", "closed")
        out = one if out is None else out.unionByName(one)
    return out


# clustering


@query(EVENTS + """SELECT least(cu, cw) AS c1, greatest(cu, cw) AS c2, count(*) AS n_edges,
round(1 / (1 + exp(-sum(ln(greatest(least(p, 1 - 1e-9), 1e-9)) - ln(1 - greatest(least(p, 1 - 1e-9), 1e-9))))), 6) AS prob FROM lab WHERE NOT is_yes GROUP BY 1, 2""")
def merge_probability(spark, sf_dir):
    return rounded(C.merge_probability(event_lab(spark, sf_dir)), "prob", digits=6)


@query(recursive(EVENTS) + greedy_sql("gold") + "SELECT rid, cid FROM found")
def scc_events(spark, sf_dir):
    """Greedy clustering of the event graph."""
    return C.scc(event_edges(spark, sf_dir), W.event_gold(spark))


@query(recursive(W2) + greedy_sql("gold") + "SELECT rid, cid FROM found")
def scc_w2(spark, sf_dir):
    return C.scc(V.build_edges(W.votes(spark, sf_dir, "w2")), W.gold(spark, sf_dir, "w2"))


@query(recursive(started(W2)) + greedy_sql("gold", "asked") + "SELECT rid, cid FROM found")
def scc_w2_started(spark, sf_dir):
    """Greedy clustering of the state after the start, where most pairs are not asked."""
    return C.scc(w2_started(spark, sf_dir), W.gold(spark, sf_dir, "w2"))


@query(recursive(started(W2, 400)) + greedy_sql("gold", "(SELECT * FROM asked)") + "SELECT rid, cid FROM found")
def scc_exact_mode(spark, sf_dir):
    return C.scc(w2_started(spark, sf_dir, count=400), W.gold(spark, sf_dir, "w2"), Config(scc_mode="exact"))


@query()
def scc_rounds_mode(spark, sf_dir):
    """Mutually best pairs merge at once, round by round: approximate, only on demand; next to the exact clusters."""
    edges, records = w2_started(spark, sf_dir, count=400), W.gold(spark, sf_dir, "w2")
    exact = C.scc(edges, records).withColumnRenamed("cid", "exact_cid")
    return C.scc(edges, records, Config(scc_mode="rounds")).join(exact, "rid").withColumn("approximate", F.lit(True))


@query()
def scc_warm_start(spark, sf_dir):
    """The clustering after the start, merged on with twice the answers."""
    records = W.gold(spark, sf_dir, "w2")
    return C.scc(w2_started(spark, sf_dir, count=400), records, start=C.scc(w2_started(spark, sf_dir), records))


LINES = """WITH RECURSIVE gold AS (SELECT s_suppkey AS rid FROM supplier), edges AS (SELECT u, w, sum(yes::INT) / count(*) AS p FROM (
SELECT a.l_suppkey AS u, b.l_suppkey AS w, a.l_returnflag = b.l_returnflag AS yes
FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_suppkey < b.l_suppkey AND a.l_linenumber <> b.l_linenumber) GROUP BY u, w)
"""


@query(LINES + greedy_sql("gold") + "SELECT rid, cid FROM found")
def scc_lineitem(spark, sf_dir):
    """Greedy clustering of the scale graph of suppliers."""
    # few votes of a pair meet before the shuffle, so sums on the way there are left out
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    edges = V.build_edges(W.lineitem_votes(spark, sf_dir).repartition(parts, "u", "w"))
    return C.scc(edges, spark.read.parquet(f"{sf_dir}/supplier.parquet").select(F.col("s_suppkey").alias("rid")))


@query("""WITH gold AS (SELECT p_partkey AS rid, p_name AS entity FROM part), pairs AS (SELECT DISTINCT least(a.l_partkey, b.l_partkey) AS u, greatest(a.l_partkey, b.l_partkey) AS w
FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey),
drawn AS (SELECT u, w, x.entity = y.entity AS same, v FROM pairs JOIN gold x ON x.rid = u JOIN gold y ON y.rid = w, range(5) t(v))
SELECT u, w, count(*)::INT AS n_votes, sum((same <> (('0x' || substr(md5('42|' || u || '|' || w || '|' || v), 1, 8))::BIGINT / 4294967296.0 < 0.05))::INT)::INT AS n_yes FROM drawn GROUP BY u, w""")
def edges_parts(spark, sf_dir):
    """The sparse scale graph: parts of one order are a pair, five simulated votes each."""
    return V.build_edges(W.part_votes(spark, sf_dir)).drop("p")


@query()
def scc_parts(spark, sf_dir):
    """Greedy clustering of the sparse scale graph, and how it compares with the parts' names."""
    records = W.part_gold(spark, sf_dir)
    return M.pair_scores(C.scc(V.build_edges(W.part_votes(spark, sf_dir)), records), records)


@query(started(W2) + """, o AS (SELECT u, w, round(ln(greatest(least(p, 1 - 1e-9), 1e-9)) - ln(1 - greatest(least(p, 1 - 1e-9), 1e-9)), 9) AS odds FROM asked),
pos AS (SELECT * FROM o WHERE odds > 0), t AS (SELECT c, sum(odds) AS total FROM (SELECT u AS c, odds FROM pos UNION ALL SELECT w, odds FROM pos) GROUP BY c)
SELECT u, w FROM pos JOIN t a ON a.c = u JOIN t b ON b.c = w WHERE odds > a.total + b.total - 2 * odds + 1e-9""")
def scc_safe_first_round(spark, sf_dir):
    return C.safe_merges(C.with_odds(w2_started(spark, sf_dir)))


COMPONENTS = """, adj AS (SELECT u AS a, w AS b FROM edges WHERE p > 0.5 UNION SELECT w, u FROM edges WHERE p > 0.5),
reach AS (SELECT rid AS a, rid AS b FROM gold UNION SELECT r.a, adj.b FROM reach r JOIN adj ON r.b = adj.a),
comp AS (SELECT a AS rid, min(b) AS cid FROM reach GROUP BY a)
"""


@query(EVENTS.replace("WITH", "WITH RECURSIVE", 1) + COMPONENTS + "SELECT rid, cid FROM comp")
def positive_components(spark, sf_dir):
    return C.positive_components(event_edges(spark, sf_dir), W.event_gold(spark))


PIVOTS = """, near AS (SELECT rid, coalesce(list(b) FILTER (b IS NOT NULL), []) AS nb FROM gold LEFT JOIN (SELECT u AS a, w AS b FROM edges WHERE p > 0.5 UNION ALL SELECT w, u FROM edges WHERE p > 0.5) ON a = rid GROUP BY rid),
line AS (SELECT list(nb ORDER BY rid) AS nbs, list(rid ORDER BY ('0x' || substr(md5('42|' || rid), 1, 8))::BIGINT, rid) AS ord FROM near),
piv AS (SELECT 0 AS step, (SELECT list(-1::BIGINT) FROM gold) AS label UNION ALL
  SELECT step + 1, CASE WHEN label[r + 1] >= 0 THEN label ELSE list_transform(range(len(label)), lambda x: CASE WHEN label[x + 1] < 0 AND (x = r OR list_contains(nbs[r + 1], x)) THEN r ELSE label[x + 1] END) END
  FROM (SELECT step, label, nbs, ord[step + 1] AS r FROM piv, line WHERE step < len(label))),
roots AS (SELECT rid, label[rid + 1] AS root FROM gold, (SELECT label FROM piv ORDER BY step DESC LIMIT 1)),
found AS (SELECT rid, min(rid) OVER (PARTITION BY root) AS cid FROM roots)
"""


@query(recursive(EVENTS) + PIVOTS + "SELECT rid, cid FROM found")
def pivot_clusters(spark, sf_dir):
    return B.pivot_clusters(event_edges(spark, sf_dir), W.event_gold(spark))


@query(recursive(W2) + PIVOTS + "SELECT rid, cid FROM found")
def pivot_clusters_w2(spark, sf_dir):
    return B.pivot_clusters(V.build_edges(W.votes(spark, sf_dir, "w2")), W.gold(spark, sf_dir, "w2"))


@query()
def pivot_refined(spark, sf_dir):
    """Pivot clusters after splits and merges that pay."""
    edges, records = w2_started(spark, sf_dir, count=400), W.gold(spark, sf_dir, "w2")
    return B.pivot_refined(edges, records, B.pivot_clusters(edges, records))


@query()
def clustering_heuristics(spark, sf_dir):
    """F1 of each clustering heuristic on the same whole vote graph."""
    records = W.gold(spark, sf_dir, "w2")
    votes = W.votes(spark, sf_dir, "w2")
    ratio, majority = V.build_edges(votes), V.build_edges(votes, "majority")
    found = {"scc": C.scc(ratio, records), "pivot": B.pivot_clusters(ratio, records), "positive_components": C.positive_components(ratio, records), "transitive": B.transitive_clusters(majority, records), "local_move": C.local_move(ratio, records), "average_odds": C.average_odds(ratio, records)}
    out = None
    for name, clusters in found.items():
        one = M.pair_scores(clusters, records).select(F.lit(name).alias("heuristic"), "precision", "recall", "f1")
        out = one if out is None else out.unionByName(one)
    return out


@query(EVENTS + "SELECT 20::BIGINT AS records, true AS partition, true AS no_worse_than_singletons FROM edges LIMIT 1")
def local_move(spark, sf_dir):
    edges, records = event_edges(spark, sf_dir), W.event_gold(spark)
    found = C.local_move(edges, records)
    own = P.log_likelihood(edges, found).select(F.col("log_likelihood").alias("a"))
    alone = P.log_likelihood(edges, records.select("rid", F.col("rid").alias("cid"))).select(F.col("log_likelihood").alias("b"))
    return found.agg(F.count("*").alias("records"), (F.count("*") == F.countDistinct("rid")).alias("partition")).crossJoin(own).crossJoin(alone).select("records", "partition", (F.col("a") >= F.col("b") - 1e-9).alias("no_worse_than_singletons"))


# reliability


@query(EVENTS + "SELECT u, w, round(p, 8) AS p, cu, cw, is_yes, round(q, 8) AS q FROM lab")
def yes_no_graph(spark, sf_dir):
    return rounded(event_lab(spark, sf_dir), "p", "q")


@query(EVENTS + "SELECT c1, c2, n_edges, round(disc, 8) AS disc FROM disc")
def disconnect_pairs(spark, sf_dir):
    return rounded(R.disconnect(event_lab(spark, sf_dir)), "disc")


CYCLE = """, four AS (SELECT cu AS cid, count(*) AS n_edges, sum(ln(greatest(p, 1e-300))) AS l, product(p) AS all4,
sum(CASE WHEN p > 0 THEN 1 / p - 1 ELSE 0 END) AS odd, list(p) AS ps FROM lab WHERE is_yes GROUP BY cu),
con AS (SELECT cid, n_edges, CASE WHEN n_edges = 4 THEN ps[1]*ps[2]*ps[3]*ps[4] + (1-ps[1])*ps[2]*ps[3]*ps[4] + ps[1]*(1-ps[2])*ps[3]*ps[4]
 + ps[1]*ps[2]*(1-ps[3])*ps[4] + ps[1]*ps[2]*ps[3]*(1-ps[4]) WHEN n_edges = 3 THEN ps[1]*ps[2]*ps[3] ELSE 0 END AS connect FROM four)
"""


@query(EVENTS + CYCLE + "SELECT c.cid, 4::BIGINT AS n_records, coalesce(n_edges, 0) AS n_edges, round(coalesce(connect, 0), 8) AS connect FROM (SELECT DISTINCT cid FROM gold) c LEFT JOIN con USING (cid)")
def connect_exact_events(spark, sf_dir):
    return rounded(R.connectivity(event_lab(spark, sf_dir), W.gold_clusters(W.event_gold(spark))), "connect")


def sampled(spark, sf_dir, k):
    """Exact connectivity, and whether the sampled one lies within five standard errors of it."""
    lab, clusters = event_lab(spark, sf_dir), W.gold_clusters(W.event_gold(spark))
    exact = R.connectivity(lab, clusters)
    drawn = R.connectivity(lab, clusters, k).select("cid", F.col("connect").alias("drawn"))
    near = F.abs(F.col("drawn") - F.col("connect")) <= 5 * F.sqrt(F.col("connect") * (1 - F.col("connect")) / k.samples) + 1e-9
    return exact.join(drawn, "cid").select("cid", "n_records", "n_edges", F.round("connect", 8).alias("connect"), near.alias("near"))


CONNECTED = "SELECT c.cid, 4::BIGINT AS n_records, coalesce(n_edges, 0) AS n_edges, round(coalesce(connect, 0), 8) AS connect, true AS near FROM (SELECT DISTINCT cid FROM gold) c LEFT JOIN con USING (cid)"


@query(EVENTS + CYCLE + CONNECTED)
def connect_mc_events(spark, sf_dir):
    return sampled(spark, sf_dir, Config(exact_max_edges=0))


@query(EVENTS + CYCLE + CONNECTED)
def connect_bfs_events(spark, sf_dir):
    """Worlds drawn edge by edge as a walk from one record meets them."""
    return sampled(spark, sf_dir, Config(exact_max_edges=0, walk="bfs"))


@query(EVENTS + CYCLE + "SELECT s.t AS samples, x.* FROM (" + CONNECTED + ") x, (VALUES (10), (100), (1000), (5000)) s(t)")
def mc_convergence(spark, sf_dir):
    """Sampled connectivity by number of samples against the exact value."""
    out = None
    for t in (10, 100, 1000, 5000):
        one = sampled(spark, sf_dir, Config(exact_max_edges=0, samples=t)).withColumn("samples", F.lit(t))
        out = one if out is None else out.unionByName(one)
    return out


@query(W2 + """, g AS (SELECT u, w, p FROM edges WHERE p > 0 AND p < 1), tri AS (SELECT a.u AS x, a.w AS y, b.w AS z, a.p AS p, b.p AS q, c.p AS r FROM g a JOIN g b ON b.u = a.w JOIN g c ON c.u = a.u AND c.w = b.w)
SELECT x, y, z, round(p * q + q * r + p * r - 2 * p * q * r, 8) AS connect FROM tri""")
def connect_triangles(spark, sf_dir):
    """Every triangle of uncertain answers as a cluster of its own, in closed form."""
    from crowdlink.graph import triangles

    e = V.build_edges(W.votes(spark, sf_dir, "w2")).where("p > 0 AND p < 1").select("u", "w", "p")
    found = triangles(e)
    for a, b, n in (("x", "y", "p"), ("y", "z", "q"), ("x", "z", "r")):
        found = found.join(e.select(F.col("u").alias(a), F.col("w").alias(b), F.col("p").alias(n)), [a, b])
    return found.select("x", "y", "z", F.round(F.expr("p * q + q * r + p * r - 2 * p * q * r"), 8).alias("connect"))


@query(EVENTS + CYCLE + """SELECT round((SELECT sum(log10(greatest(coalesce(connect, 0), 1e-9))) FROM (SELECT DISTINCT cid FROM gold) LEFT JOIN con USING (cid)), 6) AS inside,
round((SELECT sum(log10(greatest(disc, 1e-9))) FROM disc), 6) AS across, round((10 - (SELECT count(*) FROM disc)) * -9.0, 6)::DOUBLE AS edgeless,
round((SELECT sum(log10(greatest(coalesce(connect, 0), 1e-9))) FROM (SELECT DISTINCT cid FROM gold) LEFT JOIN con USING (cid)) + (SELECT sum(log10(greatest(disc, 1e-9))) FROM disc) + (10 - (SELECT count(*) FROM disc)) * -9.0, 6) AS reliability""")
def reliability_gold(spark, sf_dir):
    return rounded(R.reliability(event_lab(spark, sf_dir), W.gold_clusters(W.event_gold(spark))), "inside", "across", "edgeless", "reliability", digits=6)


@query(EVENTS + "SELECT c1, c2, n_edges, round(disc, 8) AS disc, round(0 - log10(greatest(disc, 1e-9)), 8) AS prio, rank() OVER (ORDER BY round(disc, 9)) AS place FROM disc")
def weakest_pairs_rank(spark, sf_dir):
    return rounded(Q.ranked_by_weakness(Q.across_units(event_lab(spark, sf_dir))), "disc", "prio")


@query(EVENTS + "SELECT c1, c2, i / 10.0::DOUBLE AS q, round(log10((1 - (1 - disc) * (1 - i / 10.0::DOUBLE)) / disc), 8) AS gain FROM disc, (SELECT range AS i FROM range(11)) WHERE disc > 0")
def gain_curve(spark, sf_dir):
    return rounded(Q.gain_curve(R.disconnect(event_lab(spark, sf_dir))), "gain")


# questions

GAP = """, cand AS (SELECT least(a.cid, b.cid) AS c1, greatest(a.cid, b.cid) AS c2, CASE WHEN a.cid < b.cid THEN a.rid ELSE b.rid END AS ra, CASE WHEN a.cid < b.cid THEN b.rid ELSE a.rid END AS rb
          FROM gold a JOIN gold b ON a.rid < b.rid AND a.cid <> b.cid LEFT JOIN edges e ON e.u = a.rid AND e.w = b.rid WHERE e.u IS NULL),
rep AS (SELECT c1, c2, min((ra, rb)) AS m FROM cand GROUP BY c1, c2),
top AS (SELECT disc.c1, disc.c2, least(m[1], m[2]) AS u, greatest(m[1], m[2]) AS w, 0 - log10(greatest(disc, 1e-9)) AS prio FROM disc JOIN rep USING (c1, c2))
"""


@query(EVENTS + GAP + "SELECT c1, c2, u, w FROM top")
def gap_representative(spark, sf_dir):
    lab, clusters = event_lab(spark, sf_dir), W.gold_clusters(W.event_gold(spark))
    return Q.gap_representatives(R.disconnect(lab), lab, clusters)


@query(EVENTS + GAP + "SELECT c1, c2, u, w, round(prio, 8) AS prio FROM top ORDER BY round(prio, 9) DESC, u, w LIMIT 5")
def next_across_topk(spark, sf_dir):
    found = Q.across_candidates(event_lab(spark, sf_dir), W.gold_clusters(W.event_gold(spark))).drop("kind")
    return rounded(found.orderBy(F.round("prio", 9).desc(), "u", "w").limit(5), "prio")


#: A chord of a 4-cycle that is sure leaves two pairs of parallel edges.
INSIDE = CYCLE + """, p4 AS (SELECT cu AS cid, max(p) FILTER (u < 5 AND w < 15) AS a, max(p) FILTER (u < 5 AND w >= 15) AS b, max(p) FILTER (u >= 5 AND w < 15) AS c, max(p) FILTER (u >= 5 AND w >= 15) AS d FROM lab WHERE is_yes GROUP BY cu),
chord AS (SELECT cid, cid AS u, cid + 5 AS w, (1 - (1 - a) * (1 - c)) * (1 - (1 - b) * (1 - d)) AS sure FROM p4 UNION ALL SELECT cid, cid + 10, cid + 15, (1 - (1 - a) * (1 - b)) * (1 - (1 - c) * (1 - d)) FROM p4),
inner_q AS (SELECT 'inside' AS kind, cid AS c1, cid AS c2, u, w, log10(greatest(sure, 1e-9)) - log10(greatest(connect, 1e-9)) AS prio FROM chord JOIN con USING (cid))
"""
EVERY = GAP + INSIDE.replace(", four", ", four", 1) + """, every AS (SELECT * FROM inner_q UNION ALL SELECT 'across', c1, c2, u, w, prio FROM top)
"""


@query(EVENTS + INSIDE + "SELECT kind, c1, c2, u, w, round(prio, 8) AS prio FROM inner_q")
def next_inside(spark, sf_dir):
    lab, clusters = event_lab(spark, sf_dir), W.gold_clusters(W.event_gold(spark))
    return rounded(Q.inside_candidates(lab, clusters, Config(), 2), "prio")


@query()
def next_inside_sampled(spark, sf_dir):
    """Gains of twenty unasked pairs of each cluster, drawn evenly, from sampled worlds."""
    records, edges = W.gold(spark, sf_dir, "w2"), w2_started(spark, sf_dir, count=400)
    clusters = W.gold_clusters(records)
    return Q.inside_candidates(V.labelled(edges, clusters), clusters, Config(pair_sample=20), 3)


@query(EVENTS + EVERY + "SELECT kind, c1, c2, u, w, round(prio, 8) AS prio FROM every ORDER BY round(prio, 9) DESC, kind, u, w LIMIT 1")
def next_question(spark, sf_dir):
    return rounded(Q.next_questions(event_lab(spark, sf_dir), W.gold_clusters(W.event_gold(spark)), 1), "prio")


@query(EVENTS + EVERY + "SELECT kind, c1, c2, u, w, round(prio, 8) AS prio FROM every ORDER BY round(prio, 9) DESC, kind, u, w LIMIT 10")
def next_batch(spark, sf_dir):
    return rounded(Q.next_questions(event_lab(spark, sf_dir), W.gold_clusters(W.event_gold(spark)), 10), "prio")


EDGELESS = """, line AS (SELECT rid AS cid, row_number() OVER (ORDER BY ('0x' || substr(md5('42|' || rid), 1, 8))::BIGINT, rid) AS at FROM gold),
free AS (SELECT least(a.cid, b.cid) AS c1, greatest(a.cid, b.cid) AS c2, b.at - a.at AS far FROM line a JOIN line b ON a.at < b.at WHERE (least(a.cid, b.cid), greatest(a.cid, b.cid)) NOT IN (SELECT (u, w) FROM asked))
"""


@query(started(W2) + EDGELESS + """SELECT 'edgeless' AS kind, c1, c2, c1 AS u, c2 AS w, 9.0::DOUBLE AS prio FROM free
ORDER BY far, ('0x' || substr(md5('42|' || c1 || '|' || c2), 1, 8))::BIGINT, c1, c2 LIMIT 40""")
def next_edgeless(spark, sf_dir):
    """A batch from single records after the start: pairs without an answer gain most."""
    records = W.gold(spark, sf_dir, "w2")
    alone = records.select("rid", F.col("rid").alias("cid"))
    return rounded(Q.next_questions(V.labelled(w2_started(spark, sf_dir), alone), alone, 40), "prio")


@query(started(W2, 4300) + EDGELESS + "SELECT 'edgeless' AS kind, c1, c2, c1 AS u, c2 AS w, 9.0::DOUBLE AS prio FROM free")
def next_edgeless_last(spark, sf_dir):
    """Near the end: the few pairs that are left are all found, though the batch asks for more."""
    records = W.gold(spark, sf_dir, "w2")
    alone = records.select("rid", F.col("rid").alias("cid"))
    return rounded(Q.next_questions(V.labelled(w2_started(spark, sf_dir, count=4300), alone), alone, 500), "prio")


@query(EVENTS + GAP.replace("cand AS (", "cand AS (", 1).replace("rep AS (SELECT c1, c2, min((ra, rb)) AS m FROM cand GROUP BY c1, c2)", "rep AS (SELECT c1, c2, unnest(list((ra, rb) ORDER BY ra, rb)[1:3]) AS m FROM cand GROUP BY c1, c2)") + "SELECT c1, c2, u, w FROM top")
def across_three_each(spark, sf_dir):
    """Up to three questions of each pair of clusters."""
    return Q.across_candidates(event_lab(spark, sf_dir), W.gold_clusters(W.event_gold(spark)), Config(across_per_pair=3)).select("c1", "c2", "u", "w")


@query()
def weak_clusters_first(spark, sf_dir):
    """How far the weaker cluster is asked first: ranks by connectivity and by gain."""
    return Q.weak_first(event_lab(spark, sf_dir), W.gold_clusters(W.event_gold(spark)))


@query(started(W2, 40) + """, g AS (SELECT rid, min(rid) OVER (PARTITION BY entity) AS cid FROM gold),
m AS (SELECT least(a.cid, b.cid) AS c1, greatest(a.cid, b.cid) AS c2 FROM asked JOIN g a ON a.rid = u JOIN g b ON b.rid = w WHERE a.cid <> b.cid)
SELECT count(*) AS clusters, (count(*) * (count(*) - 1) // 2 - (SELECT count(DISTINCT (c1, c2)) FROM m))::BIGINT AS edgeless FROM (SELECT DISTINCT cid FROM g)""")
def edgeless_pairs(spark, sf_dir):
    """How many cluster pairs have no asked edge: counted, never listed."""
    records = W.gold(spark, sf_dir, "w2")
    clusters = W.gold_clusters(records)
    met = R.disconnect(V.labelled(w2_started(spark, sf_dir, count=40), clusters)).agg(F.count("*").alias("met"))
    c = clusters.agg(F.countDistinct("cid").alias("clusters"))
    return c.crossJoin(met).select("clusters", F.expr("clusters * (clusters - 1) div 2 - met").alias("edgeless"))


@query(EVENTS + "SELECT bool_and(q > 0.5) AS agrees, count(*) AS answers FROM lab WHERE is_yes")
def agreement_check(spark, sf_dir):
    inside = event_lab(spark, sf_dir).where("is_yes").select("u", "w", "p")
    return Q.agrees(inside, W.gold_clusters(W.event_gold(spark)))


#: After five more votes, two of them YES, on the question of the clusters 0 and 1.
AFTER = EVENTS.replace("\ngold AS", "\nnow AS (SELECT * FROM edges UNION ALL SELECT 0, 1, 5, 2, 0.4::DOUBLE),\ngold AS", 1).replace("FROM edges JOIN gold a", "FROM now JOIN gold a", 1)


@query(AFTER + GAP.replace("LEFT JOIN edges e", "LEFT JOIN now e") + "SELECT 'across' AS kind, c1, c2, u, w, round(prio, 8) AS prio FROM top")
def queue_refresh(spark, sf_dir):
    """A kept queue after an answer: only the touched unit is judged anew, and it equals a queue built from nothing."""
    clusters, edges = W.gold_clusters(W.event_gold(spark)), event_edges(spark, sf_dir)
    queue = Q.across_candidates(V.labelled(edges, clusters), clusters)
    asked = queue.where("c1 = 0 AND c2 = 1").select("u", "w")
    answers = asked.select("u", "w", F.explode(F.sequence(F.lit(0), F.lit(4))).alias("worker")).select("u", "w", "worker", (F.col("worker") < 2).alias("yes"))
    touched = Q.units_of(asked, clusters)
    fresh = Q.unit_queue(V.labelled(V.add_answers(edges, answers), clusters), clusters, 1, touched=touched)
    return rounded(Q.refresh_units(queue, fresh, touched).select("kind", "c1", "c2", "u", "w", "prio"), "prio")


@query(AFTER + "SELECT u, w, n_votes, n_yes, round(p, 8) AS p FROM now")
def graph_update(spark, sf_dir):
    """The uncertain graph after a batch of answers to a pair that was never asked."""
    graph = V.UncertainGraph.of(W.event_gold(spark), W.event_votes(spark, sf_dir))
    more = spark.range(5).select(F.lit(0).cast("long").alias("u"), F.lit(1).cast("long").alias("w"), F.col("id").alias("worker"), (F.col("id") < 2).alias("yes"))
    return rounded(graph.add(more).edges, "p")


@query()
def loop_w2_dataframe(spark, sf_dir):
    """Three rounds of the full loop on DataFrames; one row for each round."""
    return _loop(spark, sf_dir, Config(batch=40, initial=200), 3)


@query()
def loop_empty_start(spark, sf_dir):
    """From an empty graph, where every first question is a pair without an answer."""
    return _loop(spark, sf_dir, Config(batch=120, initial="none"), 2)


@query()
def loop_spanning_start(spark, sf_dir):
    """From a path through all records, with a budget."""
    return _loop(spark, sf_dir, Config(batch=60, initial="spanning", budget=100), None)


def _loop(spark, sf_dir, k, rounds):
    from crowdlink.plans.loop import resolve

    records = W.gold(spark, sf_dir, "w2")
    pairs = W.pool(records, "w2")
    ask = lambda p: W.simulate_votes(pairs.join(p.select("u", "w"), ["u", "w"]), 5, 0.1065)
    _, _, log = resolve(records, ask, None, k, rounds)
    return spark.createDataFrame(log, "round int, asked long, reclustered boolean, greatest_gain double, loglik double, reliability double")


# baselines


@query(recursive(W2) + COMPONENTS.replace("p > 0.5", "2 * n_yes > n_votes") + "SELECT rid, cid FROM comp")
def tc_clusters(spark, sf_dir):
    return B.transitive_clusters(V.build_edges(W.votes(spark, sf_dir, "w2"), "majority"), W.gold(spark, sf_dir, "w2"))


TC = """, told AS (SELECT u, w, CASE WHEN 2 * n_yes > n_votes THEN 1 ELSE 0 END AS p FROM asked),
adj AS (SELECT u AS a, w AS b FROM told WHERE p > 0.5 UNION SELECT w, u FROM told WHERE p > 0.5),
reach AS (SELECT rid AS a, rid AS b FROM gold UNION SELECT r.a, adj.b FROM reach r JOIN adj ON r.b = adj.a),
comp AS (SELECT a AS rid, min(b) AS cid FROM reach GROUP BY a),
no AS (SELECT DISTINCT least(a.cid, b.cid) AS c1, greatest(a.cid, b.cid) AS c2 FROM told JOIN comp a ON a.rid = u JOIN comp b ON b.rid = w WHERE p <= 0.5),
rel AS (SELECT p.u, p.w, CASE WHEN a.cid = b.cid AND no.c1 IS NOT NULL THEN 'conflict' WHEN a.cid = b.cid THEN 'match' WHEN no.c1 IS NOT NULL THEN 'non_match' ELSE 'unknown' END AS relation
        FROM pairs p JOIN comp a ON a.rid = p.u JOIN comp b ON b.rid = p.w LEFT JOIN no ON c1 = least(a.cid, b.cid) AND c2 = greatest(a.cid, b.cid))
"""


def _tc(spark, sf_dir):
    records = W.gold(spark, sf_dir, "w2")
    majority = w2_started(spark, sf_dir, "majority")
    return W.pool(records, "w2"), majority, B.transitive_clusters(majority, records)


@query(recursive(started(W2)) + TC + "SELECT u, w, relation FROM rel")
def tc_inferable_pairs(spark, sf_dir):
    return B.infer_pairs(*_tc(spark, sf_dir))


@query(recursive(started(W2)) + TC + """SELECT u, w FROM rel WHERE relation = 'unknown' AND (u, w) NOT IN (SELECT (u, w) FROM asked)
ORDER BY ('0x' || substr(md5('42|' || u || '|' || w || '|tc'), 1, 8))::BIGINT, u, w LIMIT 40""")
def tc_next(spark, sf_dir):
    return B.transitive_next(*_tc(spark, sf_dir), 40, 42)


@query("SELECT u, w FROM (" + started(W2) + """SELECT u, w FROM pairs WHERE (u, w) NOT IN (SELECT (u, w) FROM asked) ORDER BY ('0x' || substr(md5('42|' || u || '|' || w || '|random'), 1, 8))::BIGINT, u, w LIMIT 40)""")
def random_next(spark, sf_dir):
    pairs = W.pool(W.gold(spark, sf_dir, "w2"), "w2")
    return B.random_next(pairs, w2_started(spark, sf_dir), 40, 42)


DENSITY = """, g AS (SELECT rid, min(rid) OVER (PARTITION BY entity) AS cid FROM gold),
unit AS (SELECT least(a.cid, b.cid) AS c1, greatest(a.cid, b.cid) AS c2, sum((2 * n_yes > n_votes)::INT)::BIGINT AS n_pos, sum((2 * n_yes <= n_votes)::INT)::BIGINT AS n_neg
         FROM asked JOIN g a ON a.rid = u JOIN g b ON b.rid = w GROUP BY 1, 2),
ratio AS (SELECT *, CASE WHEN c1 = c2 THEN n_pos ELSE n_neg END * log10(0.9 / (1 - 0.9)) AS log_ratio FROM unit)
"""


@query(started(W2) + DENSITY + "SELECT c1, c2, n_pos, n_neg, round(log_ratio, 6) AS log_ratio FROM ratio")
def density_ratio(spark, sf_dir):
    fixed = w2_started(spark, sf_dir, "fixed_accuracy")
    return rounded(B.density_ratio(fixed, W.gold_clusters(W.gold(spark, sf_dir, "w2"))), "log_ratio", digits=6)


@query(started(W2) + DENSITY + """, free AS (SELECT least(a.cid, b.cid) AS c1, greatest(a.cid, b.cid) AS c2, min((u, w)) AS m FROM pairs JOIN g a ON a.rid = u JOIN g b ON b.rid = w WHERE (u, w) NOT IN (SELECT (u, w) FROM asked) GROUP BY 1, 2)
SELECT m[1] AS u, m[2] AS w, round(log_ratio, 6) AS log_ratio FROM free JOIN ratio USING (c1, c2) ORDER BY round(log_ratio, 9) DESC, u, w LIMIT 10""")
def density_next(spark, sf_dir):
    records = W.gold(spark, sf_dir, "w2")
    fixed = w2_started(spark, sf_dir, "fixed_accuracy")
    return rounded(B.density_next(W.pool(records, "w2"), fixed, W.gold_clusters(records), 10), "log_ratio", digits=6)


TURN = """, turn AS (SELECT row_number() OVER (PARTITION BY least(a.cid, b.cid), greatest(a.cid, b.cid) ORDER BY u, w) AS turn, u, w, log_ratio
FROM pairs JOIN g a ON a.rid = u JOIN g b ON b.rid = w JOIN ratio r ON r.c1 = least(a.cid, b.cid) AND r.c2 = greatest(a.cid, b.cid) WHERE (u, w) NOT IN (SELECT (u, w) FROM asked))
SELECT u, w, turn, round(log_ratio, 6) AS log_ratio FROM turn ORDER BY turn, round(log_ratio, 9) {}, u, w LIMIT 80"""


@query(started(W2) + DENSITY + TURN.format("DESC"))
def density_batch(spark, sf_dir):
    """One pair of each unit by its ratio, then the next of each, and so on."""
    records = W.gold(spark, sf_dir, "w2")
    return rounded(B.density_batch(W.pool(records, "w2"), w2_started(spark, sf_dir, "fixed_accuracy"), W.gold_clusters(records), 80), "log_ratio", digits=6)


@query(started(W2) + DENSITY + TURN.format("ASC"))
def density_batch_opposite(spark, sf_dir):
    """The other reading of the ratio: weakest units first."""
    records = W.gold(spark, sf_dir, "w2")
    return rounded(B.density_batch(W.pool(records, "w2"), w2_started(spark, sf_dir, "fixed_accuracy"), W.gold_clusters(records), 80, rank="asc"), "log_ratio", digits=6)


#: Widest positive paths by closure over (ends, weight); a negative path has one refusing edge between two of them.
PATHS = """, e AS (SELECT u, w, round(p, 9) AS p, round(1 - p, 9) AS r FROM edges),
both_ways AS (SELECT u AS a, w AS b, p FROM e WHERE p > 0.5 UNION ALL SELECT w, u, p FROM e WHERE p > 0.5),
walk AS (SELECT rid AS a, rid AS b, 1.0::DOUBLE AS wide FROM gold UNION SELECT k.a, s.b, least(k.wide, s.p) FROM walk k JOIN both_ways s ON s.a = k.b),
wide AS (SELECT a, b, max(wide) AS wide FROM walk GROUP BY a, b),
refusing AS (SELECT u AS a, w AS b, r FROM e WHERE r > 0.5 UNION ALL SELECT w, u, r FROM e WHERE r > 0.5),
no_path AS (SELECT x.a AS u, y.b AS w, max(least(x.wide, r, y.wide)) AS neg FROM wide x JOIN refusing f ON f.a = x.b JOIN wide y ON y.a = f.b WHERE x.a < y.b GROUP BY 1, 2),
yes_path AS (SELECT a AS u, b AS w, wide AS pos FROM wide WHERE a < b),
rel AS (SELECT u, w, coalesce(pos, 0) AS pos, CASE WHEN coalesce(neg, 0) > coalesce(pos, 0) THEN neg ELSE 0 END AS neg FROM yes_path FULL JOIN no_path USING (u, w)),
relation AS (SELECT *, pos > neg AS decision FROM rel)
"""


@query(recursive(EVENTS) + PATHS + "SELECT u, w, pos, neg, decision FROM relation")
def bottleneck_relation(spark, sf_dir):
    return B.bottleneck_relation(event_edges(spark, sf_dir), W.event_gold(spark))


@query(recursive(EVENTS) + PATHS + """, adj AS (SELECT u AS a, w AS b FROM relation WHERE decision UNION SELECT w, u FROM relation WHERE decision),
reach AS (SELECT rid AS a, rid AS b FROM gold UNION SELECT r.a, adj.b FROM reach r JOIN adj ON r.b = adj.a) SELECT a AS rid, min(b) AS cid FROM reach GROUP BY a""")
def bottleneck_clusters(spark, sf_dir):
    records = W.event_gold(spark)
    return B.bottleneck_clusters(B.bottleneck_relation(event_edges(spark, sf_dir), records), records)


@query(recursive(EVENTS) + PATHS + """SELECT u, w, round(greatest(pos, CASE WHEN NOT decision THEN 1 - neg ELSE 0 END), 8) AS score FROM relation WHERE (u, w) NOT IN (SELECT (u, w) FROM edges)
ORDER BY round(greatest(pos, CASE WHEN NOT decision THEN 1 - neg ELSE 0 END), 9) DESC, u, w LIMIT 10""")
def bottleneck_next(spark, sf_dir):
    records, edges = W.event_gold(spark), event_edges(spark, sf_dir)
    pairs = records.select(F.col("rid").alias("u")).join(records.select(F.col("rid").alias("w")), F.col("u") < F.col("w"))
    return rounded(B.bottleneck_next(B.bottleneck_relation(edges, records), pairs, edges, 10), "score")


@query("""WITH n AS (SELECT count(DISTINCT l_linenumber) AS lines FROM lineitem)
SELECT 'many weak paths' AS fault, 0::BIGINT AS u, 1000000::BIGINT AS w, 0.6::DOUBLE AS pos, 0.7::DOUBLE AS neg, false AS decision FROM n UNION ALL
SELECT 'one long path', 2000000, 2000000 + lines, 0.8, 0.0, true FROM n""")
def bottleneck_faults(spark, sf_dir):
    """Two graphs where the best path misleads: it overlooks how many other paths there are, and how long it is.

    In the one each line number of the orders is a path of two edges, in the other each is a step of one path.
    """
    lines = cut(spark.read.parquet(f"{sf_dir}/lineitem.parquet").select("l_linenumber").distinct().select((F.row_number().over(Window.orderBy("l_linenumber"))).cast("long").alias("x")), "lines")
    last = lines.agg(F.max("x")).first()[0]
    edge = lambda u, w, p: lines.select(u.cast("long").alias("u"), w.cast("long").alias("w"), F.lit(p).alias("p"))
    direct = lambda u, w: spark.createDataFrame([(u, w, 0.3)], "u long, w long, p double")
    many = edge(F.lit(0), F.col("x"), 0.6).unionByName(edge(F.col("x"), F.lit(1_000_000), 0.6)).unionByName(direct(0, 1_000_000))
    long = edge(F.col("x") + 1_999_999, F.col("x") + 2_000_000, 0.8).unionByName(direct(2_000_000, 2_000_000 + last))
    out = None
    for name, edges, u, w in (("many weak paths", many, 0, 1_000_000), ("one long path", long, 2_000_000, 2_000_000 + last)):
        one = B.bottleneck_relation(edges, edges.select(F.col("u").alias("rid"))).where((F.col("u") == u) & (F.col("w") == w)).select(F.lit(name).alias("fault"), "u", "w", "pos", "neg", "decision")
        out = one if out is None else out.unionByName(one)
    return out


@query(EVENTS + "SELECT rid, cid, round(sum(1 - 2 * p), 8) AS benefit, count(*) AS n_edges FROM (SELECT u AS rid, cu AS cid, p FROM lab WHERE is_yes UNION ALL SELECT w, cu, p FROM lab WHERE is_yes) GROUP BY rid, cid")
def pivot_split_benefit(spark, sf_dir):
    return rounded(B.split_benefit(event_lab(spark, sf_dir)), "benefit")


@query(EVENTS + "SELECT least(cu, cw) AS c1, greatest(cu, cw) AS c2, round(sum(2 * p - 1), 8) AS benefit, count(*) AS n_edges FROM lab WHERE NOT is_yes GROUP BY 1, 2")
def pivot_merge_benefit(spark, sf_dir):
    return rounded(B.merge_benefit(event_lab(spark, sf_dir)), "benefit")


@query(started(W2) + """, g AS (SELECT rid, min(rid) OVER (PARTITION BY entity) AS cid FROM gold),
free AS (SELECT u, w, least(a.cid, b.cid) AS c1, greatest(a.cid, b.cid) AS c2 FROM pairs JOIN g a ON a.rid = u JOIN g b ON b.rid = w WHERE a.cid <> b.cid AND (u, w) NOT IN (SELECT (u, w) FROM asked)),
gain AS (SELECT least(a.cid, b.cid) AS c1, greatest(a.cid, b.cid) AS c2, sum(2 * p - 1) AS benefit FROM asked JOIN g a ON a.rid = u JOIN g b ON b.rid = w WHERE a.cid <> b.cid GROUP BY 1, 2),
worth AS (SELECT c1, c2, benefit / n AS worth FROM gain JOIN (SELECT c1, c2, count(*) AS n FROM free GROUP BY 1, 2) USING (c1, c2))
SELECT u, w, round(worth, 8) AS worth FROM free JOIN worth USING (c1, c2) ORDER BY round(worth, 9) DESC, u, w LIMIT 20""")
def pivot_next(spark, sf_dir):
    records = W.gold(spark, sf_dir, "w2")
    return rounded(B.pivot_next(W.pool(records, "w2"), w2_started(spark, sf_dir), W.gold_clusters(records), 20), "worth")


@query("WITH n AS (SELECT count(*) AS n FROM embeddings WHERE vec_id < 94) SELECT (n * (n - 1) // 2)::BIGINT AS pairs, 0::BIGINT AS unasked FROM n")
def ask_everything(spark, sf_dir):
    """The reference of accuracy: all pairs are asked, and none is left."""
    from crowdlink.plans.loop import initial_pairs

    records = W.gold(spark, sf_dir, "w2")
    every = initial_pairs(records, Config(initial="all"))
    left = W.pool(records, "w2").join(every, ["u", "w"], "left_anti").agg(F.count("*").alias("unasked"))
    return every.agg(F.count("*").alias("pairs")).crossJoin(left)


# measures


@query(EVENTS.replace("WITH", "WITH RECURSIVE", 1) + COMPONENTS + """, n AS (SELECT (SELECT coalesce(sum(c * (c - 1) / 2), 0)::BIGINT FROM (SELECT count(*) AS c FROM comp JOIN gold USING (rid) GROUP BY comp.cid, entity)) AS correct,
(SELECT coalesce(sum(c * (c - 1) / 2), 0)::BIGINT FROM (SELECT count(*) AS c FROM comp GROUP BY cid)) AS reported, (SELECT sum(c * (c - 1) / 2)::BIGINT FROM (SELECT count(*) AS c FROM gold GROUP BY entity)) AS matching)
SELECT correct, reported, matching, round(coalesce(correct / nullif(reported, 0), 0), 8) AS "precision", round(correct / matching, 8) AS recall,
round(coalesce(2 * correct / nullif(reported + matching, 0), 0), 8) AS f1 FROM n""")
def pair_scores_components(spark, sf_dir):
    records = W.event_gold(spark)
    return rounded(M.pair_scores(C.positive_components(event_edges(spark, sf_dir), records), records), "precision", "recall", "f1")


SCORES = """, n AS (SELECT (SELECT coalesce(sum(c * (c - 1) / 2), 0)::BIGINT FROM (SELECT count(*) AS c FROM found JOIN gold USING (rid) GROUP BY found.cid, entity)) AS correct,
(SELECT coalesce(sum(c * (c - 1) / 2), 0)::BIGINT FROM (SELECT count(*) AS c FROM found GROUP BY cid)) AS reported, (SELECT sum(c * (c - 1) / 2)::BIGINT FROM (SELECT count(*) AS c FROM gold GROUP BY entity)) AS matching)
SELECT correct, reported, matching, round(coalesce(correct / nullif(reported, 0), 0), 8) AS "precision", round(correct / matching, 8) AS recall,
round(coalesce(2 * correct / nullif(reported + matching, 0), 0), 8) AS f1 FROM n"""


@query(recursive(W2) + greedy_sql("gold") + SCORES)
def pair_scores_scc(spark, sf_dir):
    records = W.gold(spark, sf_dir, "w2")
    return rounded(M.pair_scores(C.scc(V.build_edges(W.votes(spark, sf_dir, "w2")), records), records), "precision", "recall", "f1")


@query(recursive(W2) + COMPONENTS.replace("p > 0.5", "2 * n_yes > n_votes").replace("comp AS", "found AS") + SCORES)
def pair_scores_tc(spark, sf_dir):
    """The closure of all majority answers: one wrong YES joins two entities."""
    records = W.gold(spark, sf_dir, "w2")
    return rounded(M.pair_scores(B.transitive_clusters(V.build_edges(W.votes(spark, sf_dir, "w2"), "majority"), records), records), "precision", "recall", "f1")


@query("""WITH mean AS (SELECT user_id % 3 AS workload, event_type AS method, avg(value) AS cost FROM events GROUP BY ALL)
SELECT workload::VARCHAR AS workload, m.method, round(100 * (1 - o.cost / m.cost), 2) AS saved_percent FROM mean m JOIN mean o USING (workload) WHERE m.method <> 'purchase' AND o.method = 'purchase'""")
def cost_reduction_published(spark, sf_dir):
    """The measure that the published costs are compared by, on the events: their values as costs, their types as methods."""
    e = spark.read.parquet(f"{sf_dir}/events.parquet")
    costs = e.select((F.col("user_id") % 3).cast("string").alias("workload"), F.col("event_type").alias("method"), F.lit(0.9).alias("target"), F.col("value").alias("n_next"))
    return M.cost_reduction(costs, "purchase").select("workload", "method", "saved_percent")


@query()
def question_cost(spark, sf_dir):
    return M.question_cost(X.whole(spark, sf_dir, "w2"))


# experiments: every one is all its runs at once, ten seeds, each run a task, until the target or the pool's end


@query()
def experiment_w1(spark, sf_dir):
    return X.whole(spark, sf_dir, "w1")


@query()
def experiment_w2(spark, sf_dir):
    return X.whole(spark, sf_dir, "w2")


@query()
def experiment_w3(spark, sf_dir):
    return X.whole(spark, sf_dir, "w3")


@query()
def experiment_w4(spark, sf_dir):
    return X.whole(spark, sf_dir, "w4")


@query()
def experiment_w4b(spark, sf_dir):
    """Near copies among the documents as entities."""
    return X.whole(spark, sf_dir, "w4b")


@query()
def experiment_w4d(spark, sf_dir):
    return X.whole(spark, sf_dir, "w4d")


@query()
def experiment_w2_uneven_errors(spark, sf_dir):
    """The same mean error, all of it on a hashed half of the pairs."""
    return X.run(spark, sf_dir, "w2", X.settings("w2", seeds=X.SEEDS), hard=True)


@query()
def experiment_w2_low_error(spark, sf_dir):
    return X.run(spark, sf_dir, "w2", X.settings("w2", seeds=X.SEEDS, errs=[0.05]))


COSTS = ["reliability", "minmax", "bdense", "pivot", "tc", "random"]


@query()
def cost_to_reach_w2(spark, sf_dir):
    return M.cost_reduction(M.cost_to_reach(X.whole(spark, sf_dir, "w2"), [0.75, 0.8, 0.85, 0.9, 0.95]))


@query()
def cost_table(spark, sf_dir):
    """Questions of every method to each target on the three smaller sets, and what reliability saves."""
    rounds = X.whole(spark, sf_dir, "w1").unionByName(X.whole(spark, sf_dir, "w2")).unionByName(X.whole(spark, sf_dir, "w3"))
    return M.cost_table(M.cost_to_reach(rounds, [0.75, 0.8, 0.85, 0.9, 0.95]), COSTS)


@query()
def cost_table_w4(spark, sf_dir):
    return M.cost_table(M.cost_to_reach(X.whole(spark, sf_dir, "w4"), [0.5, 0.6, 0.7, 0.8]), COSTS)


@query()
def cost_long(spark, sf_dir):
    """The table of costs turned back to one row for each method."""
    table = cost_table(spark, sf_dir).select("workload", "target", *COSTS)
    return table.unpivot(["workload", "target"], COSTS, "method", "n_next").where("n_next IS NOT NULL")


@query()
def select_time_w3(spark, sf_dir):
    return M.select_time(X.whole(spark, sf_dir, "w3"))


@query()
def select_time_w4(spark, sf_dir):
    return M.select_time(X.whole(spark, sf_dir, "w4"), 0.8)


@query()
def batch_sweep_w2(spark, sf_dir):
    """Questions to the target by batch size."""
    rows = X.settings("w2", methods=("reliability", "bdense"), batches=[1, 5, 10, 20, 40, 80])
    return X.run(spark, sf_dir, "w2", rows).groupBy("workload", "method", "batch").agg(F.min(F.when(F.col("f1") >= 0.95, F.col("n_next"))).alias("n_next"), F.max("f1").alias("best_f1"))


@query()
def initial_sweep_w2(spark, sf_dir):
    rows = X.settings("w2", methods=("reliability",), seeds=X.SEEDS, initials=[0, -1, 100, 200, 400])
    return M.cost_to_reach(X.run(spark, sf_dir, "w2", rows).withColumn("workload", F.concat_ws("/", "workload", "initial")), [0.95])


@query()
def error_sweep_w2(spark, sf_dir):
    rows = X.settings("w2", methods=("reliability", "tc", "random"), seeds=X.SEEDS, errs=[0.0, 0.05, 0.1, 0.2, 0.2777])
    return M.cost_to_reach(X.run(spark, sf_dir, "w2", rows).withColumn("workload", F.concat_ws("/", "workload", "err")), [0.95])


@query()
def recluster_rate(spark, sf_dir):
    return M.recluster_rate(X.run(spark, sf_dir, "w2", X.settings("w2", methods=("reliability",), batches=[1, 10, 40])))


@query()
def mean_over_runs(spark, sf_dir):
    return M.over_runs(X.whole(spark, sf_dir, "w2"))


from crowdlink import relational  # noqa: E402

QUERIES |= relational.QUERIES
ORACLES |= relational.ORACLES
