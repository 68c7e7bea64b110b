"""Queries against their SQL on the smallest tables, plans, loops and streams."""

import math

import duckdb
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from crowdlink import queries as core

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def con():
    c = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        c.execute(f"create view {t} as select * from read_parquet('{SF}/{t}.parquet')")
    return c


def rows_of(columns, rows):
    order = sorted(range(len(columns)), key=lambda k: columns[k])
    text = lambda v: "nan" if isinstance(v, float) and math.isnan(v) else str(v)
    return sorted(columns), sorted(tuple(text(r[k]) for k in order) for r in rows)


@pytest.mark.parametrize("name", sorted(core.ORACLES))
def test_query_equals_sql(spark, con, name):
    df = core.QUERIES[name](spark, SF)
    r = con.execute(core.ORACLES[name])
    assert rows_of(df.columns, [tuple(x) for x in df.collect()]) == rows_of([c[0] for c in r.description], r.fetchall())


@pytest.mark.parametrize("name", ["scc_rounds_mode", "scc_warm_start", "pivot_refined", "next_inside_sampled", "weak_clusters_first", "loop_empty_start", "block_minhash", "block_vectors", "block_jaccard"])
def test_query_gives_rows(spark, name):
    assert core.QUERIES[name](spark, SF).count() > 0


def test_entry(spark):
    assert entry.entry(spark).count() > 0


def test_methods_reach_the_target_in_the_expected_order(spark):
    from crowdlink.operators import measures
    from crowdlink.plans import experiments

    rows = experiments.settings("w2", methods=("reliability", "bdense", "tc", "random"), seeds=(42, 43, 44))
    rounds = experiments.run(spark, "/root/testdata/sf0.01", "w2", rows)
    cost = {}
    for r in measures.cost_to_reach(rounds, [0.95]).collect():
        cost.setdefault(r.method, []).append(r.n_next)
    mean = {m: sum(x) / len(x) for m, x in cost.items() if None not in x}
    assert mean["reliability"] < mean["random"] and mean["reliability"] < mean["bdense"]
    assert None in cost["tc"]


def test_no_cartesian_and_pushed_filters(spark):
    plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
    for name in ("edges_lineitem", "disconnect_pairs", "gap_representative", "join_asof"):
        assert "CartesianProduct" not in plan(core.QUERIES[name](spark, SF))
    assert "PushedFilters: [IsNotNull(o_orderkey)" in plan(core.QUERIES["scan_project_filter"](spark, SF))


def test_answer_loop_is_idempotent(spark):
    from crowdlink.sources import workloads
    from crowdlink.streaming import answers

    votes, calls = workloads.event_votes(spark, SF), []
    seen = lambda n, e, c, again: calls.append((n, e.count(), again))
    step = answers.answer_loop(None, workloads.event_gold(spark), seen=seen)
    step(votes.where("worker < 5"), 0)
    step(votes.where("worker < 5"), 0)
    later = answers.answer_loop(None, workloads.event_gold(spark), seen=seen, folder=step.folder)  # another driver
    later(votes.where("worker < 5"), 0)
    later(votes.where("worker >= 3"), 1)  # some votes come again in another batch
    assert [c[0] for c in calls] == [0, 1] and calls[1][1] >= calls[0][1]
    assert {(r.u, r.w): r.n_votes for r in later.edges().collect()} == {(r.u, r.w): r["count"] for r in votes.groupBy("u", "w").count().collect()}


def test_late_votes_split_at_the_exact_middle(spark, tmp_path):
    from crowdlink.streaming import answers

    rows = spark.range(600_000).select("id", F.timestamp_micros(1_704_067_200_000_000 + F.pmod(F.xxhash64("id"), F.lit(2_592_000_000_000))).cast("timestamp_ntz").alias("ts"))
    rows.repartition(6).write.parquet(str(tmp_path / "events.parquet"))
    sql = core.ORACLES["stream_late"].replace("FROM events", f"FROM read_parquet('{tmp_path}/events.parquet/*.parquet')")
    assert tuple(answers.late_votes(spark, str(tmp_path)).first()) == duckdb.sql(sql).fetchall()[0]


@pytest.mark.parametrize("name", ["stream_dedup", "stream_join", "stream_sessions"])
def test_appended_rows_of_a_stream_are_in_files(spark, name):
    assert core.QUERIES[name](spark, SF).inputFiles()  # the driver holds none of them


@pytest.mark.parametrize("name", ["bottleneck_faults", "cost_reduction_published", "partition_counts", "source_crowd_votes", "stream_crowd_votes", "stream_rate"])
def test_query_needs_its_given_table(spark, tmp_path, name):
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        core.QUERIES[name](spark, str(tmp_path)).count()


def test_a_stream_that_falls_short_is_no_result(spark):
    from crowdlink.streaming import answers

    rows = spark.readStream.format("rate-micro-batch").option("rowsPerBatch", 5).load().select("value")
    with pytest.raises(TimeoutError, match="falls_short has 3 of 4"):
        answers.run_until(rows.where("value < 3"), "falls_short", "append", 4, seconds=3)
    with pytest.raises(Exception, match="no value of this kind"):
        answers.run_until(rows.select(F.when(F.col("value") > 7, F.raise_error(F.lit("no value of this kind")).cast("long")).otherwise(F.col("value")).alias("value")), "fails", "append", 1_000)


def test_rate_calls_up_events_of_any_id(spark, tmp_path):
    ids = [None, -4, 0, 7, 7, 10**15]
    spark.createDataFrame([(x, "ab"[n % 2]) for n, x in enumerate(ids)], "event_id long, event_type string").write.parquet(str(tmp_path / "events.parquet"))
    assert sorted(map(tuple, core.QUERIES["stream_rate"](spark, str(tmp_path)).collect())) == [("a", 3), ("b", 3)]


def test_votes_of_suppliers_are_summed_after_the_shuffle(spark, monkeypatch):
    monkeypatch.setattr(core.C, "scc", lambda edges, records: edges)
    plan = core.QUERIES["scc_lineitem"](spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert plan.index("partial_count") < plan.index("Exchange hashpartitioning(u")  # upper steps stand first
