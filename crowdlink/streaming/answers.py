"""Votes as a stream: deduplicated, counted by pair, completed, windowed, joined with questions and gold."""

from __future__ import annotations

from collections.abc import Callable

import math
import time

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout

from crowdlink.config import Config
from crowdlink.operators.clustering import scc
from crowdlink.operators.questions import agrees
from crowdlink.operators.votes import build_edges, canonical_votes
from crowdlink.storage import cut, new_path

LATE = "2 hours"


def vote_stream(spark: SparkSession, sf_dir: str, ended: bool = False) -> DataFrame:
    """Votes (ts, u, w, worker, yes, kind) from the events files as they appear, with a watermark.

    If ``ended``, a last vote of pair (-1, 9) in the far future comes with the others. It moves the watermark behind
    them all, so that a run over what is there gives every row in append mode; what the mark opens itself never closes.
    """
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    e = spark.readStream.schema(schema).parquet(f"{sf_dir}/events.parquet*")
    if ended:
        mark, path = {"ts": "timestamp'9999-01-01'", "event_type": "'click'", "props": """'{"k": -1}'"""}, new_path(spark, "end")
        spark.range(1).select(*(F.expr(f"cast({mark.get(c, 'null')} as {kind})").alias(c) for c, kind in spark.createDataFrame([], schema).dtypes)).write.parquet(path)
        e = e.unionByName(spark.readStream.schema(schema).parquet(path))
    k = F.get_json_object("props", "$.k").cast("long")
    u, w = F.floor(k / 10), 10 + k % 10
    rows = e.select("event_id", F.col("ts").cast("timestamp").alias("ts"), u.alias("u"), w.alias("w"), F.col("user_id").alias("worker"), ((u % 5 == w % 5) != (F.col("event_type") == "error")).alias("yes"), (F.col("event_type") == "error").alias("wrong"), "event_type")
    return rows.withWatermark("ts", LATE)


def deduplicated(votes: DataFrame) -> DataFrame:
    """One vote for a pair and worker within the allowed lateness."""
    return votes.dropDuplicatesWithinWatermark(["u", "w", "worker"])


def edge_state(votes: DataFrame) -> DataFrame:
    return votes.groupBy("u", "w").agg(F.count("*").cast("int").alias("n_votes"), F.count_if("yes").cast("int").alias("n_yes"))


def windowed(votes: DataFrame, size: str = "6 hours", slide: str | None = None) -> DataFrame:
    """Votes and the share of wrong ones in tumbling or sliding windows."""
    win = F.window("ts", size, slide) if slide else F.window("ts", size)
    return votes.groupBy(win.alias("win")).agg(F.count("*").alias("n_votes"), F.count_if("wrong").alias("n_wrong")).select(F.col("win.start").alias("start"), "n_votes", "n_wrong")


def sittings(votes: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """A worker's sessions."""
    win = F.session_window("ts", gap)
    return votes.groupBy("worker", win.alias("win")).agg(F.count("*").alias("n_votes")).select("worker", F.col("win.start").alias("start"), F.col("win.end").alias("end"), "n_votes")


def completed_pairs(votes: DataFrame, voters: int = 5, patience: str = "1 day") -> DataFrame:
    """Rows ``(u, w, n_votes, n_yes, full)``: a pair once it has its votes, or what it has when patience ends."""
    wait = int(pd.Timedelta(patience).total_seconds() * 1000)

    def step(key, frames, state):
        n, yes, done = state.get if state.exists else (0, 0, False)
        if state.hasTimedOut:
            state.update((n, yes, True))
            if not done:
                yield pd.DataFrame({"u": [key[0]], "w": [key[1]], "n_votes": [n], "n_yes": [yes], "full": [False]})
            return
        for y in pd.concat(list(frames)).sort_values("event_id")["yes"].tolist():  # a pair's votes of one batch
            if n < voters:
                n, yes = n + 1, yes + int(y)
        if n >= voters and not done:
            yield pd.DataFrame({"u": [key[0]], "w": [key[1]], "n_votes": [n], "n_yes": [yes], "full": [True]})
            done = True
        state.update((n, yes, done))
        if not done:
            state.setTimeoutTimestamp(max(state.getCurrentWatermarkMs(), 0) + wait)

    return votes.groupBy("u", "w").applyInPandasWithState(step, "u long, w long, n_votes long, n_yes long, full boolean", "n long, yes long, done boolean", "append", GroupStateTimeout.EventTimeTimeout)


def answered_in_time(questions: DataFrame, votes: DataFrame, within: str = "24 hours") -> DataFrame:
    """Questions (u, w, asked_at) with the votes that arrive within the time; both sides have watermarks.

    A question stands in each quarter of the time that it is open in, so a vote meets only the questions near it.
    """
    quarter = int(pd.Timedelta(within).total_seconds() * 1_000_000) // 4
    part = lambda c: F.floor(F.unix_micros(c) / quarter)
    asked = F.col("asked_at")
    q = questions.withColumn("part", F.explode(F.sequence(part(asked), part(asked + F.expr(f"INTERVAL {within}"))))).alias("q")
    v = votes.withColumn("part", part(F.col("ts"))).alias("v")
    met = (F.col("q.u") == F.col("v.u")) & (F.col("q.w") == F.col("v.w")) & (F.col("q.part") == F.col("v.part")) & (F.col("v.ts") >= F.col("q.asked_at")) & (F.col("v.ts") <= F.col("q.asked_at") + F.expr(f"INTERVAL {within}"))
    return q.join(v, met).select(*(f"q.{c}" for c in questions.columns), "v.ts", "v.worker", "v.yes")


def answer_counts(questions: DataFrame, votes: DataFrame) -> DataFrame:
    """Rows ``(u, w, question, answers)`` once a question's time is over; the answers are counted where they meet."""
    met = answered_in_time(questions, votes).select("u", "w", "question", "asked_at")
    return met.groupBy("u", "w", "question", "asked_at").agg(F.count("*").alias("answers")).drop("asked_at")


def with_gold(votes: DataFrame, gold: DataFrame) -> DataFrame:
    eu, ew = (gold.select(F.col("rid").alias(c), F.col("entity").alias(f"e{c}")) for c in ("u", "w"))
    return votes.join(eu, "u").join(ew, "w").withColumn("same", F.col("eu") == F.col("ew"))


def run_once(stream: DataFrame, name: str, mode: str) -> DataFrame:
    """All that is there: appended rows in files of the shared folder, few changing rows in a memory table of that name."""
    spark, path = stream.sparkSession, None
    query = _memory(stream, name, mode)
    if mode == "append":
        path = new_path(spark, f"rows-{name}")
        query = query.format("parquet").option("path", path)
    query.trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(path) if path else spark.table(name)


def run_until(stream: DataFrame, name: str, mode: str, rows: int, seconds: float = 120, measure: str = "count(*)") -> DataFrame:
    """A stream without an end, into a memory table of that name, until it has so many rows, or so much of ``measure``.

    Fewer are never a result: a stream that fails raises its error, and one that gets no more for ``seconds`` a TimeoutError.
    """
    query, got, end = _memory(stream, name, mode).start(), None, 0.0
    try:
        while (now := stream.sparkSession.table(name).agg(F.expr(measure)).first()[0] or 0) < rows:
            if got is None or now > got:
                got, end = now, time.monotonic() + seconds
            if not query.isActive:
                query.awaitTermination()  # raises the stream's own error
                raise RuntimeError(f"stream {name} ended with {now} of {rows}")
            if time.monotonic() >= end:
                raise TimeoutError(f"stream {name} has {now} of {rows}, and no more for {seconds} seconds")
            time.sleep(0.2)
    finally:
        query.stop()
    return stream.sparkSession.table(name)


def _memory(stream: DataFrame, name: str, mode: str):
    return stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", new_path(stream.sparkSession, f"stream-{name}"))


def _micros():
    return F.unix_micros(F.col("ts").cast("timestamp"))


def times_at(events: DataFrame, shares: tuple[float, ...]) -> list[int | None]:
    """For each share the least ``ts``, in microseconds, with at least that share of the rows at or before it: exact at any size.

    Hours are counted first; only the hour that holds the rank has its times put in order.
    """
    times = events.where("ts IS NOT NULL").select(_micros().alias("us"))
    hour = F.floor(F.col("us") / 3_600_000_000)
    hours = times.groupBy(hour.alias("hour")).agg(F.count("*").alias("n")).orderBy("hour").collect()  # one row an hour
    total, out = sum(r["n"] for r in hours), []
    for share in shares:
        rank, before, at = math.ceil(share * total), 0, None
        for r in hours:
            if before + r["n"] >= rank:
                own = times.where(hour == r["hour"]).groupBy("us").agg(F.count("*").alias("n"))
                upto = own.withColumn("upto", F.sum("n").over(Window.orderBy("us"))).where(F.col("upto") >= rank - before)
                at = upto.agg(F.min("us")).first()[0]
                break
            before += r["n"]
        out.append(at)
    return out


def late_votes(spark: SparkSession, sf_dir: str, size: str = "1 hour") -> DataFrame:
    """One row (votes, late): the later half of the events comes in two files, the last quarter first, and then the other half.

    After the first file the watermark stands ``LATE`` before the last event; it holds for late votes one batch
    later. Votes of windows that have ended by then are left out; they are counted as what the windows miss.
    """
    events = spark.read.parquet(f"{sf_dir}/events.parquet")
    half, most = times_at(events, (0.5, 0.75))
    folder, at = new_path(spark, "late"), _micros()
    for part in (at >= F.lit(most), (at >= F.lit(half)) & (at < F.lit(most)), at < F.lit(half)):
        events.where(part).coalesce(1).write.mode("append").parquet(folder)
        time.sleep(1.1)  # files are read in the order of their times
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(folder)
    votes = stream.select(F.col("ts").cast("timestamp").alias("ts"), F.lit(False).alias("wrong")).withWatermark("ts", LATE)
    kept = run_once(windowed(votes, size), "late_windows", "update").groupBy("start").agg(F.max("n_votes").alias("n")).agg(F.sum("n").alias("kept"))
    # a vote without a time is in no window and never late
    return events.agg(F.count("*").alias("votes"), F.count("ts").alias("timed")).crossJoin(kept).select("votes", (F.col("timed") - F.coalesce("kept", F.lit(0))).cast("long").alias("late"))


class AnswerLoop:
    """A batch function for ``foreachBatch``: add the answers, keep the clustering if they agree, else cluster again.

    Its state is tables in the shared folder, one folder for each batch number, the edges written before the
    clusters and a mark last. A batch that comes again, also to a new driver, changes nothing: a worker's vote
    on a pair that the state holds already is its latest one.
    """

    def __init__(self, records: DataFrame, k: Config, seen: Callable[[int, DataFrame, DataFrame, bool], None] | None, folder: str | None):
        self.records, self.k, self.seen = records, k, seen
        self.spark = records.sparkSession
        self.folder = folder or new_path(self.spark, "answers")

    def last(self) -> int:
        """Number of the last batch that is whole; -1 before the first."""
        jvm = self.spark._jvm
        at = jvm.org.apache.hadoop.fs.Path(self.folder)
        fs = at.getFileSystem(self.spark._jsparkSession.sessionState().newHadoopConf())
        if not fs.exists(at):
            return -1
        names = [x.getPath().getName() for x in fs.listStatus(at)]
        return max((int(n[5:]) for n in names if n.startswith("done-")), default=-1)

    def _read(self, kind: str, schema: str) -> DataFrame:
        return self.spark.read.schema(schema).parquet(f"{self.folder}/{kind}-{self.last()}")

    def votes(self) -> DataFrame:
        return self._read("votes", "u long, w long, worker long, yes boolean")

    def edges(self) -> DataFrame:
        return build_edges(self.votes(), self.k.vote_mode, self.k.accuracy)

    def clusters(self) -> DataFrame:
        return self._read("clusters", "rid long, cid long")

    def __call__(self, batch: DataFrame, number: int) -> None:
        before = self.last()
        if number <= before or batch.isEmpty():
            return
        new = cut(canonical_votes(batch.select("u", "w", "worker", "yes")), "answers")
        held = new if before < 0 else self.votes().join(new, ["u", "w", "worker"], "left_anti").unionByName(new)
        held.write.mode("overwrite").parquet(f"{self.folder}/votes-{number}")
        edges = build_edges(self.spark.read.parquet(f"{self.folder}/votes-{number}"), self.k.vote_mode, self.k.accuracy)
        keep = before >= 0 and agrees(build_edges(new, self.k.vote_mode, self.k.accuracy), self.clusters()).first()["agrees"]
        clusters = self.clusters() if keep else scc(edges, self.records, self.k)
        clusters.write.mode("overwrite").parquet(f"{self.folder}/clusters-{number}")
        self.spark.range(1).write.mode("overwrite").parquet(f"{self.folder}/done-{number}")
        if self.seen:
            self.seen(number, edges, self.clusters(), not keep)


def answer_loop(votes: DataFrame | None, records: DataFrame, k: Config = Config(), seen: Callable[[int, DataFrame, DataFrame, bool], None] | None = None, folder: str | None = None) -> AnswerLoop:
    """The loop's batch function; with ``votes``, a stream, use ``votes.writeStream.foreachBatch`` on it."""
    return AnswerLoop(records, k, seen, folder)
