"""Accuracy and cost, without listing pairs: matching pairs are counted from group sizes."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def pair_scores(clusters: DataFrame, gold: DataFrame) -> DataFrame:
    """One row: correct, reported and true matching pairs, precision, recall, f1 (0 where undefined)."""
    pairs = F.sum(F.col("n") * (F.col("n") - 1) / 2)
    both = clusters.join(gold, "rid").groupBy("cid", "entity").agg(F.count("*").alias("n"))
    counts = [x.agg(F.coalesce(pairs, F.lit(0.0)).cast("long").alias(name)) for x, name in (
        (both, "correct"), (both.groupBy("cid").agg(F.sum("n").alias("n")), "reported"), (both.groupBy("entity").agg(F.sum("n").alias("n")), "matching"))]
    one = counts[0].crossJoin(counts[1]).crossJoin(counts[2])
    one = one.withColumn("precision", F.coalesce(F.try_divide("correct", "reported"), F.lit(0.0))).withColumn("recall", F.coalesce(F.try_divide("correct", "matching"), F.lit(0.0)))
    return one.withColumn("f1", F.coalesce(F.try_divide(2 * F.col("precision") * F.col("recall"), F.col("precision") + F.col("recall")), F.lit(0.0)))


def cost_to_reach(rounds: DataFrame, targets: list[float]) -> DataFrame:
    """Questions beyond the initial ones until each F1 target is first met, for each run; null if never."""
    goal = rounds.withColumn("target", F.explode(F.array(*map(F.lit, targets))))
    met = F.min(F.when(F.col("f1") >= F.col("target"), F.col("n_next")))
    return goal.groupBy("workload", "method", "seed", "target").agg(met.alias("n_next"), F.max("f1").alias("best_f1"))


def cost_reduction(costs: DataFrame, ours: str = "reliability") -> DataFrame:
    """Share of questions saved against each other method at the same target, in percent."""
    mean = costs.groupBy("workload", "method", "target").agg(F.avg("n_next").alias("cost"))
    own = mean.where(F.col("method") == ours).select("workload", "target", F.col("cost").alias("own"))
    return mean.where(F.col("method") != ours).join(own, ["workload", "target"]).withColumn("saved_percent", F.round(100 * (1 - F.col("own") / F.col("cost")), 2))


def select_time(rounds: DataFrame, target: float = 0.95, best_only: tuple[str, ...] = ("tc",)) -> DataFrame:
    """Processor seconds for a batch until the target: choosing and re-clustering, without the answering.

    Rounds count up to the first that meets ``target``; the methods in ``best_only`` never meet it, so theirs
    count up to their best F1.
    """
    run = ["workload", "method", "seed"]
    goal = F.when(F.col("method").isin(*best_only), F.max("f1").over(Window.partitionBy(*run))).otherwise(F.lit(target))
    until = rounds.withColumn("goal", goal).groupBy(*run).agg(F.min(F.when(F.col("f1") >= F.col("goal"), F.col("round"))).alias("last"))
    spent = rounds.where("round > 0").join(until, run).where("last IS NULL OR round <= last")
    return spent.groupBy("workload", "method").agg((F.sum("select_ms") / 1000 / F.count("*")).alias("seconds"), F.count("*").alias("batches"), F.countDistinct("seed").alias("runs"))


def cost_table(costs: DataFrame, methods: list[str], ours: str = "reliability") -> DataFrame:
    """One row for each workload and target: mean questions of each method, and the percent that ours saves against the others."""
    mean = costs.groupBy("workload", "target").pivot("method", methods).agg(F.round(F.avg("n_next"), 1))
    return mean.withColumns({f"saved_vs_{m}": F.round(100 * (1 - F.col(ours) / F.col(m)), 2) for m in methods if m != ours})


def recluster_rate(rounds: DataFrame) -> DataFrame:
    return rounds.where("round > 0").groupBy("workload", "method", "batch").agg(F.avg(F.col("reclustered").cast("double")).alias("share"), F.count("*").alias("rounds"))


def over_runs(rounds: DataFrame) -> DataFrame:
    """Mean and deviation of F1 over seeds."""
    return rounds.groupBy("workload", "method", "round").agg(F.avg("f1").alias("f1"), F.stddev("f1").alias("f1_sd"), F.avg("n_next").alias("n_next"), F.count("*").alias("runs"))


def question_cost(rounds: DataFrame) -> DataFrame:
    """Distinct pairs asked by each run: the initial ones, the next ones, and all."""
    last = rounds.groupBy("workload", "method", "seed", "batch", "initial", "err").agg(F.max("n_initial").alias("n_initial"), F.max("n_next").alias("n_next"))
    return last.withColumn("total", F.col("n_initial") + F.col("n_next"))
