"""The full loop on DataFrames: cluster, choose, ask, update, check, and cluster again only on disagreement."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from crowdlink.config import Config
from crowdlink.operators import measures
from crowdlink.operators.clustering import scc
from crowdlink.operators.questions import agrees, next_questions, refresh_units, unit_queue, units_of
from crowdlink.operators.reliability import reliability
from crowdlink.operators.votes import add_answers, build_edges, labelled, unit_hash
from crowdlink.operators.worlds import log_likelihood
from crowdlink.storage import cut


def initial_pairs(records: DataFrame, k: Config = Config()) -> DataFrame:
    """The pairs (u, w) that ``k.initial`` asks first: none, a path through all records, all, or a number in hash order.

    A number orders all pairs by their hash, so it is for record sets of experiments; the path and the empty
    start hold at any size.
    """
    kind = "none" if k.initial in (0, "none") else k.initial
    ids = records.select(F.col("rid").alias("u"))
    if kind == "none":
        return ids.select("u", F.col("u").alias("w")).limit(0)
    if kind == "spanning":
        # neighbours in order inside ranges of ids, and from the last of a range to the first of the next
        ranged = ids.repartitionByRange("u").withColumn("part", F.spark_partition_id())
        ranged = cut(ranged, "ranges")
        inner = ranged.select("u", F.lead("u").over(Window.partitionBy("part").orderBy("u")).alias("w")).where("w IS NOT NULL")
        ends = ranged.groupBy("part").agg(F.min("u").alias("first"), F.max("u").alias("last"))  # one row for each range
        bridge = ends.select(F.col("last").alias("u"), F.lead("first").over(Window.orderBy("part")).alias("w")).where("w IS NOT NULL")
        return inner.unionByName(bridge)
    every = ids.join(records.select(F.col("rid").alias("w")), F.col("u") < F.col("w"))  # as many as are asked, or record sets of experiments
    return every if kind == "all" else every.orderBy(unit_hash(k.seed, F.col("u"), F.col("w")), "u", "w").limit(int(kind))


def resolve(records: DataFrame, ask: Callable[[DataFrame], DataFrame], initial: DataFrame | None = None, k: Config = Config(), rounds: int | None = None, gold: DataFrame | None = None) -> tuple[DataFrame, DataFrame, list[dict]]:
    """Clusters, edges and one entry for each round.

    ``ask`` turns pairs (u, w) into votes; ``initial`` has the first pairs, else ``k.initial`` says which. It ends
    with the budget, with ``rounds``, when every pair is asked, or, with ``gold`` (rid, entity), at ``k.target_f1``.
    While the clustering is kept, the questions of a unit are too, until one of its pairs is answered: only the
    touched units are judged anew. Edges, clusters and questions are tables in the shared folder, cut each
    round; the driver sees counts and flags.
    """
    first = initial_pairs(records, k) if initial is None else initial
    edges = cut(build_edges(ask(cut(first, "initial")), k.vote_mode, k.accuracy), "edges")
    clusters = cut(scc(edges, records, k), "clusters")
    log, asked, queue = [], 0, None
    n = 0

    def reached() -> bool:
        return gold is not None and k.target_f1 is not None and measures.pair_scores(clusters, gold).first()["f1"] >= k.target_f1

    while (rounds is None or n < rounds) and (k.budget is None or asked < k.budget) and not reached():
        count = k.batch if k.budget is None else min(k.batch, k.budget - asked)
        lab = labelled(edges, clusters)
        if queue is None:
            queue = cut(unit_queue(lab, clusters, k.batch, k), "queue")
        chosen = cut(next_questions(lab, clusters, count, k, queue), "questions")
        got = chosen.count()
        if not got:  # every pair is asked
            break
        answers = cut(ask(chosen.select("u", "w")), "answers")
        edges = cut(add_answers(edges, answers, k.vote_mode, k.accuracy), "edges")
        kept = k.recheck == "on_disagreement" and agrees(build_edges(answers, k.vote_mode, k.accuracy), clusters).first()["agrees"]
        if kept:
            touched = cut(units_of(chosen.select("u", "w"), clusters), "touched")
            queue = cut(refresh_units(queue, unit_queue(labelled(edges, clusters), clusters, k.batch, k, touched), touched), "queue")
        else:
            clusters, queue = cut(scc(edges, records, k), "clusters"), None
        asked, n = asked + got, n + 1
        now = labelled(edges, clusters)
        score = reliability(now, clusters, k).first()
        log.append({"round": n, "asked": asked, "reclustered": not kept, "greatest_gain": chosen.agg(F.max("prio")).first()[0], "loglik": log_likelihood(edges, clusters).first()["log_likelihood"], "reliability": score["reliability"]})
    return clusters, edges, log
