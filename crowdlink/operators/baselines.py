"""The methods that reliability is compared with.

Definitions that the reference only sketches are reconstructions from general knowledge and marked [R].
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from crowdlink.graph import components
from crowdlink.operators import kernels
from crowdlink.operators.clustering import greedy, positive_components
from crowdlink.operators.votes import labelled, unit_hash
from crowdlink.storage import cut


def transitive_clusters(majority: DataFrame, records: DataFrame) -> DataFrame:
    """Components of the positive majority answers; conflicts are ignored."""
    return positive_components(majority, records)


def infer_pairs(pairs: DataFrame, majority: DataFrame, clusters: DataFrame) -> DataFrame:
    """Rows ``(u, w, relation)``: match, non_match, conflict or unknown by transitivity and anti-transitivity."""
    lab = labelled(majority, clusters)
    refused = lab.where("p <= 0.5").select(F.least("cu", "cw").alias("c1"), F.greatest("cu", "cw").alias("c2")).distinct().withColumn("refused", F.lit(True))
    cu, cw = (clusters.select(F.col("rid").alias(c), F.col("cid").alias(f"c{c}")) for c in ("u", "w"))
    placed = pairs.select("u", "w").join(cu, "u").join(cw, "w").withColumns({"c1": F.least("cu", "cw"), "c2": F.greatest("cu", "cw")})
    joined = placed.join(refused, ["c1", "c2"], "left")
    same, no = F.col("cu") == F.col("cw"), F.coalesce("refused", F.lit(False))
    return joined.select("u", "w", F.when(same & no, "conflict").when(same, "match").when(no, "non_match").otherwise("unknown").alias("relation"))


def transitive_next(pairs: DataFrame, majority: DataFrame, clusters: DataFrame, count: int, seed: int) -> DataFrame:
    """Random (hash-ordered) unasked pairs whose relation cannot be inferred."""
    unknown = infer_pairs(pairs, majority, clusters).where("relation = 'unknown'").join(majority.select("u", "w"), ["u", "w"], "left_anti")
    return unknown.select("u", "w", unit_hash(seed, F.col("u"), F.col("w"), "tc").alias("h")).orderBy("h", "u", "w").limit(count).select("u", "w")


def random_next(pairs: DataFrame, edges: DataFrame, count: int, seed: int) -> DataFrame:
    free = pairs.join(edges.select("u", "w"), ["u", "w"], "left_anti")
    return free.orderBy(unit_hash(seed, F.col("u"), F.col("w"), "random"), "u", "w").limit(count).select("u", "w")


def density_ratio(fixed: DataFrame, clusters: DataFrame, accuracy: float = 0.9) -> DataFrame:
    """[R] Strength of the present relation of each unit: odds of one answer to the number that support it."""
    lab = labelled(fixed, clusters)
    units = lab.groupBy(F.least("cu", "cw").alias("c1"), F.greatest("cu", "cw").alias("c2")).agg(F.count_if(F.col("p") > 0.5).alias("n_pos"), F.count_if(F.col("p") <= 0.5).alias("n_neg"))
    support = F.when(F.col("c1") == F.col("c2"), F.col("n_pos")).otherwise(F.col("n_neg"))
    return units.withColumn("log_ratio", support * F.log10(F.lit(accuracy / (1 - accuracy))))


def density_next(pairs: DataFrame, fixed: DataFrame, clusters: DataFrame, count: int, rank: str = "desc") -> DataFrame:
    """[R] Unasked pairs of the units of greatest ratio, the least pair of each unit first."""
    cu, cw = (clusters.select(F.col("rid").alias(c), F.col("cid").alias(f"c{c}")) for c in ("u", "w"))
    free = pairs.join(fixed.select("u", "w"), ["u", "w"], "left_anti").join(cu, "u").join(cw, "w")
    first = free.groupBy(F.least("cu", "cw").alias("c1"), F.greatest("cu", "cw").alias("c2")).agg(F.min(F.struct("u", "w")).alias("q"))
    ranked = first.join(density_ratio(fixed, clusters), ["c1", "c2"])
    order = F.round("log_ratio", 9)
    return ranked.orderBy(order.desc() if rank == "desc" else order, "q.u", "q.w").limit(count).select("q.u", "q.w", "log_ratio")


def density_batch(pairs: DataFrame, fixed: DataFrame, clusters: DataFrame, count: int, rank: str = "desc") -> DataFrame:
    """[R] The batch form: one unasked pair of each unit in the order of their ratios, then the next of each, and so on."""
    cu, cw = (clusters.select(F.col("rid").alias(c), F.col("cid").alias(f"c{c}")) for c in ("u", "w"))
    free = pairs.join(fixed.select("u", "w"), ["u", "w"], "left_anti").join(cu, "u").join(cw, "w").withColumns({"c1": F.least("cu", "cw"), "c2": F.greatest("cu", "cw")})
    turn = F.row_number().over(Window.partitionBy("c1", "c2").orderBy("u", "w"))
    ranked = free.withColumn("turn", turn).where(F.col("turn") <= count).join(density_ratio(fixed, clusters), ["c1", "c2"])
    order = F.round("log_ratio", 9)
    return ranked.orderBy("turn", order.desc() if rank == "desc" else order, "u", "w").limit(count).select("u", "w", "turn", "log_ratio")


FEW_RECORDS = 2000


def _bottleneck_in_one_task(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    held = list(frames)
    if not held:
        return
    edges = pd.concat(held)
    ids, at = np.unique(edges[["u", "w"]].to_numpy(), return_inverse=True)
    a, b = at.reshape(-1, 2).T
    pos, neg = kernels.bottleneck(len(ids), a, b, edges["p"].to_numpy())
    i, j = np.nonzero(np.triu((pos > 0) | (neg > 0), 1))
    yield pd.DataFrame({"u": ids[i], "w": ids[j], "pos": pos[i, j], "neg": neg[i, j], "decision": pos[i, j] > neg[i, j]})


def bottleneck_relation(edges: DataFrame, records: DataFrame, pairs: DataFrame | None = None, few: int = FEW_RECORDS) -> DataFrame:
    """Rows ``(u, w, pos, neg, decision)`` of the ``pairs`` (u, w) that a positive or winning negative path joins.

    Votes make the weights few, so positive paths are components of the edges at each level, and a negative
    path is one refusing edge between two components of its level. Each level's labels are joined to the pairs,
    so the cost is that of the pairs asked for. Without ``pairs`` all pairs are meant, which only record sets of
    ``few`` records may ask: one matrix in one task.
    """
    small = records.limit(few + 1).count() <= few
    if pairs is None and not small:
        raise ValueError(f"all pairs of more than {few} records are too many; name the pairs")
    if small:  # a matrix of records fits in one task
        found = edges.select("u", "w", "p").repartition(1).mapInPandas(_bottleneck_in_one_task, "u long, w long, pos double, neg double, decision boolean")
        return found if pairs is None else found.join(pairs.select("u", "w"), ["u", "w"], "left_semi")
    edges = cut(edges.select("u", "w", "p", F.round("p", 9).alias("level"), F.round(1 - F.col("p"), 9).alias("refusal")), "edges")
    levels = sorted({r[0] for r in edges.select(F.explode(F.array("level", "refusal"))).distinct().collect() if r[0] > 0.5})  # as many as votes for a pair
    asked = pairs.select("u", "w", F.lit(0.0).alias("pos"), F.lit(0.0).alias("neg"))
    for at in levels:  # from weak to strong, so that the strongest stays
        label = cut(positive_components(edges.where(F.col("level") >= at), records), "labels")
        refusing = labelled(edges.where(F.col("refusal") >= at), label).where("cu <> cw").select(F.least("cu", "cw").alias("c1"), F.greatest("cu", "cw").alias("c2"), F.lit(True).alias("no")).distinct()
        x, y = (label.select(F.col("rid").alias(r), F.col("cid").alias(c)) for r, c in (("u", "cu"), ("w", "cw")))
        here = asked.join(x, "u").join(y, "w").withColumns({"c1": F.least("cu", "cw"), "c2": F.greatest("cu", "cw")}).join(refusing, ["c1", "c2"], "left")
        same, no = F.col("cu") == F.col("cw"), F.coalesce("no", F.lit(False))
        asked = cut(here.select("u", "w", F.when(same, at).otherwise(F.col("pos")).alias("pos"), F.when(no & ~same, at).otherwise(F.col("neg")).alias("neg")), "relation")
    return asked.where("pos > 0 OR neg > 0").withColumn("decision", F.col("pos") > F.col("neg"))


def bottleneck_clusters(relation: DataFrame, records: DataFrame) -> DataFrame:
    found = components(relation.where("decision"))
    return records.select("rid").join(found.withColumnRenamed("id", "rid"), "rid", "left").select("rid", F.coalesce("component", "rid").alias("cid"))


def bottleneck_next(relation: DataFrame, pairs: DataFrame, edges: DataFrame, count: int) -> DataFrame:
    """[R] Unasked pairs by the greater of a sure match and an unsure non-match."""
    free = pairs.join(edges.select("u", "w"), ["u", "w"], "left_anti").join(relation, ["u", "w"])
    score = F.greatest("pos", F.when(~F.col("decision"), 1 - F.col("neg")).otherwise(0.0))
    return free.select("u", "w", score.alias("score")).orderBy(F.desc("score"), "u", "w").limit(count)


def pivot_clusters(edges: DataFrame, records: DataFrame, seed: int = 42) -> DataFrame:
    """[R] Pivot clustering in rounds until no record is open: whoever comes first among its open positive neighbours is a pivot; open neighbours join the first pivot."""
    pos = cut(edges.where("p > 0.5").select("u", "w"), "positive")
    both = pos.union(pos.select("w", "u")).select(F.col("u").alias("a"), F.col("w").alias("b"))
    left = cut(records.select("rid", unit_hash(seed, F.col("rid")).alias("h")), "open")
    done = None
    while done is None or not left.isEmpty():  # the first open record is always settled
        near = both.join(left.select(F.col("rid").alias("a"), F.col("h").alias("ha")), "a").join(left.select(F.col("rid").alias("b"), F.col("h").alias("hb")), "b")
        beaten = near.where(F.struct("hb", "b") < F.struct("ha", "a")).select(F.col("a").alias("rid")).distinct()
        pivots = cut(left.join(beaten, "rid", "left_anti"), "pivots")
        joins = near.join(pivots.select(F.col("rid").alias("b")), "b", "left_semi").groupBy("a").agg(F.min_by("b", F.struct("hb", "b")).alias("root")).withColumnRenamed("a", "rid")
        new = cut(joins.unionByName(pivots.select("rid", F.col("rid").alias("root"))), "joined")
        done = new if done is None else done.unionByName(new)
        left = cut(left.join(new, "rid", "left_anti"), "open")
    least = done.groupBy("root").agg(F.min("rid").alias("cid"))
    return done.join(least, "root").select("rid", "cid")


def pivot_refined(edges: DataFrame, records: DataFrame, clusters: DataFrame) -> DataFrame:
    """[R] Clusters (rid, cid) after one refinement: records whose leaving pays leave, then clusters whose merging pays merge.

    Merges are greedy by their summed benefit, as the clustering by odds is.
    """
    gone = split_benefit(labelled(edges, clusters)).where("benefit > 0").select("rid", F.lit(True).alias("gone"))
    kept = clusters.join(gone, "rid", "left").select("rid", "cid", F.coalesce("gone", F.lit(False)).alias("gone"))
    stay = kept.where("NOT gone").groupBy("cid").agg(F.min("rid").alias("least"))
    split = cut(kept.join(stay, "cid", "left").select("rid", F.when(F.col("gone"), F.col("rid")).otherwise(F.col("least")).alias("cid")), "split")
    links = merge_benefit(labelled(edges, split)).select(F.col("c1").alias("u"), F.col("c2").alias("w"), F.round("benefit", 12).alias("odds"))
    merged = greedy(links, split.select(F.col("cid").alias("rid")).distinct()).select(F.col("rid").alias("cid"), F.col("cid").alias("to"))
    named = split.join(merged, "cid").select("rid", "to")
    return named.join(named.groupBy("to").agg(F.min("rid").alias("cid")), "to").select("rid", "cid")


def split_benefit(lab: DataFrame) -> DataFrame:
    """[R] What each record would gain by leaving its cluster: the sum of 1 - 2p over its inside edges."""
    inside = lab.where("is_yes").select("u", "w", "p", "cu")
    ends = inside.select(F.col("u").alias("rid"), "cu", "p").union(inside.select("w", "cu", "p"))
    return ends.groupBy("rid", F.col("cu").alias("cid")).agg(F.sum(1 - 2 * F.col("p")).alias("benefit"), F.count("*").alias("n_edges"))


def merge_benefit(lab: DataFrame) -> DataFrame:
    """[R] What merging two clusters would gain: the sum of 2p - 1 over their edges."""
    across = lab.where(~F.col("is_yes")).select(F.least("cu", "cw").alias("c1"), F.greatest("cu", "cw").alias("c2"), "p")
    return across.groupBy("c1", "c2").agg(F.sum(2 * F.col("p") - 1).alias("benefit"), F.count("*").alias("n_edges"))


def pivot_next(pairs: DataFrame, edges: DataFrame, clusters: DataFrame, count: int) -> DataFrame:
    """[R] Unasked pairs of the cluster pairs whose merge would gain most for each pair still to ask."""
    cu, cw = (clusters.select(F.col("rid").alias(c), F.col("cid").alias(f"c{c}")) for c in ("u", "w"))
    free = pairs.join(edges.select("u", "w"), ["u", "w"], "left_anti").join(cu, "u").join(cw, "w").where("cu <> cw").withColumns({"c1": F.least("cu", "cw"), "c2": F.greatest("cu", "cw")})
    left = free.groupBy("c1", "c2").agg(F.count("*").alias("open"))
    worth = merge_benefit(labelled(edges, clusters)).join(left, ["c1", "c2"]).select("c1", "c2", (F.col("benefit") / F.col("open")).alias("worth"))
    return free.join(worth, ["c1", "c2"]).orderBy(F.round("worth", 9).desc(), "u", "w").limit(count).select("u", "w", "worth")
