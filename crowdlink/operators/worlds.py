"""Possible worlds of small graphs, and the likelihood of a clustering at any size."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from crowdlink.operators import kernels
from crowdlink.operators.votes import labelled

LOG_FLOOR = 1e-9


def possible_worlds(edges: DataFrame, most: int = 20) -> DataFrame:
    """Rows ``(world, u, w, chosen, p)`` of every subset of a graph of at most ``most`` edges."""
    m = edges.count()
    if m > most:
        raise ValueError(f"{m} edges make too many worlds; the limit is {most}")
    numbered = edges.select("u", "w", "p", (F.row_number().over(_by_pair()) - 1).alias("bit"))
    worlds = edges.sparkSession.range(1 << m).withColumnRenamed("id", "world")
    return worlds.join(F.broadcast(numbered)).withColumn("chosen", F.expr("shiftright(world, bit) & 1") == 1).select("world", "u", "w", "chosen", "p")


def _by_pair():
    from pyspark.sql import Window

    return Window.orderBy("u", "w")  # at most ``most`` rows


def world_probability(worlds: DataFrame) -> DataFrame:
    return worlds.groupBy("world").agg(F.product(F.when(F.col("chosen"), F.col("p")).otherwise(1 - F.col("p"))).alias("prob"))


def closed(worlds: DataFrame) -> DataFrame:
    """Rows ``(world, closed)``: whether a world is a clustering, that is, no edge that it leaves out joins two records that its edges connect."""
    each = worlds.groupBy("world").agg(F.collect_list(F.struct("u", "w", "chosen")).alias("edges"))

    def run(frames):
        for g in frames:
            out = []
            for edges in g["edges"]:
                ids, at = np.unique(np.array([(x["u"], x["w"]) for x in edges]), return_inverse=True)
                a, b = at.reshape(-1, 2).T
                on = np.array([x["chosen"] for x in edges], bool)
                label = kernels.components(len(ids), a[on], b[on])
                out.append(not (label[a[~on]] == label[b[~on]]).any())
            yield pd.DataFrame({"world": g["world"], "closed": out})

    return each.mapInPandas(run, "world long, closed boolean")


def not_closed(worlds: DataFrame) -> DataFrame:
    return closed(worlds).where("NOT closed").select("world")


def best_clusterings(edges: DataFrame, blocks: DataFrame) -> DataFrame:
    """Rows ``(block, rid, cid, likelihood)``: the likeliest of all partitions of each block (rid, cid) of at most nine records."""
    inside = labelled(edges, blocks).where("is_yes").groupBy(F.col("cu").alias("block")).agg(F.collect_list(F.struct("u", "w", "p")).alias("edges"))
    each = blocks.groupBy(F.col("cid").alias("block")).agg(F.sort_array(F.collect_list("rid")).alias("ids")).join(inside, "block", "left")

    def run(frames):
        for g in frames:
            out = []
            for block, ids, edges in zip(g["block"], g["ids"], g["edges"], strict=True):
                edges = [] if edges is None else list(edges)
                a, b = (np.searchsorted(ids, np.array([x[c] for x in edges], np.int64)) for c in "uw")
                labels, score = kernels.best_partition(len(ids), a, b, np.array([x["p"] for x in edges], float))
                out += [(block, int(ids[n]), int(ids[int((labels == c).argmax())]), score) for n, c in enumerate(labels.tolist())]
            yield pd.DataFrame(out, columns=["block", "rid", "cid", "likelihood"])

    return each.mapInPandas(run, "block long, rid long, cid long, likelihood double")


def partition_counts(spark, most: int = 6) -> DataFrame:
    """Number of partitions of n records by the recurrence over the block that holds the last record."""
    bell = [1]
    for n in range(most):
        c, total = 1, 0
        for k in range(n + 1):
            total += c * bell[k]
            c = c * (n - k) // (k + 1)
        bell.append(total)
    return spark.createDataFrame([(n, bell[n]) for n in range(1, most + 1)], "n int, partitions long")


def log_likelihood(edges: DataFrame, clusters: DataFrame) -> DataFrame:
    """Natural log of the product of q over all asked edges; zeros count as a tiny weight."""
    return labelled(edges, clusters).agg(F.sum(F.log(F.greatest("q", F.lit(LOG_FLOOR)))).alias("log_likelihood"), F.count("*").alias("edges"))
