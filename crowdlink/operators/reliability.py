"""Reliability of a clustering: clusters that hold together, cluster pairs that stay apart.

Scores across clusters are sums of logs, one shuffle with partial sums, and stay in the JVM. Scores inside a
cluster need its structure: exact by enumeration for a few edges, by sampled worlds beyond, one cluster at a
time in a task. Sampled edges come from a hash of (seed, pair, sample), so retries and other partitionings
give the same numbers, and what an added answer changes is not blurred by fresh noise.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from crowdlink.config import Config
from crowdlink.operators import kernels


def disconnect(lab: DataFrame) -> DataFrame:
    """Rows ``(c1, c2, n_edges, disc)``: the chance that some edge between two clusters refuses."""
    across = lab.where(~F.col("is_yes")).select(F.least("cu", "cw").alias("c1"), F.greatest("cu", "cw").alias("c2"), "p")
    certain = F.count_if(F.col("p") <= 0) > 0
    logs = F.sum(F.when(F.col("p") > 0, F.log("p")))
    return across.groupBy("c1", "c2").agg(F.count("*").alias("n_edges"), F.when(certain, 1.0).otherwise(-F.expm1(logs)).alias("disc"))


def connectivity(lab: DataFrame, clusters: DataFrame, k: Config = Config()) -> DataFrame:
    """Rows ``(cid, n_records, n_edges, connect)`` of every cluster; a single record is connected."""
    sizes = clusters.groupBy("cid").agg(F.count("*").alias("n_records"))
    inside = lab.where("is_yes").select(F.col("cu").alias("cid"), "u", "w", "p")

    def one(g: pd.DataFrame) -> pd.DataFrame:
        nodes, n = np.unique(g[["u", "w"]].to_numpy(), return_inverse=True)
        a, b = n.reshape(-1, 2).T
        p = g["p"].to_numpy()
        if len(p) <= k.exact_max_edges:
            score = kernels.connect_exact(len(nodes), a, b, p)
        else:
            score = kernels.walked(nodes, a, b, p, k.samples, k.seed) if k.walk == "bfs" else kernels.Sample.draw(nodes, a, b, p, k.samples, k.seed).connect
        return pd.DataFrame({"cid": [g["cid"].iloc[0]], "covered": [len(nodes)], "n_edges": [len(p)], "score": [float(score)]})

    scored = inside.groupBy("cid").applyInPandas(one, "cid long, covered long, n_edges long, score double")
    whole = F.when(F.col("n_records") == 1, 1.0).when(F.col("covered") == F.col("n_records"), F.col("score")).otherwise(0.0)
    return sizes.join(scored, "cid", "left").select("cid", "n_records", F.coalesce("n_edges", F.lit(0)).alias("n_edges"), F.coalesce(whole, F.lit(0.0)).alias("connect"))


def floor_log(x: Column, eps: float) -> Column:
    return F.log10(F.greatest(x, F.lit(eps)))


def reliability(lab: DataFrame, clusters: DataFrame, k: Config = Config()) -> DataFrame:
    """One row: base-10 logs of all clusters and cluster pairs; pairs without an edge are counted, not listed."""
    inside = connectivity(lab, clusters, k).agg(F.sum(floor_log(F.col("connect"), k.eps)).alias("inside"), F.count("*").alias("c"))
    across = disconnect(lab).agg(F.coalesce(F.sum(floor_log(F.col("disc"), k.eps)), F.lit(0.0)).alias("across"), F.count("*").alias("met"))
    bare = F.lit(0.0) if k.edgeless == "skip" else (F.col("c") * (F.col("c") - 1) / 2 - F.col("met")) * F.log10(F.lit(k.eps))
    return inside.crossJoin(across).select("inside", "across", bare.alias("edgeless"), (F.col("inside") + F.col("across") + bare).alias("reliability"))
