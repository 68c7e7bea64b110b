"""Correlation clustering of the uncertain graph.

``scc`` merges greedily by summed log-odds. Two records whose positive edges do not connect them never
merge, so components are independent, and one that fits goes to one task. In larger ones, pairs that out-weigh
everything else at both ends together first merge in parallel without changing what the greedy order would do;
a residue beyond the size limit follows the same greedy order block by block.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from crowdlink.config import Config
from crowdlink.graph import components
from crowdlink.operators import kernels
from crowdlink.storage import cut, forget


def with_odds(edges: DataFrame, threshold: float = 0.5) -> DataFrame:
    """Log-odds of the edges; another threshold than a half shifts every edge's, an ablation of the method."""
    q = F.greatest(F.least("p", F.lit(1 - 1e-9)), F.lit(1e-9))
    shift = 0.0 if threshold == 0.5 else float(np.log(threshold / (1 - threshold)))
    return edges.select("u", "w", F.round(F.log(q) - F.log1p(-q) - F.lit(shift), 12).alias("odds"))


def positive_components(edges: DataFrame, records: DataFrame, above: float = 0.5) -> DataFrame:
    """Clusters of records that edges with p > ``above`` connect."""
    found = components(edges.where(F.col("p") > above))
    return records.select("rid").join(found.withColumnRenamed("id", "rid"), "rid", "left").select("rid", F.coalesce("component", "rid").alias("cid"))


def merge_probability(lab: DataFrame) -> DataFrame:
    """Rows ``(c1, c2, n_edges, prob)`` of cluster pairs with edges; at 0.5 or less they do not merge."""
    across = lab.where(~F.col("is_yes")).select(F.least("cu", "cw").alias("c1"), F.greatest("cu", "cw").alias("c2"), "p")
    q = F.greatest(F.least("p", F.lit(1 - 1e-9)), F.lit(1e-9))
    return across.groupBy("c1", "c2").agg(F.count("*").alias("n_edges"), (1 / (1 + F.exp(-F.round(F.sum(F.log(q) - F.log1p(-q)), 9)))).alias("prob"))


def safe_merges(links: DataFrame) -> DataFrame:
    """Pairs whose odds exceed all other positive odds at their two ends together."""
    pos = links.where("odds > 0")
    ends = pos.select(F.col("u").alias("c"), "odds").union(pos.select(F.col("w").alias("c"), "odds")).groupBy("c").agg(F.sum("odds").alias("total"))
    both = pos.join(ends.withColumnsRenamed({"c": "u", "total": "tu"}), "u").join(ends.withColumnsRenamed({"c": "w", "total": "tw"}), "w")
    return both.where(F.col("odds") > F.col("tu") + F.col("tw") - 2 * F.col("odds") + 1e-9).select("u", "w")


def _contract(links: DataFrame, merged: DataFrame) -> DataFrame:
    to = merged.select(F.col("w").alias("id"), F.col("u").alias("to"))
    x = links.join(to.withColumnsRenamed({"id": "u", "to": "u2"}), "u", "left").join(to.withColumnsRenamed({"id": "w", "to": "w2"}), "w", "left")
    x = x.select(F.coalesce("u2", "u").alias("a"), F.coalesce("w2", "w").alias("b"), "odds").where("a <> b")
    return x.groupBy(F.least("a", "b").alias("u"), F.greatest("a", "b").alias("w")).agg(F.round(F.sum("odds"), 12).alias("odds"))


def mutual_best(links: DataFrame) -> DataFrame:
    """Pairs (u, w) of positive odds that are the best of both their ends; ties by the least ids."""
    pos = links.where("odds > 1e-12")
    at = F.struct((-F.col("odds")).alias("o"), "u", "w")
    ends = pos.select(F.col("u").alias("c"), at.alias("at")).union(pos.select(F.col("w").alias("c"), at.alias("at")))
    best = ends.groupBy("c").agg(F.min("at").alias("at")).select("at.u", "at.w")
    return best.groupBy("u", "w").count().where("count = 2").select("u", "w")


def scc(edges: DataFrame, records: DataFrame, k: Config = Config(), start: DataFrame | None = None) -> DataFrame:
    """Clusters (rid, cid) of all records; cid is the least rid.

    With ``start``, clusters (rid, cid) of an earlier clustering are merged on rather than single records.
    ``scc_mode="rounds"`` merges all mutually best pairs at once, round by round, which is no greedy order:
    approximate, and only on demand.
    """
    return greedy(with_odds(edges, k.merge_threshold), records, k, start)


def greedy(links: DataFrame, records: DataFrame, k: Config = Config(), start: DataFrame | None = None) -> DataFrame:
    """Clusters by greedy merging of the greatest summed ``odds`` of links (u, w, odds) while they are positive."""
    label: DataFrame | None = None
    if start is not None:
        label = cut(start.where("rid <> cid").select(F.col("rid").alias("id"), F.col("cid").alias("to")), "labels")
        links = _contract(links, label.select(F.col("to").alias("u"), F.col("id").alias("w")))
    links = cut(links, "links")
    if k.scc_mode == "rounds":
        while not (merged := cut(mutual_best(links), "merged")).isEmpty():
            past, links = links, cut(_contract(links, merged), "links")
            step = merged.select(F.col("w").alias("id"), F.col("u").alias("to"))
            older, label = label, cut(step if label is None else _follow(label, step), "labels")
            forget(past, older, merged)
        return _least_named(records, label)
    rest, links = _in_tasks(links, k)
    if links is not None:
        rest = rest.unionByName(_large(links, k))
    rest = rest.where("id <> to")
    return _least_named(records, rest if label is None else _follow(label, rest))


def _in_tasks(links: DataFrame, k: Config) -> tuple[DataFrame, DataFrame | None]:
    """Labels (id, to) of the components that a task can merge, and the links of the others, if there are any."""
    found = cut(components(links.where("odds > 0")), "components")
    member = found.withColumnRenamed("component", "comp")
    inside = links.join(member.withColumnsRenamed({"id": "u", "comp": "cu"}), "u").join(member.withColumnsRenamed({"id": "w", "comp": "cw"}), "w").where("cu = cw").select(F.col("cu").alias("comp"), "u", "w", "odds")
    sizes = inside.groupBy("comp").agg(F.count("*").alias("size")).join(member.groupBy("comp").agg(F.count("*").alias("nodes")), "comp")
    large = cut(sizes.where(F.least("size", F.col("nodes") * F.col("nodes") / kernels.CELLS) > k.max_component).select("comp"), "large")

    def one(g: pd.DataFrame) -> pd.DataFrame:
        nodes, n = np.unique(g[["u", "w"]].to_numpy(), return_inverse=True)
        a, b = n.reshape(-1, 2).T
        merge = kernels.agglomerate_dense if len(nodes) ** 2 <= kernels.CELLS * len(g) else kernels.agglomerate
        return pd.DataFrame({"id": nodes, "to": nodes[merge(len(nodes), a, b, g["odds"].to_numpy())]})

    # a number of partitions that is asked for is kept, so that components do not wait for each other in one task
    parts = int(links.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    small = inside.join(large, "comp", "left_anti").repartition(parts, "comp").groupBy("comp").applyInPandas(one, "id long, to long")
    return small, None if large.isEmpty() else cut(inside.join(large, "comp", "left_semi").select("u", "w", "odds"), "links")


def _large(links: DataFrame, k: Config) -> DataFrame:
    """Labels (id, to) of components beyond a task: safe pairs merge in parallel, then what is left is split anew."""
    label: DataFrame | None = None
    while k.scc_mode == "contract":
        merged = cut(safe_merges(links), "merged")  # disjoint pairs, since each out-weighs all else at its ends
        if merged.isEmpty():
            break
        past, links = links, cut(_contract(links, merged), "links")
        step = merged.select(F.col("w").alias("id"), F.col("u").alias("to"))
        older, label = label, cut(step if label is None else _follow(label, step), "labels")
        forget(past, older, merged)
    rest, links = _in_tasks(links, k)
    if links is not None:
        rest = rest.unionByName(greedy_blocks(links, k.max_component))
    return rest if label is None else _follow(label, rest.where("id <> to"))


def _least_named(records: DataFrame, label: DataFrame | None) -> DataFrame:
    if label is None:
        return records.select("rid", F.col("rid").alias("cid"))
    out = records.select("rid").join(label.withColumnRenamed("id", "rid"), "rid", "left").select("rid", F.coalesce("to", "rid").alias("root"))
    least = out.groupBy("root").agg(F.min("rid").alias("cid"))
    return out.join(least, "root").select("rid", "cid")


def _follow(label: DataFrame, step: DataFrame) -> DataFrame:
    onward = step.select(F.col("id").alias("to"), F.col("to").alias("further"))
    return label.join(onward, "to", "left").select("id", F.coalesce("further", "to").alias("to")).unionByName(step)


def greedy_blocks(links: DataFrame, most: int) -> DataFrame:
    """Labels (id, to) of the exact greedy order, with at most ``most`` links in a task.

    The order of pairs is (-odds, u, w), and the place of a node is that of its first pair. A block is the first
    nodes with all their links, so every pair before the first place outside is between nodes of the block. The
    block's task merges until a pair is not before that place, or has an end outside; the graph is contracted,
    and the next block follows. Every block merges the first pair of all, so this ends with the positive pairs.
    """
    label: DataFrame | None = None

    def merge(whole: dict[int, bool] | None, bound: tuple | None):
        def one(g: pd.DataFrame) -> pd.DataFrame:
            nodes, n = np.unique(g[["u", "w"]].to_numpy(), return_inverse=True)
            a, b = n.reshape(-1, 2).T
            full = None if whole is None else np.array([x in whole for x in nodes.tolist()])
            stop = None if bound is None else (bound[0], *np.searchsorted(nodes, bound[1:]).tolist())
            return pd.DataFrame({"u": nodes, "w": nodes[kernels.agglomerate(len(nodes), a, b, g["odds"].to_numpy(), full, stop)]}).query("u != w").rename(columns={"u": "w", "w": "u"})[["u", "w"]]

        return one

    while True:
        # a cluster without a positive link never gets one again
        pos = links.where("odds > 1e-12").select("u", "w", (-F.col("odds")).alias("o"))
        ends = F.explode(F.array("u", "w")).alias("id")
        place = cut(pos.select(ends, F.struct("o", "u", "w").alias("at")).groupBy("id").agg(F.min("at").alias("at")), "places")
        if place.isEmpty():
            break
        links = cut(links.join(place.select(F.col("id").alias("u")), "u", "left_semi").join(place.select(F.col("id").alias("w")), "w", "left_semi").select("u", "w", "odds"), "links")
        last = links.count() <= most
        if last:
            merged = links.groupBy().applyInPandas(merge(None, None), "u long, w long")
        else:
            degree = links.select(ends).groupBy("id").agg(F.count("*").alias("links"))
            first = place.join(degree, "id").orderBy("at", "id").limit(10_000).collect()  # bounded
            total, block, bound = 0, {}, tuple(first[-1]["at"])
            for r in first[:-1]:
                total += r["links"]
                if total > most:
                    bound = tuple(r["at"])
                    break
                block[r["id"]] = True
            if len(block) < 2 or bound == tuple(first[0]["at"]):  # the first pair alone
                merged = links.sparkSession.createDataFrame([tuple(first[0]["at"])[1:]], "u long, w long")
            else:
                own = links.sparkSession.createDataFrame([(x,) for x in block], "id long")
                u, w = (F.broadcast(own.select(F.col("id").alias(c), F.lit(True).alias(f"in_{c}"))) for c in ("u", "w"))
                near = links.join(u, "u", "left").join(w, "w", "left").where("in_u OR in_w").select("u", "w", "odds")
                merged = near.groupBy().applyInPandas(merge(block, bound), "u long, w long")
        merged = cut(merged, "merged")
        step = merged.select(F.col("w").alias("id"), F.col("u").alias("to"))
        label = cut(step if label is None else _follow(label, step), "labels")
        if last:
            break
        links = _contract(links, merged)
    if label is None:
        return links.select(F.col("u").alias("id"), F.col("u").alias("to")).limit(0)
    return label


def local_move(edges: DataFrame, records: DataFrame) -> DataFrame:
    """Another heuristic: single records move while the likelihood rises; components of positive edges apart."""
    links = with_odds(edges)
    member = components(links.where("odds > 0")).withColumnRenamed("component", "comp")
    inside = links.join(member.withColumnsRenamed({"id": "u", "comp": "cu"}), "u").join(member.withColumnsRenamed({"id": "w", "comp": "cw"}), "w").where("cu = cw")

    def one(g: pd.DataFrame) -> pd.DataFrame:
        nodes, n = np.unique(g[["u", "w"]].to_numpy(), return_inverse=True)
        a, b = n.reshape(-1, 2).T
        return pd.DataFrame({"rid": nodes, "to": nodes[kernels.local_moves(len(nodes), a, b, g["odds"].to_numpy())]})

    found = inside.select(F.col("cu").alias("comp"), "u", "w", "odds").groupBy("comp").applyInPandas(one, "rid long, to long")
    return records.select("rid").join(found, "rid", "left").select("rid", F.coalesce("to", "rid").alias("cid"))


def average_odds(edges: DataFrame, records: DataFrame) -> DataFrame:
    """Another heuristic: greedy merging by the mean odds of the asked pairs between two clusters, components apart."""
    links = with_odds(edges)
    member = components(links.where("odds > 0")).withColumnRenamed("component", "comp")
    inside = links.join(member.withColumnsRenamed({"id": "u", "comp": "cu"}), "u").join(member.withColumnsRenamed({"id": "w", "comp": "cw"}), "w").where("cu = cw")

    def one(g: pd.DataFrame) -> pd.DataFrame:
        nodes, n = np.unique(g[["u", "w"]].to_numpy(), return_inverse=True)
        a, b = n.reshape(-1, 2).T
        return pd.DataFrame({"rid": nodes, "to": nodes[kernels.average_merges(len(nodes), a, b, g["odds"].to_numpy())]})

    found = inside.select(F.col("cu").alias("comp"), "u", "w", "odds").groupBy("comp").applyInPandas(one, "rid long, to long")
    return records.select("rid").join(found, "rid", "left").select("rid", F.coalesce("to", "rid").alias("cid"))
