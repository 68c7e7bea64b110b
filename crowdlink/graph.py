"""Connected components by rounds of hooking, shortcutting and contraction.

Each round every root hooks to its least neighbour, chains of hooks are followed by doubling, and the
edges are rewritten between roots, without loops and repeats. A round at least halves the roots that
still have edges, so rounds grow with the logarithm of the largest component. Only counts reach the
driver; every round is cut by a table in the shared folder.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from crowdlink.storage import cut, forget
from crowdlink.triangles import count_triangles, triangles  # noqa: F401

#: So many edges are connected in one task; more of them by rounds.
SMALL = 1_000_000


def _in_one_task(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    from crowdlink.operators import kernels

    held = list(frames)
    if not held:
        return
    edges = pd.concat(held)
    ids, at = np.unique(edges[["low", "high"]].to_numpy(), return_inverse=True)
    a, b = at.reshape(-1, 2).T
    yield pd.DataFrame({"id": ids, "component": ids[kernels.components(len(ids), a, b)]})


def components(edges: DataFrame, a: str = "u", b: str = "w") -> DataFrame:
    """Rows ``(id, component)`` for each end of an edge; the component is its least id.

    Edges with a null end are not edges; loops make their node known; repeats and direction do not matter.
    """
    ends = edges.where(F.col(a).isNotNull() & F.col(b).isNotNull()).select(F.least(a, b).alias("low"), F.greatest(a, b).alias("high"))
    live = cut(ends.distinct(), "edges")
    integral = dict(live.dtypes)["low"] in ("bigint", "int", "smallint", "tinyint")
    if integral and live.limit(SMALL + 1).count() <= SMALL:  # the size is checked, so the task is bounded
        kind = dict(live.dtypes)["low"]
        return live.repartition(1).mapInPandas(_in_one_task, f"id {kind}, component {kind}")
    nodes = live.select(F.col("low").alias("id")).union(live.select(F.col("high").alias("id"))).distinct()
    labels: DataFrame | None = None
    first = live = live.where("low <> high")
    while not live.isEmpty():
        # a node hooks to its least neighbour if that is less than itself; hooks always lead to lower ids
        hook = cut(live.groupBy(F.col("high").alias("id")).agg(F.min("low").alias("to")), "hooks")
        while True:
            onward = hook.select(F.col("id").alias("to"), F.col("to").alias("further"))
            stepped = cut(hook.join(onward, "to", "left").select("id", F.coalesce("further", "to").alias("to"), F.col("further").isNotNull().alias("moved")), "hooks")
            forget(hook)
            hook = stepped.select("id", "to")
            hook.cut_path = stepped.cut_path
            if stepped.where("moved").isEmpty():
                break
        older, labels = labels, hook if labels is None else _through(labels, hook)
        forget(older)
        low, high = (hook.select(F.col("id").alias(c), F.col("to").alias(f"{c}_to")) for c in ("low", "high"))
        moved = live.join(low, "low", "left").join(high, "high", "left").select(F.coalesce("low_to", "low").alias("x"), F.coalesce("high_to", "high").alias("y"))
        past, live = live, cut(moved.where("x <> y").select(F.least("x", "y").alias("low"), F.greatest("x", "y").alias("high")).distinct(), "edges")
        if past is not first:
            forget(past)
    if labels is None:
        return nodes.select("id", F.col("id").alias("component"))
    return nodes.join(labels, "id", "left").select("id", F.coalesce("to", "id").alias("component"))


def _through(labels: DataFrame, hook: DataFrame) -> DataFrame:
    """The labels after one more round: old ones follow the new hooks, new hooks are added."""
    onward = hook.select(F.col("id").alias("to"), F.col("to").alias("further"))
    older = labels.join(onward, "to", "left").select("id", F.coalesce("further", "to").alias("to"))
    return cut(older.unionByName(hook), "labels")  # only roots hook, and no root has a label yet


def degrees(edges: DataFrame, a: str = "u", b: str = "w") -> DataFrame:
    """Rows ``(id, degree)`` of the ends of undirected edges."""
    return edges.select(F.explode(F.array(a, b)).alias("id")).groupBy("id").agg(F.count("*").alias("degree"))


def levels(edges: DataFrame, start: DataFrame, a: str = "u", b: str = "w", most: int | None = None) -> DataFrame:
    """Rows ``(id, level)``: fewest edges from the rows (id) of ``start``, breadth first; ``most`` ends it earlier.

    Every level joins only its new nodes with the edges and leaves out what was reached before.
    """
    both = cut(edges.select(F.col(a).alias("x"), F.col(b).alias("y")).unionByName(edges.select(F.col(b).alias("x"), F.col(a).alias("y"))).distinct(), "edges")
    front = cut(start.select("id", F.lit(0).alias("level")).distinct(), "level")
    found, n = front, 0
    while (most is None or n < most) and not front.isEmpty():
        n += 1
        front = cut(both.join(front.select(F.col("id").alias("x")), "x", "left_semi").select(F.col("y").alias("id")).distinct().join(found.select("id"), "id", "left_anti").withColumn("level", F.lit(n)), "level")
        found = found.unionByName(front)
    return found
