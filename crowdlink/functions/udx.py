"""Functions that SQL users can register: vector cosine, noisy or, summed odds, pairs of a list, worlds."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def cosine(a: Column, b: Column) -> Column:
    """Cosine of two arrays of numbers, in built-in functions."""
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q), F.lit(0.0), lambda s, v: s + v)
    return dot(a, b) / F.sqrt(dot(a, a) * dot(b, b))


@F.pandas_udf(T.DoubleType())
def cosine_arrow(a: pd.Series, b: pd.Series) -> pd.Series:
    x, y = (np.stack(s.to_numpy()).astype(np.float64) for s in (a, b))
    return pd.Series((x * y).sum(axis=1) / np.sqrt((x * x).sum(axis=1) * (y * y).sum(axis=1)))


@F.pandas_udf(T.DoubleType())
def noisy_or(p: pd.Series) -> float:
    return float(1 - np.prod(1 - p.to_numpy()))


@F.udf(T.IntegerType())
def digit_sum(text: str) -> int:
    return sum(int(c) for c in text or "" if c.isdigit() and c.isascii())


@F.udtf(returnType=T.StructType([T.StructField("u", T.LongType()), T.StructField("w", T.LongType())]))
class PairsOf:
    """All pairs u < w of a list of ids."""

    def eval(self, ids: list[int]) -> Iterator[tuple[int, int]]:
        ids = sorted(set(ids))
        for i, u in enumerate(ids):
            for w in ids[i + 1 :]:
                yield u, w


@F.udtf(returnType=T.StructType([T.StructField("world", T.LongType()), T.StructField("edge", T.IntegerType())]))
class PossibleWorlds:
    """The chosen edges of every world of a graph of a given number of edges, twenty at most."""

    def eval(self, edges: int) -> Iterator[tuple[int, int]]:
        if edges > 20:
            raise ValueError("more than 20 edges make too many worlds")
        for world in range(1 << edges):
            for edge in range(edges):
                if world >> edge & 1:
                    yield world, edge


@F.udtf(returnType=T.StructType([T.StructField("gap", T.LongType())]))
class NextGap:
    """The least number from 0 that a list leaves out."""

    def eval(self, taken: list[int]) -> Iterator[tuple[int]]:
        held, n = set(taken or ()), 0
        while n in held:
            n += 1
        yield (n,)


def register(spark: SparkSession) -> None:
    spark.udf.register("noisy_or", noisy_or)
    spark.udf.register("cosine_arrow", cosine_arrow)
    spark.udtf.register("pairs_of", PairsOf)
    spark.udtf.register("possible_worlds", PossibleWorlds)
    spark.udtf.register("next_gap", NextGap)
