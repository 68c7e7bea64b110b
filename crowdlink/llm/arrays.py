"""Array expressions that stay linear: ``aggregate`` copies what it carries at every step."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

BLOCK = 32


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body(value)``, where ``value`` is computed once even if lambdas inside use it."""
    return F.element_at(F.transform(F.array(value), body), 1)


def total(values: Column) -> Column:
    return F.aggregate(values, F.lit(0), lambda a, x: a + x)


def sums_before(sizes: Column, levels: int = 3) -> Column:
    """For each whole number of an array the sum of those before it.

    Blocks are summed, the blocks' own sums go the same way one level lower, and the last level is so short
    that its square does not matter: 3 levels of 32 leave one number for 32,768.
    """

    def inside(block: Column, begin: Column) -> Column:
        return F.transform(block, lambda _, j: begin + total(F.slice(block, 1, j)))

    def cut_up(x: Column) -> Column:
        count = F.floor((F.size(x) + BLOCK - 1) / BLOCK).cast("int")
        return F.transform(F.sequence(F.lit(0), F.greatest(count - 1, F.lit(0))), lambda b: F.slice(x, b * BLOCK + 1, BLOCK))

    def all_blocks(blocks: Column) -> Column:
        return F.flatten(F.zip_with(blocks, sums_before(F.transform(blocks, total), levels - 1), inside))

    if not levels:
        return let(sizes, lambda x: inside(x, F.lit(0)))
    return let(sizes, lambda x: let(cut_up(x), all_blocks))
