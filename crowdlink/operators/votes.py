"""Votes and the uncertain graph: a pair's weight is the share of its voters who said YES."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

TWO_32 = 4294967296.0


def unit_hash(*parts: Column | str | int) -> Column:
    """A number in [0, 1) that depends on nothing but its parts, the same in any SQL engine with MD5."""
    columns = [p if isinstance(p, Column) else F.lit(str(p)) for p in parts]
    text = F.concat_ws("|", *(c.cast("string") for c in columns))
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long") / F.lit(TWO_32)


def canonical_votes(votes: DataFrame, latest_by: str | None = None) -> DataFrame:
    """u < w, no self pairs or nulls, one vote for each pair and worker: the latest, else the least."""
    ends = votes.where("u <> w AND yes IS NOT NULL").withColumns({"u": F.least("u", "w"), "w": F.greatest("u", "w")})
    pick = F.max_by("yes", latest_by) if latest_by else F.min("yes")
    return ends.groupBy("u", "w", "worker").agg(pick.alias("yes"))


def build_edges(votes: DataFrame, mode: str = "ratio", accuracy: float = 0.9) -> DataFrame:
    """Edges (u, w, n_votes, n_yes, p): by vote share, by majority (ties refuse), or by majority and a fixed accuracy."""
    counts = votes.groupBy("u", "w").agg(F.count("*").cast("int").alias("n_votes"), F.count_if("yes").cast("int").alias("n_yes"))
    return counts.withColumn("p", weight(mode, accuracy))


def weight(mode: str, accuracy: float = 0.9) -> Column:
    wins = 2 * F.col("n_yes") > F.col("n_votes")
    return {
        "ratio": F.col("n_yes") / F.col("n_votes"),
        "majority": F.when(wins, 1.0).otherwise(0.0),
        "fixed_accuracy": F.when(wins, accuracy).otherwise(F.round(F.lit(1 - accuracy), 12)),
    }[mode]


def add_answers(edges: DataFrame, answers: DataFrame, mode: str = "ratio", accuracy: float = 0.9) -> DataFrame:
    """The graph after more votes; counts add up, and a pair without a row is still a pair never asked."""
    more = build_edges(answers).drop("p")
    return edges.drop("p").unionByName(more).groupBy("u", "w").agg(F.sum("n_votes").cast("int").alias("n_votes"), F.sum("n_yes").cast("int").alias("n_yes")).withColumn("p", weight(mode, accuracy))


def labelled(edges: DataFrame, clusters: DataFrame) -> DataFrame:
    """Edges with both ends' clusters; ``q`` is the chance that the edge agrees with the clustering."""
    cu, cw = (clusters.select(F.col("rid").alias(c), F.col("cid").alias(f"c{c}")) for c in ("u", "w"))
    inside = F.col("cu") == F.col("cw")
    return edges.join(cu, "u").join(cw, "w").select("u", "w", "p", "cu", "cw", inside.alias("is_yes"), F.when(inside, F.col("p")).otherwise(1 - F.col("p")).alias("q"))


def crowd_error(votes: DataFrame, gold: DataFrame) -> DataFrame:
    """Mean over asked pairs of the share of wrong votes."""
    eu, ew = (gold.select(F.col("rid").alias(c), F.col("entity").alias(f"e{c}")) for c in ("u", "w"))
    wrong = F.avg((F.col("yes") != (F.col("eu") == F.col("ew"))).cast("double"))
    return votes.join(eu, "u").join(ew, "w").groupBy("u", "w").agg(wrong.alias("wrong")).agg(F.avg("wrong").alias("crowd_error"), F.count("*").alias("pairs"))


@dataclass(frozen=True)
class UncertainGraph:
    """Records (rid) and asked pairs (u, w, n_votes, n_yes, p); a pair without a row was never asked."""

    records: DataFrame
    edges: DataFrame
    mode: str = "ratio"
    accuracy: float = 0.9

    @classmethod
    def of(cls, records: DataFrame, votes: DataFrame, mode: str = "ratio", accuracy: float = 0.9) -> UncertainGraph:
        return cls(records, build_edges(votes, mode, accuracy), mode, accuracy)

    def add(self, votes: DataFrame) -> UncertainGraph:
        """The graph after one answer or a batch of them."""
        return replace(self, edges=add_answers(self.edges, votes, self.mode, self.accuracy))
