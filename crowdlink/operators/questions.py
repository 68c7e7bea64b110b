"""Which pairs to ask next: best-case gain in reliability, one candidate for each unit.

A unit is a cluster (its unasked inside pairs differ in gain) or a pair of clusters (all its pairs gain the
same, so one stands for it). Cluster pairs without an asked edge all share the greatest gain; they are a
class of their own: as many as are needed are drawn by their distance in hash order.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from crowdlink.config import Config
from crowdlink.operators import kernels
from crowdlink.operators.reliability import disconnect, floor_log
from crowdlink.operators.votes import unit_hash
from crowdlink.storage import cut


def across_units(lab: DataFrame, k: Config = Config()) -> DataFrame:
    """Rows ``(c1, c2, n_edges, disc, prio)``: the weaker the separation, the more a refusal would gain."""
    return disconnect(lab).withColumn("prio", -floor_log(F.col("disc"), k.eps))


def gap_representatives(units: DataFrame, lab: DataFrame, clusters: DataFrame, each: int = 1) -> DataFrame:
    """The ``each`` least unasked pairs of each cluster pair (c1, c2).

    Of m asked pairs at most m come before them, so the first m + ``each`` pairs of the product hold them: with
    the members in order, rows of the first cluster fill up one by one.
    """
    place = F.row_number().over(Window.partitionBy("cid").orderBy("rid")) - 1
    ordered = clusters.select("rid", "cid", place.alias("i"))
    sizes = clusters.groupBy("cid").agg(F.count("*").alias("size"))
    u = units.select("c1", "c2", "n_edges").join(sizes.withColumnsRenamed({"cid": "c1", "size": "s1"}), "c1").join(sizes.withColumnsRenamed({"cid": "c2", "size": "s2"}), "c2")
    u = u.where("n_edges < s1 * s2").withColumn("slot", F.explode(F.expr(f"sequence(0, least(n_edges + {each - 1}, s1 * s2 - 1))")))
    u = u.withColumn("i", F.floor(F.col("slot") / F.col("s2")).cast("int")).withColumn("j", (F.col("slot") % F.col("s2")).cast("int"))
    first, second = (ordered.select(F.col("cid").alias(c), F.col("i").alias(i), F.col("rid").alias(r)) for c, i, r in (("c1", "i", "ra"), ("c2", "j", "rb")))
    pairs = u.join(first, ["c1", "i"]).join(second, ["c2", "j"]).select("c1", "c2", "ra", "rb", F.least("ra", "rb").alias("u"), F.greatest("ra", "rb").alias("w"))
    free = pairs.join(lab.select("u", "w"), ["u", "w"], "left_anti")
    if each == 1:
        return free.groupBy("c1", "c2").agg(F.min_by(F.struct("u", "w"), F.struct("ra", "rb")).alias("q")).select("c1", "c2", "q.u", "q.w")
    rank = F.row_number().over(Window.partitionBy("c1", "c2").orderBy("ra", "rb"))
    return free.withColumn("rank", rank).where(F.col("rank") <= each).select("c1", "c2", "u", "w")


def _unasked(n: int, a: np.ndarray, b: np.ndarray, cid: int, k: Config) -> tuple[np.ndarray, np.ndarray]:
    """Places (i, j) of the unasked pairs of n records; of more than ``pair_sample`` so many, drawn evenly by a seed."""
    every, taken = n * (n - 1) // 2, set((np.minimum(a, b).astype(np.int64) * n + np.maximum(a, b)).tolist())
    if k.pair_sample is None or every - len(taken) <= k.pair_sample:
        i, j = np.triu_indices(n, 1)
        free = np.ones(every, bool) if not taken else ~np.isin(i.astype(np.int64) * n + j, list(taken))
        return i[free], j[free]
    rng, drawn = np.random.default_rng([k.seed, cid & 0x7FFFFFFF]), {}
    while len(drawn) < k.pair_sample:
        x = np.sort(rng.integers(0, n, (2 * k.pair_sample, 2)), axis=1)
        for key in (x[:, 0].astype(np.int64) * n + x[:, 1])[x[:, 0] < x[:, 1]].tolist():
            if key not in taken and len(drawn) < k.pair_sample:
                drawn[key] = True
    keys = np.array(sorted(drawn), np.int64)
    return keys // n, keys % n


def inside_candidates(lab: DataFrame, clusters: DataFrame, k: Config = Config(), top: int = 1) -> DataFrame:
    """Rows ``(kind, c1, c2, u, w, prio)``: the ``top`` unasked pairs of each cluster by gain.

    One set of sampled worlds serves all pairs: a sure edge connects the worlds that were in two parts and
    have its ends apart. Clusters of few edges are scored exactly. Only pairs are judged that ``pair_sample``
    leaves, so a large cluster needs no matrix of all its pairs.
    """
    members = clusters.groupBy("cid").agg(F.sort_array(F.collect_list("rid")).alias("members")).where(F.size("members") > 1)
    edges = lab.where("is_yes").groupBy(F.col("cu").alias("cid")).agg(F.collect_list(F.struct("u", "w", "p")).alias("edges"))

    def run(frames):
        for g in frames:
            out = []
            for cid, ids, pairs in zip(g["cid"], g["members"], g["edges"], strict=True):
                ids, pairs = np.asarray(ids), [] if pairs is None else list(pairs)
                if len(pairs) == len(ids) * (len(ids) - 1) // 2:
                    continue
                a = np.searchsorted(ids, np.array([x["u"] for x in pairs], np.int64))
                b = np.searchsorted(ids, np.array([x["w"] for x in pairs], np.int64))
                p = np.array([x["p"] for x in pairs], float)
                i, j = _unasked(len(ids), a, b, int(cid), k)
                if len(pairs) <= k.exact_gain_edges:
                    now = kernels.connect_exact(len(ids), a, b, p)
                    then = np.array([kernels.connect_exact(len(ids), np.append(a, x), np.append(b, y), np.append(p, 1.0)) for x, y in zip(i, j, strict=True)])
                else:
                    s = kernels.Sample.draw(ids, a, b, p, k.samples, k.seed)
                    now, then = s.connect, s.connect_pairs(i, j)
                gain = np.log10(np.maximum(then, k.eps)) - np.log10(max(now, k.eps))
                best = np.lexsort((j, i, -np.round(gain, 9)))[:top]
                out += [("inside", int(cid), int(cid), int(ids[i[n]]), int(ids[j[n]]), float(gain[n])) for n in best]
            yield pd.DataFrame(out, columns=["kind", "c1", "c2", "u", "w", "prio"])

    return members.join(edges, "cid", "left").mapInPandas(run, "kind string, c1 long, c2 long, u long, w long, prio double")


def across_candidates(lab: DataFrame, clusters: DataFrame, k: Config = Config()) -> DataFrame:
    units = across_units(lab, k)
    return units.join(gap_representatives(units, lab, clusters, k.across_per_pair), ["c1", "c2"]).select(F.lit("across").alias("kind"), "c1", "c2", "u", "w", "prio")


def unit_queue(lab: DataFrame, clusters: DataFrame, count: int, k: Config = Config(), touched: DataFrame | None = None) -> DataFrame:
    """Candidates of all units with an asked edge, or of the ``touched`` units (c1, c2) alone.

    For the latter only edges and records of touched units are read on, so the cost is that of the units.
    """
    if touched is not None:
        pair = [F.least("cu", "cw").alias("c1"), F.greatest("cu", "cw").alias("c2")]
        lab = lab.select("*", *pair).join(touched, ["c1", "c2"], "left_semi").drop("c1", "c2")
        met = cut(touched.select(F.explode(F.array("c1", "c2")).alias("cid")).distinct(), "touched")
        whole = touched.where("c1 = c2").select(F.col("c1").alias("cid"))
        clusters = clusters.join(met, "cid", "left_semi").select("rid", "cid")
        inside = inside_candidates(lab, clusters.join(whole, "cid", "left_semi"), k, count)
    else:
        inside = inside_candidates(lab, clusters, k, count)
    return inside.unionByName(across_candidates(lab, clusters, k))


def edgeless_candidates(lab: DataFrame, clusters: DataFrame, count: int, k: Config = Config()) -> DataFrame:
    """``count`` cluster pairs without an asked edge, or all of them if they are fewer.

    Clusters stand in hash order, and pairs are met by the distance of their places. Of m pairs with an asked
    edge at most m are in the way, so the first distances that hold m + ``count`` pairs hold enough.
    """
    met = cut(lab.where(~F.col("is_yes")).select(F.least("cu", "cw").alias("c1"), F.greatest("cu", "cw").alias("c2")).distinct(), "met")
    order = cut(clusters.select("cid").distinct().withColumn("h", unit_hash(k.seed, F.col("cid"))), "order")
    n, m = order.count(), met.count()
    far, held = 0, 0
    while far < n - 1 and held < m + count:
        far += 1
        held += n - far
    # places by counts of buckets of the hash, so that no single task sorts all clusters
    bucket = F.floor(F.col("h") * 4096).cast("int")
    sizes = order.groupBy(bucket.alias("bucket")).agg(F.count("*").alias("size"))
    before = sizes.select("bucket", (F.sum("size").over(Window.orderBy("bucket")) - F.col("size")).alias("before"))  # 4,096 rows at most
    at = cut(order.withColumn("bucket", bucket).join(before, "bucket").select("cid", (F.col("before") + F.row_number().over(Window.partitionBy("bucket").orderBy("h", "cid")) - 1).alias("at")), "places")
    reach = at.withColumn("far", F.explode(F.sequence(F.lit(1), F.lit(far)))).select("cid", "far", (F.col("at") + F.col("far")).alias("at")) if far else at.select("cid", F.lit(0).alias("far"), "at").limit(0)
    pairs = reach.join(at.withColumnRenamed("cid", "other"), "at").select(F.least("cid", "other").alias("c1"), F.greatest("cid", "other").alias("c2"), "far")
    free = pairs.join(met, ["c1", "c2"], "left_anti")
    return free.orderBy("far", unit_hash(k.seed, F.col("c1"), F.col("c2")), "c1", "c2").limit(count).select(F.lit("edgeless").alias("kind"), "c1", "c2", F.col("c1").alias("u"), F.col("c2").alias("w"), F.lit(float(-np.log10(k.eps))).alias("prio"))


def next_questions(lab: DataFrame, clusters: DataFrame, count: int, k: Config = Config(), queue: DataFrame | None = None) -> DataFrame:
    """The ``count`` candidates of greatest gain over all units; ``queue`` has those of the units with edges, if they are kept."""
    every = unit_queue(lab, clusters, count, k) if queue is None else queue
    if k.edgeless != "skip":
        every = every.unionByName(edgeless_candidates(lab, clusters, count, k))
    return every.orderBy(F.round("prio", 9).desc(), "kind", "u", "w").limit(count)


def units_of(pairs: DataFrame, clusters: DataFrame) -> DataFrame:
    """Rows ``(c1, c2)``: the units that answered pairs (u, w) touch."""
    cu, cw = (clusters.select(F.col("rid").alias(c), F.col("cid").alias(f"c{c}")) for c in ("u", "w"))
    return pairs.join(cu, "u").join(cw, "w").select(F.least("cu", "cw").alias("c1"), F.greatest("cu", "cw").alias("c2")).distinct()


def refresh_units(queue: DataFrame, fresh: DataFrame, touched: DataFrame) -> DataFrame:
    """The kept queue with the touched units (c1, c2) replaced by what ``fresh`` has for them."""
    return queue.join(touched, ["c1", "c2"], "left_anti").unionByName(fresh.join(touched, ["c1", "c2"], "left_semi"))


def agrees(answers: DataFrame, clusters: DataFrame) -> DataFrame:
    """One row: whether every answered pair (u, w, p) is likelier to agree with the clustering than not."""
    from crowdlink.operators.votes import labelled

    return labelled(answers, clusters).agg(F.coalesce(F.bool_and(F.col("q") > 0.5), F.lit(True)).alias("agrees"), F.count("*").alias("answers"))


def gain_curve(units: DataFrame, steps: int = 10) -> DataFrame:
    """Gain of one more answer of weight q on each cluster pair: never falls, 0 at q = 0, greatest at q = 1."""
    qs = F.transform(F.sequence(F.lit(0), F.lit(steps)), lambda i: i / F.lit(float(steps)))
    gain = F.log10((1 - (1 - F.col("disc")) * (1 - F.col("q"))) / F.col("disc"))
    return units.where("disc > 0").withColumn("q", F.explode(qs)).select("c1", "c2", "q", gain.alias("gain"))


def ranked_by_weakness(units: DataFrame, buckets: int = 1024) -> DataFrame:
    """``units`` with ``place``: the rank of each by its separation, the weakest first, equal ones alike.

    Ranks come from counts of the values in buckets and below, so no task sorts all units.
    """
    value = F.round("disc", 9)
    counts = cut(units.groupBy(value.alias("value")).agg(F.count("*").alias("n")), "values")
    bucket = F.least(F.floor(F.col("value") * buckets), F.lit(buckets - 1)).cast("int")
    sums = counts.groupBy(bucket.alias("bucket")).agg(F.sum("n").alias("n"))
    before = sums.select("bucket", (F.sum("n").over(Window.orderBy("bucket")) - F.col("n")).alias("before"))  # ``buckets`` rows at most
    inside = F.coalesce(F.sum("n").over(Window.partitionBy("bucket").orderBy("value").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    places = counts.withColumn("bucket", bucket).join(F.broadcast(before), "bucket").select("value", (F.col("before") + inside + 1).cast("long").alias("place"))
    return units.withColumn("value", value).join(places, "value").drop("value")


def weak_first(lab: DataFrame, clusters: DataFrame, k: Config = Config()) -> DataFrame:
    """Diagnostic rows ``(cid, connect, gain, connect_rank, gain_rank)``: how far weak clusters are asked first.

    The best gain of a cluster is log10(1 + d / connect) for the rise d that a sure edge brings, so weak ones
    are preferred unless their rise is small; the two ranks show how often that holds.
    """
    from crowdlink.operators.reliability import connectivity

    best = inside_candidates(lab, clusters, k, 1).select(F.col("c1").alias("cid"), F.col("prio").alias("gain"))
    both = connectivity(lab, clusters, k).join(best, "cid").select("cid", "connect", "gain")
    # one row for each cluster that still has a question
    return both.withColumn("connect_rank", F.rank().over(Window.orderBy(F.round("connect", 9))).cast("long")).withColumn("gain_rank", F.rank().over(Window.orderBy(F.round("gain", 9).desc())).cast("long"))
