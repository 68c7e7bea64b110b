"""Runs of the experiment workloads: one task per (method, seed, setting), all at once."""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from crowdlink.config import Config
from crowdlink.plans import simulate
from crowdlink.sources import workloads as W
from crowdlink.storage import cut


def settings(name: str, methods=simulate.METHODS, seeds=(42,), batches=None, initials=None, errs=None) -> list[tuple]:
    """Rows (method, seed, batch, initial, err); -1 initial pairs mean a spanning path."""
    w = W.WORKLOADS[name]
    return [(m, s, b, i, float(e)) for m in methods for s in seeds for b in (batches or [w.batch]) for i in (initials if initials is not None else [w.initial]) for e in (errs or [w.err])]


PACKED = "vseed int, verr double, pairs binary"


def packed(batches: Iterator[pa.RecordBatch], most: int = 1_000_000) -> Iterator[pa.RecordBatch]:
    """Pairs and their YES votes of one draw, some at a time, as compressed bytes of differences."""
    schema = pa.schema([("vseed", pa.int32()), ("verr", pa.float64()), ("pairs", pa.binary())])

    def flushed() -> pa.RecordBatch:
        t = pa.Table.from_batches(held).to_pandas()
        out = [(*key, zlib.compress(b"".join(np.diff(g[c].to_numpy(), prepend=0).astype(k).tobytes() for c, k in (("u", "<i8"), ("w", "<i8"), ("n_yes", "<i2"))), 1)) for key, g in t.groupby(["vseed", "verr"])]
        return pa.RecordBatch.from_arrays([pa.array(x, f.type) for x, f in zip(zip(*out, strict=True), schema, strict=True)], schema=schema)

    held: list[pa.RecordBatch] = []
    for b in batches:
        held.append(b)
        if sum(map(len, held)) >= most:
            yield flushed()
            held = []
    if sum(map(len, held)):
        yield flushed()


def unpacked(parts) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The columns u, w and n_yes of ``packed`` parts."""
    columns: list[list[np.ndarray]] = [[], [], []]
    for part in parts:
        raw = zlib.decompress(part)
        n = len(raw) // 18
        for k, (start, end, kind) in enumerate(((0, 8, "<i8"), (8, 16, "<i8"), (16, 18, "<i2"))):
            columns[k].append(np.cumsum(np.frombuffer(raw[start * n : end * n], kind), dtype=kind))
    return tuple(np.concatenate(c) if c else np.empty(0, np.int64) for c in columns)


def run(spark: SparkSession, sf_dir: str, name: str, rows: list[tuple], target: float | None = 0.95, samples: int = Config.samples, hard: bool = False) -> DataFrame:
    """Rounds of every setting on a workload until the target or the pool's end.

    One task holds the pool of a run; pairs go there packed, about two bytes each. ``hard`` puts all errors on a hashed half of the pairs.
    """
    w = W.WORKLOADS[name]
    records = W.gold(spark, sf_dir, name)
    pairs = W.pool(records.repartition(2 * spark.sparkContext.defaultParallelism, "rid"), name)
    plan = spark.createDataFrame(rows, "method string, seed int, batch int, initial int, err double")
    drawn = plan.select(F.col("seed").alias("vseed"), F.col("err").alias("verr")).distinct()
    each = pairs.crossJoin(F.broadcast(drawn))
    chance = F.when(W.unit_hash(F.col("vseed"), F.col("u"), F.col("w"), "hard") < 0.5, 2 * F.col("verr")).otherwise(0.0) if hard else F.col("verr")
    votes = [F.coalesce((F.col("same") != (W.unit_hash(F.col("vseed"), F.col("u"), F.col("w"), F.lit(k)) < chance)).cast("int"), F.lit(0)) for k in range(w.voters)]
    shown = each.select("vseed", "verr", "u", "w", sum(votes[1:], votes[0]).alias("n_yes")).mapInArrow(packed, PACKED)
    asks = (F.col("seed") == F.col("vseed")) & (F.col("err") == F.col("verr"))
    full = shown.join(F.broadcast(plan), asks).drop("vseed", "verr").withColumns({"rid": F.lit(None).cast("long"), "entity": F.lit(None).cast("string")})
    full = full.unionByName(records.select("rid", "entity").crossJoin(F.broadcast(plan)), allowMissingColumns=True)

    def one(g: pd.DataFrame) -> pd.DataFrame:
        entities = g.loc[g["pairs"].isna(), ["rid", "entity"]].sort_values("rid")
        u, v, yes = unpacked(g["pairs"].dropna())
        if not len(u):
            return pd.DataFrame(columns=[c.split()[0] for c in kept.split(", ")])
        ids = np.union1d(u, v)
        u, v = (np.searchsorted(ids, x).astype(np.int32) for x in (u, v))
        at = np.lexsort((v, u))
        u, v, yes = u[at], v[at], yes[at]
        names = entities["entity"].to_numpy()[np.searchsorted(entities["rid"].to_numpy(), ids)]
        entity = np.unique(names.astype(str), return_inverse=True)[1]
        first = g.iloc[0]
        pool = simulate.Pool(len(ids), u, v, yes / w.voters, (2 * yes > w.voters).astype(float), int(first["seed"]))
        out = simulate.run(pool, entity, first["method"], int(first["batch"]), "spanning" if first["initial"] < 0 else int(first["initial"]), samples, target)
        for c in ("method", "seed", "batch", "initial", "err"):
            out[c] = first[c]
        return out

    kept = "method string, seed int, batch int, initial int, err double, round int, n_initial long, n_next long, precision double, recall double, f1 double, loglik double, reliability double, select_ms double, reclustered boolean"
    full = full.repartition(len(rows), "method", "seed", "batch", "initial", "err")  # long runs do not wait for each other in one task
    found = full.groupBy("method", "seed", "batch", "initial", "err").applyInPandas(lambda g: one(g)[[c.split()[0] for c in kept.split(", ")]], kept)
    return found.withColumn("workload", F.lit(name))


SEEDS = tuple(range(42, 52))
#: The F1 that a run of a workload ends at.
TARGETS = {"w1": 0.95, "w2": 0.95, "w3": 0.95, "w4": 0.8, "w4b": 0.95, "w4d": 0.8}
_kept: dict[tuple[str, str, str], DataFrame] = {}


def whole(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Rounds of all methods and ten seeds on a workload; a table that the session's other measures read again."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _kept:
        methods = ("reliability", "random") if name == "w4d" else simulate.METHODS
        _kept[key] = cut(run(spark, sf_dir, name, settings(name, methods, SEEDS), TARGETS[name]), f"rounds-{name}")
    return _kept[key]
