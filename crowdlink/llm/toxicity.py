"""Toxic passages as maximal scoring segments of token log-odds, calibrated by extreme values.

Fitting: counts of the toxic and the clean labelled texts with each word give log-odds under an informative
Dirichlet prior (the pooled rates), shrunk towards zero where the evidence is weak. Less a small drift,
the scores of a clean text sum to ever less, so its best segment follows an extreme-value law whose rate
solves ``sum p * exp(rate * score) = 1`` and whose constant comes from the clean texts themselves.
Scoring: one linear scan finds all maximal segments of a text; each that is significant adds its
evidence, and a logistic curve over the evidence, fitted to the same labelled texts, gives the score.

Bounds: at most ``LABELLED`` labelled rows (those of the least hashed ids) are learned from, a parameter; the
model holds every word of clear evidence in them. Everything else reads all rows.

Defined results: null and empty texts have no segment and get the score of no evidence; null labels and
labels of unknown documents teach nothing; repeated labels of one document are averaged; without labels
every score is that of no evidence; repeated documents get a row each; a null id is never held out; extra
columns do not matter; texts of any length are read whole, in linear time; an empty table gives no rows.
"""

from __future__ import annotations

import pickle
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from crowdlink.llm.decontaminate import words_of

LABELLED = 20_000
#: Weight of the prior in tokens, the least clear z-value that counts, and the drift of every token.
PRIOR, CLEAR, DRIFT = 20_000.0, 2.5, 0.15
SIGNIFICANT = 3.0


@dataclass
class Model:
    scores: dict[bytes, float] = field(default_factory=dict)
    rate: float = 1.0
    log_k: float = 0.0
    curve: tuple[float, ...] = (-20.0, 0.0, 0.0)


def segments(values: list[float]) -> list[tuple[int, int, float]]:
    """All maximal scoring segments (start, end, sum) of a sequence, in time linear in its length.

    A candidate remembers the nearest earlier one that starts lower, so a search follows these links and never
    meets what it has passed; where no earlier candidate starts lower, all of them are final and retire.
    """
    done: list[tuple[int, int, float]] = []
    starts: list[int] = []
    ends: list[int] = []
    lows: list[float] = []  # sums before the candidates
    highs: list[float] = []  # sums at their ends
    lower: list[int] = []  # places of the nearest earlier candidates that start lower; -1 if there is none
    total = 0.0
    for n, v in enumerate(values):
        before, total = total, total + v
        if v <= 0:
            continue
        start, low, k = n, before, len(lows) - 1
        while True:
            while k >= 0 and lows[k] >= low:
                k = lower[k]
            if k < 0 or highs[k] >= total:
                break
            start, low, link = starts[k], lows[k], lower[k]
            del starts[k:], ends[k:], lows[k:], highs[k:], lower[k:]
            k = link
        if k < 0 and lows:
            done.extend((a, b, high - low_) for a, b, low_, high in zip(starts, ends, lows, highs, strict=True))
            for held in (starts, ends, lows, highs, lower):
                held.clear()
        starts.append(start)
        ends.append(n + 1)
        lows.append(low)
        highs.append(total)
        lower.append(k)
    return done + [(a, b, high - low) for a, b, low, high in zip(starts, ends, lows, highs, strict=True)]


def candidates(words: list[bytes], model: Model) -> tuple[float, list[tuple[int, int, float]]]:
    """What a chance segment of so many words would reach, and all maximal segments of word numbers with their scaled sums."""
    found = list(map(model.scores.get, words, repeat(0.0)))
    at = [n for n, v in enumerate(found) if v]
    # stretches of neutral words act as one negative value between the others
    values, places, last = [], [], 0
    for n in at:
        if n > last:
            values.append(-DRIFT * (n - last))
            places.append(last)
        values.append(found[n] - DRIFT)
        places.append(n)
        last = n + 1
    return float(np.log(max(len(words), 1))), [(places[a], places[b - 1] + 1, model.rate * s) for a, b, s in segments(values)]


def passages(words: list[bytes], model: Model) -> list[tuple[int, int, float]]:
    """Significant passages of word numbers with their evidence, and the best evidence first at (0, 0)."""
    spread, found = candidates(words, model)
    spread += model.log_k
    best = max((s for _, _, s in found), default=0.0)
    return [(0, 0, best - spread), *((a, b, s - spread) for a, b, s in found if s - spread >= SIGNIFICANT)]


def _features(evidence: np.ndarray, total: np.ndarray) -> np.ndarray:
    return np.stack([np.ones_like(evidence), np.clip(evidence, -15, 30), np.log1p(total)], axis=-1)


def training_rows(labels: DataFrame, keep, id_col: str = "doc_id", label_col: str = "toxic", limit: int = LABELLED) -> DataFrame:
    """At most ``limit`` rows (id, toxic), of the least hashed ids; ``keep`` is a condition on the id."""
    usable = labels.select(F.col(id_col).alias("label_id"), F.col(label_col).alias("y")).where("label_id IS NOT NULL AND y IS NOT NULL").where(keep(F.col("label_id")))
    one = usable.groupBy("label_id").agg((F.avg("y") >= 0.5).cast("int").alias("y"))
    rows = one.orderBy(F.xxhash64("label_id"), "label_id").limit(limit).collect()  # bounded by ``limit``
    return labels.sparkSession.createDataFrame(rows, one.schema)


def _counts(chosen: DataFrame) -> DataFrame:
    """Texts with each word (word, toxic, clean) over rows (y, text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sums = (Counter(), Counter())
            for y, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                sums[y].update({*words_of(text)})  # once a text: a burst in one text is one observation
            words = list(sums[0] | sums[1])
            yield pa.RecordBatch.from_arrays([pa.array(words, pa.binary()), *(pa.array([sums[y][w] for w in words], pa.int64()) for y in (1, 0))], names=["word", "toxic", "clean"])

    return chosen.select("y", "text").mapInArrow(run, "word binary, toxic long, clean long").groupBy("word").agg(F.sum("toxic").alias("toxic"), F.sum("clean").alias("clean"))


def fit(docs: DataFrame, train: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> Model:
    """Model from the texts of the bounded table ``train``."""
    chosen = docs.select(F.col(id_col).alias("label_id"), F.col(text_col).alias("text")).join(F.broadcast(train), "label_id").select("y", "text")
    counts = _counts(chosen)
    totals = counts.agg(F.sum("toxic").cast("double").alias("t"), F.sum("clean").cast("double").alias("c")).first()
    if not totals["t"] or not totals["c"]:
        return Model()
    prior = (F.col("toxic") + F.col("clean")) * (PRIOR / (totals["t"] + totals["c"]))
    a, b = F.col("toxic") + prior, F.col("clean") + prior
    delta = F.log(a / (totals["t"] + PRIOR)) - F.log(b / (totals["c"] + PRIOR))
    judged = counts.select("word", "toxic", "clean", delta.alias("delta"), (delta / F.sqrt(1 / a + 1 / b)).alias("z"))
    clear = judged.where(F.abs("z") > CLEAR).toPandas().sort_values("word", kind="stable")  # bounded by the words of the training rows
    shrunk = clear["delta"] * (1 - (CLEAR / clear["z"]) ** 2)
    model = Model({bytes(w): float(s) for w, s in zip(clear["word"], shrunk, strict=True)})
    # rate of the extreme-value law over the clean texts' words
    share = clear["clean"].to_numpy(float) / totals["c"]
    score = shrunk.to_numpy(float) - DRIFT
    neutral = max(0.0, 1.0 - share.sum())
    low, high = 1e-3, 1e-3
    excess = lambda r: float(share @ np.exp(np.minimum(r * score, 500)) + neutral * np.exp(-r * DRIFT) - 1)
    while high < 50 and excess(high) < 0:
        high *= 2
    for _ in range(60):
        mid = (low + high) / 2
        low, high = (mid, high) if excess(mid) < 0 else (low, mid)
    model.rate = high
    # one pass over the training texts: the scaled sums of their segments, before the constant is known
    rows = _sums(chosen, model).toPandas()  # bounded by the training rows
    best = np.array([max(x, default=0.0) for x in rows["sums"]]) - rows["spread"].to_numpy(float)
    y = rows["y"].to_numpy(float)
    clean = best[(y == 0) & (rows["n_words"].to_numpy() > 0)]
    model.log_k = float(np.median(clean) + np.log(np.log(2))) if len(clean) else 0.0
    total = [sum(e for s in x if (e := s - at - model.log_k) >= SIGNIFICANT) for x, at in zip(rows["sums"], rows["spread"], strict=True)]
    model.curve = tuple(_logistic(_features(best - model.log_k, np.array(total)), y))
    return model


def _sums(chosen: DataFrame, model: Model) -> DataFrame:
    """Rows ``(y, n_words, spread, sums)`` of rows (y, text): the scaled sums of all maximal segments."""
    sent = chosen.sparkSession.sparkContext.broadcast(pickle.dumps(model))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own: Model = pickle.loads(sent.value)
        for batch in batches:
            size, spread, sums = [], [], []
            for text in batch.column(1).to_pylist():
                words = words_of(text)
                at, found = candidates(words, own)
                size.append(len(words))
                spread.append(at)
                sums.append([s for _, _, s in found])
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(size, pa.int64()), pa.array(spread, pa.float64()), pa.array(sums, pa.list_(pa.float64()))], names=["y", "n_words", "spread", "sums"])

    return chosen.select("y", "text").mapInArrow(run, "y int, n_words long, spread double, sums array<double>")


def _logistic(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    w = np.zeros(x.shape[1])
    for _ in range(50):
        p = 1 / (1 + np.exp(-x @ w))
        h = (x * (p * (1 - p))[:, None]).T @ x + 1e-3 * np.eye(len(w))
        step = np.linalg.solve(h, x.T @ (y - p) - 1e-3 * w)
        w += step
        if np.abs(step).max() < 1e-8:
            break
    return w


def _evidence(docs: DataFrame, model: Model) -> DataFrame:
    """Rows ``(id, n_words, evidence, total, spans, score)`` of rows (id, text)."""
    sent = docs.sparkSession.sparkContext.broadcast(pickle.dumps(model))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own: Model = pickle.loads(sent.value)
        curve = np.array(own.curve)
        for batch in batches:
            size, evidence, total, spans = [], [], [], []
            for text in batch.column(1).to_pylist():
                words = words_of(text)
                first, *rest = passages(words, own)
                size.append(len(words))
                evidence.append(first[2])
                total.append(sum(e for _, _, e in rest))
                spans.append([{"start": a, "end": b, "evidence": e} for a, b, e in rest])
            score = 1 / (1 + np.exp(-_features(np.array(evidence), np.array(total)) @ curve))
            kind = pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32()), ("evidence", pa.float64())]))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(size, pa.int64()), pa.array(evidence, pa.float64()), pa.array(total, pa.float64()), pa.array(spans, kind), pa.array(score)], names=["id", "n_words", "evidence", "total", "spans", "score"])

    kind = docs.schema["id"].dataType.simpleString()
    return docs.select("id", "text").mapInArrow(run, f"id {kind}, n_words long, evidence double, total double, spans array<struct<start:int,end:int,evidence:double>>, score double")


def score(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows ``(id, n_words, evidence, total, spans, score)``; spans are the toxic passages as word numbers."""
    return _evidence(docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")), model)


def drop_toxic(docs: DataFrame, model: Model, least: float = 0.3, text_col: str = "text") -> DataFrame:
    """The documents with all their columns whose score is less than ``least``."""
    row = F.struct(*(F.col(f"`{c}`").alias(f"c{k}") for k, c in enumerate(docs.columns)))
    scored = _evidence(docs.select(row.alias("id"), F.col(f"`{text_col}`").alias("text")), model)
    return scored.where(F.col("score") < least).select(*(F.col(f"id.c{k}").alias(c) for k, c in enumerate(docs.columns)))


def held_out(doc_id: Column) -> Column:
    """Documents that are never learned from."""
    return F.coalesce(F.crc32(doc_id.cast("string")) % 4 == 2, F.lit(False))


def report(scored: DataFrame, least: float = 0.3) -> DataFrame:
    return scored.select(F.col("id").alias("doc_id"), held_out(F.col("id")).alias("held_out"), "score", (F.col("score") >= least).cast("int").alias("predicted"))
