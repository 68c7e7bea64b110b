"""Scores of whole documents under a recurrent language model and under corpus counts.

Counts of every token and the recurrent weights come from all training documents. Weights are learnt in
rounds: every learner starts from the same weights, reads its documents of the round (whole texts), and the
weights of all learners are averaged by tokens. Words with a number of their own grow with the training tokens
(their power ``GROWTH``). Tasks hold these and the ``LOOKUP`` most frequent tokens with their counts; all other
tokens of a document are joined with the counts by shuffle.

Defined results: a null text is empty, and an empty text is its end token alone; a null id is a training
document; repeated rows get a row each; without training documents all counts are 0; extra columns do
not matter; texts of any length are read whole, the state carried from window to window; an empty table gives
no rows.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator
from math import isqrt

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from crowdlink.llm.recurrent import Recurrent, one_thread
from crowdlink.storage import cut

HEAD, LOOKUP = 1024, 200_000  # least number of words with a number of their own; tokens held in tasks
#: Words with a number of their own are this power of the training tokens.
GROWTH = 0.42
#: Every document is read once in a pass, in one of ROUNDS rounds; there are PASSES of them, whatever the tokens.
ROUNDS, PASSES = 4, 1
#: Tokens that a task gathers before it trains or scores, and numbers in a row of weights.
GATHERED, PIECE = 2_000_000, 1 << 16
#: Bytes of texts that are split into words at once.
BYTES = 4 << 20
#: The token that ends each text; no word can hold a line end.
END = b"\n"


def words_of(texts: pa.Array) -> tuple[pa.Array, np.ndarray]:
    """Words between white space of ASCII, A-Z lowered, of all texts in turn, and how many each text has."""
    lists = pc.ascii_split_whitespace(pc.ascii_lower(pc.fill_null(texts.cast(pa.string()), "")))
    words, begins = lists.values.cast(pa.binary()), lists.offsets.to_numpy()
    there = pc.binary_length(words).to_numpy() > 0  # white space at an end of a text gives an empty word
    return words.filter(pa.array(there)), np.diff(np.append(0, np.cumsum(there))[begins])


def with_ends(numbers: np.ndarray, sizes: np.ndarray, end: int) -> tuple[np.ndarray, np.ndarray]:
    """Numbers of words with one for the end after each text, and the places of the ends."""
    ends = np.cumsum(sizes + 1) - 1
    out = np.full(len(numbers) + len(sizes), end, numbers.dtype)
    inner = np.ones(len(out), bool)
    inner[ends] = False
    out[inner] = numbers
    return out, ends


def numbered(words: pa.Array, known: pa.Array, other: int) -> np.ndarray:
    """Place of each word in ``known``, or ``other``."""
    return pc.fill_null(pc.index_in(words, value_set=known), other).to_numpy()


def pieces(texts: pa.Array) -> Iterator[tuple[int, pa.Array]]:
    """Begin and texts of parts of about ``BYTES``; a longer text is a part of its own."""
    size = np.append(0, np.cumsum(pc.fill_null(pc.binary_length(texts), 0).to_numpy().astype(np.int64)))
    begin = 0
    while begin < len(texts):
        end = max(begin + 1, int(np.searchsorted(size, size[begin] + BYTES, "right")) - 1)
        yield begin, texts.slice(begin, end - begin)
        begin = end


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string")) % 7 == 2, F.lit(False))


def token_counts(texts: DataFrame) -> DataFrame:
    """Rows ``(word, c)`` over rows (text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.Table] = []

        def flush() -> Iterator[pa.RecordBatch]:
            if held:
                sums = pa.concat_tables(held).group_by("word").aggregate([("c", "sum")])
                held.clear()
                yield from sums.select(["word", "c_sum"]).rename_columns(["word", "c"]).to_batches()

        for batch in batches:
            for _, piece in pieces(batch.column(0)):
                words, sizes = words_of(piece)
                found = words.value_counts()
                held += [pa.table({"word": found.field(0), "c": found.field(1)}), pa.table({"word": pa.array([END], pa.binary()), "c": pa.array([len(sizes)], pa.int64())})]
                if sum(map(len, held)) > 600_000:
                    yield from flush()
        yield from flush()

    return texts.select("text").mapInArrow(run, "word binary, c long").groupBy("word").agg(F.sum("c").alias("c"))


def fit(docs: DataFrame, counts: DataFrame) -> dict:
    """What the tasks need: frequent tokens, totals and the recurrent weights."""
    # frequent tokens by fine steps of their counts: as many steps as hold LOOKUP tokens at most
    step = F.floor(F.log2("c") * 64).cast("int")
    sizes = sorted(((r["step"], r["n"]) for r in counts.groupBy(step.alias("step")).agg(F.count("*").alias("n")).collect()), reverse=True)
    kept, least = 0, None
    for s, many in sizes:
        if kept + many > LOOKUP:
            break
        kept, least = kept + many, s
    top = [] if least is None else sorted(counts.where(step >= least).collect(), key=lambda r: (-r["c"], r["word"]))  # bounded by LOOKUP
    n, v = counts.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count("*")).first()
    words = [bytes(r["word"]) for r in top]
    many = max(HEAD, int(n**GROWTH))
    head = words[:many]
    if END not in head:
        head = [END, *head[: many - 1]]
    of = {w: k for k, w in enumerate(head)}
    count = {bytes(r["word"]): r["c"] for r in top}
    for w in words:
        of.setdefault(w, len(of))
    known = np.array([count.get(w, 0) for w in of], np.float64)
    model = Recurrent.fresh(len(head), classes=max(32, isqrt(len(head))))
    if n:
        learn(docs.where(~F.col("held_out")), of, model, PASSES)
    spare = float(n - known[: len(head)].sum() + max(v - len(head), 0) + 1)
    return {"of": of, "counts": known, "n": int(n), "v": int(v), "head": len(head), "spare": spare, "model": model}


def learn(texts: DataFrame, of: dict[bytes, int], model: Recurrent, passes: int) -> None:
    """Fit the weights to all rows (id, text) in rounds of averages; only averages reach the driver."""
    spark = texts.sparkSession
    words = spark.sparkContext.broadcast(list(of)[: model.head])
    # a learner reads several partitions one after another, so that it makes more steps between averages
    dealt = texts.select(F.pmod(F.xxhash64("id", "text"), F.lit(ROUNDS)).alias("turn"), "text").coalesce(2 * spark.sparkContext.defaultParallelism)
    total = passes * ROUNDS
    for k in range(total):
        sent, rate = spark.sparkContext.broadcast(pickle.dumps(model)), 4e-3 * (1 - 0.9 * k / total)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            one_thread()
            known, own = pa.array(words.value, pa.binary()), pickle.loads(sent.value)
            first = words.value.index(END)
            held, size, seen, state = [], 0, 0, {}
            for batch in batches:
                for _, piece in pieces(batch.column(0)):
                    found, sizes = words_of(piece)
                    numbers, ends = with_ends(numbered(found, known, own.head), sizes, first)
                    for text in np.split(numbers, ends[:-1] + 1):
                        held.append(text)
                        size += len(text)
                        if size >= GATHERED:
                            own.train(held, first, rate, state)
                            held, size, seen = [], 0, seen + size
            if held:
                own.train(held, first, rate, state)
            seen += size
            if seen:
                flat = own.flat()
                cuts = range(0, len(flat), PIECE)
                yield pa.RecordBatch.from_arrays([pa.array(list(cuts), pa.int64()), pa.array([seen] * len(cuts), pa.int64()), pa.array([flat[c : c + PIECE].tobytes() for c in cuts], pa.binary())], names=["at", "seen", "part"])

        def mean(g: pd.DataFrame) -> pd.DataFrame:
            g = g.sort_values(["seen", "part"])  # the order of sums must not depend on who was first
            parts = np.stack([np.frombuffer(x, np.float32) for x in g["part"]])
            out = np.average(parts.astype(np.float64), axis=0, weights=g["seen"].to_numpy()).astype(np.float32)
            return pd.DataFrame({"at": [g["at"].iloc[0]], "part": [out.tobytes()]})

        rows = dealt.where(F.col("turn") == k % ROUNDS).select("text").mapInArrow(run, "at long, seen long, part binary").groupBy("at").applyInPandas(mean, "at long, part binary").collect()
        if rows:  # a round may have no documents
            model.put(np.concatenate([np.frombuffer(r["part"], np.float32) for r in sorted(rows, key=lambda r: r["at"])]))
        sent.unpersist()
    words.unpersist()


def score(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", apart=held_out) -> DataFrame:
    """Rows ``(id, held_out, n_tokens, n_known, train_tokens, base_score, score)``; scores are log10 probabilities."""
    rows = docs.select(F.col(id_col).alias("id"), apart(F.col(id_col)).alias("held_out"), F.coalesce(text_col, F.lit("")).alias("text"))
    counts = cut(token_counts(rows.where(~F.col("held_out"))), "counts")
    fitted = fit(rows, counts)
    sent = docs.sparkSession.sparkContext.broadcast(pickle.dumps(fitted))
    n, v, spare = fitted["n"], fitted["v"], fitted["spare"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        one_thread()
        f = pickle.loads(sent.value)
        known, head, model = pa.array(list(f["of"]), pa.binary()), f["head"], f["model"]
        first, off = f["of"][END], np.log10(f["spare"])
        log_count, seen = np.append(np.log10(f["counts"] + 1), 0.0), np.append(f["counts"] > 0, False)  # -1 is the last

        def flush(batch: pa.RecordBatch, ids: list, rest: list, partial: list) -> pa.RecordBatch:
            size, hits, base, tails = (np.concatenate(c) for c in zip(*partial, strict=True))
            total = model.score_texts(ids, first) / np.log(10) + tails
            return pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(1), batch.column(2), pa.array(size, pa.int64()), pa.array(hits, pa.int64()), pa.array(base, pa.float64()), pa.array(total, pa.float64()), pa.concat_arrays(rest)],
                names=["id", "th", "held_out", "n_tokens", "known", "base", "total", "rest"],
            )

        for whole in batches:
            # texts go to the model by GATHERED tokens, as a long one takes as many steps alone as beside others
            begun, held, ids, rest, partial = 0, 0, [], [], []
            for _, piece in pieces(whole.column(3)):
                words, sizes = words_of(piece)
                inner = numbered(words, known, -1)
                at, ends = with_ends(inner, sizes, first)
                starts, logs, far = ends - sizes, log_count[at], at >= head
                partial.append((sizes + 1, np.add.reduceat(seen[at].astype(np.int64), starts), np.add.reduceat(logs, starts), np.add.reduceat(np.where(far, logs - off, 0.0), starts)))
                missed = inner < 0
                begins = np.append(0, np.cumsum(missed))[np.append(0, np.cumsum(sizes))]
                rest.append(pa.ListArray.from_arrays(pa.array(begins, pa.int32()), words.filter(pa.array(missed))))
                at[far | (at < 0)] = head
                ids += np.split(at, ends[:-1] + 1)
                held += len(at)
                if held >= GATHERED:
                    yield flush(whole.slice(begun, len(ids)), ids, rest, partial)
                    begun, held, ids, rest, partial = begun + len(ids), 0, [], [], []
            if ids:
                yield flush(whole.slice(begun, len(ids)), ids, rest, partial)

    kind = docs.schema[id_col].dataType.simpleString()
    keyed = rows.select("id", F.xxhash64("text").alias("th"), "held_out", "text")
    part = cut(keyed.mapInArrow(run, f"id {kind}, th long, held_out boolean, n_tokens long, known long, base double, total double, rest array<binary>"), "parts")
    # rows of one id and text have the same rest, so one of them stands for all
    rare = part.where(F.size("rest") > 0).groupBy("id", "th").agg(F.any_value("rest").alias("rest")).select("id", "th", F.explode("rest").alias("word"))
    rare = rare.join(counts, "word", "left").groupBy("id", "th").agg(F.sum(F.log10(F.coalesce("c", F.lit(0)) + 1.0)).alias("logs"), F.count("*").alias("tokens"), F.count("c").alias("hits"))
    met = F.col("p.id").eqNullSafe(F.col("r.id")) & (F.col("p.th") == F.col("r.th"))
    joined = part.drop("rest").alias("p").join(rare.alias("r"), met, "left")
    logs, tokens = F.coalesce("logs", F.lit(0.0)), F.coalesce("tokens", F.lit(0))
    return joined.select(
        F.col("p.id").alias("id"),
        "held_out",
        "n_tokens",
        (F.col("known") + F.coalesce("hits", F.lit(0))).alias("n_known"),
        F.lit(n).cast("long").alias("train_tokens"),
        (F.col("base") + logs - F.col("n_tokens") * F.lit(float(np.log10(n + v + 1)))).alias("base_score"),
        (F.col("total") + logs - tokens * F.lit(float(np.log10(spare)))).alias("score"),
    )
