"""Benchmark decontamination: an FM-index of each training shard is searched for all benchmark windows.

A window is ``width`` consecutive words of an item (or all words of a shorter one). A shard is a bounded
run of documents of one task; its index holds every run of benchmark words that is as long as the
shortest window, which are the only places where a window can occur. Occurrences are located by sampled
suffix positions and merged into removal spans. Documents are never shuffled.

Defined results: a null text or item has no words; an empty benchmark hits nothing; a repeated item id
counts once; a null item id hits but is not listed; repeated documents get a row each; extra columns do
not matter; one text longer than a shard is a shard of its own.
"""

from __future__ import annotations

import pickle
import re
from collections.abc import Iterator
from itertools import repeat

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from crowdlink.llm.fm_index import FmIndex
from crowdlink.storage import cut

WORD = re.compile(rb"[0-9a-z\x80-\xff]+")
#: Bytes of text in a shard, and of benchmark text that is broadcast and that a task holds at a time.
SHARD_BYTES = 6 << 20
BLOCK_BYTES = 16 << 20
SPANS = "array<struct<start:int,end:int>>"
#: Occurrences that are located at a time.
LOCATED = 1 << 20


def words_of(text: str | None) -> list[bytes]:
    return WORD.findall((text or "").encode("utf-8", "replace").lower())


class Phrases:
    """Distinct windows of a block of items as rows of word numbers, and the items of each."""

    def __init__(self, items: list[tuple[str | None, str | None]], width: int):
        self.vocab: dict[bytes, int] = {}
        owners: dict[tuple[int, ...], set[str]] = {}
        for item, text in items:
            ids = [self.vocab.setdefault(w, len(self.vocab) + 1) for w in words_of(text)]
            for k in range(max(1, len(ids) - width + 1) if ids else 0):
                owners.setdefault(tuple(ids[k : k + width]), set()).update(() if item is None else (item,))
        self.lengths = np.array([len(w) for w in owners], np.int64)
        self.rows = np.zeros((len(owners), width), np.int32)
        for row, w in zip(self.rows, owners, strict=True):
            row[: len(w)] = w
        self.items = sorted({i for x in owners.values() for i in x})
        number = {i: n for n, i in enumerate(self.items)}
        lists = [sorted(number[i] for i in x) for x in owners.values()]
        self.item_start = np.cumsum([0, *map(len, lists)])
        self.item_list = np.array([i for x in lists for i in x], np.int64)
        self.shortest = int(self.lengths.min()) if len(owners) else 0

    def mark(self, texts: list[list[bytes]], starts: np.ndarray, change: np.ndarray) -> set[tuple[int, int]]:
        """Add each occurrence to ``change`` (+1 where it begins, -1 behind its end); pairs of text and item."""
        if not self.shortest:
            return set()
        get = self.vocab.get
        codes = np.zeros(len(change), np.int32)
        for n, words in enumerate(texts):
            codes[starts[n] : starts[n] + len(words)] = np.fromiter(map(get, words, repeat(0)), np.int32, len(words))
        known = codes > 0
        edges = np.flatnonzero(np.diff(known, prepend=False, append=False))
        begin, end = edges[::2], edges[1::2]
        long = end - begin >= self.shortest
        begin, size = begin[long], (end - begin)[long]
        if not size.size:
            return set()
        ahead = np.cumsum(size + 1) - (size + 1)
        origin = np.repeat(begin - ahead, size + 1) + np.arange(int((size + 1).sum()))
        text = codes[origin].astype(np.int64)  # the place behind a run holds 0: a stranger or a text's end
        index = FmIndex(text, len(self.vocab))
        low, high = index.search(self.rows, self.lengths)
        window = np.flatnonzero(high > low)
        pairs: set[tuple[int, int]] = set()
        counts = (high - low)[window]
        total = np.cumsum(counts)
        for first in range(0, int(total[-1]) if len(total) else 0, LOCATED):
            nth = np.arange(first, min(first + LOCATED, int(total[-1])))
            which = np.searchsorted(total, nth, side="right")
            w = window[which]
            at = origin[index.locate(low[w] + nth - (total - counts)[which])]
            np.add.at(change, at, 1)
            np.add.at(change, at + self.lengths[w], -1)
            owner = np.searchsorted(starts, at, side="right") - 1
            seen = np.unique(owner * len(self.lengths) + w)
            for o, x in zip((seen // len(self.lengths)).tolist(), (seen % len(self.lengths)).tolist(), strict=True):
                pairs.update((o, int(i)) for i in self.item_list[self.item_start[x] : self.item_start[x + 1]])
        return pairs


def phrase_blocks(benchmark: DataFrame, width: int, id_col: str, text_col: str) -> DataFrame:
    """Rows ``(block, phrases)``: pickled phrases of items, each block of bounded size whatever the benchmark's size.

    Tasks build them, so the driver never holds items; an item longer than a block is a block of its own.
    """
    items = benchmark.select(F.col(id_col).cast("string").alias("id"), F.col(text_col).alias("text"))
    size = items.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]

    def build(g: pd.DataFrame) -> pd.DataFrame:
        rows = [tuple(None if x is None else x for x in r) for r in zip(g["id"], g["text"], strict=True)]
        return pd.DataFrame({"block": [g["block"].iloc[0]], "phrases": [pickle.dumps(Phrases(rows, width))]})

    block = F.pmod(F.xxhash64("id", "text"), F.lit(int(size) // BLOCK_BYTES + 1))
    return cut(items.withColumn("block", block).groupBy("block").applyInPandas(build, "block long, phrases binary"), "phrases")


def find_spans(docs: DataFrame, benchmark: DataFrame, width: int = 10, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text") -> DataFrame:
    """Rows ``(id, n_words, spans, items, cleaned)``: spans of word numbers (end exclusive), item ids, and the text without the spans.

    The documents are read once for each block of the benchmark (``BLOCK_BYTES`` of items), so that only one block
    is broadcast at a time; from pass to pass the spans and items found so far go along with the rows.
    """
    blocks = phrase_blocks(benchmark, width, item_col, item_text)
    numbers = sorted(r[0] for r in blocks.select("block").collect())  # a number for each BLOCK_BYTES of the benchmark
    none = f"cast(array() as {SPANS})"
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"), F.expr(none).alias("spans"), F.expr("cast(array() as array<string>)").alias("items"))
    if not numbers:
        return _pass(rows, None, True)
    for n in numbers:
        sent = docs.sparkSession.sparkContext.broadcast(blocks.where(F.col("block") == n).first()["phrases"])
        rows = _pass(rows, sent, n == numbers[-1])
        if n != numbers[-1]:
            rows = cut(rows, "spans")
            sent.unpersist()
    return rows


def _pass(rows: DataFrame, sent: Broadcast | None, last: bool) -> DataFrame:
    """Rows (id, text, spans, items) with what one block of phrases adds; the last pass gives what ``find_spans`` promises."""

    def shard(phrases: Phrases | None, part: pa.RecordBatch) -> pa.RecordBatch:
        texts = part.column(1).to_pylist()
        raws = [(t or "").encode("utf-8") for t in texts]
        words = [WORD.findall(r.lower()) for r in raws]
        counts = np.array([len(w) for w in words], np.int64)
        starts = np.cumsum(counts + 1) - (counts + 1)  # a gap behind each text
        change = np.zeros(int((counts + 1).sum()) + 1, np.int32)
        items = [set(x) for x in part.column(3).to_pylist()]
        for at, held in zip(starts.tolist(), part.column(2).to_pylist(), strict=True):
            for x in held:
                change[at + x["start"]] += 1
                change[at + x["end"]] -= 1
        if phrases is not None:
            for n, i in phrases.mark(words, starts, change):
                items[n].add(phrases.items[i])
        hit = np.cumsum(change) > 0
        edges = np.flatnonzero(np.diff(hit, prepend=False, append=False))
        spans: list[list[dict]] = [[] for _ in words]
        owner = np.searchsorted(starts, edges[::2], side="right") - 1
        for n, a, z in zip(owner.tolist(), edges[::2].tolist(), edges[1::2].tolist(), strict=True):
            spans[n].append({"start": a - int(starts[n]), "end": z - int(starts[n])})
        kind = pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32())]))
        found = [pa.array(spans, kind), pa.array([sorted(x) for x in items], pa.list_(pa.string()))]
        if not last:
            return pa.RecordBatch.from_arrays([part.column(0), part.column(1), *found], names=["id", "text", "spans", "items"])
        cleaned = [t if not s else without(r, s) for t, r, s in zip(texts, raws, spans, strict=True)]
        return pa.RecordBatch.from_arrays([part.column(0), pa.array(counts), *found, pa.array(cleaned, pa.string())], names=["id", "n_words", "spans", "items", "cleaned"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        phrases = None if sent is None else pickle.loads(sent.value)
        for batch in batches:
            first, size = 0, 0
            for n, t in enumerate(pc.fill_null(pc.binary_length(batch.column(1)), 0).to_pylist()):
                if size and size + t > SHARD_BYTES:
                    yield shard(phrases, batch.slice(first, n - first))
                    first, size = n, 0
                size += t
            if first < batch.num_rows:
                yield shard(phrases, batch.slice(first))

    kind = rows.schema["id"].dataType.simpleString()  # of any type: a whole row in ``remove``
    shape = f"id {kind}, n_words long, spans {SPANS}, items array<string>, cleaned string" if last else f"id {kind}, text string, spans {SPANS}, items array<string>"
    return rows.mapInArrow(run, shape)


def remove(docs: DataFrame, benchmark: DataFrame, width: int = 10, text_col: str = "text", item_col: str = "item_id", item_text: str = "text") -> DataFrame:
    """The documents with all their columns, the removal spans cut out of the text."""
    names = docs.columns
    at = names.index(text_col)
    packed = docs.select(F.struct(*(F.col(f"`{c}`").alias(f"c{k}") for k, c in enumerate(names) if k != at)).alias("row"), F.col(f"`{text_col}`").alias("text"))
    found = find_spans(packed, benchmark, width, "row", "text", item_col, item_text)
    return found.select(*(F.col("cleaned" if k == at else f"id.c{k}").alias(c) for k, c in enumerate(names)))


def without(raw: bytes, spans: list[dict]) -> str:
    """The text without the bytes from each span's first word to its last."""
    places = [m.span() for m in WORD.finditer(raw.lower())]
    out, last = [], 0
    for s in spans:
        out.append(raw[last : places[s["start"]][0]])
        last = places[s["end"] - 1][1]
    return b"".join([*out, raw[last:]]).decode("utf-8")


def report(found: DataFrame) -> DataFrame:
    n_hit = F.aggregate("spans", F.lit(0), lambda n, s: n + s["end"] - s["start"])
    return found.select(
        F.col("id").alias("doc_id"),
        "n_words",
        n_hit.cast("long").alias("n_hit"),
        F.size("items").cast("long").alias("n_items"),
        F.sha2(F.array_join("items", ","), 256).alias("items_sha256"),
        (n_hit > 0).alias("contaminated"),
    )
