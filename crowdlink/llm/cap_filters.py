"""Near-duplicate vectors by spherical-cap filters: product codes, list decoding, join on filters, verify.

A filter is a direction whose parts come from one small random codebook for each block of dimensions.
A vector lies in every filter whose direction its own exceeds by the cap; only a vector that lies in fewer
than ``FLOOR`` of them takes its ``FLOOR`` best ones instead. The codebooks grow with the rows of the largest
label, and the cap with the filters, so that a vector lies in about ``MEAN`` filters and a filter holds about
``FILLED`` vectors at any size. Decoding walks the blocks, drops each beginning that even the best ends cannot
lift high enough, and lists the ends of the last block from the best on. Vectors of one (label, filter) are
compared in blocks of bounded size with double-precision cosines, and a pair counts in the least filter that
both share, so no pair counts twice.

Vectors of the same bytes and label are one representative from the start. Defined results: ids are whole
numbers; null ids, null labels or vectors, zero vectors, and vectors that hold null or non-finite components
link with nothing and are kept; vectors of different lengths do not link; an empty table gives no rows;
repeated rows are copies of each other if their ids differ; extra columns do not matter.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from crowdlink.graph import components
from crowdlink.storage import cut

BLOCKS, CODES, SEED = 2, 64, 20240101  # CODES: of a block, at least
#: Filters of a vector by the cap alone, filters that it takes at least, and vectors that share a filter.
MEAN, FLOOR, FILLED = 24, 10, 256
#: Vectors of fewer dimensions have one block, for its codes alone cover their few directions.
FEW_DIMS = 8
#: Vectors of a bucket that stand on one side of a comparison.
SIDE = 512


def codebooks(dims: int, blocks: int = BLOCKS, codes: int = CODES) -> list[np.ndarray]:
    """Unit directions for each block of dimensions, scaled so that a whole direction has length 1."""
    rng = np.random.default_rng([SEED, dims])
    blocks = blocks if dims >= FEW_DIMS else 1
    out = []
    for part in np.array_split(np.arange(dims), blocks):
        c = rng.standard_normal((codes, len(part)))
        out.append(c / (np.linalg.norm(c, axis=1, keepdims=True) * np.sqrt(blocks)))
    return out


def codes_for(rows: int, blocks: int = BLOCKS) -> int:
    """Codes of a block for so many vectors of one label: a power of two."""
    codes = CODES
    while codes**blocks * FILLED < rows * MEAN:
        codes *= 2
    return codes


def cap_for(books: list[np.ndarray]) -> float:
    """The cap above which a vector lies with about ``MEAN`` filters: the median score of the ``MEAN``-th best of random vectors."""
    dims = sum(b.shape[1] for b in books)
    unit = np.random.default_rng([SEED, dims, 1]).standard_normal((64, dims))
    unit /= np.linalg.norm(unit, axis=1, keepdims=True)
    row, _, score = _decode(unit, books, np.inf, MEAN)
    least = np.full(len(unit), np.inf)
    np.minimum.at(least, row, score)
    return float(np.median(least))


def decode(unit: np.ndarray, books: list[np.ndarray], cap: float, floor: int = FLOOR) -> tuple[np.ndarray, np.ndarray]:
    """Pairs (row, filter) of the filters that each unit vector lies in, in order."""
    return _decode(unit, books, cap, floor)[:2]


def _decode(unit: np.ndarray, books: list[np.ndarray], cap: float, floor: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    scores, at = [], 0
    for b in books:
        scores.append(unit[:, at : at + b.shape[1]] @ b.T)
        at += b.shape[1]
    rest = np.cumsum([s.max(axis=1) for s in scores[::-1]], axis=0)[::-1]
    # a lower bound of the floor-th best score: its best beginnings with the best ends
    bound = np.full(len(unit), np.inf)
    for s, r in zip(scores, rest, strict=True):
        k = min(floor, s.shape[1])
        bound = np.minimum(bound, np.partition(s, -k, axis=1)[:, -k] + rest[0] - s.max(axis=1))
    need = np.minimum(cap, bound)
    row, code, sum_ = np.arange(len(unit)), np.zeros(len(unit), np.int64), np.zeros(len(unit))
    for s, ahead in zip(scores[:-1], rest[1:], strict=True):
        grown = sum_[:, None] + s[row]
        r, c = np.nonzero(grown + ahead[row][:, None] >= need[row][:, None] - 1e-12)
        row, code, sum_ = row[r], code[r] * s.shape[1] + c, grown[r, c]
    # the ends of the last block from the best on, found by bisection in rows that stand 4 apart
    s = scores[-1]
    best = np.argsort(-s, axis=1, kind="stable")
    flat = (4.0 * np.arange(len(unit))[:, None] - np.take_along_axis(s, best, axis=1)).ravel()
    ends = np.searchsorted(flat, 4.0 * row + np.clip(sum_ - need[row] + 1e-9, -1.9, 1.9), side="right") - row * s.shape[1]
    r = np.repeat(np.arange(len(row)), ends)
    c = best[row[r], np.arange(len(r)) - np.repeat(np.cumsum(ends) - ends, ends)]
    row, code, sum_ = row[r], code[r] * s.shape[1] + c, sum_[r] + s[row[r], c]
    # now all above ``need``; of those keep what exceeds the cap, or the best ones
    order = np.lexsort((code, -sum_, row))
    row, code, sum_ = row[order], code[order], sum_[order]
    place = np.arange(len(row)) - np.searchsorted(row, row)
    kept = (sum_ >= cap) | (place < floor)
    row, code, sum_ = row[kept], code[kept], sum_[kept]
    order = np.lexsort((code, row))
    return row[order], code[order], sum_[order]


def _prepare(vectors: DataFrame, id_col: str, vec_col: str, label_col: str, codes: int) -> DataFrame:
    """Rows ``(id, label, digest, vector, filters)``; the last three are null for vectors that link with nothing."""
    step = max(64, 2048 * CODES // codes)  # vectors that are decoded at a time

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: dict[int, tuple[list[np.ndarray], float]] = {}  # books and cap by dimensions
        for whole in batches:
            for start in range(0, whole.num_rows, step):
                batch = whole.slice(start, step)
                values = [None if v is None or any(x is None for x in v) else np.asarray(v, np.float64) for v in batch.column(1).to_pylist()]
                good = [v is not None and v.size > 0 and np.isfinite(v).all() and bool(v.any()) for v in values]
                digests, packed, lists = [None] * len(values), [None] * len(values), [None] * len(values)
                for dims in {len(v) for v, g in zip(values, good, strict=True) if g}:
                    rows = [n for n, g in enumerate(good) if g and len(values[n]) == dims]
                    x = np.stack([values[n] for n in rows])
                    x /= np.abs(x).max(axis=1, keepdims=True)
                    if dims not in known:
                        books = codebooks(dims, codes=codes)
                        known[dims] = books, cap_for(books)
                    row, code = decode(x / np.linalg.norm(x, axis=1, keepdims=True), *known[dims])
                    ends = np.searchsorted(row, np.arange(len(rows) + 1))
                    for k, n in enumerate(rows):
                        digests[n] = hashlib.blake2b((values[n] + 0.0).tobytes(), digest_size=16).digest()
                        packed[n] = values[n].tobytes()
                        lists[n] = code[ends[k] : ends[k + 1]]
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0), batch.column(2), pa.array(digests, pa.binary()), pa.array(packed, pa.binary()), pa.array(lists, pa.list_(pa.int64()))],
                    names=["id", "label", "digest", "vector", "filters"],
                )

    kind, label = (vectors.schema[c].dataType.simpleString() for c in (id_col, label_col))
    chosen = vectors.select(F.col(id_col).alias("id"), F.col(vec_col).alias("v"), F.col(label_col).alias("label"))
    return chosen.mapInArrow(run, f"id {kind}, label {label}, digest binary, vector binary, filters array<long>")


def _least_reached(a: np.ndarray, b: np.ndarray, m: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Least id that each row (ids ``a``) and each column (ids ``b``) reaches through the links ``m``."""
    none = np.iinfo(np.int64).max
    while True:
        row = np.minimum(a, np.where(m, b[None, :], none).min(axis=1))
        col = np.minimum(b, np.where(m, row[:, None], none).min(axis=0))
        if (row == a).all() and (col == b).all():
            return a, b
        a, b = row, col


def compare(unit: np.ndarray, chunk: np.ndarray, ids: np.ndarray, copies: np.ndarray, filters: pa.Array, first: int, low: int, high: int, least: float) -> list[tuple]:
    """Links (id, other, copies) of one cell, if the cell's filter is the first that the two share.

    ``other`` is the least id that the cell's links lead to, so that these links connect what all do.
    """
    a, b = np.flatnonzero(chunk == low), np.flatnonzero(chunk == high)
    linked = unit[a] @ unit[b].T >= least
    if low == high:
        np.fill_diagonal(linked, False)
    rows, columns = linked.any(axis=1), linked.any(axis=0)
    if not rows.any():
        return []
    a, b, linked = a[rows], b[columns], linked[rows][:, columns]
    lists = [[filters[int(n)].values.to_numpy() for n in x] for x in (a, b)]
    earlier = np.unique(np.concatenate([f for x in lists for f in x]))
    earlier = earlier[earlier < first]
    if len(earlier):
        hot = []
        for x in lists:
            m = np.zeros((len(x), len(earlier)), np.float32)
            for n, f in enumerate(x):
                m[n, np.searchsorted(earlier, f[f < first])] = 1
            hot.append(m)
        linked &= hot[0] @ hot[1].T == 0
    reached = _least_reached(ids[a], ids[b], linked)
    out = [(ids[a], reached[0], linked.astype(np.int64) @ copies[b])]
    if low < high:  # inside one block the matrix holds both directions
        out.append((ids[b], reached[1], linked.T.astype(np.int64) @ copies[a]))
    return out


def _compare_all(cells: DataFrame, least: float) -> DataFrame:
    """``compare`` for every cell; the rows come dealt and sorted by cell, so a task holds a cell at a time."""
    keys = ["label", "dims", "filter", "low", "high"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: pa.Table | None = None

        def work(t: pa.Table, final: bool) -> tuple[pa.RecordBatch, pa.Table | None]:
            t = t.combine_chunks()
            label = np.asarray(t["label"].combine_chunks().dictionary_encode().indices)
            dims, filt, low, high, chunk, ids, copies = (t[c].to_numpy() for c in ("dims", "filter", "low", "high", "chunk", "id", "copies"))
            change = np.ones(len(ids), bool)
            change[1:] = (label[1:] != label[:-1]) | (dims[1:] != dims[:-1]) | (filt[1:] != filt[:-1]) | (low[1:] != low[:-1]) | (high[1:] != high[:-1])
            starts = np.flatnonzero(change)
            ends = np.append(starts[1:], len(ids))
            if not final:
                starts, ends = starts[:-1], ends[:-1]
            filters, found = t["filters"].combine_chunks(), []
            packed = t["vector"].combine_chunks()
            step = 0
            while step < len(starts):  # as many cells of one length as fit together
                last = step
                while last + 1 < len(starts) and dims[starts[last + 1]] == dims[starts[step]] and ends[last + 1] - starts[step] <= 4 * SIDE:
                    last += 1
                lo, hi = starts[step], ends[last]
                x = np.frombuffer(b"".join(packed[lo:hi].to_pylist()), np.float64).reshape(hi - lo, -1)
                x = x / np.abs(x).max(axis=1, keepdims=True)
                x /= np.linalg.norm(x, axis=1, keepdims=True)
                for k in range(step, last + 1):
                    i, j = starts[k], ends[k]
                    if j - i > 1:
                        found += compare(x[i - lo : j - lo], chunk[i:j], ids[i:j], copies[i:j], filters.slice(i, j - i), int(filt[i]), int(low[i]), int(high[i]), least)
                step = last + 1
            columns = [np.concatenate(c) for c in zip(*found, strict=True)] if found else [np.zeros(0, np.int64)] * 3
            rest = None if final else t.slice(int(np.flatnonzero(change)[-1]))
            return pa.RecordBatch.from_arrays([pa.array(c.astype(np.int64)) for c in columns], names=["id", "other", "links"]), rest

        for batch in batches:
            if batch.num_rows:
                table = pa.Table.from_batches([batch])
                done, held = work(table if held is None else pa.concat_tables([held, table]), False)
                yield done
        if held is not None:
            yield work(held, True)[0]

    return cells.repartition(*keys).sortWithinPartitions(*keys).mapInArrow(run, "id long, other long, links long")


def near_vectors(vectors: DataFrame, least: float = 0.98, id_col: str = "vec_id", vec_col: str = "embedding", label_col: str = "label") -> DataFrame:
    """Rows ``(id, n_links, component_id, kept)`` of every vector."""
    most = vectors.groupBy(label_col).agg(F.count("*").alias("rows")).agg(F.coalesce(F.max("rows"), F.lit(0))).first()[0]
    ready = cut(_prepare(vectors, id_col, vec_col, label_col, codes_for(most)), "filters")
    able = F.col("digest").isNotNull() & F.col("label").isNotNull() & F.col("id").isNotNull()
    reps = ready.where(able).groupBy("label", "digest").agg(F.min("id").alias("id"), F.count("*").alias("copies"), F.any_value("vector").alias("vector"), F.any_value("filters").alias("filters"))
    reps = cut(reps, "representatives")
    inside = reps.select("label", "id", F.explode("filters").alias("filter"))
    sizes = inside.groupBy("label", "filter").agg(F.count("*").alias("size")).where("size > 1").withColumn("chunks", F.ceil(F.col("size") / SIDE).cast("int"))
    placed = inside.join(sizes.select("label", "filter", "chunks"), ["label", "filter"]).withColumn("chunk", F.pmod(F.xxhash64("id"), F.col("chunks")).cast("int"))
    cells = placed.withColumn("mate", F.explode(F.expr("sequence(0, chunks - 1)")))
    cells = cells.join(reps.select("id", "copies", "vector", "filters"), "id").select(
        "label", (F.octet_length("vector") / 8).cast("int").alias("dims"), "filter", F.least("chunk", "mate").alias("low"), F.greatest("chunk", "mate").alias("high"), "chunk", "id", "copies", "vector", "filters"
    )
    links = cut(_compare_all(cells, least), "links")
    label = components(links.select(F.col("id").alias("u"), F.col("other").alias("w")))
    counts = links.groupBy("id").agg(F.sum("links").alias("links"))
    of_rep = reps.select("label", "digest", "id", "copies").join(counts, "id", "left").join(label, "id", "left")
    of_rep = of_rep.select("label", "digest", (F.col("copies") - 1 + F.coalesce("links", F.lit(0))).alias("n_links"), F.coalesce("component", "id").alias("component_id"))
    linked = ready.where(able).join(of_rep, ["label", "digest"]).select("id", "n_links", "component_id")
    alone = ready.where(~able).select("id", F.lit(0).cast("long").alias("n_links"), F.col("id").alias("component_id"))
    return linked.unionByName(alone).withColumn("kept", F.col("id").eqNullSafe(F.col("component_id")))
