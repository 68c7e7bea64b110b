"""Near-duplicate texts: weighted signatures of word shingles, bands, verified multiset overlap, classes.

Similarity is the Jaccard similarity of the multisets of shingles (``width`` consecutive lower-cased
words; a text of fewer words, but not none, is one shingle). A class is a set of texts joined by links of
at least ``least``; its id is its least document id.

Texts of the same words are one representative from the start. A bucket holds the representatives that
agree in all registers of a band; each is compared with the bucket's least one, and afterwards only with
bucket members of other classes where two exact bounds allow a link: the distance is a metric and both
distances to the least one are known; shingles that no other open text has cannot overlap. The member with the
fewest such shingles, the likely original, is compared first. So a group of thousands of copies costs about
two comparisons for each copy (what two texts have in common lies inside or outside the known one, which
bounds it once more), and no link that could join two classes is left out. Members that are still
open meet in cells of bounded blocks, so that no task holds all pairs of a large group.

Defined results: a null text or one without words has no shingles and is a class of its own; repeated
rows get a row each with one class; a row without an id gets the class of the rows with its words, or null if
none of them has an id, and is no class's name; an empty table gives no rows; extra columns do not matter;
texts of any length are read whole.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from crowdlink.graph import components
from crowdlink.llm.bag_minhash import signatures
from crowdlink.llm.text import mix, shingle_hashes, word_hashes
from crowdlink.storage import cut

WIDTH, LEAST = 5, 0.8
#: 32 bands of 4 registers: a pair of similarity 0.8 shares none with probability (1 - 0.8**4)**32, about 5e-8.
BANDS, DEPTH = 32, 4
#: Bytes of text that are worked on at a time.
PIECE = 1 << 20
#: Open members of a head that stand on one side of a comparison.
SIDE = 1024


def pieces(batch: pa.RecordBatch, *columns: int) -> Iterator[pa.RecordBatch]:
    """Slices of a batch with a bounded number of text bytes, or a single row."""
    size = sum(np.asarray(pc.fill_null(pc.binary_length(batch.column(c)), 0), np.int64) for c in columns)
    first, held = 0, 0
    for n, x in enumerate(size.tolist()):
        if held and held + x > PIECE:
            yield batch.slice(first, n - first)
            first, held = n, 0
        held += x
    if first < batch.num_rows:
        yield batch.slice(first)


def multisets(shingles: np.ndarray, owner: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct elements of each owner, their owners, and how often they occur; owners are in order."""
    order = np.lexsort((shingles, owner))
    s, o = shingles[order], owner[order]
    fresh = np.ones(len(s), bool)
    fresh[1:] = (s[1:] != s[:-1]) | (o[1:] != o[:-1])
    at = np.flatnonzero(fresh)
    return s[at], o[at], np.diff(np.append(at, len(s)))


def sign(docs: DataFrame, id_col: str, text_col: str, width: int = WIDTH) -> DataFrame:
    """Rows ``(id, n, same1, same2, bands)``: shingles, a 128-bit digest of the words, and band hashes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in pieces(batch, 1):
                words, bounds = word_hashes(part.column(1))
                rows = part.num_rows
                shingles, owner = shingle_hashes(words, bounds, width)
                elements, own, counts = multisets(shingles, owner)
                registers = signatures(elements, counts, own, rows, BANDS * DEPTH)
                by_band = registers.reshape(rows, BANDS, DEPTH)
                with np.errstate(over="ignore"):
                    bands = np.broadcast_to(mix(np.arange(BANDS, dtype=np.uint64)), (rows, BANDS)).copy()
                    for k in range(DEPTH):
                        bands = mix(bands * np.uint64(0x2545F4914F6CDD1D) + by_band[:, :, k])
                    # digest of the word sequence: two sums of words weighted by their place
                    place = np.arange(len(words), dtype=np.uint64) - np.repeat(bounds[:-1], np.diff(bounds)).astype(np.uint64)
                    sums = [np.append(np.uint64(0), np.cumsum(mix(words ^ mix(place * np.uint64(2) + np.uint64(k + 1))))) for k in range(2)]
                    same = [(x[bounds[1:]] - x[bounds[:-1]]) ^ np.diff(bounds).astype(np.uint64) for x in sums]
                n = np.bincount(owner, minlength=rows).astype(np.int64)
                lists = pa.ListArray.from_arrays(pa.array(np.arange(0, rows * BANDS + 1, BANDS, dtype=np.int32)), pa.array(bands.reshape(-1).view(np.int64)))
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(n), *(pa.array(x.view(np.int64)) for x in same), lists], names=["id", "n", "same1", "same2", "bands"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")).mapInArrow(run, f"id {kind}, n long, same1 long, same2 long, bands array<long>")


def overlap(pairs: DataFrame, texts: DataFrame, width: int = WIDTH) -> DataFrame:
    """Rows ``(a, b, similarity)`` of pairs (a, b) of ids of ``texts`` (id, text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in pieces(batch, 2, 3):
                sides = []
                for c in (2, 3):
                    shingles, owner = shingle_hashes(*word_hashes(part.column(c)), width)
                    sides.append((shingles, owner))
                elements, own, _ = multisets(np.concatenate([s for s, _ in sides]), np.concatenate([o for _, o in sides]))
                # where each side's elements stand among the distinct ones of the pair
                counts = []
                for shingles, owner in sides:
                    e, o, n = multisets(shingles, owner)
                    both = multisets_place(elements, own, e, o)
                    full = np.zeros(len(elements), np.int64)
                    full[both] = n
                    counts.append(full)
                least = np.bincount(own, np.minimum(*counts), part.num_rows)
                most = np.bincount(own, np.maximum(*counts), part.num_rows)
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(least / np.maximum(most, 1))], names=["a", "b", "similarity"])

    kind = texts.schema["id"].dataType.simpleString()
    left, right = (texts.select(F.col("id").alias(c), F.col("text").alias(f"text_{c}")) for c in "ab")
    return pairs.join(left, "a").join(right, "b").select("a", "b", "text_a", "text_b").mapInArrow(run, f"a {kind}, b {kind}, similarity double")


def own_shingles(texts: DataFrame, width: int = WIDTH) -> DataFrame:
    """Rows ``(id, own)``: how many of a text's shingles, with repeats, no other of these texts (id, text) has."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in pieces(batch, 1):
                elements, own, counts = multisets(*shingle_hashes(*word_hashes(part.column(1)), width))
                yield pa.RecordBatch.from_arrays([part.column(0).take(pa.array(own)), pa.array(elements.view(np.int64)), pa.array(counts)], names=["id", "shingle", "n"])

    kind = texts.schema["id"].dataType.simpleString()
    each = texts.select("id", "text").mapInArrow(run, f"id {kind}, shingle long, n long")
    lone = each.groupBy("shingle").agg(F.count("*").alias("texts"), F.min("id").alias("id"), F.min("n").alias("n")).where("texts = 1")
    return lone.groupBy("id").agg(F.sum("n").alias("own"))


def multisets_place(elements: np.ndarray, own: np.ndarray, e: np.ndarray, o: np.ndarray) -> np.ndarray:
    """Index of each (o, e) among the sorted (own, elements), all of which are there."""
    order = np.lexsort((np.concatenate([elements, e]), np.concatenate([own, o])), axis=0)
    first = order < len(elements)
    rank = np.cumsum(first) - 1
    out = np.empty(len(e), np.int64)
    late = ~first
    out[order[late] - len(elements)] = rank[late]
    return out


def _mixed(bucket: DataFrame, label: DataFrame) -> DataFrame:
    """Members of the buckets (key, rep) that hold more than one class, with their class."""
    placed = bucket.join(label.withColumnRenamed("id", "rep"), "rep", "left").withColumn("component", F.coalesce("component", "rep"))
    mixed = placed.groupBy("key").agg(F.min("component").alias("c1"), F.max("component").alias("c2")).where("c1 <> c2").select("key")
    return placed.join(mixed, "key", "left_semi")


def classes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", least: float = LEAST) -> DataFrame:
    """Rows ``(id, class_id, n_shingles)`` of every document."""
    signed = cut(sign(docs, id_col, text_col), "signatures")
    alone = signed.where("n = 0").select("id", F.col("id").alias("class_id"), F.col("n").alias("n_shingles"))
    signed = signed.where("n > 0")
    reps = signed.where("id IS NOT NULL").groupBy("same1", "same2").agg(F.min("id").alias("rep"), F.any_value("n").alias("n"), F.any_value("bands").alias("bands"))
    reps = cut(reps, "representatives")
    members = reps.select("rep", "n", F.explode("bands").alias("key"))
    heads = members.groupBy("key").agg(F.min(F.struct("rep", "n")).alias("head"), F.count("*").alias("size")).where("size > 1").select("key", "head.*")
    heads = heads.select("key", F.col("rep").alias("head"), F.col("n").alias("head_n"))
    bucket = cut(members.join(heads, "key").select("key", "head", "head_n", "rep", "n"), "buckets")
    near = lambda x, y: F.least(x, y) >= F.greatest(x, y) * F.lit(least)  # noqa: E731  else the sizes forbid a link
    pairs = bucket.where("rep <> head").where(near(F.col("n"), F.col("head_n"))).select(F.col("head").alias("a"), F.col("rep").alias("b")).distinct()
    texts = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    involved = bucket.select(F.col("rep").alias("id")).distinct()
    texts = cut(texts.join(involved, "id", "left_semi").dropDuplicates(["id"]), "texts")
    first = cut(overlap(pairs, texts), "overlaps")
    links = first.where(F.col("similarity") >= least).select(F.col("a").alias("u"), F.col("b").alias("w"))
    label = cut(components(links), "classes")
    # what the least ones could not show: members of one bucket that are still in different classes
    bucket = bucket.join(first.select(F.col("a").alias("head"), F.col("b").alias("rep"), "similarity"), ["head", "rep"], "left")
    # of n shingles and those of another text, whose similarity is known, so many are in both
    met = lambda n, other, similarity: F.round(similarity * (n + other) / (1 + similarity)).cast("long")
    same = F.when(F.col("rep") == F.col("head"), 1.0).otherwise(F.col("similarity"))
    bucket = bucket.select("key", "head", "rep", "n", (1 - same).alias("far"), met(F.col("n"), F.col("head_n"), same).alias("in_far"))
    open_ = cut(_mixed(bucket, label), "open")
    own = own_shingles(texts.join(open_.select(F.col("rep").alias("id")).distinct(), "id", "left_semi"))
    open_ = open_.join(own.withColumnRenamed("id", "rep"), "rep", "left").withColumn("shared", F.col("n") - F.coalesce("own", F.lit(0)))
    open_ = cut(open_.where(F.col("shared") >= F.col("n") * least).drop("own", "component"), "open")

    def link(u: str, v: str) -> Column:
        most = F.least(f"{u}.shared", f"{v}.shared")  # no more can overlap
        return most >= (F.col(f"{u}.n") + F.col(f"{v}.n") - most) * least

    # the member with the least of its own, of all buckets with one head, stands in the middle of them
    member = cut(open_.select("head", "rep", "n", "far", "in_far", "shared").distinct(), "members")
    middle = member.groupBy("head").agg(F.min(F.struct((-F.col("shared") / F.col("n")).alias("r"), "rep", "n", "shared")).alias("m")).select("head", "m.rep", "m.n", "m.shared")
    second = member.alias("x").join(middle.alias("m"), "head").where((F.col("x.rep") != F.col("m.rep")) & link("x", "m"))
    found = cut(overlap(second.select(F.col("m.rep").alias("a"), F.col("x.rep").alias("b")).distinct(), texts), "overlaps")
    links = cut(links.unionByName(found.where(F.col("similarity") >= least).select(F.col("a").alias("u"), F.col("b").alias("w"))), "links")
    label = cut(components(links), "classes")
    # whatever is still apart and could be linked is compared
    open_ = _mixed(open_, label).where("rep <> head").select("head", "rep", "component").distinct().join(member, ["head", "rep"])
    open_ = open_.join(middle.select("head", F.col("rep").alias("a"), F.col("n").alias("a_n")), "head").join(found.select("a", F.col("b").alias("rep"), "similarity"), ["a", "rep"], "left")
    open_ = open_.withColumns({"off": 1 - F.col("similarity"), "in_off": met(F.col("n"), F.col("a_n"), F.col("similarity"))}).drop("similarity")
    heads = open_.groupBy("rep").agg(F.collect_set("head").alias("heads"))  # as many as bands at most
    sizes = open_.groupBy("head").agg(F.ceil(F.count("*") / SIDE).cast("int").alias("blocks"))
    open_ = cut(open_.join(heads, "rep").join(sizes, "head").withColumn("block", F.pmod(F.xxhash64("rep"), F.col("blocks")).cast("int")), "open")
    every = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))
    x, y = (open_.withColumn(other, every).withColumnRenamed("block", own).alias(side) for side, own, other in (("x", "low", "high"), ("y", "high", "low")))
    near = link("x", "y")
    for d in ("far", "off"):  # by distances to the head and to the middle, and by what each has inside and outside of it
        ix, iy = F.col(f"x.in_{d}"), F.col(f"y.in_{d}")
        most = F.least(ix, iy) + F.least(F.col("x.shared") - ix, F.col("y.shared") - iy)
        near = near & F.coalesce((F.abs(F.col(f"x.{d}") - F.col(f"y.{d}")) <= 1 - least + 1e-9) & (most >= (F.col("x.n") + F.col("y.n") - most) * least), F.lit(True))
    once = F.array_min(F.array_intersect("x.heads", "y.heads")) == F.col("x.head")  # of the heads that both have, one brings the pair
    cell = (F.col("x.head") == F.col("y.head")) & (F.col("x.low") == F.col("y.low")) & (F.col("x.high") == F.col("y.high"))
    third = x.join(y, cell & (F.col("x.rep") < F.col("y.rep")) & (F.col("x.component") != F.col("y.component")) & near & once)
    third = third.select(F.col("x.rep").alias("a"), F.col("y.rep").alias("b"))
    known = first.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).union(found.select(F.least("a", "b"), F.greatest("a", "b")))
    third = cut(third.join(known, ["a", "b"], "left_anti"), "pairs")  # no pair is compared twice
    if not third.isEmpty():
        more = overlap(third, texts).where(F.col("similarity") >= least).select(F.col("a").alias("u"), F.col("b").alias("w"))
        label = cut(components(links.unionByName(more)), "classes")
    rep_label = reps.select("rep", "same1", "same2").join(label.withColumnRenamed("id", "rep"), "rep", "left").select("same1", "same2", F.coalesce("component", "rep").alias("class_id"))
    return signed.join(rep_label, ["same1", "same2"], "left").select("id", "class_id", F.col("n").alias("n_shingles")).unionByName(alone)


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The documents of the least id of each class; rows that repeat an id leave one, rows without an id all stay."""
    stay = classes(docs, id_col, text_col).where("id = class_id").select(F.col("id").alias(id_col))
    return docs.join(stay, id_col, "left_semi").dropDuplicates([id_col]).unionByName(docs.where(F.col(id_col).isNull()))


def report(found: DataFrame) -> DataFrame:
    """A row without an id is kept, as ``keep_one`` does."""
    return found.select(F.col("id").alias("doc_id"), "class_id", "n_shingles", F.coalesce(F.col("id") == F.col("class_id"), F.lit(True)).alias("kept"))
