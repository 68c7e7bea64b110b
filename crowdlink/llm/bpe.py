"""Byte-pair encoding and decoding with a segment tree over the ranks of adjacent pairs.

Null texts are empty texts; an empty text has no tokens and decodes to an empty text. Rows are mapped
one by one, so repeated rows and ties stay as they are and extra columns do not matter. A text of any
length takes memory in proportion to its length.
"""

from __future__ import annotations

import json
import unicodedata
from collections.abc import Iterable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from tokenizers import Tokenizer

#: Words whose tokens a worker remembers; then it forgets them all.
REMEMBERED_WORDS = 200_000
_NEVER = 1 << 62
#: Beyond Latin letters and usual punctuation.
_RARE = regex.compile("[^\x00-\u024f\u2010-\u2027]")


def _byte_letters() -> list[str]:
    """The printable stand-in of each byte: printable Latin-1 stays, the others follow from U+0100 on."""
    plain = {*range(33, 127), *range(161, 173), *range(174, 256)}
    spare = iter(range(256, 512))
    return [chr(b) if b in plain else chr(next(spare)) for b in range(256)]


class PairTree:
    """Least value over a fixed row of slots, with point updates in logarithmic time.

    A slot holds rank * slots + place, so the root (node 1) names the leftmost of the lowest-ranked pairs.
    """

    __slots__ = ("width", "nodes")

    def __init__(self, values: list[int]):
        count = len(values)
        width = 1 << (count - 1).bit_length()
        nodes = [_NEVER] * width + values + [_NEVER] * (width - count)
        for i in range(width - 1, 0, -1):
            a, b = nodes[2 * i], nodes[2 * i + 1]
            nodes[i] = a if a < b else b
        self.width, self.nodes = width, nodes

    def put(self, place: int, value: int) -> None:
        nodes, i = self.nodes, place + self.width
        if nodes[i] == value:
            return
        nodes[i] = value
        while i > 1:
            other = nodes[i ^ 1]
            least = value if value < other else other
            i >>= 1
            if nodes[i] == least:
                return
            nodes[i] = value = least


class PairEncoder:
    """Encoder and decoder of one vocabulary file of the ``tokenizers`` library (BPE with a word-end mark).

    Supports what such files state: NFC, white-space folding and lower-casing, a split pattern whose
    matches are the words, bytes as letters, and added tokens that are matched in the raw text.
    """

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        self.end_mark = model.get("end_of_word_suffix") or ""
        self.vocab: dict[str, int] = model["vocab"]
        pairs = [m.split(" ") if isinstance(m, str) else m for m in model["merges"]]
        self.rank = {}
        for n, (a, b) in enumerate(pairs):
            self.rank.setdefault((self.vocab[a], self.vocab[b]), (n, self.vocab[a + b]))
        self.added = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.token_of = {i: t for t, i in self.vocab.items()} | {i: t for t, i in self.added.items()}
        self.added_pattern = regex.compile("(" + "|".join(map(regex.escape, sorted(self.added, key=len, reverse=True))) + ")") if self.added else None
        steps = spec["pre_tokenizer"]["pretokenizers"]
        self.words = regex.compile(next(s["pattern"]["Regex"] for s in steps if s["type"] == "Split"))
        letters = _byte_letters()
        self.letter_ids = [self.vocab[c] for c in letters]
        self.last_ids = [self.vocab[c + self.end_mark] for c in letters]
        self.byte_of = {c: b for b, c in enumerate(letters)}
        self.path, self._library = path, None
        self.known: dict[str, tuple[int, ...]] = {}

    @property
    def library(self) -> Tokenizer:
        if self._library is None:  # few texts need it
            self._library = Tokenizer.from_file(self.path)
        return self._library

    @staticmethod
    def normal(text: str) -> str:
        """NFC and lower case letter by letter (a final sigma is no special case)."""
        if text.isascii():
            return text.lower()
        return unicodedata.normalize("NFC", text).replace("Σ", "σ").lower()

    def merge(self, word: str) -> tuple[int, ...]:
        """Token ids of one word: while a pair can merge, merge the leftmost of lowest rank."""
        return self.merge_bytes(word.encode("utf-8"))

    def merge_bytes(self, raw: bytes) -> tuple[int, ...]:
        letters, find = self.letter_ids, self.rank.get
        ids = [letters[b] for b in raw]
        ids[-1] = self.last_ids[raw[-1]]
        n = len(ids)
        if n == 1:
            return (ids[0],)
        found = list(map(find, zip(ids, ids[1:])))
        tree = PairTree([_NEVER if f is None else f[0] * n + i for i, f in enumerate(found)])
        nodes, put = tree.nodes, tree.put
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        while (top := nodes[1]) != _NEVER:
            i = top % n
            j = after[i]
            own = ids[i] = found[i][1]
            ids[j] = -1
            after[i] = k = after[j]
            if k < n:
                before[k] = i
                put(j, _NEVER)
                f = found[i] = find((own, ids[k]))
                put(i, _NEVER if f is None else f[0] * n + i)
            else:
                put(i, _NEVER)
            if (h := before[i]) >= 0:
                f = found[h] = find((ids[h], own))
                put(h, _NEVER if f is None else f[0] * n + h)
        return tuple([x for x in ids if x >= 0])

    def encode(self, text: str) -> list[int]:
        known, out = self.known, []
        for piece in self.added_pattern.split(text) if self.added_pattern else (text,):
            if piece in self.added:
                out.append(self.added[piece])
                continue
            if _RARE.search(piece):
                # letters on which Unicode versions may differ: the library's own splitter decides
                for word, _ in self.library.pre_tokenizer.pre_tokenize_str(self.library.normalizer.normalize_str(piece)):
                    out += self.merge_bytes(bytes(map(self.byte_of.__getitem__, word)))
                continue
            for word in self.words.findall(self.normal(piece)):
                ids = known.get(word)
                if ids is None:
                    if len(known) >= REMEMBERED_WORDS:
                        known.clear()
                    ids = self.merge(word)
                    if len(word) <= 64:
                        known[word] = ids
                out += ids
        return out

    def decode(self, ids: Iterable[int]) -> str:
        """These files name no decoder, so the tokens stand with a space between them."""
        return " ".join(map(self.token_of.__getitem__, ids))


@lru_cache(maxsize=4)
def encoder(path: str) -> PairEncoder:
    return PairEncoder(path)


def encode_texts(docs: DataFrame, vocabulary: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows ``(id, ids array<int>, decoded string)`` of every whole text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = encoder(vocabulary)
        for batch in batches:
            for start in range(0, batch.num_rows, 512):
                part = batch.slice(start, 512)
                lists = [own.encode(t or "") for t in part.column(1).to_pylist()]
                offsets = np.zeros(len(lists) + 1, np.int32)
                np.cumsum([len(x) for x in lists], out=offsets[1:])
                flat = np.fromiter((i for x in lists for i in x), np.int32, int(offsets[-1]))
                decoded = pa.array([own.decode(x) for x in lists], pa.string())
                yield pa.RecordBatch.from_arrays([part.column(0), pa.ListArray.from_arrays(pa.array(offsets), pa.array(flat)), decoded], names=["id", "ids", "decoded"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")).mapInArrow(run, f"id {kind}, ids array<int>, decoded string")


def digests(encoded: DataFrame) -> DataFrame:
    """Token count and digests of the ids and of the decoded text."""
    return encoded.select(
        F.col("id").alias("doc_id"),
        F.size("ids").cast("long").alias("n_tokens"),
        F.sha2(F.array_join(F.col("ids").cast("array<string>"), " "), 256).alias("ids_sha256"),
        F.sha2(F.col("decoded"), 256).alias("decoded_sha256"),
    )
