"""Benchmark items inside documents: containment search with size-partitioned MinHash sketches.

An item is contained if at least ``threshold`` of its distinct word shingles occur in the
document. Items are partitioned by size. A partition's signature size k is tuned by its largest
item: the shingles that a containing document may lack, and MATCHES more. An item's signature
are its k smallest shingle hashes (bottom-k MinHash). A document's signature in a partition are
its shingle hashes up to the largest that any item of the partition has: documents are long and
items short, so a sketch of fixed size would lose the item, one by threshold cannot. Signatures
are compared: a containing document shares all but the lacking hashes with the item, so an
item is proposed if that many are shared, which misses nothing; what is proposed is verified by
exact containment of its shingles.
"""

from __future__ import annotations

import re
from collections import defaultdict
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cubelens.llm.arrow import map_rows, texts

SHINGLE_WORDS, THRESHOLD = 5, 0.8
#: Hashes that a containing document shares with an item's signature at least, if the item has so many.
MATCHES = 4
#: Items that are searched for in one pass over the documents, and the bytes of their texts; more are searched in blocks.
BLOCK_ITEMS, BLOCK_BYTES = 100_000, 16 << 20
_WORD = re.compile(r"\w+")
_MIX = [np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x27D4EB2F165667C5, 0xFF51AFD7ED558CCD, 0xC4CEB9FE1A85EC53)]


def words_of(text: str | None) -> list[str]:
    """Runs of letters, digits and underscores of the lower-cased text."""
    return _WORD.findall((text or "").lower())


def shingle_hashes(word_hashes: np.ndarray, size: int) -> np.ndarray:
    """One hash for every run of ``size`` words."""
    n = len(word_hashes) - size + 1
    if n < 1:
        return np.zeros(0, np.uint64)
    h = np.zeros(n, np.uint64)
    for k in range(size):
        h = (h ^ (word_hashes[k : k + n] * _MIX[k % 5])) * _MIX[5]
        h ^= h >> np.uint64(31)
    return h


def word_hashes(words: list[str]) -> np.ndarray:
    digest = xxhash.xxh3_64_intdigest
    return np.array([digest(w.encode("utf-8", "surrogatepass")) for w in words], "<u8")


def shingles(words: list[str], size: int) -> set[tuple[str, ...]]:
    return set(zip(*[words[k:] for k in range(size)]))


def allowed_gaps(n: int, threshold: float) -> int:
    """How many of n shingles a containing document may lack."""
    return n - int(np.ceil(threshold * n - 1e-9))


@dataclass
class Partition:
    """Signatures of the items of one size class: their hashes, sorted, with the owners of each; the largest bounds a document's signature."""

    length: int
    hashes: np.ndarray
    first: np.ndarray
    owners: np.ndarray

    @classmethod
    def build(cls, length: int, members: dict[int, list[int]]) -> Partition:
        pairs = sorted((h, key) for key, hs in members.items() for h in hs)
        h = np.array([x for x, _ in pairs], "<u8")
        known, first = np.unique(h, return_index=True)
        return cls(length, known, np.append(first, len(h)), np.array([k for _, k in pairs], np.int64))

    def shared(self, signature: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Items with a hash in a document's sorted distinct shingle hashes, and how many they share."""
        own = signature[: np.searchsorted(signature, self.hashes[-1], side="right")]
        at = np.searchsorted(self.hashes, own)
        hit = at[self.hashes[at] == own]
        if not len(hit):
            return hit, hit
        return np.unique(np.concatenate([self.owners[self.first[i] : self.first[i + 1]] for i in hit.tolist()]), return_counts=True)


@dataclass
class ItemIndex:
    """Signatures of a block of items by size class, and the items themselves."""

    items: dict[int, tuple[int, set]]
    least: np.ndarray
    partitions: list[Partition]
    threshold: float
    ids: list[int | None]

    @classmethod
    def build(cls, rows: list[tuple[int | None, str]], size: int = SHINGLE_WORDS, threshold: float = THRESHOLD) -> ItemIndex:
        items, parts, least = {}, defaultdict(list), np.zeros(len(rows), np.int64)
        for key, (_, text) in enumerate(rows):  # ids may repeat or be null: the place is the key
            w = words_of(text)
            if w:
                length = min(size, len(w))  # an item of fewer words is one shingle
                s = shingles(w, length)
                items[key] = (length, s)
                parts[length, len(s).bit_length()].append((key, s))
        partitions = []
        for (length, _), members in sorted(parts.items()):
            k = MATCHES + allowed_gaps(max(len(s) for _, s in members), threshold)
            signatures = {}
            for key, s in members:
                signatures[key] = sorted({int(shingle_hashes(word_hashes(list(x)), length)[0]) for x in s})[:k]
                # equal hashes of different shingles count once, which a document may share all the same
                least[key] = max(1, len(signatures[key]) - allowed_gaps(len(s), threshold))
            partitions.append(Partition.build(length, signatures))
        return cls(items, least, partitions, threshold, [i for i, _ in rows])

    def search(self, text: str | None) -> list[tuple[int | None, float]]:
        """(item, containment) of the items that the text contains; of an id's texts the one contained most."""
        words = words_of(text)
        if not words:
            return []
        hashed, signature, proposed = word_hashes(words), {}, []
        for p in self.partitions:
            if p.length > len(words):
                continue
            if p.length not in signature:
                signature[p.length] = np.unique(shingle_hashes(hashed, p.length))
            keys, n = p.shared(signature[p.length])
            proposed += keys[n >= self.least[keys]].tolist()
        found, own = {}, {}
        for key in proposed:
            length, s = self.items[key]
            if length not in own:
                own[length] = shingles(words, length)
            share = len(s & own[length])
            if share >= len(s) - allowed_gaps(len(s), self.threshold):
                found[self.ids[key]] = max(found.get(self.ids[key], 0.0), share / len(s))
        return list(found.items())


def _indexes(benchmark: DataFrame, size: int, threshold: float, block: int):
    """Indexes of blocks of items; a block is bounded in items and bytes, the number of blocks is not."""
    items = benchmark.select(F.col("item_id").cast("long").alias("item_id"), "text").filter("text is not null").distinct()
    n, volume = items.agg(F.count("*"), F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()
    blocks = max(1, -(-n // block) + (n > block), -(-volume // BLOCK_BYTES))
    for b in range(blocks):
        # all texts of an id are in one block; those without an id are spread by their text
        key = F.when(F.col("item_id").isNull(), F.xxhash64("text")).otherwise(F.xxhash64("item_id"))
        rows = items.filter(F.pmod(key, F.lit(blocks)) == b) if blocks > 1 else items
        yield ItemIndex.build(sorted(map(tuple, rows.toLocalIterator()), key=lambda r: (r[0] is None, r[0] or 0, r[1])), size, threshold)


def find_items(docs: DataFrame, benchmark: DataFrame, size: int = SHINGLE_WORDS, threshold: float = THRESHOLD, block: int = BLOCK_ITEMS) -> DataFrame:
    """(doc_id, item_id, containment): every contained item of every row of ``docs``.

    Null and wordless texts and items match nothing; an item of fewer than ``size`` words is
    one shingle of its length. All texts of an item_id are searched for; items without one
    cannot be named here (``drop_contaminated`` knows them). Repeated rows give repeated matches. Other columns are not
    read. Nothing is shuffled: each block of items is one pass over the documents.
    """
    schema, out = "doc_id long, item_id long, containment double", None
    for index in _indexes(benchmark, size, threshold, block):

        def run(part: pa.RecordBatch, index=index) -> pa.RecordBatch:
            hits = [(d, i, c) for d, t in zip(part.column(0).to_pylist(), texts(part.column(1))) for i, c in index.search(t) if i is not None]
            return pa.record_batch([pa.array([h[k] for h in hits], kind) for k, kind in enumerate((pa.int64(), pa.int64(), pa.float64()))], ["doc_id", "item_id", "containment"])

        found = map_rows(docs.select("doc_id", "text"), run, schema)
        out = found if out is None else out.unionByName(found)
    return out


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, size: int = SHINGLE_WORDS, threshold: float = THRESHOLD, block: int = BLOCK_ITEMS) -> DataFrame:
    """The rows of ``docs`` that contain no item, named or not, with all their columns."""
    at = docs.columns.index("text")
    for index in _indexes(benchmark, size, threshold, block):

        def run(part: pa.RecordBatch, index=index) -> pa.RecordBatch:
            return part.filter(pa.array([not index.search(t) for t in texts(part.column(at))], pa.bool_()))

        docs = map_rows(docs, run, docs.schema)
    return docs
