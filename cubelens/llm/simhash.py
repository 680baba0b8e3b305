"""Near-duplicates by 64-bit similarity hashes, found through anchors of a covering code.

Two blocks of 31 bits (two bits are left to the final comparison) each carry the perfect
single-error-correcting code of length 31: every pattern lies within one bit of exactly one
code word. Fingerprints that differ in at most ``2 * t + 1`` bits differ in at most ``t`` bits
of one block, so some pattern lies within ceil(t / 2) bits of both, and the code word that
covers it lies within 1 + ceil(t / 2) bits of both. Every fingerprint therefore goes to all
anchors within that distance, and linked pairs always meet at an anchor.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType

from cubelens.llm.arrow import map_rows, slices, texts
from cubelens.llm.components import connected_components
from cubelens.storage import keep, materialize, release

SHINGLE_WORDS, SEED, MAX_BITS = 4, 42, 4
BLOCK = 31
#: Groups up to this size are compared in full; larger ones by walking or splitting.
SMALL, LARGE = 12, 4096


def fingerprint(text: str | None, words: int = SHINGLE_WORDS, seed: int = SEED) -> int:
    """Unsigned 64-bit majority hash of the word shingles; 0 for a text without words."""
    parts = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not parts:
        return 0
    joined, n = b" ".join(parts), max(1, len(parts) - words + 1)
    ends = np.cumsum(np.fromiter(map(len, parts), np.int64, len(parts)) + 1) - 1
    starts = np.concatenate(([0], ends[:-1] + 1))[:n].tolist()
    stops = ends[min(words, len(parts)) - 1 :].tolist()
    counts = np.zeros(64, np.int64)
    digest = xxhash.xxh64_intdigest
    for at in range(0, n, 16384):
        h = np.array([digest(joined[a:b], seed) for a, b in zip(starts[at : at + 16384], stops[at : at + 16384])], "<u8")
        counts += np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(2 * counts > n, bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, words: int = SHINGLE_WORDS, seed: int = SEED) -> DataFrame:
    """(doc_id, fp): one row per row of ``docs``; fp holds the 64 bits as a signed BIGINT."""

    def run(part: pa.RecordBatch) -> pa.RecordBatch:
        fp = np.array([fingerprint(t, words, seed) for t in texts(part.column(1))], "<u8")
        return pa.record_batch([part.column(0).cast(pa.int64()), pa.array(fp.view("<i8"))], ["doc_id", "fp"])

    return map_rows(docs.select("doc_id", "text"), run, "doc_id long, fp long")


def _error_patterns(radius: int) -> tuple[np.ndarray, np.ndarray]:
    """For each syndrome, the bit patterns of at most ``radius`` ones with it; and how many there are."""
    found: list[list[int]] = [[] for _ in range(BLOCK + 1)]
    for k in range(radius + 1):
        for places in combinations(range(1, BLOCK + 1), k):
            found[int(np.bitwise_xor.reduce(places)) if places else 0].append(sum(1 << (p - 1) for p in places))
    n = np.array([len(x) for x in found])
    table = np.zeros((BLOCK + 1, n.max()), np.int64)
    for s, x in enumerate(found):
        table[s, : len(x)] = x
    return table, n


def _syndromes(x: np.ndarray) -> np.ndarray:
    """Exclusive-or of the places of the ones, from the parity of five masks."""
    out = np.zeros(x.shape, np.int64)
    for bit in range(5):
        mask = sum(1 << (p - 1) for p in range(1, BLOCK + 1) if p >> bit & 1)
        out |= (np.bitwise_count(x & mask).astype(np.int64) & 1) << bit
    return out


def anchors(fps: np.ndarray, max_bits: int = MAX_BITS) -> tuple[np.ndarray, np.ndarray]:
    """(index into fps, anchor key) for every anchor within covering radius plus the block's threshold."""
    radius = 1 + -(-(max_bits // 2) // 2)
    table, count = _error_patterns(radius)
    rows, keys = [], []
    for block in (0, 1):
        x = (fps.view("<u8") >> np.uint64(block * BLOCK)).astype(np.int64) & ((1 << BLOCK) - 1)
        s = _syndromes(x)
        n = count[s]
        i = np.repeat(np.arange(len(x)), n)
        k = np.arange(len(i)) - np.repeat(np.cumsum(n) - n, n)
        rows.append(i)
        keys.append(x[i] ^ table[s[i], k] | block << BLOCK)
    return np.concatenate(rows), np.concatenate(keys)


def _outside(fps: np.ndarray, block: int) -> np.ndarray:
    """The 33 bits that the anchor's block leaves."""
    top = fps >> np.uint64(2 * BLOCK)
    rest = fps >> np.uint64(BLOCK) & np.uint64((1 << BLOCK) - 1) if block == 0 else fps & np.uint64((1 << BLOCK) - 1)
    return rest | top << np.uint64(BLOCK)


def _forest(fps: np.ndarray, max_bits: int, block: int = 0) -> list[tuple[np.ndarray, np.ndarray]]:
    """Edges that connect whatever links of ``max_bits`` connect among distinct fingerprints at an anchor of ``block``.

    A large group is cut by pieces of the bits outside of the block, in which its members are
    not already alike: a link leaves one of the pieces equal.
    """
    if len(fps) <= LARGE:
        return _walk(fps, max_bits)
    edges, rest, at = [], _outside(fps, block), 0
    for k in range(max_bits + 1):
        width = (64 - BLOCK - at) // (max_bits + 1 - k)
        x = rest >> np.uint64(at) & np.uint64((1 << width) - 1)
        at += width
        order = np.argsort(x, kind="stable")
        for group in np.split(fps[order], np.flatnonzero(np.diff(x[order])) + 1):
            if len(group) > 1:
                edges += _walk(group, max_bits)
    return edges


def _walk(left: np.ndarray, max_bits: int) -> list[tuple[np.ndarray, np.ndarray]]:
    edges, todo = [], []
    while len(left):
        if not todo:
            todo, left = [left[0]], left[1:]
        at = todo.pop()
        near = np.bitwise_count(left ^ at) <= max_bits
        if near.any():
            hit = left[near]
            edges.append((np.full(len(hit), at), hit))
            todo += list(hit)
            left = left[~near]
    return edges


def _link_runs(key: np.ndarray, fp: np.ndarray, max_bits: int) -> list[tuple[np.ndarray, np.ndarray]]:
    """Links inside each run of equal keys; runs are whole."""
    cut = np.flatnonzero(np.diff(key)) + 1
    start = np.concatenate(([0], cut))
    size = np.diff(np.concatenate((start, [len(key)])))
    edges = []
    for n in range(2, SMALL + 1):
        at = start[size == n]
        if len(at):
            m = fp[at[:, None] + np.arange(n)]
            for i, j in combinations(range(n), 2):
                near = np.bitwise_count(m[:, i] ^ m[:, j]) <= max_bits
                edges.append((m[near, i], m[near, j]))
    for at, n in zip(start[size > SMALL], size[size > SMALL]):
        edges += _forest(np.unique(fp[at : at + n]), max_bits, int(key[at]) >> BLOCK)
    return edges


def links(distinct_fps: DataFrame, max_bits: int = MAX_BITS) -> DataFrame:
    """(u, v): pairs of fingerprints whose transitive closure is that of all links.

    distinct_fps: column fp, no value twice. Copies to anchors are streamed in key order,
    and one group of equal keys is held at a time: 8 bytes a fingerprint.
    """

    def spread(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in slices(batches, 4096):
            fp = np.asarray(part.column(0)).astype("<i8")
            i, key = anchors(fp, max_bits)
            yield pa.record_batch([pa.array(key), pa.array(fp[i])], ["key", "fp"])

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray]] = []

        def flush(key: np.ndarray, fp: np.ndarray) -> Iterator[pa.RecordBatch]:
            edges = _link_runs(key, fp.view("<u8"), max_bits) if len(key) else []
            if edges:
                u, v = (np.concatenate([e[k] for e in edges]).view("<i8") for k in (0, 1))
                if len(u):
                    yield pa.record_batch([pa.array(np.maximum(u, v)), pa.array(np.minimum(u, v))], ["u", "v"])

        for batch in batches:
            key, fp = np.asarray(batch.column(0)), np.asarray(batch.column(1)).astype("<i8")
            if not len(key):
                continue
            if held and held[-1][0][-1] != key[-1] or not held and key[0] != key[-1]:
                last = int(np.searchsorted(key, key[-1]))  # the last run may go on in the next batch
                head = [*held, (key[:last], fp[:last])]
                yield from flush(np.concatenate([x[0] for x in head]), np.concatenate([x[1] for x in head]))
                held = [(key[last:], fp[last:])]
            else:
                held.append((key, fp))
        if held:
            yield from flush(np.concatenate([x[0] for x in held]), np.concatenate([x[1] for x in held]))

    sent = distinct_fps.select("fp").mapInArrow(spread, "key long, fp long")
    parts = int(distinct_fps.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return sent.repartition(parts, "key").sortWithinPartitions("key").mapInArrow(meet, "u long, v long").distinct()


def near_duplicates(docs: DataFrame, max_bits: int = MAX_BITS) -> DataFrame:
    """(doc_id, fingerprint, component_id, n_links), one row per row of ``docs``.

    Fingerprints of at most ``max_bits`` differing bits link; component_id is the smallest
    doc_id that links reach, n_links the number of rows with other or equal text in the
    component. Null and wordless texts have fingerprint zero and link like others. A row
    whose doc_id is null keeps its component, but cannot name one; if no row of a component
    has a doc_id, component_id is null. Repeated rows are all returned. Other columns of
    ``docs`` are not read.
    """
    found = _classes(docs, max_bits)
    return keep(found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id", "n_links"), found)


def _classes(docs: DataFrame, max_bits: int) -> DataFrame:
    """(doc_id, fp, root, component_id, n_links), one row per row of ``docs``; root names a class by one of its fingerprints."""
    fps = materialize(fingerprints(docs), "fps")
    reps = materialize(fps.groupBy("fp").agg(F.min("doc_id").alias("rep"), F.count("*").alias("n")), "reps")
    roots = connected_components(links(reps, max_bits))
    named = reps.join(roots.withColumnRenamed("node", "fp"), "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    total = named.groupBy("root").agg(F.min("rep").alias("component_id"), F.sum("n").alias("n"))
    classes = materialize(named.select("fp", "root").join(total, "root").select("fp", "root", "component_id", (F.col("n") - 1).alias("n_links")), "classes")
    release(reps)
    release(roots)
    return keep(fps.join(classes, "fp").select("doc_id", "fp", "root", "component_id", "n_links"), fps, classes)


def keep_one(docs: DataFrame, max_bits: int = MAX_BITS) -> DataFrame:
    """``docs`` with one row of each near-duplicate class: that of the smallest doc_id.

    Rows without a doc_id stay. Of rows that repeat the kept doc_id inside a class one stays, the
    first by text, then by its other columns as JSON; an id that repeats with texts of different
    classes is decided about in each class. Columns may be of any type and keep their order.
    """
    found = _classes(docs, max_bits)
    ids = materialize(found.filter("doc_id is not null").groupBy("doc_id").agg(F.max(F.struct("root", "component_id")).alias("c"), F.count("*").alias("n")), "kept")
    gone = ids.filter("n > 1 or c.component_id <> doc_id").select("doc_id")
    # the ids that go are hashed, the texts are not sorted; the plan is the same at every size
    left = docs.join(gone.hint("shuffle_hash"), "doc_id", "left_anti").select(*docs.columns)
    twice = ids.filter("n > 1").select("doc_id")
    if not twice.take(1):
        release(found)
        return keep(left, ids)
    # ids that repeat: decided by the row's own fingerprint
    again = docs.join(twice.hint("shuffle_hash"), "doc_id", "left_semi").select(*docs.columns)
    place = docs.columns.index("text")

    def run(part: pa.RecordBatch) -> pa.RecordBatch:
        fp = np.array([fingerprint(t) for t in texts(part.column(place))], "<u8")
        return pa.RecordBatch.from_arrays([*part.columns, pa.array(fp.view("<i8"))], names=[*part.schema.names, "fp_"])

    marked = map_rows(again, run, StructType([*again.schema.fields, StructField("fp_", LongType())]))
    firsts = found.filter("component_id = doc_id").select(F.col("fp").alias("f"), F.col("root").alias("r"), F.col("component_id").alias("c")).distinct()
    marked = marked.join(firsts, (F.col("fp_") == F.col("f")) & (F.col("doc_id").cast("long") == F.col("c")))
    order = F.struct("text", F.to_json(F.struct(*[F.col(f"`{c}`") for c in docs.columns])))
    one = marked.groupBy("r").agg(F.min_by(F.struct(*[F.col(f"`{c}`") for c in docs.columns]), order).alias("row"))
    out = left.unionByName(one.select(*[F.col("row")[c].alias(c) for c in docs.columns]))
    return keep(out, found, ids)
