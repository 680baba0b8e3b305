"""Exact bins without ranks: the places where bins begin are found, and every row is compared with them.

Keys become numbers or byte strings in the order of the keys (nulls first). A sample of
the rows says where to count, never what is counted: counts between its keys are those of
all rows, so they tell the one stretch in which a cut lies. Rows of one key are ordered by
their digests, which are only computed where a cut lies inside a key, in NumPy and for those rows
alone; of a frequent key only the digests near the cut are ordered, after the others were counted.
"""

from __future__ import annotations

import io
import zlib
from bisect import bisect_left
from collections.abc import Iterable, Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from cubelens.dimension import DimensionSpec
from cubelens.operators.binning import bin_type, width
from cubelens.operators.cube import blocks
from cubelens.operators.digest import Ties
from cubelens.storage import LONG_ROWS, keep, materialize, materialize_each, release, small_scans

#: Keys of a dimension between which rows are counted.
SPLITTERS = 4096
#: A key of no more rows is ordered whole where a cut lies in it.
WHOLE = 1 << 14
#: Rows that a task looks at together; they are kept together in one value of a table.
BLOCK = 1 << 16
_NUMBERS = {"tinyint", "smallint", "int", "bigint", "boolean", "date", "timestamp", "timestamp_ntz", "float", "double"}

# Keys of a row are a tuple of (False, 0) for null or (True, int or bytes); an order is such keys and a digest, two numbers.


def _types(df: DataFrame, spec: DimensionSpec) -> list[str]:
    return [t for _, t in df.select(*[F.expr(k.removesuffix(" desc")).alias(f"k{j}") for j, k in enumerate(spec.keys)]).dtypes]


def comparable(df: DataFrame, specs: list[DimensionSpec]) -> bool:
    """Whether all keys have types whose order is known here; strings only ascending."""
    return all(t in _NUMBERS or t == "string" and not k.endswith(" desc") for s in specs for k, t in zip(s.keys, _types(df, s)))


def _key(expression: str, kind: str) -> Column:
    """A key as BIGINT, DOUBLE or BINARY, of the same order."""
    c = F.expr(expression.removesuffix(" desc"))
    if kind == "string":
        return c.cast("binary")
    if kind in ("float", "double"):
        return c.cast("double") + 0.0  # one zero
    if kind == "date":
        return F.unix_date(c).cast("long")
    if kind in ("timestamp", "timestamp_ntz"):
        return F.unix_micros(c.cast("timestamp"))
    return c.cast("int").cast("long") if kind == "boolean" else c.cast("long")


def _code(column: pa.Array, down: bool) -> tuple[np.ndarray, np.ndarray | None, list | None]:
    """Numbers in the order of the keys, which rows are null (None: no row), and of byte strings the values that are numbered."""
    null = np.asarray(column.is_null()) if column.null_count else None
    if pa.types.is_binary(column.type):
        words = column.dictionary_encode()
        return words.indices.fill_null(0).to_numpy(zero_copy_only=False), null, words.dictionary.to_pylist() or [b""]
    if pa.types.is_floating(column.type):
        v = column.fill_null(0.0).to_numpy(zero_copy_only=False)
        bits = np.where(np.isnan(v), np.nan, v).view(np.int64)
        bits = bits ^ ((bits >> 63) & np.int64(0x7FFFFFFFFFFFFFFF))
    else:
        bits = column.fill_null(0).to_numpy(zero_copy_only=False)
    return (~bits if down else bits), null, None


class _Rows:
    """Keys of one dimension in a block of rows, and their digests on demand."""

    def __init__(self, keys: list[tuple], name: str, ties: Ties):
        self.keys, self.name, self.ties = keys, name, ties

    def order(self, i: int) -> tuple:
        return tuple((False, 0) if null is not None and null[i] else (True, int(code[i]) if words is None else words[code[i]]) for code, null, words in self.keys)

    def place(self, marks: _Marks | None) -> np.ndarray:
        """Twice the number of marks below each row, and one more on a mark."""
        out = np.zeros(len(self.ties), np.int64)
        if marks is not None:
            marks.place(self.keys, None, out)
        return out

    def digests(self, at: np.ndarray) -> np.ndarray:
        """Digests that order ties, as two numbers a row: those of ``keyed_digest``."""
        return self.ties.digests(self.name, at)


class _Marks:
    """Sorted distinct keys, as a tree with one level a key."""

    def __init__(self, marks: list[tuple], part: int = 0, base: int = 0):
        self.part, self.base = part, base
        self.last = part + 1 == len(marks[0])
        self.nulls = sum(1 for m in marks if not m[part][0])
        below = None if self.last else [(base, marks[: self.nulls])]
        self.below_null = _Marks(below[0][1], part + 1, base) if below and self.nulls else None
        values = [m[part][1] for m in marks[self.nulls :]]
        self.values = sorted(set(values))
        self.starts = np.array([base + self.nulls + bisect_left(values, v) for v in self.values] + [base + len(marks)], np.int64)
        self.numbers = None if self.values and isinstance(self.values[0], bytes) else np.array(self.values, np.int64)
        self.children = None if self.last else [_Marks(marks[a - base : z - base], part + 1, int(a)) for a, z in zip(self.starts, self.starts[1:])]

    def place(self, keys: list[tuple], at: np.ndarray | None, out: np.ndarray) -> None:
        code, null, words = keys[self.part]
        if at is not None:
            code, null = code[at], None if null is None else null[at]
        if not self.values:
            spot, on = np.zeros(len(code), np.int64), np.zeros(len(code), bool)
        elif words is None:
            spot = np.searchsorted(self.numbers, code)
            on = self.numbers[np.minimum(spot, len(self.numbers) - 1)] == code
        else:
            low = [bisect_left(self.values, w) for w in words]
            spot, on = np.array(low, np.int64)[code], np.array([k < len(self.values) and self.values[k] == w for k, w in zip(low, words)], bool)[code]
        found = 2 * self.starts[spot] + (on if self.last else 0)
        if null is not None and null.any():
            found[null] = 2 * self.base + (1 if self.last and self.nulls else 0)
            on = on & ~null
        if at is None:
            out[:] = found
        else:
            out[at] = found
        if self.last:
            return
        here = np.arange(len(code)) if at is None else at
        if self.below_null is not None and null is not None and null.any():
            self.below_null.place(keys, here[null], out)
        tied = np.flatnonzero(on)
        if not len(tied):
            return
        which = spot[tied].astype(np.uint16 if len(self.values) < 65536 else np.int64)
        order = np.argsort(which, kind="stable")
        tied, which = here[tied[order]], which[order]
        edges = [0, *(np.flatnonzero(np.diff(which)) + 1).tolist(), len(tied)]
        for a, z in zip(edges, edges[1:]):
            self.children[int(which[a])].place(keys, tied[a:z], out)


def _above(known: list[tuple[int, int]], found: np.ndarray) -> np.ndarray:
    """How many of the sorted digests are not above each row's."""
    marks = np.array(known, np.uint64).reshape(-1, 2)
    low, high = np.searchsorted(marks[:, 0], found[:, 0], "left"), np.searchsorted(marks[:, 0], found[:, 0], "right")
    for i in np.flatnonzero(low < high):
        low[i] += np.searchsorted(marks[low[i] : high[i], 1], found[i, 1], "right")
    return low


class _Layout:
    """The rows as Arrow columns: the different keys of all dimensions, then the row's key as text."""

    def __init__(self, base: DataFrame, specs: list[DimensionSpec], row_key: tuple[str, ...]):
        # joined once a row, not once a digest; null where the key is all null, as concat_ws leaves nulls out
        self.joined = F.nullif(F.concat_ws(":", *[F.expr(k).cast("string") for k in row_key]), F.lit(""))
        self.specs, self.kinds = specs, [_types(base, s) for s in specs]
        self.columns: dict[tuple[str, str], int] = {}
        self.places = [[(self.columns.setdefault((k.removesuffix(" desc"), t), len(self.columns)), k.endswith(" desc")) for k, t in zip(s.keys, kinds)] for s, kinds in zip(specs, self.kinds)]
        self.schema = self.frame(base).schema

    def frame(self, base: DataFrame) -> DataFrame:
        return base.select(*[_key(k, t).alias(f"k{i}") for (k, t), i in self.columns.items()], self.joined.alias("rowkey_"))

    def pack(self, base: DataFrame) -> DataFrame:
        """(rows, data): many rows in one, as a small file of columns, so that scans hand a value a block to Python, not one a row and key."""

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for block in blocks(batches, BLOCK):
                file = io.BytesIO()
                pq.write_table(pa.Table.from_batches([block]), file, compression="zstd", write_statistics=False)
                yield pa.record_batch([pa.array([block.num_rows], pa.int32()), pa.array([file.getvalue()], pa.binary())], ["rows", "data"])

        return self.frame(base).mapInArrow(run, "rows int, data binary")

    def reader(self):
        """What turns a block into its dimensions' rows, free of session objects."""
        places, names = self.places, [s.name for s in self.specs]

        def rows(block: pa.RecordBatch) -> Iterator[_Rows]:
            codes: dict = {}
            ties = Ties(block.column(block.num_columns - 1))
            for name, own in zip(names, places):
                for at in own:
                    if at not in codes:
                        codes[at] = _code(block.column(at[0]), at[1])
                yield _Rows([codes[at] for at in own], name, ties)

        return rows


def _encode(keys: tuple) -> bytes:
    """Bytes in the order of the keys."""
    out = b""
    for known, v in keys:
        out += bytes([known])
        if isinstance(v, bytes):
            out += v.replace(b"\0", b"\0\xff") + b"\0\0"
        else:
            out += (v + (1 << 63)).to_bytes(8, "big")
    return out


def _decode(data: bytes, kinds: list[str]) -> tuple:
    out, at = [], 0
    for kind in kinds:
        known, at = bool(data[at]), at + 1
        if kind == "string" and known:
            end = at
            while data[end : end + 2] != b"\0\0":
                end += 2 if data[end : end + 2] == b"\0\xff" else 1
            out.append((True, data[at:end].replace(b"\0\xff", b"\0")))
            at = end + 2
        else:
            v, at = int.from_bytes(data[at : at + 8], "big") - (1 << 63), at + 8
            out.append((known, v if known else 0))
    return tuple(out)


def _blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The blocks of packed rows."""
    for batch in batches:
        for data in batch.column(batch.schema.names.index("data")):
            yield pq.read_table(pa.BufferReader(data.as_buffer()), use_threads=False).combine_chunks().to_batches()[0]


def _splitters(layout: _Layout, packed: DataFrame, n: int) -> list[list[tuple]]:
    """Sorted distinct keys of a sample, between and on which rows are counted."""
    share = min(1.0, 1.2 * SPLITTERS / max(n, 1))

    def some(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for block in _blocks(batches):
            chance = np.random.default_rng(zlib.crc32(str(block.column(block.num_columns - 1)[0]).encode()))
            yield block.take(pa.array(np.flatnonzero(chance.random(block.num_rows) < share)))

    found = packed.select("data").mapInArrow(some, layout.schema).toArrow().combine_chunks()
    if not found.num_rows:
        return [[] for _ in layout.specs]
    return [sorted({rows.order(i) for i in range(found.num_rows)}) for rows in layout.reader()(found.to_batches()[0])]


def _trees(marks: list[list[tuple]]) -> list[_Marks | None]:
    return [_Marks(m) if m else None for m in marks]


def _count(layout: _Layout, packed: DataFrame, marks: list[list[tuple]]) -> list[np.ndarray]:
    """Rows of all stretches: below the first mark, on it, between it and the next, and so on."""
    read, trees, sizes = layout.reader(), _trees(marks), [2 * len(m) + 1 for m in marks]

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums = [np.zeros(k, np.int64) for k in sizes]
        for block in _blocks(batches):
            for i, rows in enumerate(read(block)):
                sums[i] += np.bincount(rows.place(trees[i]), minlength=sizes[i])
        for i, own in enumerate(sums):
            full = np.flatnonzero(own)
            yield pa.record_batch([pa.array(np.full(len(full), i, np.int32)), pa.array(full), pa.array(own[full])], ["d", "at", "c"])

    counted = packed.select("data").mapInArrow(count, "d int, at bigint, c bigint").groupBy("d", "at").agg(F.sum("c").alias("c")).toArrow()
    counts = [np.zeros(k, np.int64) for k in sizes]
    for d, at, c in zip(*[counted.column(k).to_numpy() for k in range(3)]):
        counts[d][at] = c
    return counts


class _Held:
    """What one dimension looks for: the stretches in which cuts lie, cut further by digests where one key is frequent.

    A held stretch has parts, numbered through: parts to be ordered, and between them parts that are only counted.
    """

    def __init__(self, marks: list[tuple], counts: np.ndarray, places: list[int], whole: set[int]):
        ends = np.cumsum(counts)
        found = np.searchsorted(ends, places, "right").tolist()
        stretches = sorted(set(found))
        needed = sorted({m for s in stretches for m in ((s // 2,) if s % 2 else (s // 2 - 1, s // 2)) if 0 <= m < len(marks)})
        self.marks = [marks[m] for m in needed]
        self.tree = _Marks(self.marks) if self.marks else None
        self.parts: dict[int, tuple[int, np.ndarray | None]] = {}  # stretch among the marks kept: its first part, bounds of digests
        self.key: dict[int, tuple] = {}  # part: the key that all its rows have
        self.wanted: list[tuple[int, int, int, list[int], int]] = []  # cut, its part, its place in the stretch, parts before it there, stretch
        part = 0
        for s in stretches:
            here = 2 * bisect_left(needed, s // 2) + s % 2
            cuts = [(c, int(p - (ends[s] - counts[s]))) for c, (p, f) in enumerate(zip(places, found)) if f == s]
            rows, spans = int(counts[s]), []
            if s % 2 and rows > WHOLE and s not in whole:
                for _, nth in cuts:  # digests are spread evenly: the cut's is far outside of this once in 10**15
                    slack = 4 * int(rows**0.5) + 4
                    low, high = max(0, nth - slack) * 2**64 // rows, min(rows, nth + 1 + slack) * 2**64 // rows
                    if spans and low <= spans[-1][1]:
                        spans[-1][1] = high
                    else:
                        spans.append([low, high])
            bounds = [x for span in spans for x in span]  # a bound of 2**64 is that of no digest
            inside = [x for x in bounds if x < 2**64]
            self.parts[here] = part, np.array(inside, np.uint64) if spans else None
            for c, nth in cuts:
                own = 2 * next(k for k, (low, high) in enumerate(spans) if low <= nth * 2**64 // rows < high) + 1 if spans else 0
                self.wanted.append((c, part + own, nth, list(range(part, part + own)), s))
            many = len(inside) + 1
            if s % 2:
                self.key.update({part + k: marks[s // 2] for k in range(many)})
            part += many
        self.size = part

    def look(self, rows: _Rows) -> Iterator[tuple[int, np.ndarray, np.ndarray | None, bool]]:
        """(part, rows in it, their digests or None if not known yet, whether they are to be ordered)."""
        place = rows.place(self.tree)
        for stretch, (part, bounds) in self.parts.items():
            at = np.flatnonzero(place == stretch)
            if not len(at):
                continue
            found = rows.digests(at)
            if bounds is None:
                yield part, at, found, True
                continue
            own = np.searchsorted(bounds, found[:, 0], "right")
            for k in np.unique(own).tolist():
                here = np.flatnonzero(own == k)
                yield part + k, at[here], found[here], k % 2 == 1


def _look(layout: _Layout, packed: DataFrame, held: list[_Held]) -> DataFrame:
    """(d, part, k, t, c): rows to be ordered, of which c is 1, and how many others a part has."""
    read = layout.reader()

    def select(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        beside = [np.zeros(h.size, np.int64) for h in held]
        for block in _blocks(batches):
            for i, rows in enumerate(read(block)):
                for part, at, found, ordered in held[i].look(rows):
                    if not ordered:
                        beside[i][part] += len(at)
                        continue
                    keys = [b""] * len(at) if part in held[i].key else [_encode(rows.order(k)) for k in at.tolist()]
                    ties = found.astype(">u8").tobytes()
                    yield pa.record_batch([pa.array(np.full(len(at), i, np.int32)), pa.array(np.full(len(at), part, np.int32)), pa.array(keys, pa.binary()), pa.array([ties[k : k + 16] for k in range(0, len(ties), 16)], pa.binary()), pa.array(np.ones(len(at), np.int64))], ["d", "part", "k", "t", "c"])
        for i, own in enumerate(beside):
            full = np.flatnonzero(own)
            yield pa.record_batch([pa.array(np.full(len(full), i, np.int32)), pa.array(full.astype(np.int32)), pa.nulls(len(full), pa.binary()), pa.nulls(len(full), pa.binary()), pa.array(own[full])], ["d", "part", "k", "t", "c"])

    return packed.select("data").mapInArrow(select, "d int, part int, k binary, t binary, c bigint")


def bin_starts(layout: _Layout, packed: DataFrame, n: int, places: list[int]) -> list[list[tuple]]:
    """For every dimension the orders of the rows at these sorted places (0-based); each is the first of its bin."""
    marks = _splitters(layout, packed, n)
    counts = _count(layout, packed, marks)
    out: list[list] = [[None] * len(places) for _ in layout.specs]
    whole: list[set[int]] = [set() for _ in layout.specs]
    while True:
        held = [_Held(m, c, places, w) for m, c, w in zip(marks, counts, whole)]
        near = materialize(_look(layout, packed, held), "near")
        try:
            sizes = {(r.d, r.part): r.c for r in near.groupBy("d", "part").agg(F.sum("c").alias("c")).collect()}  # dimensions times bins
            asked, missed = [], False
            for i, h in enumerate(held):
                for cut, part, nth, before, stretch in h.wanted:
                    nth -= sum(sizes.get((i, p), 0) for p in before)
                    if 0 <= nth < sizes.get((i, part), 0):
                        asked.append((i, part, nth, cut))
                    else:  # digests that are not spread evenly, as of repeated row keys
                        whole[i].add(stretch)
                        missed = True
            if missed:
                continue
            wanted = packed.sparkSession.createDataFrame(asked, "d int, part int, nth int, cut int")
            placed = near.filter("k IS NOT NULL").withColumn("nth", F.row_number().over(Window.partitionBy("d", "part").orderBy("k", "t")) - 1)
            for r in placed.join(F.broadcast(wanted), ["d", "part", "nth"]).select("d", "part", "cut", "k", "t").collect():
                key, tie = held[r.d].key.get(r.part), bytes(r.t)
                out[r.d][r.cut] = (_decode(bytes(r.k), layout.kinds[r.d]) if key is None else key, (int.from_bytes(tie[:8], "big"), int.from_bytes(tie[8:], "big")))
            return out
        finally:
            release(near)


class _Starts:
    """The orders with which one dimension's bins begin: how many of them are not above a row."""

    def __init__(self, starts: list[tuple]):
        keys = sorted({k for k, _ in starts})
        self.tree = _Marks(keys)
        self.ties = [[t for k, t in starts if k == key] for key in keys]
        below = np.cumsum([0, *map(len, self.ties)])
        self.below = np.repeat(below, 2)[: 2 * len(keys) + 1]  # between keys and on them

    def place(self, rows: _Rows) -> np.ndarray:
        place = rows.place(self.tree)
        out = self.below[place]
        for k, ties in enumerate(self.ties):
            at = np.flatnonzero(place == 2 * k + 1)
            if len(at):
                out[at] += _above(ties, rows.digests(at))
        return out


def starts_of(n: int, bins: int, rule: str = "ceil") -> tuple[list[int], list[int]]:
    """Places at which a new bin begins, the first row's left out, and the bins from the first row on."""
    if rule == "proportional":
        at = sorted({-(-b * n // bins) for b in range(1, bins)} - {0, n})
        return at, [0, *[p * bins // n for p in at]]
    w = width(n, bins)
    at = list(range(w, n, w))
    return at, [p // w for p in [0, *at]]


def bin_rows(base: DataFrame | Iterable[DataFrame], specs: list[DimensionSpec], row_key: tuple[str, ...], bins: int, rule: str = "ceil") -> DataFrame:
    """``b_<dimension>`` of every row and nothing else: the bins of ``bin_by_rank`` over ``build_ranks``, without ranks.

    ``base`` (one frame, or slices that are read one after another) is read once, to write its keys, which are scanned four
    times; ``release`` of the result deletes them. No row is sent anywhere, but for those of the stretches in which cuts lie.
    """
    frames = iter([base] if isinstance(base, DataFrame) else base)
    first = next(frames)
    layout = _Layout(first, specs, row_key)
    packed = materialize_each((layout.pack(d) for d in chain([first], frames)), "keys", LONG_ROWS)
    n, kind = packed.agg(F.sum("rows")).first()[0] or 0, bin_type(bins)
    places, numbers = starts_of(n, bins, rule)
    with small_scans(packed.sparkSession):
        marks = bin_starts(layout, packed, n, places) if places else [[] for _ in specs]
    starts = [_Starts(m) if m else None for m in marks]
    read, table = layout.reader(), np.array(numbers, np.int8 if kind == "tinyint" else np.int16 if kind == "smallint" else np.int32)
    names = [s.bin for s in specs]

    def assign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for block in _blocks(batches):
            yield pa.record_batch([pa.array(table[starts[i].place(rows) if starts[i] else np.zeros(block.num_rows, np.int64)]) for i, rows in enumerate(read(block))], names)

    return keep(packed.select("data").mapInArrow(assign, ", ".join(f"{b} {kind}" for b in names)), packed)
