"""Aggregates of all triples of binned dimensions, by several strategies with one result.

Result: (triple, b0, b1, b2, cnt, one column a measure), non-empty cells only; b0 < b1 < b2 in
the order of the dimensions, triple numbered lexicographically.
"""

from __future__ import annotations

from collections.abc import Iterator
from concurrent.futures import ThreadPoolExecutor
from functools import reduce
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cubelens.dimension import DimensionSpec, MeasureSpec
from cubelens.plans import cost
from cubelens.plans.triples import Owned, plan_by_triple, plan_rounds, triples_of
from cubelens.storage import LONG_ROWS, keep, materialize, materialize_each, release

#: Plans of at most so many parts are united into one query; more run in written batches.
UNION_PARTS = 64
#: Packed rows that are on their way to units at a time, if one owner's are not more.
ROUTED_BYTES = 3 << 29
#: Rows that a task packs together.
BLOCK_ROWS = 1 << 17
#: Cells of dimensions that are counted together.
JOINT_CELLS = 1 << 16


def narrow(binned: DataFrame, specs: list[DimensionSpec], measures: list[MeasureSpec] = ()) -> DataFrame:
    """Bins of the dimensions and the measures' values, nothing else."""
    return binned.select(*[F.col(s.bin) for s in specs], *[F.expr(m.expression).cast(m.type).alias(m.name) for m in measures])


def _aggs(measures) -> list:
    return [F.count("*").alias("cnt"), *[F.sum(m.name).alias(m.name) for m in measures]]


def _result(df: DataFrame, measures) -> DataFrame:
    return df.select("triple", *[F.col(f"b{k}").cast("int").alias(f"b{k}") for k in range(3)], "cnt", *[m.name for m in measures])


def expand(rows: DataFrame, specs, measures=()) -> DataFrame:
    """Record-major baseline: grouping sets of all triples, one expansion of every row."""
    triples = triples_of(len(specs))
    cols = [F.col(s.bin) for s in specs]
    n = len(cols)
    grouped = rows.groupingSets([[cols[d] for d in t] for t in triples], *cols).agg(F.grouping_id().alias("gid"), *_aggs(measures))
    number = {sum(1 << (n - 1 - d) for d in range(n) if d not in t): k for k, t in enumerate(triples)}
    table = F.create_map(*[x for g, k in number.items() for x in (F.lit(g).cast("long"), F.lit(k))])
    held = F.array_compact(F.array(*cols))  # the three dimensions that are not rolled up, in order
    return _result(grouped.select(table[F.col("gid").cast("long")].alias("triple"), *[F.get(held, k).alias(f"b{k}") for k in range(3)], "cnt", *[m.name for m in measures]), measures)


def explode(rows: DataFrame, specs, measures=()) -> DataFrame:
    """Record-major with an explicit list of cells for each row: keys stay three small numbers."""
    cells = [F.struct(F.lit(k).alias("triple"), *[F.col(specs[d].bin).alias(f"b{i}") for i, d in enumerate(t)]) for k, t in enumerate(triples_of(len(specs)))]
    melted = rows.select(F.explode(F.array(*cells)).alias("c"), *[m.name for m in measures])
    return _result(melted.groupBy("c.triple", "c.b0", "c.b1", "c.b2").agg(*_aggs(measures)), measures)


def per_triple(rows: DataFrame, specs, measures=(), bins: int = 128, parts: int = 1, threads: int = 4, only: list[int] | None = None) -> DataFrame:
    """Aggregate-major: for each triple (or the numbered ones) a scan of its three columns, or ``parts`` scans of a range of its first bin."""

    def one(k: int, t, p: int) -> DataFrame:
        a, b, c = (specs[d].bin for d in t)
        own = rows.select(a, b, c, *[m.name for m in measures])
        if parts > 1:
            own = own.filter(F.col(a).between(p * bins // parts, (p + 1) * bins // parts - 1))
        out = own.groupBy(F.col(a).alias("b0"), F.col(b).alias("b1"), F.col(c).alias("b2")).agg(*_aggs(measures))
        return _result(out.withColumn("triple", F.lit(k)), measures)

    jobs = [(k, t, p) for k, t in enumerate(triples_of(len(specs))) if only is None or k in only for p in range(parts)]
    unite = lambda some: _unite([one(*j) for j in some])
    if len(jobs) <= UNION_PARTS:
        return unite(jobs)
    batches = [jobs[i : i + UNION_PARTS] for i in range(0, len(jobs), UNION_PARTS)]
    with ThreadPoolExecutor(threads) as pool:  # batches overlap: one fills slots that another leaves
        done = list(pool.map(lambda b: materialize(unite(b), "cube"), batches))
    return keep(_unite(done), *done)


def _unite(frames: list[DataFrame]) -> DataFrame:
    while len(frames) > 1:
        frames = [frames[i].unionByName(frames[i + 1]) if i + 1 < len(frames) else frames[i] for i in range(0, len(frames), 2)]
    return frames[0]


def _bincount(index: np.ndarray, size: int, weights: np.ndarray | None = None) -> np.ndarray:
    """Counts, or sums that stay exact for integers."""
    if weights is None:
        return np.bincount(index, minlength=size)
    if weights.dtype.kind == "f":
        return np.bincount(index, weights, minlength=size)
    low, high = weights & 0x3FFFFF, weights >> 22  # halves whose double sums are exact
    return np.bincount(index, low, minlength=size).astype(np.int64) + (np.bincount(index, high, minlength=size).astype(np.int64) << 22)


def _column(batch: pa.RecordBatch, k: int) -> np.ndarray:
    return batch.column(k).to_numpy(zero_copy_only=False)


def _value(batch: pa.RecordBatch, k: int) -> np.ndarray:
    c = batch.column(k)
    return (c.fill_null(0) if c.null_count else c).to_numpy(zero_copy_only=False)


def route(rows: DataFrame, specs, owners: list[int], measures=(), replicas: int = 1) -> DataFrame:
    """(owner, owner_bin, salt, bins, values): every row once for each owner, at the unit of its bin."""
    to = F.explode(F.array(*[F.struct(F.lit(o).alias("owner"), F.col(specs[o].bin).cast("int").alias("owner_bin")) for o in owners])).alias("u")
    salt = F.lit(0) if replicas == 1 else F.pmod(F.monotonically_increasing_id(), F.lit(replicas)).cast("int")
    return rows.select(to, salt.alias("salt"), *[s.bin for s in specs], *[m.name for m in measures]).select("u.owner", "u.owner_bin", "salt", *[s.bin for s in specs], *[m.name for m in measures])


def _layout(bins: int) -> tuple[type, int, int]:
    """Type of the words that hold a row's bins, dimensions in a word, bits of one."""
    bits = max(1, (bins - 1).bit_length())
    return (np.uint16, 16 // bits, bits) if bits <= 16 else (np.uint32, 1, 32)


def _unpack(words: np.ndarray, d: int, bins: int) -> np.ndarray:
    """Bins of dimension ``d``; words come word by word, not row by row."""
    kind, fit, bits = _layout(bins)
    return words[d // fit] >> kind(d % fit * bits) & kind((1 << bits) - 1)


def _words(n: int, bins: int) -> int:
    return -(-n // _layout(bins)[1])


def _row_bytes(n: int, bins: int, measures=()) -> int:
    return _words(n, bins) * np.dtype(_layout(bins)[0]).itemsize + 8 * len(measures)


def pack_rows(rows: DataFrame, n: int, bins: int, measures=()) -> DataFrame:
    """(rows, bins, one column a measure): many rows in one, their bins in few words."""
    names, (kind, fit, bits), wide = [m.name for m in measures], _layout(bins), _words(n, bins)
    # words are put together before Python sees them: handing a value over costs more than joining it to others
    words = []
    for at in range(0, n, fit):
        parts = [F.shiftleft(F.col(f"`{c}`").cast("int"), k * bits) for k, c in enumerate(rows.columns[at : min(at + fit, n)])]
        words.append(reduce(lambda x, y: x.bitwiseOR(y), parts).alias(f"w{at}"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for block in blocks(batches, BLOCK_ROWS):
            packed = np.stack([_column(block, k).astype(kind) for k in range(wide)], axis=1)
            yield pa.record_batch([pa.array([block.num_rows], pa.int32()), *[pa.array([x.tobytes()], pa.binary()) for x in (packed, *[_value(block, wide + k) for k in range(len(names))])]], ["rows", "bins", *names])

    return rows.select(*words, *names).mapInArrow(run, "rows int, bins binary" + "".join(f", {m} binary" for m in names))


def route_blocks(packed: DataFrame, n: int, bins: int, owners: list[int], measures=()) -> DataFrame:
    """``route`` of packed rows without salts, rows of a unit together: (owner, owner_bin, rows, bins, one column a measure)."""
    names, kinds, wide = [m.name for m in measures], [np.int64 if m.integer else np.float64 for m in measures], _words(n, bins)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for rows, data, *more in zip(*[batch.column(k) for k in range(2 + len(names))]):
                words = np.frombuffer(data.as_buffer(), _layout(bins)[0], rows.as_py() * wide).reshape(-1, wide)
                values = [np.frombuffer(v.as_buffer(), k) for v, k in zip(more, kinds)]
                columns = words.T
                for o in owners:
                    own = _unpack(columns, o, bins)
                    order = np.argsort(own, kind="stable")
                    own = own[order]
                    edges = [0, *(np.flatnonzero(np.diff(own)) + 1).tolist(), len(own)]
                    spans = list(zip(edges, edges[1:]))
                    yield pa.record_batch(
                        [pa.array(np.full(len(spans), o, np.int32)), pa.array(own[edges[:-1]].astype(np.int32)), pa.array([z - a for a, z in spans], pa.int32()), *[pa.array([v[a:z].tobytes() for a, z in spans], pa.binary()) for v in (np.take(words, order, axis=0), *[x[order] for x in values])]],
                        ["owner", "owner_bin", "rows", "bins", *names],
                    )

    return packed.mapInArrow(run, "owner int, owner_bin int, rows int, bins binary" + "".join(f", {m} binary" for m in names))


def blocks(batches: Iterator[pa.RecordBatch], rows: int) -> Iterator[pa.RecordBatch]:
    """Batches put together until they hold so many rows."""
    held, n = [], 0
    for b in batches:
        held.append(b)
        n += b.num_rows
        if n >= rows:
            yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]
            held, n = [], 0
    if n:
        yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]


def cover(pairs: list[tuple[int, int]], size: int) -> list[tuple[int, ...]]:
    """Groups of ``size`` dimensions at most that together hold every pair; each takes as many pairs as it finds."""
    near: dict[int, set[int]] = {}
    for j, k in pairs:
        near.setdefault(j, set()).add(k)
        near.setdefault(k, set()).add(j)
    out = []
    while any(near.values()):
        first = max(near, key=lambda d: (len(near[d]), -d))
        group = [first, max(near[first], key=lambda d: (len(near[d]), -d))]
        while len(group) < size:
            gain, _, best = max((len(near[d].intersection(group)), len(near[d]), -d) for d in near if d not in group) if len(near) > len(group) else (0, 0, 0)
            if not gain:
                break
            group.append(-best)
        for d in group:
            near[d].difference_update(group)
        out.append(tuple(sorted(group)))
    return out


def joint_size(bins: int) -> int:
    """Dimensions that are counted together, so that the cells stay near the processor; two at least."""
    size = 2
    while size < 6 and bins ** (size + 1) <= JOINT_CELLS:
        size += 1
    return size


def update_blocks(sent: DataFrame, owned: dict[int, list[tuple[int, int, int]]], n: int, bins: int, measures=(), partitions: int | None = None) -> DataFrame:
    """``update_units`` of packed rows: a task holds one unit and adds a block at a time.

    Where bins are few, dimensions of several triples are counted together, in one joint array, which is
    summed to each triple's cells when the unit ends.
    """
    names, kinds, wide = [m.name for m in measures], [np.int64 if m.integer else np.float64 for m in measures], _words(n, bins)
    units = {(o, b): k for k, (o, b) in enumerate((o, b) for b in range(bins) for o in sorted(owned))}
    parts = min(partitions or int(sent.sparkSession.conf.get("spark.sql.shuffle.partitions")), len(units))
    # units are equal: dealt in turn, not by a hash that would give some tasks several
    place = (F.col("owner_bin") * len(owned) + F.array_position(F.lit(sorted(owned)), F.col("owner")) - 1) % parts
    sent = sent.repartitionById(parts, place.cast("int")).sortWithinPartitions("owner", "owner_bin")
    joint = {o: cover([(j, k) for _, j, k in t], joint_size(bins)) for o, t in owned.items()}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        unit, cells, kept, waiting = None, {}, [], 0

        def update() -> None:
            """Adds the rows that wait."""
            nonlocal kept, waiting
            words = np.ascontiguousarray(np.concatenate([np.frombuffer(x[0], _layout(bins)[0]) for x in kept]).reshape(-1, wide).T)
            values = [None, *[np.concatenate([np.frombuffer(x[1 + m], k) for x in kept]) for m, k in enumerate(kinds)]]
            cols = {d: _unpack(words, d, bins) for d in {d for g in joint[unit[0]] for d in g}}
            for g in joint[unit[0]]:
                kind = np.uint16 if bins ** len(g) <= 1 << 16 else np.int64
                index = cols[g[0]].astype(kind)
                for d in g[1:]:
                    index *= kind(bins)
                    index += cols[d].astype(kind, copy=False)
                for m, v in enumerate(values, -1):
                    cells[g, m] = cells.get((g, m), 0) + _bincount(index, bins ** len(g), v)
            kept, waiting = [], 0

        def finish() -> pa.RecordBatch:
            if kept:
                update()
            of, order = {}, sorted(owned[unit[0]])
            for g in joint[unit[0]]:
                of.update({p: g for p in combinations(g, 2)})
            lists = []
            for m in range(-1, len(names)):
                sums = []
                for _, j, k in order:
                    g = of[j, k]
                    sums.append(cells[g, m].reshape((bins,) * len(g)).sum(axis=tuple(a for a, d in enumerate(g) if d not in (j, k))).ravel())
                lists.append(pa.ListArray.from_arrays(pa.array(np.arange(len(order) + 1, dtype=np.int32) * (bins * bins)), pa.array(np.concatenate(sums))))
            return pa.record_batch([pa.array([t for t, _, _ in order], pa.int32()), pa.array([unit[1]] * len(order), pa.int32()), *lists], ["triple", "owner_bin", "cnt", *names])

        for batch in batches:
            for owner, owner_bin, rows, *data in zip(*[batch.column(k) for k in range(4 + len(names))]):
                here = (owner.as_py(), owner_bin.as_py())
                if unit is not None and here != unit:
                    yield finish()
                    cells = {}
                unit = here
                kept.append([x.as_buffer() for x in data])
                waiting += rows.as_py()
                if waiting >= BLOCK_ROWS:
                    update()
        if unit is not None:
            yield finish()

    schema = "triple int, owner_bin int, cnt array<bigint>" + "".join(f", {m.name} array<{'bigint' if m.integer else 'double'}>" for m in measures)
    return sent.mapInArrow(run, schema)


def owned_by_round(plan: list[Owned]) -> list[dict[int, list[tuple[int, int, int]]]]:
    """For each round, the triples of every owner as (triple, first other dimension, second)."""
    rounds: dict[int, dict[int, list[tuple[int, int, int]]]] = {}
    for p in plan:
        j, k = (d for d in p.dims if d != p.owner)
        rounds.setdefault(p.round, {}).setdefault(p.owner, []).append((p.triple, j, k))
    return [rounds[r] for r in sorted(rounds)]


def owner_slices(rows: DataFrame, specs, bins: int, measures=(), plan: list[Owned] | None = None, replicas: int = 1, kernel: str = "tile", partitions: int | None = None, staged: bool = False) -> DataFrame:
    """(triple, owner_bin, cnt, one column a measure): dense slices of bins x bins cells.

    Rows are sent once to each owner dimension of a round. A unit (owner, bin) keeps one small
    array for each triple it owns; units are disjoint, so nothing is merged unless ``replicas``
    salts them. Rounds belong to one job: one round's units are filled while another's update
    (pipelined). ``staged`` writes the routed rows of all rounds, side by side, before any
    kernel starts (synchronous).

    Plain runs (``tile``, one copy of a unit) send packed rows. If all copies of them are more than
    ``ROUTED_BYTES``, owners work in turn, as many as fit, and at least one; their slices are written and the
    rows sent to them deleted before the next ones begin.
    """
    rounds = owned_by_round(plan or plan_rounds(len(specs)))
    if kernel == "tile" and replicas == 1 and not staged:
        n, count = len(specs), rows.count() if partitions is None else 0
        step = max(1, ROUTED_BYTES // max(1, count * _row_bytes(n, bins, measures)))
        packed = pack_rows(rows, n, bins, measures)
        work = lambda some: update_blocks(route_blocks(packed, n, bins, sorted(some), measures), some, n, bins, measures, partitions)
        if step >= sum(map(len, rounds)):
            return _unite([work(owned) for owned in rounds])
        turns = [dict(sorted(owned.items())[i : i + step]) for owned in rounds for i in range(0, len(owned), step)]
        packed = materialize(packed, "packed", LONG_ROWS)  # rows are taken apart once, not once a turn
        try:
            return materialize_each((work(some) for some in turns), "slices")
        finally:
            release(packed)
    sent = [route(rows, specs, sorted(owned), measures, replicas) for owned in rounds]
    if staged:
        with ThreadPoolExecutor(4) as pool:
            sent = list(pool.map(lambda d: materialize(d, "routed"), sent))
    slices = [update_units(d, owned, len(specs), bins, measures, replicas, kernel, partitions) for d, owned in zip(sent, rounds)]
    return keep(_unite(slices), *sent)


def update_units(sent: DataFrame, owned: dict[int, list[tuple[int, int, int]]], n: int, bins: int, measures=(), replicas: int = 1, kernel: str = "tile", partitions: int | None = None) -> DataFrame:
    """Slices of one round from its routed rows.

    ``tile``: a task streams sorted batches and updates all of a unit's triples from each, holding
    one unit; ``scan_per_triple`` (baseline): it gathers a unit's rows and goes over them once
    for each triple.
    """
    size, names = bins * bins, [m.name for m in measures]
    units = len(owned) * bins * replicas
    # more partitions than the session's shuffle partitions would only add small tasks
    parts = min(partitions or int(sent.sparkSession.conf.get("spark.sql.shuffle.partitions")), units)
    sent = sent.repartition(parts, "owner", "owner_bin", "salt").sortWithinPartitions("owner", "owner_bin", "salt")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        unit, cells, kept = None, {}, []

        def update(owner: int, part: list[np.ndarray]) -> None:
            for t, j, k in owned[owner]:
                index = part[j].astype(np.int64) * bins + part[k]
                for m in range(-1, len(names)):
                    cells[t, m] = cells.get((t, m), 0) + _bincount(index, size, None if m < 0 else part[n + m])

        def finish() -> pa.RecordBatch:
            if kernel != "tile":
                update(unit[0], [np.concatenate(c) for c in zip(*kept)])
            order = sorted(t for t, _, _ in owned[unit[0]])
            offsets = pa.array(np.arange(len(order) + 1, dtype=np.int32) * size)
            lists = [pa.ListArray.from_arrays(offsets, pa.array(np.concatenate([cells[t, m] for t in order]))) for m in range(-1, len(names))]
            return pa.record_batch([pa.array(order, pa.int32()), pa.array([unit[1]] * len(order), pa.int32()), *lists], ["triple", "owner_bin", "cnt", *names])

        for batch in batches:
            key = [_column(batch, k) for k in range(3)]
            edge = np.flatnonzero((np.diff(key[0]) != 0) | (np.diff(key[1]) != 0) | (np.diff(key[2]) != 0)) + 1
            bounds = [0, *edge.tolist(), batch.num_rows]
            cols = [_column(batch, 3 + k) for k in range(n)] + [_value(batch, 3 + n + k) for k in range(len(names))]
            for a, z in zip(bounds, bounds[1:]):
                if a == z:
                    continue
                here = (int(key[0][a]), int(key[1][a]), int(key[2][a]))
                if unit is not None and here != unit:
                    yield finish()
                    cells, kept = {}, []
                unit = here
                part = [c[a:z] for c in cols]
                if kernel == "tile":
                    update(unit[0], part)
                else:
                    kept.append(part)
        if unit is not None:
            yield finish()

    schema = "triple int, owner_bin int, cnt array<bigint>" + "".join(f", {m.name} array<{'bigint' if m.integer else 'double'}>" for m in measures)
    return sent.mapInArrow(run, schema)


def merge_slices(slices: DataFrame, measures=()) -> DataFrame:
    """Element-wise sums of the copies of a slice, as (triple, owner_bin, cell, cnt, measures); empty cells left out."""
    names = ["cnt", *[m.name for m in measures]]
    cells = slices.select("triple", "owner_bin", F.posexplode(F.arrays_zip(*names)).alias("cell", "v")).filter("v.cnt > 0")
    return cells.groupBy("triple", "owner_bin", "cell").agg(*[F.sum(f"v.{m}").alias(m) for m in names])


def slices_to_cube(slices: DataFrame, n: int, bins: int, plan: list[Owned], measures=(), merged: bool = False) -> DataFrame:
    """Cells of slices in the order of the triple's dimensions."""
    names = ["cnt", *[m.name for m in measures]]
    if merged:
        cells = slices
    else:
        cells = slices.select("triple", "owner_bin", F.posexplode(F.arrays_zip(*names)).alias("cell", "v")).filter("v.cnt > 0").select("triple", "owner_bin", "cell", *[f"v.{m}" for m in names])
    place = {p.triple: p.dims.index(p.owner) for p in plan}
    at = F.element_at(F.lit([place[t] for t in range(len(place))]), F.col("triple") + 1)
    low, high, own = F.expr(f"cell div {bins}").cast("int"), F.expr(f"cell % {bins}").cast("int"), F.col("owner_bin")
    b0 = F.when(at == 0, own).otherwise(low)
    b1 = F.when(at == 1, own).when(at == 0, low).otherwise(high)
    b2 = F.when(at == 2, own).otherwise(high)
    return cells.select("triple", b0.alias("b0"), b1.alias("b1"), b2.alias("b2"), *names)


def owner_slice(rows: DataFrame, specs, measures=(), bins: int = 128, owners: int | None = None, replicas: int = 1, kernel: str = "tile", staged: bool = False) -> DataFrame:
    plan = plan_rounds(len(specs), owners)
    slices = owner_slices(rows, specs, bins, measures, plan, replicas, kernel, staged=staged)
    if replicas > 1:
        return keep(slices_to_cube(merge_slices(slices, measures), len(specs), bins, plan, measures, True), slices)
    return keep(slices_to_cube(slices, len(specs), bins, plan, measures), slices)


def _dense(rows: DataFrame, combos: list[tuple[int, ...]], n: int, measures, bins: int, memory: int) -> DataFrame:
    """(combo, cell, cnt, measures): every task adds its rows up in one dense array a combination and sends the non-empty cells.

    Combinations go in batches whose arrays fit ``memory``, one scan of the narrow rows each.
    Those of a batch that begin with the same dimensions share the first part of their index.
    """
    names, size = [m.name for m in measures], bins ** len(combos[0]) if combos else 1
    step = max(1, memory // (size * 8 * (1 + len(names))))
    out = []
    for at in range(0, len(combos), step):
        some = list(enumerate(combos))[at : at + step]

        def run(batches: Iterator[pa.RecordBatch], some=some) -> Iterator[pa.RecordBatch]:
            cells: dict = {}
            for batch in batches:
                cols = [_column(batch, k).astype(np.int64) for k in range(n)]
                values = [None] + [_value(batch, n + k) for k in range(len(names))]
                head, start = None, 0
                for t, dims in some:
                    if dims[:-1] != head:
                        head, start = dims[:-1], 0
                        for d in head:
                            start = (start + cols[d]) * bins
                    index = start + cols[dims[-1]]
                    for m, v in enumerate(values):
                        if (t, m) in cells:
                            cells[t, m] += _bincount(index, size, v)
                        else:
                            cells[t, m] = _bincount(index, size, v)
            for t, _ in some:
                if (t, 0) in cells:
                    full = np.flatnonzero(cells[t, 0])
                    for a in range(0, len(full), 65536):
                        f = full[a : a + 65536]
                        yield pa.record_batch([pa.array(np.full(len(f), t, np.int32)), pa.array(f), *[pa.array(cells[t, m][f]) for m in range(1 + len(names))]], ["combo", "cell", "cnt", *names])

        schema = "combo int, cell bigint, cnt bigint" + "".join(f", {m.name} {m.type}" for m in measures)
        out.append(rows.mapInArrow(run, schema))
    return _unite(out).groupBy("combo", "cell").agg(*[F.sum(x).alias(x) for x in ["cnt", *names]])


def _digit(bins: int, k: int):
    return F.expr(f"(cell div {bins**k}) % {bins}").cast("int")


def local_dense(rows: DataFrame, specs, measures=(), bins: int = 128, memory: int = cost.LOCAL_BYTES) -> DataFrame:
    """Every task adds its rows up in dense arrays and sends the non-empty cells; these are summed.

    What moves does not grow with the rows once a task has filled its cells.
    """
    summed = _dense(rows, triples_of(len(specs)), len(specs), measures, bins, memory)
    return summed.select(F.col("combo").alias("triple"), *[_digit(bins, 2 - k).alias(f"b{k}") for k in range(3)], "cnt", *[m.name for m in measures])


def by_triple(rows: DataFrame, specs, measures=(), bins: int = 128, workers: int = 4) -> DataFrame:
    """Baseline: triples are dealt to workers and every row is sent to each of them; nothing is merged, all is transfer."""
    n, names = len(specs), [m.name for m in measures]
    own: dict[int, list[int]] = {}
    for t, w in plan_by_triple(n, workers):
        own.setdefault(w, []).append(t)
    triples = triples_of(n)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cells: dict = {}
        for batch in batches:
            worker = _column(batch, 0)
            cols = [_column(batch, 1 + k).astype(np.int64) for k in range(n)]
            values = [None] + [_value(batch, 1 + n + k) for k in range(len(names))]
            for w in np.unique(worker).tolist():
                at = worker == w
                for t in own.get(w, []):
                    i, j, k = triples[t]
                    index = (cols[i][at] * bins + cols[j][at]) * bins + cols[k][at]
                    for m, v in enumerate(values):
                        cells[t, m] = cells.get((t, m), 0) + _bincount(index, bins**3, None if v is None else v[at])
        for t in sorted({t for t, _ in cells}):
            f = np.flatnonzero(cells[t, 0])
            yield pa.record_batch([pa.array(np.full(len(f), t, np.int32)), pa.array(f), *[pa.array(cells[t, m][f]) for m in range(1 + len(names))]], ["triple", "cell", "cnt", *names])

    schema = "triple int, cell bigint, cnt bigint" + "".join(f", {m.name} {m.type}" for m in measures)
    sent = rows.select(F.explode(F.sequence(F.lit(0), F.lit(workers - 1))).alias("worker"), *rows.columns).repartition(workers, "worker")
    out = sent.mapInArrow(run, schema)
    b = lambda k: F.expr(f"(cell div {bins**k}) % {bins}").cast("int")
    return out.select("triple", b(2).alias("b0"), b(1).alias("b1"), b(0).alias("b2"), "cnt", *names)


STRATEGIES = ("expand", "explode", "per_triple", "owner_slice", "by_triple", "local_dense")


def build_cube(binned: DataFrame, specs: list[DimensionSpec], bins: int, measures=(), strategy: str = "auto", **options) -> DataFrame:
    """All triple aggregates by the named strategy, or the one the cost model finds cheapest."""
    rows = narrow(binned, specs, measures)
    if strategy == "auto":
        # counting rows of a written table reads file footers only
        strategy = cost.choose_strategy(rows.count(), len(specs), bins, input_tasks(rows))
    if strategy == "expand":
        return expand(rows, specs, measures)
    if strategy == "explode":
        return explode(rows, specs, measures)
    if strategy == "per_triple":
        return per_triple(rows, specs, measures, bins, **options)
    if strategy == "owner_slice":
        return owner_slice(rows, specs, measures, bins, **options)
    if strategy == "by_triple":
        return by_triple(rows, specs, measures, bins, **options)
    if strategy == "local_dense":
        return local_dense(rows, specs, measures, bins, **options)
    raise ValueError(strategy)


def input_tasks(df: DataFrame) -> int:
    """Tasks of a scan of ``df``'s input, from the sizes the planner knows; nothing runs."""
    spark = df.sparkSession
    size = int(str(df._jdf.queryExecution().analyzed().collectLeaves().head().stats().sizeInBytes()))
    part = spark._jvm.org.apache.spark.network.util.JavaUtils.byteStringAsBytes(spark.conf.get("spark.sql.files.maxPartitionBytes"))
    return max(spark.sparkContext.defaultParallelism, -(-size // part))


def build_pairs(binned: DataFrame, specs, measures=(), bins: int | None = None) -> DataFrame:
    """(pair, b0, b1, cnt, measures) of all pairs in a single pass.

    With ``bins`` every task adds its rows up in dense arrays, bins x bins cells a pair; without,
    rows are expanded to their pairs and grouped.
    """
    rows, n = narrow(binned, specs, measures), len(specs)
    pairs = list(combinations(range(n), 2))
    if bins:
        summed = _dense(rows, pairs, n, measures, bins, cost.LOCAL_BYTES)
        return summed.select(F.col("combo").alias("pair"), _digit(bins, 1).alias("b0"), _digit(bins, 0).alias("b1"), "cnt", *[m.name for m in measures])
    cells = [F.struct(F.lit(k).alias("pair"), F.col(specs[i].bin).alias("b0"), F.col(specs[j].bin).alias("b1")) for k, (i, j) in enumerate(pairs)]
    melted = rows.select(F.explode(F.array(*cells)).alias("c"), *[m.name for m in measures])
    out = melted.groupBy("c.pair", "c.b0", "c.b1").agg(*_aggs(measures))
    return out.select("pair", F.col("b0").cast("int").alias("b0"), F.col("b1").cast("int").alias("b1"), "cnt", *[m.name for m in measures])


def summarise(cube: DataFrame, measures=()) -> DataFrame:
    """(triple, cells, cnt, top, squares, measures' sums): what identifies a triple's cube in one row."""
    return cube.groupBy("triple").agg(F.count("*").alias("cells"), F.sum("cnt").alias("cnt"), F.max("cnt").alias("top"), F.sum(F.col("cnt") * (F.col("cnt") + F.col("b0") + 3 * F.col("b1") + 7 * F.col("b2"))).alias("squares"), *[F.sum(m.name).alias(m.name) for m in measures])


def build_marginals(binned: DataFrame, specs) -> DataFrame:
    """(dim, bin, cnt): populations of the bins of every dimension."""
    cells = F.array(*[F.struct(F.lit(s.name).alias("dim"), F.col(s.bin).cast("int").alias("bin")) for s in specs])
    return binned.select(F.explode(cells).alias("c")).groupBy("c.dim", "c.bin").agg(F.count("*").alias("cnt"))


def build_extremes(binned: DataFrame, specs, expression: str) -> DataFrame:
    """(triple, b0, b1, b2, cnt, avg, least, most): aggregates that dense arrays do not add up."""
    v = F.expr(expression)
    cells = [F.struct(F.lit(k).alias("triple"), *[F.col(specs[d].bin).cast("int").alias(f"b{i}") for i, d in enumerate(t)]) for k, t in enumerate(triples_of(len(specs)))]
    melted = binned.select(F.explode(F.array(*cells)).alias("c"), v.alias("v"))
    return melted.groupBy("c.triple", "c.b0", "c.b1", "c.b2").agg(F.count("*").alias("cnt"), (F.sum("v") / F.count("v")).alias("avg"), F.min("v").alias("least"), F.max("v").alias("most"))


def read_cube(spark, path: str, triples: list[int] | None = None) -> DataFrame:
    """A kept cube, or some of its triples: the filter reaches the files, whose ranges of triples are known."""
    cube = spark.read.parquet(path)
    return cube if triples is None else cube.filter(F.col("triple").isin(triples))


def write_cube(cube: DataFrame, path: str, files: int | None = None) -> None:
    """Keep a cube ordered by triple, so that a reader of few triples skips the rest."""
    n = files or int(cube.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    cube.repartitionByRange(n, "triple", "b0").sortWithinPartitions("triple", "b0", "b1", "b2").write.mode("overwrite").parquet(path)
