"""Equal-population bins: exactly from ranks of a subset, or through a wide histogram of rank prefixes."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from cubelens.dimension import DimensionSpec
from cubelens.operators.rank import build_ranks, rank_small

BINS, FINE_BITS = 128, 20
#: Buckets of the first of two histograms, from which the second one's are chosen.
COARSE_BITS = 10
#: A frame of at most so many rows may be ordered by one window.
SMALL_ROWS = 200_000


def width(n: int, bins: int) -> int:
    return max(1, -(-n // bins))


def bin_of(place: Column, n: int, bins: int, rule: str = "ceil") -> Column:
    """Bin of a 0-based place among n rows: equal widths rounded up, or in proportion (no empty tail bins)."""
    if rule == "proportional":
        return _div(place * bins, max(n, 1)).cast("int")
    return _div(place, width(n, bins)).cast("int")


def _div(a: Column, b: int) -> Column:
    """Integer quotient of non-negative BIGINTs, exact beyond 2**53."""
    return F.call_function("div", a, F.lit(b).cast("long"))


def bin_type(bins: int) -> str:
    return "tinyint" if bins <= 128 else "smallint" if bins <= 32768 else "int"


def bin_exact(df: DataFrame, specs: list[DimensionSpec], row_key: tuple[str, ...], bins: int = BINS, rule: str = "ceil", tie: str = "keyed") -> DataFrame:
    """``df`` with ``b_<dimension>``: order all rows, cut the order into equal runs."""
    n = df.count()
    if n <= SMALL_ROWS and len(specs) == 1:
        ranked = rank_small(df, specs[0], row_key, tie)
    else:
        ranked = build_ranks(df, specs, row_key, tie)
    return bin_by_rank(ranked, specs, n, bins, rule)


def bin_by_rank(ranked: DataFrame, specs: list[DimensionSpec], n: int, bins: int = BINS, rule: str = "ceil") -> DataFrame:
    """Bins of a whole ranked table straight from its ranks; the ranks are dropped."""
    cols = {s.bin: bin_of(F.col(s.rank), n, bins, rule).cast(bin_type(bins)) for s in specs}
    return ranked.withColumns(cols).drop(*[s.rank for s in specs])


def shift_of(total: int, fine_bits: int = FINE_BITS) -> int:
    """Low bits of a rank that the histogram drops; none where ranks have fewer bits."""
    return max(0, max(total - 1, 0).bit_length() - fine_bits)


def fine_histogram(aug: DataFrame, specs: list[DimensionSpec], total: int, fine_bits: int = FINE_BITS) -> DataFrame:
    """(dim, bucket, cnt): rows of the subset by the high bits of their ranks, all dimensions in one scan.

    Counted by each task first, so the exchange carries a row for each bucket a task has seen.
    """
    shift = shift_of(total, fine_bits)
    cells = F.array(*[F.struct(F.lit(s.name).alias("dim"), F.shiftright(s.rank, shift).cast("int").alias("bucket")) for s in specs])
    return aug.select(F.explode(cells).alias("x")).groupBy("x.dim", "x.bucket").agg(F.count("*").alias("cnt"))


def histogram_cuts(hist: DataFrame, n: int, bins: int = BINS) -> DataFrame:
    """(dim, bin, first_bucket, first_pos): a bucket's bin is that of the rows in earlier buckets."""
    before = Window.partitionBy("dim").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    placed = hist.withColumn("pos", F.coalesce(F.sum("cnt").over(before), F.lit(0)))
    placed = placed.withColumn("bin", _div(F.col("pos"), width(n, bins)).cast("int"))
    return placed.groupBy("dim", "bin").agg(F.min("bucket").alias("first_bucket"), F.min("pos").alias("first_pos"))


def step_function(value: Column, cuts: list[int]) -> Column:
    """Index of the last cut that is not above value, for sorted cuts: nested halving, log depth, compiled code."""

    def build(lo: int, hi: int) -> Column:
        if hi - lo == 1:
            return F.lit(lo)
        mid = (lo + hi) // 2
        return F.when(value < cuts[mid], build(lo, mid)).otherwise(build(mid, hi))

    return build(0, len(cuts))


def apply_cuts(aug: DataFrame, specs: list[DimensionSpec], cuts: DataFrame, total: int, bins: int = BINS, fine_bits: int = FINE_BITS, how: str = "steps") -> DataFrame:
    """Bins for all dimensions in one narrow pass.

    ``steps``: the at most ``bins`` cuts of a dimension become nested comparisons. ``join``: a
    broadcast table bucket -> bin (at most 2**fine_bits rows a dimension). ``search``: binary
    search in Arrow batches. At most dimensions times bins cuts reach the driver.
    """
    shift = shift_of(total, fine_bits)
    known: dict[str, list[tuple[int, int]]] = {s.name: [] for s in specs}
    for r in cuts.collect():
        known[r.dim].append((r.first_bucket, r.bin))
    kind = bin_type(bins)
    if how == "search":
        return _search_cuts(aug, specs, known, shift, kind)
    for s in specs:
        steps = sorted(known[s.name]) or [(0, 0)]
        bucket = F.shiftright(s.rank, shift)
        if how == "join":
            spark = aug.sparkSession
            edges = [*[b for b, _ in steps], 1 << fine_bits]
            table = spark.createDataFrame([(b, e, k) for (b, k), e in zip(steps, edges[1:])], "lo int, hi int, bin int")
            table = table.select(F.explode(F.sequence("lo", F.col("hi") - 1)).alias("bucket_"), F.col("bin").cast(kind).alias(s.bin))
            aug = aug.withColumn("bucket_", bucket.cast("int")).join(F.broadcast(table), "bucket_", "left").drop("bucket_")
        else:
            numbers = [k for _, k in steps]
            at = step_function(bucket, [b for b, _ in steps])
            same = numbers == list(range(len(numbers)))
            aug = aug.withColumn(s.bin, (at if same else F.element_at(F.lit(numbers), at + 1)).cast(kind))
    return aug


def _search_cuts(aug: DataFrame, specs, known, shift: int, kind: str) -> DataFrame:
    import numpy as np
    import pyarrow as pa

    steps = {s.name: sorted(known[s.name]) or [(0, 0)] for s in specs}
    tables = [(s.rank, np.array([b for b, _ in steps[s.name]]), np.array([k for _, k in steps[s.name]], np.int8 if kind == "tinyint" else np.int16 if kind == "smallint" else np.int32)) for s in specs]

    def run(batches):
        for batch in batches:
            new = [pa.array(bins[np.searchsorted(first, np.asarray(batch.column(batch.schema.get_field_index(rank))) >> shift, "right") - 1]) for rank, first, bins in tables]
            yield pa.RecordBatch.from_arrays([*batch.columns, *new], names=[*batch.schema.names, *[s.bin for s in specs]])

    from pyspark.sql.types import StructType, _parse_datatype_string

    schema = aug.schema
    for s in specs:
        schema = StructType([*schema.fields, *_parse_datatype_string(f"{s.bin} {kind}").fields])
    return aug.mapInArrow(run, schema)


def refined_cuts(aug: DataFrame, specs: list[DimensionSpec], total: int, bins: int = BINS, fine_bits: int = FINE_BITS) -> tuple[DataFrame, int]:
    """The cuts of ``histogram_cuts`` over the whole fine histogram, and the number of rows, from two small ones.

    A cut lies in a bucket whose place is known from a coarse histogram; only the at most
    twice ``bins`` coarse buckets of a dimension in which a cut can lie are counted finely. What
    tasks exchange falls from 2**fine_bits buckets a dimension to 2**COARSE_BITS and as many for
    each bin, for one more scan of the ranks. Coarse counts reach the driver.
    """
    shift = shift_of(total, fine_bits)
    coarse = shift_of(total, min(COARSE_BITS, fine_bits))
    known: dict[str, dict[int, int]] = {s.name: {} for s in specs}
    for r in fine_histogram(aug, specs, total, min(COARSE_BITS, fine_bits)).collect():
        known[r.dim][r.bucket] = r.cnt
    n = sum(known[specs[0].name].values()) if specs else 0
    step, cells, rows = width(n, bins), [], []
    for s in specs:
        pos, last, wanted, starts = 0, -1, [], []
        for bucket, cnt in sorted(known[s.name].items()):
            # a cut is the first fine bucket that starts in its bin: a new bin starts inside, or between the bucket before and this one
            here = pos // step != last or pos // step != (pos + cnt - 1) // step
            rows.append((s.name, bucket, pos, here))
            wanted.append(here)
            starts.append(bucket)
            last = pos // step
            pos += cnt
        marks = [False] * (max(starts, default=0) + 1)
        for bucket, w in zip(starts, wanted):
            marks[bucket] = w
        high = F.shiftright(s.rank, coarse)
        cells.append(F.when(F.element_at(F.lit(marks), (high + 1).cast("int")), F.struct(F.lit(s.name).alias("dim"), F.shiftright(s.rank, shift).cast("int").alias("bucket"))))
    if coarse == shift:
        spark = aug.sparkSession
        hist = spark.createDataFrame([(d, b, c) for d, m in known.items() for b, c in m.items()], "dim string, bucket int, cnt long")
        return histogram_cuts(hist, n, bins), n
    fine = aug.select(F.explode(F.array_compact(F.array(*cells))).alias("x")).groupBy("x.dim", "x.bucket").agg(F.count("*").alias("cnt"))
    start = aug.sparkSession.createDataFrame([(d, b, p) for d, b, p, here in rows if here], "dim string, high_ int, start_ long")
    fine = fine.withColumn("high_", F.shiftright("bucket", coarse - shift)).join(F.broadcast(start), ["dim", "high_"])  # dimensions times bins
    before = Window.partitionBy("dim", "high_").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    placed = fine.withColumn("pos", F.col("start_") + F.coalesce(F.sum("cnt").over(before), F.lit(0)))
    placed = placed.withColumn("bin", _div(F.col("pos"), step).cast("int"))
    found = placed.groupBy("dim", "bin").agg(F.min("bucket").alias("first_bucket"), F.min("pos").alias("first_pos"))
    return found, n


def bin_by_histogram(aug: DataFrame, specs: list[DimensionSpec], total: int, bins: int = BINS, fine_bits: int = FINE_BITS, how: str = "steps") -> DataFrame:
    """Bins of a subset of a ranked table without any sort; ``total`` counts the whole table's rows."""
    cuts, _ = refined_cuts(aug, specs, total, bins, fine_bits)
    return apply_cuts(aug, specs, cuts, total, bins, fine_bits, how)


def needs_sort(n: int, total: int, bins: int = BINS, fine_bits: int = FINE_BITS) -> bool:
    """Whether a subset is so small that its rows may fall into too few buckets to be cut evenly."""
    return shift_of(total, fine_bits) > 0 and n * (1 << fine_bits) < total * bins


def bin_auto(aug: DataFrame, specs: list[DimensionSpec], total: int, bins: int = BINS, fine_bits: int = FINE_BITS) -> DataFrame:
    """Through the histogram, or by ordering the ranks of a subset below the share bins / 2**fine_bits."""
    n = aug.count()
    if not needs_sort(n, total, bins, fine_bits):
        return bin_by_histogram(aug, specs, total, bins, fine_bits)
    plain = [DimensionSpec(s.name + "_sub", (s.rank,)) for s in specs]
    placed = build_ranks(aug, plain, tuple(s.rank for s in specs), "columns")
    placed = bin_by_rank(placed, plain, n, bins)
    return reduce(lambda d, s: d.withColumnRenamed(s.bin + "_sub", s.bin), specs, placed)


def axis_table(binned: DataFrame, specs: list[DimensionSpec]) -> DataFrame:
    """(dim, bin, lo, hi, n): what a bin shows when pointed at."""
    out = None
    for s in specs:
        part = binned.groupBy(F.col(s.bin).cast("int").alias("bin")).agg(F.min(s.label()).cast("string").alias("lo"), F.max(s.label()).cast("string").alias("hi"), F.count("*").alias("n"))
        part = part.select(F.lit(s.name).alias("dim"), "bin", "lo", "hi", "n")
        out = part if out is None else out.unionByName(part)
    return out


def bin_balance(binned: DataFrame, specs: list[DimensionSpec], bins: int) -> DataFrame:
    """(dim, bins_used, least, most, ideal, cv): how even the populations are, empty bins included."""
    cells = F.array(*[F.struct(F.lit(s.name).alias("dim"), F.col(s.bin).cast("int").alias("bin")) for s in specs])
    counts = binned.select(F.explode(cells).alias("x")).groupBy("x.dim", "x.bin").agg(F.count("*").alias("n"))
    mean = F.sum("n") / F.lit(bins)
    spread = F.sqrt(F.greatest(F.sum(F.col("n") * F.col("n")) / F.lit(bins) - mean * mean, F.lit(0.0))) / mean
    least = F.when(F.count("*") < bins, F.lit(0)).otherwise(F.min("n"))
    return counts.groupBy("dim").agg(F.count("*").alias("bins_used"), least.cast("long").alias("least"), F.max("n").alias("most"), F.round(mean, 6).alias("ideal"), F.round(spread, 6).alias("cv"))


def drop_one_to_one(df: DataFrame, cols: list[str], slack: float = 0.1) -> tuple[list[str], list[tuple[str, str]]]:
    """Columns without those in a 1:1 relation to an earlier one, and the pairs found.

    One scan of distinct-count sketches for every column, one for pairs of similar counts, and
    one of exact distinct counts for the pairs that are left.
    """
    pairs = [(a, b) for i, a in enumerate(cols) for b in cols[i + 1 :]]
    rough = df.agg(*[F.approx_count_distinct(c).alias(f"s{i}") for i, c in enumerate(cols)]).first()
    size = dict(zip(cols, rough))
    maybe = [(a, b) for a, b in pairs if abs(size[a] - size[b]) <= slack * max(size[a], size[b], 10)]
    if not maybe:
        return list(cols), []
    both = df.agg(*[F.approx_count_distinct(F.struct(a, b)).alias(f"p{i}") for i, (a, b) in enumerate(maybe)]).first()
    maybe = [p for p, n in zip(maybe, both) if n <= (1 + 2 * slack) * max(size[p[0]], size[p[1]], 10)]
    if not maybe:
        return list(cols), []
    some = sorted({c for p in maybe for c in p})
    exact = df.agg(*[F.countDistinct(F.struct(c)).alias(f"c{i}") for i, c in enumerate(some)], *[F.countDistinct(F.struct(a, b)).alias(f"p{i}") for i, (a, b) in enumerate(maybe)]).first()
    single = dict(zip(some, exact))
    out = [(a, b) for i, (a, b) in enumerate(maybe) if exact[f"p{i}"] == single[a] == single[b]]
    gone = set()
    for a, b in out:
        if a not in gone:
            gone.add(b)
    return [c for c in cols if c not in gone], out
