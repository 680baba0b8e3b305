"""Bins without ranks, and units that work in turn."""

from collections import Counter
from hashlib import md5
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from cubelens import storage
from cubelens.dimension import DimensionSpec
from cubelens.operators import binning, cube, cuts
from cubelens.operators.digest import Ties
from cubelens.operators.rank import build_ranks
from cubelens.plans.triples import plan_rounds
from cubelens.queries import base as Q
from cubelens.sources import catalog as C


def test_bins_are_those_of_ranks(spark, monkeypatch):
    """Nulls, NaN, both zeros, frequent values, strings with null bytes, descending and second keys; fewer rows than bins too."""
    monkeypatch.setattr(cuts, "SPLITTERS", 300)
    specs = [DimensionSpec("x", ("x",)), DimensionSpec("down", ("x desc",)), DimensionSpec("w", ("w",)), DimensionSpec("w_by_i", ("w", "i desc")), DimensionSpec("same", ("same",))]
    x = F.expr("CASE WHEN id % 7 = 0 THEN NULL WHEN id % 11 = 0 THEN CAST('NaN' AS DOUBLE) WHEN id % 5 = 0 THEN -0.0D WHEN id % 3 = 0 THEN 0.0D ELSE sin(id) END")
    w = F.expr("CASE WHEN id % 13 = 0 THEN NULL WHEN id % 4 = 0 THEN concat('a', chr(0), id % 17) WHEN id % 4 = 1 THEN 'a' ELSE concat('é', id % 50) END")
    for n, bins, rule in ((4000, 16, "ceil"), (4000, 100, "proportional"), (5, 8, "proportional"), (1, 4, "ceil")):
        d = spark.range(n).select("id", x.alias("x"), w.alias("w"), (F.col("id") * 37 % 101).alias("i"), F.lit(1).alias("same"))
        assert cuts.comparable(d, specs)
        want = binning.bin_by_rank(build_ranks(d, specs, ("id",)), specs, n, bins, rule).select(*[s.bin for s in specs])
        got = cuts.bin_rows(d, specs, ("id",), bins, rule)
        assert got.schema == want.schema or got.dtypes == want.dtypes
        assert Counter(map(tuple, got.collect())) == Counter(map(tuple, want.collect()))


def test_star_slices_hold_every_row_once(spark, sf):
    columns = ["l_orderkey", "cents", "p_name", "c_region", "s_acctbal"]
    got = [r for d in C.order_star_slices(spark, sf, columns) for r in map(tuple, d.collect())]
    assert Counter(got) == Counter(map(tuple, C.order_star(spark, sf).select(*columns).collect()))


def test_bins_leave_no_wide_table(spark, sf, tmp_path, monkeypatch):
    from cubelens import storage

    monkeypatch.setattr(storage, "shared_dir", lambda s: f"file://{tmp_path}")
    Q.bins_only(spark, sf, C.STAR_DIMS[:5], 7)
    assert [p.name.split("-")[0] for p in (tmp_path / "cubelens").iterdir()] == ["bins"]


def test_owners_in_turn(spark, monkeypatch):
    """Owners that work one after another, odd row counts, 16 and more bins: the cells of the other strategies."""
    specs = [DimensionSpec(c, (c,)) for c in "abcd"]
    for bins in (5, 20):
        rows = spark.range(1001).select(*[F.pmod(F.xxhash64("id", F.lit(k)), F.lit(bins)).cast("tinyint").alias(s.bin) for k, s in enumerate(specs)], F.col("id").alias("v"))
        m = [C.MeasureSpec("v", "v")]
        want = Counter(map(tuple, cube.build_cube(rows, specs, bins, m, "local_dense").collect()))
        for limit in (1, 1 << 30):
            monkeypatch.setattr(cube, "ROUTED_BYTES", limit)
            got = cube.build_cube(rows, specs, bins, m, "owner_slice")
            assert bool(getattr(got, "_shared_paths", [])) == (limit == 1)
            assert Counter(map(tuple, got.select("triple", "b0", "b1", "b2", "cnt", "v").collect())) == want


def test_digests_are_those_of_md5():
    """Null and empty texts, several blocks of 64 bytes, long texts, slices of an array."""
    texts = [None if i % 17 == 0 else "" if i % 19 == 0 else "x" * (i * 7 % 300) if i % 5 == 0 else f"{i}:é{i * 7}" for i in range(3000)]
    for some in (pa.array(texts), pa.array(texts)[100:2000], pa.array([None, None], pa.string()), pa.array(["", ""])):
        for name in ("a", "segment_by_balance", "n" * 70):
            want = [md5((name if t is None else f"{name}:{t}").encode()).digest() for t in some.to_pylist()]
            got = Ties(some).digests(name, np.arange(len(some)))
            assert [int(a).to_bytes(8, "big") + int(b).to_bytes(8, "big") for a, b in got] == want


def test_cuts_inside_a_key_need_no_order_of_all_its_rows(spark, monkeypatch):
    """Bins are those of ranks, and of a frequent key a few rows near the cuts are ordered; row keys that repeat too."""
    monkeypatch.setattr(cuts, "WHOLE", 50)
    n, bins, ordered = 40_000, 8, []
    write = cuts.materialize
    monkeypatch.setattr(cuts, "materialize", lambda df, name: ordered.append(write(df, name)) or ordered[-1])
    kept = []
    monkeypatch.setattr(cuts, "release", kept.append)
    specs = [DimensionSpec("two", ("two",)), DimensionSpec("two_by_three", ("two", "three desc"))]
    d = spark.range(n).select("id", (F.col("id") % 2).alias("two"), F.concat(F.lit("k"), F.col("id") % 3).alias("word"), (F.col("id") % 3).alias("three"))
    want = binning.bin_by_rank(build_ranks(d, specs, ("id",)), specs, n, bins).select(*[s.bin for s in specs])
    assert Counter(map(tuple, cuts.bin_rows(d, specs, ("id",), bins).collect())) == Counter(map(tuple, want.collect()))
    assert len(ordered) == 1 and ordered[0].filter("k IS NOT NULL").count() < n  # both dimensions have n rows in such keys
    same = d.withColumn("id", F.col("id") % 4)
    got = Counter(r[0] for r in cuts.bin_rows(same, specs[:1], ("id",), bins).collect())
    assert sum(got.values()) == n and len(ordered) == 3  # found by ordering the whole keys
    for t in kept:
        storage.release(t)


def test_keys_reach_python_without_digests(spark, sf):
    """Digests were made for all dimensions and rows of frequent keys in every scan."""
    base = C.order_star(spark, sf)
    frame = cuts._Layout(base, C.STAR_DIMS, C.STAR_KEY).frame(base)
    assert "md5" not in frame._jdf.queryExecution().toString() and len(frame.columns) < len(C.STAR_DIMS)


def test_pairs_are_counted_together():
    """Every pair of an owner is in a group, and groups are a fifth of the triples at 32 dimensions and 8 bins."""
    for n, bins, most in ((32, 8, 992), (16, 16, 280), (8, 128, 56)):
        owned, groups = cube.owned_by_round(plan_rounds(n))[0], 0
        for triples in owned.values():
            pairs = [(j, k) for _, j, k in triples]
            found = cube.cover(pairs, cube.joint_size(bins))
            assert set(pairs) <= {p for g in found for p in combinations(g, 2)} and all(len(g) <= cube.joint_size(bins) for g in found)
            groups += len(found)
        assert groups <= most
