import pytest
from pyspark.sql import functions as F

from cubelens.dimension import DimensionSpec, resolve
from cubelens.operators import baselines as BL
from cubelens.operators import binning as B
from cubelens.operators import insert
from cubelens.operators.rank import build_fine_buckets, build_ranks, rank_small

V = DimensionSpec("v", ("v",))


def ramp(spark, n):
    return spark.range(n).select("id", F.pmod(F.col("id") * 7919, F.lit(n)).alias("v"))


@pytest.mark.parametrize("n,used,rule", [(129, 65, "ceil"), (129, 128, "proportional"), (1000, 125, "ceil"), (200, 100, "ceil")])
def test_widths_and_tail_bins(spark, n, used, rule):
    out = B.bin_exact(ramp(spark, n), [V], ("id",), 128, rule)
    c = out.groupBy("b_v").count().collect()
    assert len(c) == used
    assert max(r["count"] for r in c) - min(r["count"] for r in c if rule == "proportional" or r.b_v < used - 1) <= (1 if rule == "proportional" else 0)


def test_ranks_are_permutations_without_a_single_task(spark):
    d = spark.range(5000).select("id", (F.col("id") % 2).alias("h"), F.when(F.col("id") % 10 > 0, F.col("id") % 7).alias("x"))
    specs = [DimensionSpec("h", ("h",)), DimensionSpec("x", ("x", "h desc"))]
    r = build_ranks(d, specs, ("id",))
    for s in specs:
        assert r.agg(F.min(s.rank), F.max(s.rank), F.countDistinct(s.rank)).first()[:] == (0, 4999, 5000)
        assert r.join(rank_small(d, s, ("id",)).select("id", F.col(s.rank).alias("w")), "id").filter(F.col(s.rank) != F.col("w")).count() == 0
    assert r.filter("x is null").agg(F.max("rk_x")).first()[0] == 499  # nulls first
    assert "SinglePartition" not in r._jdf.queryExecution().toString()


def test_empty_and_tiny(spark):
    e = build_ranks(spark.range(0).select("id", F.col("id").alias("v")), [V], ("id",))
    assert e.count() == 0 and B.bin_by_rank(e, [V], 0, 8).count() == 0
    assert B.bin_by_histogram(e, [V], 0, 8).count() == 0
    one = B.bin_exact(spark.range(3).select("id", F.col("id").alias("v")), [V], ("id",), 1)
    assert {r.b_v for r in one.collect()} == {0}


def test_heavy_value_owns_its_share_of_bins(spark):
    d = spark.range(10000).select("id", F.when(F.col("id") < 3050, 0).otherwise(F.col("id")).alias("v"))
    out = B.bin_exact(d, [V], ("id",), 128)
    n = out.filter("v = 0").select("b_v").distinct().count()
    assert 38 <= n <= 40


@pytest.mark.parametrize("how", ["steps", "join", "search"])
def test_histogram_bins(spark, how):
    n = 4096
    r = build_ranks(ramp(spark, n), [V], ("id",))
    exact = {x.id: x.b_v for x in B.bin_by_rank(r, [V], n, 16).collect()}
    assert {x.id: x.b_v for x in B.bin_by_histogram(r, [V], n, 16, 20, how).collect()} == exact
    rough = {x.id: x.b_v for x in B.bin_by_histogram(r.filter("id % 3 = 0"), [V], n, 16, 8, how).collect()}
    place = {k: i for i, k in enumerate(sorted(rough, key=lambda k: k * 7919 % n))}
    width = -(-len(rough) // 16)
    assert all(abs(b - place[k] // width) <= 1 for k, b in rough.items())


def test_two_small_histograms_give_the_cuts_of_the_whole_one(spark, monkeypatch):
    """Subsets with gaps, runs and few rows: every cut and every place is that of the full fine histogram."""
    monkeypatch.setattr(B, "COARSE_BITS", 4)
    n = 1 << 14
    other = DimensionSpec("w", ("w",))
    d = spark.range(n).select(F.col("id").alias("rk_v"), F.pmod(F.col("id") * 7919, F.lit(n)).alias("rk_w"))
    for where in ("true", "rk_v % 37 = 5", "rk_v < 3000", "rk_v between 5000 and 5100 or rk_v > 16000", "rk_v = 77", "false", "rk_v % 4096 < 9"):
        sub = d.filter(where)
        for bins, fine in ((16, 10), (7, 9), (128, 14), (1, 8), (16, 4)):
            m = sub.count()
            want = sorted(map(tuple, B.histogram_cuts(B.fine_histogram(sub, [V, other], n, fine), m, bins).collect()))
            got, rows = B.refined_cuts(sub, [V, other], n, bins, fine)
            assert rows == m and sorted(map(tuple, got.collect())) == want, (where, bins, fine)


def test_running_totals_without_a_single_task(spark):
    from cubelens.operators.rank import running

    d = spark.range(3000).select(F.pmod(F.col("id") * 7919, F.lit(3000)).alias("v"), (F.col("id") % 5).alias("x"))
    out = running(d, [F.col("v").asc_nulls_first()], "x")
    assert "SinglePartition" not in out._jdf.queryExecution().toString()
    total = 0
    for k, r in enumerate(out.orderBy("v").collect()):
        assert (r.v, r.place_, r.before_) == (k, k, total)
        total += r.x
    assert running(d.limit(0), [F.col("v")], "x").collect() == []


def test_subset_threshold_and_fallback(spark):
    assert B.needs_sort(11000, 100_000_000) and not B.needs_sort(13000, 100_000_000)
    assert not B.needs_sort(1, 1 << 20)
    n = 1 << 12
    r = build_ranks(ramp(spark, n), [V], ("id",))
    small = r.filter("rk_v < 64")  # contiguous: two fine buckets at 7 bits
    assert B.bin_balance(B.bin_by_histogram(small, [V], n, 16, 7), [V], 16).first().bins_used == 2
    assert B.bin_balance(B.bin_auto(small, [V], n, 16, 7), [V], 16).first().cv == 0


def test_sketch_buckets_are_even(spark):
    d = spark.range(20000).select("id", (F.col("id") % 3).alias("v"))
    c = build_fine_buckets(d, [V], ("id",), 4).groupBy("rk_v").count().collect()
    assert len(c) == 16 and max(r["count"] for r in c) < 2 * min(r["count"] for r in c) + 400
    assert build_fine_buckets(d, [V], ("id",), 4).groupBy("v").agg(F.min("rk_v").alias("a"), F.max("rk_v").alias("z")).filter("a > z").count() == 0


def test_inserts(spark):
    d = spark.range(4000).select("id", (F.col("id") * 10).alias("v"))
    r = build_ranks(d, [V], ("id",))
    bounds = insert.capture_bounds(r, V, 4000, 8)
    new = spark.createDataFrame([(9000 + k, v) for k, v in enumerate([-5, 0, 19999, 39990, 10**9])], "id long, v long")
    out, cuts = insert.bin_inserts(new, bounds, V, 16, ("id",))
    assert [x.b_v for x in out.orderBy("v").collect()] == [0, 0, 7, 15, 15]
    assert cuts.count() == 16


def test_baselines(spark):
    d = spark.createDataFrame([(float(x),) for x in (0, 1, 2, 3, 4, 100)] + [(None,)], "v double")
    assert [r.b for r in BL.bin_equidistance(d, "v", 10).orderBy(F.col("v").asc_nulls_last()).collect()] == [0, 0, 0, 0, 0, 9, None]
    assert {r.b for r in BL.bin_equidistance(d.filter("v = 1"), "v", 10).collect()} == {0}
    w = BL.bin_equidepth_whole(spark.createDataFrame([(1,)] * 6 + [(2,), (3,)], "v int"), V, 4)
    assert {(r.v, r.b_v, r.width) for r in w.collect()} == {(1, 0, 0.75), (2, 1, 0.25), (3, 1, 0.25)}
    assert BL.clip_rows(d, {"v": (1, 4)}).count() == 4


def test_outliers_leave_equal_populations_alone(spark):
    d = spark.range(3000).select("id", (F.col("id") * 1.0).alias("v"))
    wild = d.unionByName(spark.range(900).select((F.col("id") + 10000).alias("id"), (-F.col("id") - 1.0).alias("v"))).unionByName(spark.createDataFrame([(99999, 1e9)], "id long, v double"))
    assert BL.bin_equidistance(wild, "v", 16).select("b").distinct().count() == 2
    assert B.bin_balance(B.bin_exact(wild, [V], ("id",), 16), [V], 16).first().bins_used == 16


def test_specs_are_checked(spark):
    with pytest.raises(Exception, match="nope"):
        resolve(spark.range(1), [DimensionSpec("a", ("nope",))])
    with pytest.raises(ValueError):
        resolve(spark.range(1), [DimensionSpec("a", ("id",)), DimensionSpec("a", ("id",))])


def test_one_to_one(spark):
    d = spark.range(500).select("id", (F.col("id") + 7).alias("same"), (F.col("id") % 20).alias("k"), (F.col("id") % 20).cast("string").alias("name"))
    kept, pairs = B.drop_one_to_one(d, ["id", "same", "k", "name"])
    assert kept == ["id", "k"] and pairs == [("id", "same"), ("k", "name")]
