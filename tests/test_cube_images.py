import itertools
import random
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from cubelens.dimension import DimensionSpec, MeasureSpec
from cubelens.functions import intensity as I
from cubelens.operators import cube as Q
from cubelens.operators import image, metrics, recommend, render
from cubelens.plans.triples import balance, plan_rounds

B = 4
SPECS = [DimensionSpec(c, (c,)) for c in "abcde"]
MEASURES = [MeasureSpec("big", "big"), MeasureSpec("x", "x", False)]


@pytest.fixture(scope="module")
def rows(spark):
    rng = random.Random(4)
    data = [(*[rng.randrange(B) for _ in SPECS], rng.choice([-1, 1]) * rng.getrandbits(50), rng.choice([None, 0.5, 2.0])) for _ in range(700)]
    schema = ", ".join(f"b_{s.name} byte" for s in SPECS) + ", big long, x double"
    return spark.createDataFrame(data, schema).repartition(3), data


def brute(data):
    out = {}
    for r in data:
        for t, d in enumerate(itertools.combinations(range(len(SPECS)), 3)):
            k = (t, *[r[i] for i in d])
            n, big, x, seen = out.get(k, (0, 0, 0.0, 0))
            out[k] = (n + 1, big + r[5], x + (r[6] or 0), seen + (r[6] is not None))
    return out


@pytest.mark.parametrize("strategy,options", [("expand", {}), ("explode", {}), ("per_triple", {}), ("per_triple", {"parts": 4}), ("owner_slice", {}), ("owner_slice", {"owners": 2}), ("owner_slice", {"replicas": 3}), ("owner_slice", {"kernel": "scan_per_triple", "staged": True}), ("by_triple", {}), ("local_dense", {}), ("local_dense", {"memory": 1})])
def test_strategies_agree_with_counting(rows, strategy, options):
    df, data = rows
    want = brute(data)
    got = {(r.triple, r.b0, r.b1, r.b2): (r.cnt, r.big, r.x or 0.0) for r in Q.build_cube(df, SPECS, B, MEASURES, strategy, **options).collect()}
    assert got == {k: v[:3] for k, v in want.items()}


def test_empty_input(spark, rows):
    none = rows[0].limit(0)
    for s in Q.STRATEGIES:
        assert Q.build_cube(none, SPECS, B, MEASURES, s).collect() == []


def test_routing_and_invariants(rows):
    df, data = rows
    sent = Q.route(Q.narrow(df, SPECS), SPECS, [0, 1, 2, 3, 4])
    assert sent.count() == 5 * len(data)
    c = Q.build_cube(df, SPECS, B, [], "explode")
    assert {r.n for r in c.groupBy("triple").agg(F.sum("cnt").alias("n")).collect()} == {len(data)}
    marg = {(r.dim, r.bin): r.cnt for r in Q.build_marginals(df, SPECS).collect()}
    for r in c.filter("triple = 0").groupBy("b0").agg(F.sum("cnt").alias("n")).collect():
        assert marg["a", r.b0] == r.n
    loads = metrics.unit_loads(sent).collect()
    assert sum(r.rows for r in loads) == 5 * len(data)


def test_slabs_add_up_to_the_pair(rows):
    df, _ = rows
    c = Q.build_cube(df, SPECS, B, [], "explode")
    pair = {(r.xdim, r.ydim, r.x, r.y): r.v for r in image.pair_images(Q.build_pairs(df, SPECS), SPECS).collect()}
    for parts in (1, 4):
        im = image.slab_images(c, SPECS, B, parts)
        sums = im.groupBy("xdim", "ydim", "zdim", "x", "y").agg(F.sum("v").alias("v")).collect()
        assert all(pair[r.xdim, r.ydim, r.x, r.y] == r.v for r in sums)
    scores = recommend.score_images(image.slab_images(c, SPECS, B, 4), B)
    assert scores.count() == 3 * 4 * 10 and scores.filter("score < 0 or score > 1").count() == 0
    g = recommend.score_groups(scores).collect()
    assert len(g) == 10 and {r.images for r in g} == {12}


def test_scores_from_cubes_equal_those_of_images(rows):
    df, _ = rows
    c = Q.build_cube(df, SPECS, B, [MEASURES[0]], "local_dense")
    key = lambda r: (r.xdim, r.ydim, r.zdim, r.slab)
    for parts in (1, 3, 4):
        for value, heuristic in (("cnt", "red"), ("cnt", "blue"), ("cnt", "chi_square"), ("cnt", "information"), ("big", "brightness")):
            want = {key(r): r for r in recommend.score_images(image.slab_images(c, SPECS, B, parts, value), B, heuristic=heuristic).collect()}
            got = {key(r): r for r in recommend.score_cube(c, SPECS, B, parts, value, heuristic).collect()}
            assert got.keys() == want.keys() and len(got) == 30 * parts
            for k, r in got.items():
                assert (r.total, r.expected, r.degenerate) == (want[k].total, want[k].expected, want[k].degenerate) and abs(r.score - want[k].score) < 1e-9


def test_expected_values_follow_the_plan_of_slabs(spark):
    """Three slabs of four bins are two, one and one bin wide; the middle one is empty."""
    cells = spark.createDataFrame([("a", "b", "c", 0, 0, 0, 6), ("a", "b", "c", 2, 1, 1, 2)], "xdim string, ydim string, zdim string, slab int, x int, y int, v long")
    want = {"slab": {0: 6 / 16, 2: 2 / 16}, "dataset": {0: 8 / 16, 2: 8 / 16}, "dataset_share": {0: 8 / 16 * 2 / 4, 2: 8 / 16 / 4}}
    for scope, s in want.items():
        assert {r.slab: r.expected for r in I.with_expected(cells, 4, scope, 3).collect()} == s
    with pytest.raises(ValueError):
        I.with_expected(cells, 4, "other")


def test_pairs_dense_and_expanded_agree(rows):
    df, _ = rows
    key = lambda d: sorted(tuple(r) for r in d.select("pair", "b0", "b1", "cnt", "big").collect())
    assert key(Q.build_pairs(df, SPECS, MEASURES[:1], bins=B)) == key(Q.build_pairs(df, SPECS, MEASURES[:1]))


def test_kept_cube_is_read_by_triple(rows, tmp_path):
    df, _ = rows
    c = Q.build_cube(df, SPECS, B, [], "local_dense")
    path = f"file://{tmp_path}/cube"
    Q.write_cube(c, path)
    some = Q.read_cube(c.sparkSession, path, [2, 5])
    assert sorted(map(tuple, some.collect())) == sorted(map(tuple, c.filter("triple in (2, 5)").collect()))
    assert "PushedFilters: [In(triple, [2,5])]" in some._jdf.queryExecution().toString()


def test_colours(spark):
    s = 4.0
    d = spark.createDataFrame([(v,) for v in (0.0, 2.0, 4.0, 6.0, 8.0, 12.0)], "v double")
    got = [(r.r, r.b) for r in d.select(I.heat_red(F.col("v"), F.lit(s)).alias("r"), I.heat_blue(F.col("v"), F.lit(s)).alias("b")).collect()]
    assert got == [(0, 1), (0, 0.5), (0, 0), (0.5, 0), (1, 0), (1, 0)]
    cells = spark.createDataFrame([("a", "b", "c", 0, 0, 0, -5), ("a", "b", "c", 0, 1, 1, 2)], "xdim string, ydim string, zdim string, slab int, x int, y int, v long")
    out = I.diverging(cells, 2).collect()
    assert all(r.degenerate and r.r == 0 and r.b == 0 for r in out)


def planted(spark, n=40000):
    d = spark.range(n)
    h = lambda k: F.pmod(F.xxhash64("id", F.lit(k)), F.lit(8)).cast("int")
    base = d.select("id", h(1).alias("b_a"), h(2).alias("b_b"), h(3).alias("b_c"), h(4).alias("b_d"))
    return base.select("id", "b_a", "b_b", F.when((F.col("b_d") < 2) & (h(5) < 1), F.col("b_a")).otherwise(F.col("b_c")).alias("b_c"), "b_d")


def test_planted_pattern_ranks_first_in_its_slab(spark):
    specs = SPECS[:4]
    c = Q.build_cube(planted(spark), specs, 8, [], "local_dense")
    im = recommend.score_images(image.slab_images(c, specs, 8, 4), 8)
    top = recommend.recommend(im, 1, 1).first()
    assert (top.xdim, top.ydim, top.zdim, top.slab) == ("a", "c", "d", 0)
    assert metrics.recall_at(recommend.score_groups(im), [("a", "c")], 1) == 1
    order = [r.appearance for r in recommend.prioritise(im).orderBy("priority").collect()]
    assert order == sorted(order)
    floor = im.filter("xdim = 'a' and ydim = 'b'").agg(F.avg("score")).first()[0]
    lam = 40000 / 4 / 64
    assert abs(floor - 0.3989 / np.sqrt(lam)) < 0.01


def test_noise_floor_values(spark):
    #: Expected mean red at these densities.
    known = {1.0: 0.264, 3.7: 0.199, 9.2: 0.131, 36.6: 0.066, 58.6: 0.052, 146.0: 0.033, 234.0: 0.026, 586.0: 0.017}
    d = spark.createDataFrame([(k,) for k in known], "s double").select("s", recommend.noise_floor(F.col("s")).alias("f"))
    assert all(abs(r.f - known[r.s]) < 0.004 for r in d.collect())


def test_tie_orders(spark):
    """Two independent heavy-valued dimensions stay at the floor with keyed ties and not with shared ones."""
    from cubelens.operators import binning
    from cubelens.operators.rank import build_ranks

    d = spark.range(20000).select("id", F.pmod(F.xxhash64("id", F.lit(1)), F.lit(2)).alias("p"), F.pmod(F.xxhash64("id", F.lit(2)), F.lit(3)).alias("q"))
    specs = [DimensionSpec("p", ("p",)), DimensionSpec("q", ("q",))]
    score = {}
    for tie in ("keyed", "fast", "columns"):
        b = binning.bin_by_rank(build_ranks(d, specs, ("id",), tie), specs, 20000, 16)
        score[tie] = recommend.score_images(image.pair_images(Q.build_pairs(b, specs), specs), 16).first().score
    assert score["keyed"] < 0.06 and score["fast"] < 0.06 and score["columns"] > 0.2


def test_png(spark):
    px = spark.createDataFrame([("a", "b", "", 0, 0, 0, 1.0, 0.0, 0.0)], "xdim string, ydim string, zdim string, slab int, x int, y int, r double, g double, b double")
    row = render.render_png(px, 4, 2).first()
    assert row.width == row.height == 8 and bytes(row.png[:8]) == b"\x89PNG\r\n\x1a\n"
    data = bytes(row.png)
    at = data.index(b"IDAT")
    raw = zlib.decompress(data[at + 4 : at + 4 + int.from_bytes(data[at - 4 : at], "big")])
    assert raw[25 * 7 + 1 : 25 * 7 + 4] == b"\xff\x00\x00" and raw[1:4] == b"\x00\x00\xff"
    assert render.montage(px, 4).first().width == 4


def test_round_plan_matches_units():
    assert sum(k for k, _, _ in balance(plan_rounds(16, 4)).values()) == 16
