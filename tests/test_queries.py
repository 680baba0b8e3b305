"""Registered queries beside their SQL twins at the smallest scale: one or two of each family."""

import math

import duckdb
import pytest

import __spark_entry__ as entry

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
NAMES = """q02b_augmented_reuse q02c_sketch_buckets q08_bin_subset q08c_small_subset q12_equidepth_whole q15_categorical q19_one_to_one q20_insert_bins
q20b_insert_tail q20c_insert_runs q22b_plan_replicate q22c_plan_units q23b_orbits q24b_costs q37_cube_pairs q43_star16_owner_slice q43d_star32_owner_slice
q44d_log16_types q46_coordinates32 q47_cube_kept q47b_cube_synchronous q51b_signed_sums q51e_scope_dataset_share q56b_score_minus_noise q56c_score_cube
q60_bottom_groups q61b_montage q62b_hover q72b_axis_share q72f_area_equal_width q78_recommender q90_theta_join q93_interval_join
q97_approx_distinct q127_udf_udaf_udtf q132_stream_session q133_stream_late q138_stream_stateful q139_stream_inserts""".split()


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    con.execute("SET TimeZone = 'UTC'")
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf}/{t}.parquet')")
    return con


def same(a, b):
    return a == b or isinstance(a, (int, float)) and isinstance(b, (int, float)) and math.isclose(a, b, rel_tol=1e-9, abs_tol=1e-6)


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_its_twin(spark, sf, duck, name):
    df = entry.queries()[name](spark, sf)
    done = duck.execute(entry.oracle_sql()[name])
    columns = [d[0] for d in done.description]
    assert sorted(columns) == sorted(df.columns)
    key = lambda r: tuple((x is None, round(x, 5) if isinstance(x, float) else x) for x in r)
    want = sorted(done.fetchall(), key=lambda r: str(key(r)))
    got = sorted(map(tuple, df.select(*[f"`{c}`" for c in columns]).collect()), key=lambda r: str(key(r)))
    assert len(got) == len(want) and all(same(x, y) for g, w in zip(got, want) for x, y in zip(g, w))


def test_timings_are_measured(spark, sf):
    parts = {r.part: r.seconds for r in entry.queries()["q48_stage_times"](spark, sf).collect()}
    assert set(parts) == {"fill", "update", "read_back", "synchronous", "pipelined", "overlap"}
    assert min(parts[k] for k in ("fill", "update", "read_back", "pipelined")) > 0
    assert abs(parts["synchronous"] - parts["fill"] - parts["update"] - parts["read_back"]) < 1e-9
    units = entry.queries()["q48b_units_speedup"](spark, sf).collect()
    assert [r.units for r in units] == [1, 2, 4] and units[0].saved_percent == 0
