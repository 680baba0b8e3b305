"""Timings of the headline queries and of the experiments' sweeps: one JSON line.

BENCH_SF_DIR, BENCH_CPUS, BENCH_CHECKPOINT_DIR; --headline leaves the sweeps out.
"""

from __future__ import annotations

import json
import os
import sys
import time

HERE = os.path.dirname(os.path.abspath(__file__))
sys.path.insert(0, HERE)
os.environ["PYTHONPATH"] = os.pathsep.join(x for x in (HERE, os.environ.get("PYTHONPATH", "")) if x)

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
SHARED = os.environ.get("BENCH_CHECKPOINT_DIR", "file:///tmp/checkpoints/bench")


def session(cpus: str):
    from pyspark.sql import SparkSession

    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", cpus)
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.sql.execution.arrow.maxRecordsPerBatch", "65536")
        .config("spark.checkpoint.dir", SHARED)
        .config("spark.driver.memory", "8g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def main() -> None:
    spark = session(CPUS)
    from cubelens.operators import binning, cube, metrics, rank, recommend
    from cubelens.sources import catalog as C
    from cubelens.storage import materialize, release

    cores = int(CPUS)
    heads: dict[str, float] = {}
    sweeps: dict[str, float] = {}

    def timed(name: str, make, repeats: int = 1, into: dict | None = None) -> None:
        (heads if into is None else into)[name] = round(min(metrics.timed(make) for _ in range(repeats)), 3)

    began = time.perf_counter()
    sixteen, eight = C.STAR_DIMS[:16], C.STAR_DIMS[:8]
    facts = materialize(C.order_star(spark, SF_DIR).repartition(cores), "facts")
    n = facts.count()
    t = time.perf_counter()
    ranked = rank.build_ranks(facts, sixteen, C.STAR_KEY, tie="fast")
    heads["rank_16_dims"] = round(time.perf_counter() - t, 3)
    timed("bin_histogram_16_dims", lambda: binning.bin_by_histogram(ranked, sixteen, n, 32), 2)
    timed("bin_subset_8_dims", lambda: binning.bin_by_histogram(ranked.filter("l_returnflag = 'R'"), eight, n, 32), 2)

    def binned(source, specs, rows, bins):
        return materialize(binning.bin_by_rank(source, specs, rows, bins).repartition(cores), "binned")

    rows = {b: binned(ranked, sixteen, n, b) for b in (16, 32)}
    for s in ("expand", "explode", "per_triple", "owner_slice", "local_dense"):
        timed(f"cube_n8_b32_{s}", lambda s=s: cube.build_cube(rows[32], eight, 32, [], s))
    timed("cube_n8_b32_sum_local_dense", lambda: cube.build_cube(rows[32], eight, 32, [C.CENTS, C.QUANTITY_DOUBLE], "local_dense"))
    timed("cube_n16_b16_owner_slice", lambda: cube.build_cube(rows[16], sixteen, 16, [], "owner_slice"))
    timed("cube_n16_b16_local_dense", lambda: cube.build_cube(rows[16], sixteen, 16, [], "local_dense"))
    timed("pairs_n16_b32", lambda: cube.build_pairs(rows[32], sixteen, bins=32))
    cells = materialize(cube.build_cube(rows[16], sixteen, 16, [], "local_dense"), "cube")
    timed("recommend_6720_images", lambda: recommend.recommend(recommend.score_cube(cells, sixteen, 16), 30, 1))
    ratios: dict[str, float] = {}

    if "--headline" not in sys.argv:
        sweep = lambda name, make: timed(name, make, into=sweeps)
        # scan-per-triple baseline at 16 dimensions: 20 of the 560 triples, by partitions of the cube
        some = list(range(0, 560, 28))
        for parts in (1, 2, 4):
            sweep(f"n16_b16_per_triple_20_of_560_p{parts}", lambda parts=parts: cube.per_triple(cube.narrow(rows[16], sixteen), sixteen, (), 16, parts, only=some))
        best = min(sweeps[f"n16_b16_per_triple_20_of_560_p{p}"] for p in (1, 2, 4)) * 28
        for s in ("owner_slice", "local_dense"):
            ratios[f"n8_saved_percent_{s}"] = round(metrics.speedup(heads[f"cube_n8_b32_{s}"], heads["cube_n8_b32_per_triple"]), 1)
            ratios[f"n16_saved_percent_{s}_against_best_p"] = round(metrics.speedup(heads[f"cube_n16_b16_{s}"], best), 1)
        # value types
        for kind, m in (("float", [C.PRICE_FLOAT]), ("double", [C.QUANTITY_DOUBLE])):
            for s in ("owner_slice", "local_dense"):
                sweep(f"n16_b16_{kind}_{s}", lambda s=s, m=m: cube.build_cube(rows[16], sixteen, 16, m, s))
        # bins
        fine = binned(ranked, sixteen, n, 128)
        sweep("n8_b128_owner_slice", lambda: cube.build_cube(fine, eight, 128, [], "owner_slice"))
        sweep("n8_b128_local_dense", lambda: cube.build_cube(fine, eight, 128, [], "local_dense"))
        sweep("n16_b32_owner_slice", lambda: cube.build_cube(rows[32], sixteen, 32, [], "owner_slice"))
        sweep("n16_b32_local_dense", lambda: cube.build_cube(rows[32], sixteen, 32, [], "local_dense"))
        # dimensions
        wide = rank.build_ranks(facts, C.STAR_DIMS[16:], C.STAR_KEY, tie="fast")
        more = materialize(binning.bin_by_rank(wide, C.STAR_DIMS[16:], n, 16), "more")
        all32 = materialize(rows[16].join(more.select(*C.STAR_KEY, *[s.bin for s in C.STAR_DIMS[16:]]), list(C.STAR_KEY)).repartition(cores), "binned32")
        for k in (24, 32):
            for s in ("owner_slice", "local_dense"):
                sweep(f"n{k}_b16_{s}", lambda s=s, k=k: cube.build_cube(all32, C.STAR_DIMS[:k], 16, [], s))
        # rounds of owners, kernels
        sweep("n16_b16_owner_slice_4_owners_a_round", lambda: cube.build_cube(rows[16], sixteen, 16, [], "owner_slice", owners=4))
        sweep("n16_b16_owner_slice_scan_kernel", lambda: cube.build_cube(rows[16], sixteen, 16, [], "owner_slice", kernel="scan_per_triple"))
        # the second dataset
        log = materialize(C.activity_log(spark, SF_DIR).repartition(cores), "log")
        m = log.count()
        logs = binned(rank.build_ranks(log, C.LOG_DIMS, C.LOG_KEY, tie="fast"), C.LOG_DIMS, m, 16)
        for k in (8, 16, 24):
            for s in ("owner_slice", "local_dense"):
                sweep(f"log_n{k}_b16_{s}", lambda s=s, k=k: cube.build_cube(logs, C.LOG_DIMS[:k], 16, [], s))
        # parts one after another and pipelined; units; inserts
        for part, sec in metrics.staged_times(cube.narrow(rows[16], sixteen), sixteen, 16, owners=8).items():
            (ratios if part == "overlap" else sweeps)[f"stages_n16_b16_{part}"] = round(sec, 3)
        units = metrics.units_times(lambda d, k: cube.owner_slices(cube.narrow(d, sixteen), sixteen, 16, partitions=k), rows[16], sorted({1, 2, 4, cores}))
        for k, sec in units.items():
            sweeps[f"n16_b16_units_{k}"] = round(sec, 3)
            ratios[f"n16_units_{k}_speedup"] = round(units[1] / sec, 2)
        late = log.filter("event_id % 100 = 7")
        spec = C.LOG["ts"]
        early = rank.build_ranks(log.filter("event_id % 100 <> 7"), [spec], C.LOG_KEY, tie="fast")
        for part, sec in metrics.insert_share(early, late, spec, 16, C.LOG_KEY, early.count()).items():
            (ratios if part == "share" else sweeps)[f"inserts_{part}"] = round(sec, 3)
    for d in (facts, ranked, *rows.values(), cells):
        release(d)
    print(json.dumps({"metric": "total_seconds_of_headline_queries", "value": round(sum(heads.values()), 3), "unit": "sec", "queries": heads, "sweeps": sweeps, "ratios": ratios, "sf": os.path.basename(SF_DIR.rstrip("/")), "rows": n, "cpus": CPUS, "wall": round(time.perf_counter() - began, 1)}))


if __name__ == "__main__":
    main()
