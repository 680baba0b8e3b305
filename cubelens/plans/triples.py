"""Which dimension owns which triple: disjoint, equal groups, in as many rounds as the units need.

A triple is owned by one of its own dimensions. Among three members below the number of
owners R, seen as places on a circle of R, the owner is the member from which the clockwise
gaps read smallest; of two members the one that reaches the other in less than half a turn
(at half a turn the third dimension's parity decides); a single member owns. Triples with
no member below R wait for the next round, where all indexes are R smaller.
"""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass
from itertools import combinations

from pyspark.sql import DataFrame, SparkSession


@dataclass(frozen=True)
class Owned:
    """A triple's place in the plan; ``owner`` is the index of the owning dimension among all."""

    triple: int
    dims: tuple[int, int, int]
    round: int
    owner: int


def triples_of(n: int) -> list[tuple[int, int, int]]:
    """All triples in lexicographic order; the place is the triple's number."""
    return list(combinations(range(n), 3))


def rotate(dims: tuple[int, ...], by: int, n: int) -> tuple[int, ...]:
    return tuple(sorted((d + by) % n for d in dims))


def same_orbit(a: tuple[int, ...], b: tuple[int, ...], n: int) -> bool:
    return any(rotate(a, k, n) == tuple(sorted(b)) for k in range(n))


def circle_owner(dims: tuple[int, ...], n: int) -> int:
    """Owner among three places on a circle of n."""
    m = sorted(dims)

    def gaps(k: int) -> tuple[int, ...]:
        turn = m[k:] + m[:k]
        return tuple((b - a) % n for a, b in zip(turn, turn[1:] + turn[:1]))

    return m[min(range(3), key=lambda k: (gaps(k), m[k]))]


def pair_owner(i: int, j: int, r: int, front: bool = True) -> int:
    """Owner of a pair i < j on a circle of r; ``front`` settles pairs half a turn apart."""
    ahead = 2 * (j - i)
    return i if ahead < r or ahead == r and front else j


def place_of(dims: tuple[int, int, int], n: int, r: int) -> tuple[int, int]:
    """(round, owner) of a triple of n dimensions when a round has r owners; owner counts over all dimensions."""
    offset = 0
    while True:
        here, size = [d - offset for d in dims], n - offset
        circle = min(r, size)
        low = [d for d in here if d < circle]
        if len(low) == 3:
            return offset // r, circle_owner(tuple(low), circle) + offset
        if len(low) == 2:
            return offset // r, pair_owner(*low, circle, (here[2] - circle) % 2 == 1) + offset
        if low:
            return offset // r, low[0] + offset
        offset += r


def plan_rounds(n: int, owners: int | None = None) -> list[Owned]:
    """The plan of all triples; ``owners`` dimensions own in each round (default: all, one round)."""
    r = n if owners is None else max(1, owners)
    return [Owned(k, d, *place_of(d, n, r)) for k, d in enumerate(triples_of(n))]


def owners_for(units: int, bins: int) -> int:
    """Owners a round can have when each needs one unit a bin."""
    return max(1, units // bins)


def replicas_for(units: int, bins: int, owners: int) -> int:
    """Copies of each unit that spare units allow."""
    return max(1, units // (bins * owners))


def plan_by_triple(n: int, workers: int) -> list[tuple[int, int]]:
    """Baseline: (triple, worker) in turn; every row then has to reach every worker."""
    return [(k, k % workers) for k in range(len(triples_of(n)))]


def plan_replicate(n: int, workers: int, bins: int, cell_bytes: int = 4) -> dict:
    """Baseline: every worker holds all cubes of its share of the rows, and all copies are merged: cubes, MiB a worker, MiB to merge."""
    cubes = len(triples_of(n))
    mib = cubes * bins**3 * cell_bytes / 2**20
    return {"cubes": cubes, "worker_mib": mib, "merge_mib": mib * workers, "row_updates": cubes}


def orbits(n: int) -> list[tuple[tuple[int, ...], int]]:
    """The triples of n dimensions up to rotation: the smallest of each orbit, and its size."""
    return sorted(Counter(min(rotate(t, k, n) for k in range(n)) for t in triples_of(n)).items())


def plan_pairs(n: int) -> list[tuple[int, int, int]]:
    """(i, j, owner) of all pairs on a circle of n."""
    return [(i, j, pair_owner(i, j, n, i % 2 == 0)) for i, j in combinations(range(n), 2)]


def balance(plan: list[Owned]) -> dict[int, tuple[int, int, int]]:
    """For each round: owners, fewest and most triples of one."""
    count = Counter((p.round, p.owner) for p in plan)
    out = {}
    for r in sorted({p.round for p in plan}):
        own = [c for (q, _), c in count.items() if q == r]
        out[r] = (len(own), min(own), max(own))
    return out


def plan_frame(spark: SparkSession, plan: list[Owned]) -> DataFrame:
    return spark.createDataFrame([(p.triple, *p.dims, p.round, p.owner) for p in plan], "triple int, d0 int, d1 int, d2 int, round int, owner int")


def unit_sweep(n: int, bins: int, units: int, cell_bytes: int = 4) -> dict:
    """What a number of units means: owners, rounds, copies of a row, replicas, memory of the fullest unit."""
    r = owners_for(units, bins)
    b = balance(plan_rounds(n, r))
    return {
        "owners": r,
        "rounds": len(b),
        "copies": sum(k for k, _, _ in b.values()),
        "replicas": [replicas_for(units, bins, k) for k, _, _ in b.values()],
        "unit_mib": max(m for _, _, m in b.values()) * bins * bins * cell_bytes / 2**20,
    }
