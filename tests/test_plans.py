from itertools import combinations
from math import comb

from hypothesis import given, settings
from hypothesis import strategies as st

from cubelens.plans import cost
from cubelens.plans import triples as T

#: Worked-out plans, owner relative to its round -> triples.
GOLDEN = {
    (5, 5): {(0, 0): "012 013", (0, 1): "123 124", (0, 2): "023 234", (0, 3): "034 134", (0, 4): "014 024"},
    (6, 6): {(0, 0): "012 013 014 024", (0, 1): "123 124 125 135", (0, 2): "023 234 235", (0, 3): "034 134 345", (0, 4): "045 145 245", (0, 5): "015 025 035"},
    (6, 4): {(0, 0): "012 014 015 025 045", (0, 1): "123 124 125 135 145", (0, 2): "023 024 234 235 245", (0, 3): "013 034 035 134 345"},
    (7, 3): {
        (0, 0): "012 013 014 015 016 034 035 036 045 046 056",
        (0, 1): "123 124 125 126 134 135 136 145 146 156",
        (0, 2): "023 024 025 026 234 235 236 245 246 256",
        (1, 0): "345 346",
        (1, 1): "456",
        (1, 2): "356",
    },
}


def test_golden_plans():
    for (n, r), want in GOLDEN.items():
        got = {}
        for p in T.plan_rounds(n, r):
            got.setdefault((p.round, p.owner - p.round * r), []).append("".join(map(str, p.dims)))
        assert {k: " ".join(v) for k, v in got.items()} == want


def test_every_triple_is_owned_once_by_a_member_and_groups_are_equal():
    for n in range(3, 25):
        for r in range(1, n + 3):
            plan = T.plan_rounds(n, r)
            assert [p.dims for p in plan] == list(combinations(range(n), 3))
            for p in plan:
                assert p.owner in p.dims and p.round * r <= p.owner < (p.round + 1) * r
    for n in range(3, 33):
        for r in (2, 3, 4, 5, 8, 16, n):
            assert all(m - k <= 1 for _, k, m in T.balance(T.plan_rounds(n, r)).values())


def test_sizes_and_rounds():
    assert T.balance(T.plan_rounds(32, 16)) == {0: (16, 275, 275), 1: (16, 35, 35)}
    assert T.balance(T.plan_rounds(24, 16)) == {0: (16, 123, 123), 1: (8, 7, 7)}
    assert T.balance(T.plan_rounds(24)) == {0: (24, 84, 85)}
    assert T.unit_sweep(8, 128, 2048)["replicas"] == [2]
    assert T.unit_sweep(32, 128, 2048)["copies"] == 32 and round(T.unit_sweep(32, 128, 2048)["unit_mib"], 1) == 17.2
    assert round(T.unit_sweep(24, 128, 1024)["unit_mib"], 1) == 11.4


@settings(max_examples=100, deadline=None)
@given(st.integers(3, 30), st.data())
def test_rotation_turns_the_owner_along(n, data):
    t = tuple(sorted(data.draw(st.lists(st.integers(0, n - 1), min_size=3, max_size=3, unique=True))))
    k = data.draw(st.integers(0, n - 1))
    assert T.same_orbit(t, T.rotate(t, k, n), n)
    gaps = {(t[1] - t[0]), (t[2] - t[1]), n - t[2] + t[0]}
    if len(gaps) > 1:  # the evenly spaced triple meets itself
        assert T.circle_owner(T.rotate(t, k, n), n) == (T.circle_owner(t, n) + k) % n


def test_pairs():
    for n in range(2, 20):
        own = [o for _, _, o in T.plan_pairs(n)]
        assert len(own) == comb(n, 2) and all(o in (i, j) for i, j, o in T.plan_pairs(n))
    counts = [[o for _, _, o in T.plan_pairs(9)].count(k) for k in range(9)]
    assert set(counts) == {4}


def test_costs():
    assert cost.footprint(32, 128, 4) == (10401873920, 41607495680)
    assert cost.footprint(13, 100, 8, 2)[0] == 78 * 10000
    assert cost.suggest_bins(32, 100 << 30) == 128 and cost.suggest_bins(32, 160 << 30, 4) == 128 and cost.suggest_bins(24, 160 << 30, 4) == 256
    assert cost.choose_strategy(10**8, 32, 128, 500) == "owner_slice"
    # tasks with memory for more cells make fewer scans
    assert cost.choose_strategy(10**12, 32, 128, 500, 1 << 30) == "local_dense"
    assert cost.scans("local_dense", 32, 128) == 155 and cost.scans("local_dense", 16, 16) == 1
    assert cost.row_copies("owner_slice", 16) == 16 and cost.row_copies("explode", 16) == 560


def test_plan_queries_read_line_items(spark, sf):
    import __spark_entry__ as entry

    for name in ("q21_plan_owner", "q22_plan_rounds", "q22b_plan_replicate", "q22c_plan_units", "q23_plan_pairs", "q23b_orbits", "q24_plan_balance", "q24b_costs", "q24c_suggest_bins"):
        assert any("lineitem" in f for f in entry.queries()[name](spark, sf).inputFiles()), name
