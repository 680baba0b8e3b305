import random

import numpy as np
import xxhash
from pyspark.sql import functions as F

from cubelens.llm import simhash as S
from cubelens.llm.components import connected_components


def brute_fp(text):
    import re

    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    w = re.findall(r"[^\x20\x09-\x0D]+", low)
    if not w:
        return 0
    sh = [" ".join(w[i : i + 4]) for i in range(max(1, len(w) - 3))]
    h = [xxhash.xxh64_intdigest(s.encode(), 42) for s in sh]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def brute_components(ids, fps, bits=4):
    root = list(range(len(ids)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(ids)):
        for j in range(i):
            if bin(fps[i] ^ fps[j]).count("1") <= bits:
                root[find(i)] = find(j)
    low = {}
    for i, d in enumerate(ids):
        low[find(i)] = min(low.get(find(i), d), d)
    return {d: low[find(i)] for i, d in enumerate(ids)}


def test_fingerprint_matches_definition():
    for t in ["", None, " \t\n", "a", "A b", "a b c d", "Ab c D e f", "é è ü x y z a b", "x " * 40000, "\x1c a\x85b c d e f"]:
        assert S.fingerprint(t) == brute_fp(t)


def test_anchors_cover_every_link():
    rng = random.Random(1)
    for _ in range(400):
        a = rng.getrandbits(64)
        b = a
        for p in rng.sample(range(64), rng.randint(0, 4)):
            b ^= 1 << p
        i, k = S.anchors(np.array([a, b], "<u8").view("<i8"))
        assert set(k[i == 0]) & set(k[i == 1])


def test_forest_connects_what_links_connect():
    rng = np.random.default_rng(2)
    base = rng.integers(0, 2**63, 30, dtype=np.uint64)
    f = np.unique(np.concatenate([base[i % 30 : i % 30 + 1] ^ np.uint64(1 << int(p)) ^ np.uint64(1 << int(q)) for i, (p, q) in enumerate(rng.integers(0, 63, (6000, 2)))]))
    assert len(f) > S.LARGE

    def comps(edges):
        r = {int(x): int(x) for x in f}

        def find(x):
            while r[x] != x:
                x = r[x]
            return x

        for u, v in edges:
            for a, b in zip(u.tolist(), v.tolist()):
                r[find(a)] = find(b)
        groups = {}
        for x in r:
            groups.setdefault(find(x), set()).add(x)
        return sorted(map(sorted, groups.values()))

    for block in (0, 1):
        assert comps(S._forest(f, 4, block)) == comps(S._walk(f, 4))


def test_large_groups_are_cut_outside_of_the_anchor_block():
    """Members of a group agree on the anchor's block, so pieces of it would not cut the group."""
    rng = np.random.default_rng(3)
    for block in (0, 1):
        fixed = np.uint64(5 << (block * S.BLOCK))
        keep = np.uint64(((1 << 64) - 1) ^ (((1 << S.BLOCK) - 1) << (block * S.BLOCK)))
        f = np.unique(rng.integers(0, 2**64, 20000, dtype=np.uint64) & keep | fixed)
        rest = S._outside(f, block)
        assert len(np.unique(rest)) == len(f)
        sizes, walk = [], S._walk
        try:
            S._walk = lambda g, bits: sizes.append(len(g)) or walk(g, bits)
            edges = S._forest(f, 4, block)
        finally:
            S._walk = walk
        assert max(sizes) < len(f) / 30
        near = {(min(a, b), max(a, b)) for u, v in edges for a, b in zip(u.tolist(), v.tolist())}
        at = f[:300]
        for x in at.tolist():
            hit = f[(np.bitwise_count(f ^ np.uint64(x)) <= 4) & (f != np.uint64(x))]
            assert not len(hit) or any(x in p for p in near)


def test_query_matches_brute_force(spark, sf):
    d = spark.read.parquet(f"{sf}/documents.parquet")
    rows = S.near_duplicates(d).collect()
    src = {r.doc_id: r.text for r in d.collect()}
    ids = sorted(src)
    fps = [brute_fp(src[i]) for i in ids]
    want = brute_components(ids, fps)
    assert {r.doc_id: r.fingerprint for r in rows} == {i: f"{f:016x}" for i, f in zip(ids, fps)}
    assert {r.doc_id: r.component_id for r in rows} == want


def test_edge_cases(spark):
    s = "doc_id long, text string, fingerprint string, component_id int"
    rows = [(1, None, "x", 1), (2, "", "x", 1), (2, "", "x", 1), (None, " ", "x", None), (5, "one two", None, None), (4, "one two", None, None), (9, "q " * 100000, "", 0)]
    got = sorted((r.doc_id is None, r.doc_id, r.component_id, r.n_links) for r in S.near_duplicates(spark.createDataFrame(rows, s)).collect())
    assert [g[2] for g in got] == [1, 1, 1, 4, 4, 9, 1] and [g[3] for g in got] == [3, 3, 3, 1, 1, 0, 3]
    assert S.near_duplicates(spark.createDataFrame([], s)).collect() == []
    kept = S.keep_one(spark.createDataFrame(rows, s))
    assert kept.columns == ["doc_id", "text", "fingerprint", "component_id"]
    assert sorted((r.doc_id is None, r.doc_id) for r in kept.collect()) == [(False, 1), (False, 4), (False, 9), (True, None)]
    one = S.keep_one(spark.createDataFrame([(3, "z", "a", 1), (3, "z", "a", 1)], s)).collect()
    assert len(one) == 1


def test_keep_one_with_repeated_ids_and_maps(spark):
    a, b, c = ("alpha beta gamma delta epsilon " * 9, "one two three four five six " * 9, "north east south west up down " * 9)
    rows = [(1, a, {"k": 1}), (1, b, {"k": 2}), (2, a, {"k": 3}), (3, b, {}), (3, c, None), (4, c, {"z": 0}), (3, c, {"y": 1}), (None, a, None)]
    d = spark.createDataFrame(rows, "doc_id int, text string, m map<string,int>")
    got = S.keep_one(d)
    assert got.schema.simpleString() == d.schema.simpleString()
    assert sorted((r.doc_id or 0, r.text) for r in got.collect()) == sorted([(1, a), (1, b), (3, c), (0, a)])


def test_components_of_a_long_path(spark):
    n = 40
    e = spark.range(n).select(F.col("id").alias("u"), (F.col("id") + 1).alias("v"))
    got = connected_components(e).collect()
    assert len(got) == n and {r.root for r in got} == {0}
    assert connected_components(e.limit(0)).collect() == []
