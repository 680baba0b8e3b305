import numpy as np

from cubelens.llm import decontamination as C


def brute(docs, items, size=5, threshold=0.8):
    out = set()
    for i, t in items.items():
        w = C.words_of(t)
        if not w:
            continue
        n = min(size, len(w))
        s = C.shingles(w, n)
        for d, x in docs.items():
            share = len(s & C.shingles(C.words_of(x), n)) / len(s)
            if share >= threshold - 1e-12:
                out.add((d, i, round(share, 9)))
    return out


def test_query_matches_brute_force(spark, sf):
    d, b = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/benchmark.parquet")
    docs, items = ({r[0]: r[1] for r in t.select(k, "text").collect()} for t, k in ((d, "doc_id"), (b, "item_id")))
    want = brute(docs, items)
    assert want
    for block in (C.BLOCK_ITEMS, 7):
        assert {(r.doc_id, r.item_id, round(r.containment, 9)) for r in C.find_items(d, b, block=block).collect()} == want
        assert {r.doc_id for r in C.drop_contaminated(d, b, block=block).collect()} == set(docs) - {x[0] for x in want}


def test_partial_containment_at_the_border(spark):
    import random

    rng = random.Random(3)
    items = {k: " ".join(f"i{k}w{j}" for j in range(n)) for k, n in enumerate([1, 2, 4, 5, 6, 9, 14, 19, 24, 54, 104])}
    docs = {}
    for k, t in items.items():
        for cut in range(8):
            w = t.split()
            for p in rng.sample(range(len(w)), min(cut, len(w))):
                w[p] = "zz"
            half = len(w) // 2  # the two halves lie far apart in a long text
            docs[100 * k + cut] = " ".join([*(f"a{j}" for j in range(400)), *(w if cut % 2 else [*w[:half], *(["far"] * 500), *w[half:]])])
    d = spark.createDataFrame(list(docs.items()), "doc_id long, text string")
    b = spark.createDataFrame(list(items.items()), "item_id long, text string")
    assert {(r.doc_id, r.item_id, round(r.containment, 9)) for r in C.find_items(d, b).collect()} == brute(docs, items)


def test_signatures_propose_what_contains_and_little_else():
    import random

    rng = random.Random(5)
    rows = [(k, " ".join(f"w{rng.randrange(400)}" for _ in range(n))) for k, n in enumerate([6, 7, 9, 12, 12, 20, 33, 40, 64, 90, 150, 300])]
    index = C.ItemIndex.build(rows)
    assert len({(p.length, len(p.hashes)) for p in index.partitions}) > 4
    for p in index.partitions:  # a document's signature is cut at the partition's largest hash
        text = " ".join(f"w{rng.randrange(400)}" for _ in range(3000))
        whole = np.unique(C.shingle_hashes(C.word_hashes(C.words_of(text + " " + rows[0][1])), p.length))
        keys, n = p.shared(whole)
        assert all(n[i] == len(set(whole.tolist()) & {int(h) for h, a, z in zip(p.hashes, p.first, p.first[1:]) if k in p.owners[a:z]}) for i, k in enumerate(keys.tolist()))
    docs = {}
    for k, t in rows:
        w = t.split()
        for lost in range(0, 4):
            docs[10 * k + lost] = " ".join(x if i % max(2, len(w) // (lost + 1)) or not lost else "zz" for i, x in enumerate(w)) + " tail" * 50
    want = brute(docs, dict(rows))
    assert {(d, i, round(c, 9)) for d, t in docs.items() for i, c in index.search(t)} == want


def test_very_long_text_and_blocks_by_bytes(spark, monkeypatch):
    monkeypatch.setattr(C, "BLOCK_BYTES", 40)
    items = {k: f"alpha{k} beta gamma{k} delta eps zeta{k}" for k in range(6)}
    d = spark.createDataFrame([(1, "x y " * 300000 + items[3] + " z" * 1000), (2, items[5])], "doc_id long, text string")
    b = spark.createDataFrame(list(items.items()), "item_id long, text string")
    assert sorted((r.doc_id, r.item_id) for r in C.find_items(d, b).collect()) == [(1, 3), (2, 5)]


def test_edge_cases(spark):
    d = spark.createDataFrame([(1, None, 7), (None, "A b, c", 7), (2, "", None), (3, "x a B c!", 7), (3, "x a B c!", 7)], "doc_id int, text string, item_id int")
    b = spark.createDataFrame([(1, "a b c"), (1, "a b c"), (2, None), (None, "x"), (4, " ")], "item_id int, text string")
    got = sorted((str(r.doc_id), r.item_id) for r in C.find_items(d, b).collect())
    assert got == [("3", 1), ("3", 1), ("None", 1)]
    left = C.drop_contaminated(d, b)
    assert left.schema == d.schema and left.count() == 2
    assert C.find_items(d.limit(0), b).collect() == [] and C.find_items(d, b.limit(0)).collect() == []


def test_repeated_and_null_item_ids(spark):
    d = spark.createDataFrame([(1, "x one two three y"), (2, "x four five six y"), (3, "x seven eight nine y"), (4, "clean")], "doc_id int, text string")
    b = spark.createDataFrame([(1, "one two three"), (1, "four five six"), (None, "seven eight nine")], "item_id int, text string")
    for block in (C.BLOCK_ITEMS, 1):
        assert sorted((r.doc_id, r.item_id) for r in C.find_items(d, b, block=block).collect()) == [(1, 1), (2, 1)]
        assert [r.doc_id for r in C.drop_contaminated(d, b, block=block).collect()] == [4]
