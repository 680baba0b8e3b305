import random
import re

from cubelens.llm import licenses as L

WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def brute(text):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    w = WORD.findall(low)
    spots, own = [], set()
    for p, label in L.BASE_PHRASES:
        p = p.split()
        at = [i for i in range(len(w) - len(p) + 1) if w[i : i + len(p)] == p]
        spots += at
        own |= {label} if at else set()
    best, labels = 0.0, set(own)
    for t in L.templates():
        for s in range(0, len(w), t.stride):
            k = len(set(w[s : s + 2 * t.stride]) & set(t.tokens))
            if k >= t.needed:
                labels.add(t.label)
                best = max(best, k / len(t.tokens))
    return len(w), len(spots), min(spots, default=None), max(spots, default=None), ",".join(sorted(own)), ",".join(sorted(labels)), 1.0 if spots else best


def check(rows, src):
    for r in rows:
        assert (r.n_words, r.n_base, r.first_word, r.last_word, r.base_labels, r.labels, r.score) == brute(src[r.doc_id]), r


def test_query_matches_brute_force(spark, sf):
    d = spark.read.parquet(f"{sf}/documents.parquet")
    rows = L.license_report(d).collect()
    src = {r.doc_id: r.text for r in d.collect()}
    assert len(rows) == len(src) and any(r.labels for r in rows)
    check(rows, src)


def test_broken_notices(spark):
    rng = random.Random(2)
    texts = ["Under the MIT License under the mit license", "apache license, version 2", "CC BY-NC cc by nc", "undér the mit license", "the mit license"]
    for t, _ in L.TEMPLATES:
        for drop in (0, 1, 2, 4):
            w = t.split()
            for _ in range(drop):
                w[rng.randrange(len(w))] = "zz"
            texts.append(" ".join([f"f{k}" for k in range(rng.randrange(90))] + w + [f"g{k}" for k in range(rng.randrange(90))]).upper())
    texts.append(" ".join(["filler"] * 40000 + ["under the mit license"]))
    d = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    check(L.license_report(d).collect(), dict(enumerate(texts)))


def test_whole_license_texts_wherever_they_stand(spark):
    """A license text of any length is found at every offset, and templates of a caller too."""
    rng = random.Random(6)
    texts = []
    for t, _ in L.LICENSE_TEXTS:
        for at in (0, 31, 100, 255, 700):
            texts.append(" ".join([f"f{k}" for k in range(at)] + [t] + [f"g{k}" for k in range(rng.randrange(300))]))
    d = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    rows = {r.doc_id: r for r in L.license_report(d).collect()}
    check(rows.values(), dict(enumerate(texts)))
    for i, (_, label) in enumerate(x for x in L.LICENSE_TEXTS for _ in range(5)):
        assert label in rows[i].labels.split(",") and rows[i].score == 1
    assert max(len(x.tokens) for x in L.templates()) > 33
    assert all(x.stride + 1 >= len(WORD.findall(t.lower())) for x, (t, _) in zip(L.templates(), L.TEMPLATES))
    own = " ".join(f"own{k}" for k in range(900))
    got = L.license_report(spark.createDataFrame([(1, "x " * 333 + own), (2, "own1 own2")], "doc_id long, text string"), texts=((own, "own"),)).collect()
    assert sorted((r.doc_id, r.labels) for r in got) == [(1, "own"), (2, "")]


def test_edge_cases(spark):
    s = "doc_id int, text string, labels string, key int"
    d = spark.createDataFrame([(1, None, "a", 1), (2, " .,; ", None, None), (None, "Under the MIT license", "b", 2), (3, "under the mit license", "b", 2), (3, "under the mit license", "b", 2)], s)
    got = sorted((str(r.doc_id), r.n_words, r.n_base, r.labels, r.score) for r in L.license_report(d).collect())
    assert got == [("1", 0, 0, "", 0.0), ("2", 0, 0, "", 0.0), ("3", 4, 1, "mit", 1.0), ("3", 4, 1, "mit", 1.0), ("None", 4, 1, "mit", 1.0)]
    assert L.license_report(d.limit(0)).collect() == []


def test_no_python_in_the_plan(spark, sf):
    plan = L.license_report(spark.read.parquet(f"{sf}/documents.parquet"))._jdf.queryExecution().toString()
    assert "Python" not in plan and "MapInArrow" not in plan and "Cartesian" not in plan
