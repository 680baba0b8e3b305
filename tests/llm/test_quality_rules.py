import re
from collections import Counter

import numpy as np
from hypothesis import given, settings
from hypothesis import strategies as st

from cubelens.llm import quality_rules as Q

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def brute(text):
    text = text or ""
    w = WORD.findall(text)
    lines = text.split("\n")
    dup = sum(1 for i, x in enumerate(lines) if WORD.search(x) and x in lines[:i])
    c = Counter(tuple(w[i : i + 3]) for i in range(len(w) - 2))
    hit = {j for i in range(len(w) - 2) if c[tuple(w[i : i + 3])] > 1 for j in (i, i + 1, i + 2)}
    return len(w), sum(map(len, w)), sum(x in "#*$%&|<>" for x in text), dup, len(hit)


@settings(max_examples=500, deadline=None)
@given(st.lists(st.sampled_from(["a", "b", "é", "#", "<x>", " ", "\n", "\t", "\x1c", "\xa0", "\r", "a b c", "\n\n"]), max_size=30).map("".join))
def test_counts_match_definition(text):
    assert Q.rule_counts(text) == brute(text)


def test_counts_of_odd_texts():
    for t in (None, "", " \n ", "a b c " * 20000, "x\nx\n x\nx"):
        assert Q.rule_counts(t) == brute(t)


def test_log_ratio():
    r = Q.log_ratio(np.array([100, 0, 0]), np.array([100, 1000, 0]))
    assert r[0] > 0 > r[1] and r[2] == 0
    assert not Q.log_ratio(np.zeros(3), np.array([1, 2, 3])).any()


def test_query(spark, sf):
    d, lab = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    src = {r.doc_id: r.text for r in d.collect()}
    rows = Q.assess(d, lab).collect()
    assert len(rows) == len(src)
    good = {r.doc_id for r in lab.filter("quality = 1").collect()}
    # the ratio again, by plain counting
    grams = lambda t: [g for b in [t.lower().encode()] for g in (b[i : i + 3] for i in range(len(b) - 2))]
    hashed = lambda g: (int.from_bytes(g, "big") * 0x9E3779B97F4A7C15 % 2**64) >> 48
    corpus, trusted = Counter(), Counter()
    for i, t in src.items():
        c = Counter(map(hashed, grams(t)))
        corpus.update(c)
        trusted.update(c if i in good else {})
    n, m = sum(corpus.values()), sum(trusted.values())
    for r in rows:
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == brute(src[r.doc_id])
        g = list(map(hashed, grams(src[r.doc_id])))
        want = np.mean([np.log((trusted[b] + 20) / (corpus[b] * m / n + 20)) for b in g]) if g else 0
        assert abs(r.llr - want) < 1e-9
        assert r.kept == (not r.base_failed and r.llr >= Q.THRESHOLD)
    kept = Q.keep_good(d, lab)
    assert kept.schema == d.schema and {r.doc_id for r in kept.collect()} == {r.doc_id for r in rows if r.kept}


def test_labels_agree(spark):
    sf = "/root/testdata/sf0.01"
    d, lab = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    j = Q.assess(d, lab).join(lab, "doc_id").filter("not base_failed").collect()
    assert all(r.kept for r in j if r.quality == 1) and not any(r.kept for r in j if r.quality == 0)


def test_edge_cases(spark):
    s = "doc_id long, text string, kept string, n_words string"
    rows = [(1, None, "a", "b"), (None, "x y", None, None), (2, "w" + " ".join(map(str, range(99))), "", ""), (2, "w" + " ".join(map(str, range(99))), "", "")]
    d = spark.createDataFrame(rows, s)
    lab = spark.createDataFrame([(None, 1, 0), (5, None, 0)], "doc_id long, quality int, toxic int")
    got = sorted((str(r.doc_id), r.n_words, r.base_failed, r.llr, r.kept) for r in Q.assess(d, lab).collect())
    assert got == [("1", 0, True, 0.0, False), ("2", 99, False, 0.0, True), ("2", 99, False, 0.0, True), ("None", 2, True, 0.0, False)]
    assert Q.assess(d.limit(0), lab.limit(0)).collect() == []
    assert Q.keep_good(d, lab).columns == d.columns and Q.keep_good(d, lab).count() == 2
