import math
from collections import defaultdict

from pyspark.sql import functions as F

from cubelens.llm import mixing as M


def weights(shares, a):
    z = sum(p**a for p in shares)
    return [p**a / z for p in shares]


def test_token_count(spark):
    rows = [None, "", " ", "a", " a", "a ", " a  b\t\nc ", "x\x1cy z"]
    d = spark.createDataFrame([(t,) for t in rows], "text string")
    assert [r.n for r in d.select(M.token_count(F.col("text")).alias("n")).collect()] == [len((t or "").encode().split()) for t in rows]


def test_weights_meet_the_limits(spark):
    tok = {"a": 90000, "b": 9000, "c": 900, "d": 100, None: 50, "e": 0}
    d = spark.createDataFrame(list(tok.items()), "source string, n_tokens long")
    full = {k: v for k, v in tok.items() if v}
    shares = [v / sum(full.values()) for v in full.values()]
    for target, limit in ((0.9, None), (0.5, 4.0), (0.9, 1.0), (None, 3.0), (0.0, None)):
        rows = {r.source: r for r in M.source_weights(d, target, limit).collect()}
        a = rows["a"].exponent
        want = dict(zip(full, weights(shares, a)))
        assert all(abs(rows[k].weight - w) < 1e-9 for k, w in want.items()) and rows["e"].weight == 0
        entropy = -sum(w * math.log(w) for w in want.values())
        repeats = max(w / p for w, p in zip(want.values(), shares))
        if limit is not None and a < 1:
            assert repeats <= limit + 1e-6
        if target and limit is None:
            assert abs(entropy - target * math.log(len(full))) < 1e-6


def brute(rows, plan):
    """Copies by plain walking through the permuted blocks."""
    out = {}
    for source, docs in rows.items():
        whole, rest = plan[source]
        seen = 0
        for doc, n in docs:
            out[doc] = whole + (1 if seen < rest - 1e-6 else 0)
            seen += n
    return out


def test_copies_follow_the_budget(spark):
    docs = [(i, ("w " * (1 + i % 13)).strip(), "hot" if i % 3 else f"s{i % 5}") for i in range(6000)]
    d = spark.createDataFrame(docs, "doc_id long, text string, source string")
    out = M.mix_sources(d)
    got = {r.doc_id: r for r in out.collect()}
    assert len(got) == 6000
    order = out.select("doc_id", "source", "n_tokens", "block", "block_rank", F.xxhash64(F.lit(18), "doc_id").alias("p")).collect()
    rows = defaultdict(list)
    for r in sorted(order, key=lambda r: (r.source, r.block_rank, r.p, r.doc_id)):
        rows[r.source].append((r.doc_id, r.n_tokens))
    tokens = {s: sum(n for _, n in x) for s, x in rows.items()}
    budget = sum(tokens.values())
    plan = {}
    for s, x in rows.items():
        due = budget * got[x[0][0]].weight
        plan[s] = (int(due // tokens[s]), round(due - (due // tokens[s]) * tokens[s], 3))
    assert {k: r.copies for k, r in got.items()} == brute(rows, plan)
    spent = sum(r.copies * r.n_tokens for r in got.values())
    assert abs(spent - budget) <= 13 * len(rows)
    assert len({r.block for r in got.values() if r.source == "hot"}) > 2


def test_repeats_are_limited_at_any_budget(spark):
    docs = [(i, "w " * 9 + "w", "big" if i % 10 else "small") for i in range(4000)]
    d = spark.createDataFrame(docs, "doc_id long, text string, source string")
    total = 40000
    for budget, limit in ((total // 10, 2.0), (total, 1.5), (3 * total, 4.0), (5 * total, 4.0)):
        rows = M.mix_sources(d, 0.999, limit, budget).collect()
        passes = {r.source: r.passes for r in rows}
        assert max(passes.values()) <= limit + 1e-6, (budget, limit, passes)
        assert max(r.copies for r in rows) <= limit + 1
        spent = sum(r.copies * r.n_tokens for r in rows)
        assert abs(spent - min(budget, limit * total)) <= 20


def test_rows_without_id_are_spread_over_blocks(spark):
    d = spark.createDataFrame([(None, f"a b {k}", "x") for k in range(5000)], "doc_id long, text string, source string")
    out = M.mix_sources(d)
    n = [r["count"] for r in out.groupBy("block").count().collect()]
    assert len(n) == 5 and max(n) < 1500
    from cubelens.storage import release

    paths = out._shared_paths
    release(out)
    import os

    assert len(paths) == 2 and not any(os.path.exists(p.removeprefix("file:")) for p in paths)


def test_edge_cases(spark):
    s = "doc_id int, text string, source string, weight string, copies int"
    rows = [(1, None, None, "a", 1), (1, "a b", None, "a", 1), (None, "c", "x", None, None), (2, "", "x", "", 0), (2, "", "x", "", 0), (3, "q " * 50000, "y", "", 0)]
    out = M.mix_sources(spark.createDataFrame(rows, s)).collect()
    assert len(out) == 6 and all(r.copies >= 0 for r in out)
    assert M.mix_sources(spark.createDataFrame([], s)).collect() == []
    only = M.mix_sources(spark.createDataFrame([(1, None, "x", "", 0)], s)).collect()
    assert only[0].copies == 0 and only[0].weight == 0


def test_no_python_in_the_plan(spark, sf):
    plan = M.mix_sources(spark.read.parquet(f"{sf}/documents.parquet"))._jdf.queryExecution().toString()
    assert "Python" not in plan and "Arrow" not in plan and "Cartesian" not in plan
