import corpus_pipeline as P
from cubelens.llm import decontamination as C
from cubelens.llm import quality_rules as Q
from cubelens.llm import secrets as S
from tests.llm.test_decontamination import brute as brute_items
from tests.llm.test_secrets import brute as brute_secrets
from tests.llm.test_simhash import brute_components, brute_fp


def test_stages_match_brute_force(spark):
    sf = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    text = {r.doc_id: r.text for r in docs.collect()}
    frame = docs
    seen = {}
    for name, stage in P.STAGES:
        frame = stage(spark, frame, sf)
        seen[name] = {r.doc_id: r for r in frame.collect()}
        if name != "mix_sources":
            assert frame.columns == docs.columns
    good = {r.doc_id for r in Q.assess(docs, spark.read.parquet(f"{sf}/labels.parquet")).filter("kept").collect()}
    assert set(seen["quality_rules"]) == good
    ids = sorted(good)
    root = brute_components(ids, [brute_fp(text[i]) for i in ids])
    one = {i for i in ids if root[i] == i}
    assert set(seen["simhash_dedup"]) == one
    items = {r.item_id: r.text for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()}
    clean = one - {d for d, _, _ in brute_items({i: text[i] for i in one}, items)}
    assert set(seen["decontamination"]) == clean
    assert set(seen["secret_scan"]) == clean
    for i, r in seen["secret_scan"].items():
        assert not brute_secrets(r.text) and (r.text == text[i] or S.MASK in r.text)
    assert set(seen["mix_sources"]) == clean and C.THRESHOLD == 0.8
    assert {r.doc_id for r in P.run(spark, sf).collect()} == clean


def _tables(spark, path, docs, labels, items):
    docs.write.parquet(f"{path}/documents.parquet")
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{path}/labels.parquet")
    spark.createDataFrame(items, "item_id long, text string").write.parquet(f"{path}/benchmark.parquet")
    return str(path)


def _prose(k, n=120):
    return " ".join(f"word{(k * 7919 + i * 104729) % 5000} of{(k + i) % 90}" for i in range(n))


S_DOCS = "doc_id long, text string, lang string, source string, n_chars long, fingerprint string, copies int, fp long, spans map<string,int>"


def test_run_on_hard_rows(spark, tmp_path):
    """Null, empty and repeated texts, repeated and null ids, a key of a secret, a leaked item, extra columns with the operators' own names."""
    item = "the quick brown fox jumps over the lazy dog near the river bank today"
    rows = [
        (1, None), (2, ""), (3, " \n"), (4, _prose(4)), (5, _prose(4)), (6, _prose(6) + " password = hunter22secret"), (7, _prose(7) + " " + item),
        (8, "same line\n" * 200), (9, _prose(9)), (9, _prose(9)), (9, _prose(10)), (None, _prose(11)), (None, _prose(11)), (12, _prose(12, 60000)),
    ]
    docs = spark.createDataFrame([(i, t, None if i == 4 else "en", None if i == 9 else "s", None, "f", 7, None, {"a": 1}) for i, t in rows], S_DOCS)
    sf = _tables(spark, tmp_path / "t", docs, [(4, 1, 0), (12, 1, 0), (None, 1, 0), (9, None, None)], [(1, item), (None, "lorem ipsum dolor sit"), (2, None)])
    frame = spark.read.parquet(f"{sf}/documents.parquet")
    for name, stage in P.STAGES[:-1]:
        out = stage(spark, frame, sf)
        assert out.schema.simpleString() == frame.schema.simpleString(), name
        frame = out
    got = frame.collect()
    assert sorted((r.doc_id or 0, (r.text or "")[:25]) for r in got) == sorted([(4, _prose(4)[:25]), (6, _prose(6)[:25]), (9, _prose(9)[:25]), (9, _prose(10)[:25]), (0, _prose(11)[:25]), (0, _prose(11)[:25]), (12, _prose(12)[:25])])
    assert all("hunter22secret" not in r.text for r in got) and all(r.spans == {"a": 1} and r.copies == 7 for r in got)
    out = P.run(spark, sf)
    assert out.columns == ["doc_id", "source", "n_tokens", "weight", "passes", "copies", "block", "block_rank"]
    rows = out.collect()
    assert len(rows) == 7 and all(r.copies >= 0 for r in rows)


def test_run_on_empty_tables(spark, tmp_path):
    none = spark.createDataFrame([], S_DOCS)
    assert P.run(spark, _tables(spark, tmp_path / "a", none, [], [])).collect() == []
    only = spark.createDataFrame([(1, _prose(1), "en", "s", 5, "", 0, 0, None)], S_DOCS)
    assert [r.doc_id for r in P.run(spark, _tables(spark, tmp_path / "b", only, [], [])).collect()] == [1]


def test_run_leaves_only_its_last_tables(spark, tmp_path):
    import os

    from cubelens.storage import release, shared_dir

    at = f"{shared_dir(spark).removeprefix('file://')}/cubelens"
    before = set(os.listdir(at)) if os.path.isdir(at) else set()
    out = P.run(spark, "/root/testdata/sf0.001")
    out.count()
    release(out)
    assert set(os.listdir(at)) <= before
