import itertools
import math
import zlib
from collections import Counter

import numpy as np

from cubelens.llm import cotraining as C
from cubelens.llm import toxicity as T


def brute(s, t, n=3, d=T.DECAY, span=T.SPAN):
    sub = lambda x: [i for i in itertools.combinations(range(len(x)), n) if i[-1] - i[0] < span]
    return sum(d ** (i[-1] - i[0] + 1 + j[-1] - j[0] + 1) for i in sub(s) for j in sub(t) if [s[a] for a in i] == [t[b] for b in j])


def test_kernel_matches_its_definition():
    words = ["idiot", "i-d-i-o-t", "iddiioott", "moron", "thaed", "ab", "trashy", "aaaaaa", "naïve", "", "\U0001f600bc\U0001f600"]
    marks = ["idiot", "moron", "trash", "aaa", "naïv"]
    got = T.Landmarks(marks).kernel(words)
    want = [[(brute(w, t) / np.sqrt(brute(w, w) * brute(t, t))) ** T.POWER if brute(w, w) else 0 for t in marks] for w in words]
    assert np.allclose(got, want, atol=1e-5)
    assert np.allclose(np.diag(T.Landmarks(marks).kernel(marks)), 1, atol=1e-5)


def plain_score(model, text):
    """A text's score by the definition: all kernel values by brute force, sorted, whitened, weighted."""
    tokens = T.tokens_of(text)
    words = sorted({v for w in tokens for v in T.readings(w)})
    k = np.zeros((max(len(words), T.LARGEST), len(model.landmarks.words)))
    for i, w in enumerate(words):
        for j, t in enumerate(model.landmarks.words):
            k[i, j] = max((brute(v, t) / np.sqrt(brute(v, v) * brute(t, t))) ** T.POWER for v in (w, w[: len(t)]))
    k[(k < T.LEAST).all(axis=1)] = 0  # words like no landmark
    x = np.concatenate([(np.sort(k, axis=0)[::-1][: T.LARGEST] @ model.whiten).reshape(-1), [np.log1p(len(tokens)) / 6]])
    return 1 / (1 + np.exp(-((x @ model.w + model.b) * model.platt[0] + model.platt[1])))


def test_toxicity_query_matches_plain_scoring(spark, sf, monkeypatch):
    """The query's score of whole texts again, by plain loops, with memories that overflow."""
    monkeypatch.setattr(T, "TOXIC_LANDMARKS", 6)
    monkeypatch.setattr(T, "CLEAN_LANDMARKS", 3)
    d, lab = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    model = T.fit(d, lab)
    monkeypatch.setattr(T, "REMEMBERED", 50)
    rows = {r.doc_id: r for r in T.score(d, lab).collect()}
    src = sorted(((r.doc_id, r.text) for r in d.collect()), key=lambda r: len(r[1]))
    for i, t in src[:12]:
        assert abs(rows[i].score - plain_score(model, t)) < 1e-4


def test_landmarks_come_from_all_languages():
    rows = []
    for k in range(40):
        for stem in ("vexga", "üblok", "règno"):
            rows += [([f"{stem}{'mnprst'[k % 6]}{k}", f"w{k}aa"], 1), ([f"w{k}aa", f"u{k}bb"], 0)]
    got = list(T.choose_landmarks(rows, 3, 2))
    assert sorted(got[:3]) == ["règno", "vexga", "üblok"] and len(got) == 5


def held(spark, fn, label, sf="/root/testdata/sf0.01"):
    d, lab = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    rows = {r.doc_id: r for r in fn(d, lab).collect()}
    assert len(rows) == d.count()
    for i, r in rows.items():
        assert r.held_out == (zlib.crc32(str(i).encode()) % 5 == 0) and 0 <= r.score <= 1 and r.predicted == (r.score >= 0.5)
    return rows, [(rows[r.doc_id], r[label]) for r in lab.collect() if rows[r.doc_id].held_out], {r.doc_id: r.text for r in d.collect()}


def test_toxicity_on_held_out_rows(spark):
    rows, pairs, text = held(spark, T.score, "toxic")
    assert np.mean([r.predicted == y for r, y in pairs]) > 0.93
    assert not any(r.predicted for r, y in pairs if y == 0)


def toy(toxic, clean, n=60):
    """Texts of two to eleven words with one to three of theirs, the other words the same for both classes."""
    filler = [a + b + c for a in ("br", "sel", "fa", "lun") for b in ("a", "e", "u") for c in ("ck", "nd", "rm", "vis")]
    out = []
    for k in range(n):
        for x, y in [(x, 1) for x in toxic] + [(x, 0) for x in clean]:
            rest = [filler[(7 * k + 5 * j) % len(filler)] for j in range(1 + k % 9)]
            out.append((" ".join(rest[: k % 3] + [x] * (1 + k % 3) + rest[k % 3 :]) + ".", y))
        out += [(" ".join(rest[: k % 7]), 0)] * 2
    return out


def test_toxicity_tolerates_gaps():
    rows = toy(("idiot", "moron"), ("garden", "table"))
    m = T.train(rows)
    s = m.scores(["an i d i o t", "such an i.d.i.o.t there", "id1ot", "idiioot now", "the m-o-r-o-n", "a garden table", "", "m"])
    assert (s[:5] > 0.5).all() and (s[5:] < 0.5).all()
    assert T.train([]).scores(["idiot", ""]).tolist() == T.train([]).scores(["", "x"]).tolist()


def test_toxicity_tolerates_inserted_letters_at_every_place():
    m = T.train(toy(("idiot", "stupid"), ("garden", "table")))
    base = m.scores(["the garden and table", "we saw it here"]).max()
    for word in ("idiot", "stupid"):
        for at in range(1, len(word)):
            assert m.scores([f"you {word[:at]}x{word[at:]} there"])[0] > 20 * base
        assert m.scores([f"you {'x'.join(word)} there"])[0] > base


def test_toxicity_scores_are_graded(spark):
    rows, pairs, _ = held(spark, T.score, "toxic")
    scores = [round(r.score, 9) for r in rows.values()]
    assert max(scores.count(s) for s in set(scores)) < len(scores) / 10


def test_toxicity_pools_inflected_forms():
    ends = [a + b for a in "mnprstv" for b in ("ak", "el", "in", "or", "um")]
    rows = []
    for k in range(60):
        some = [ends[(7 * k + 3 * j) % len(ends)] for j in range(4)]
        rows += [(f"w{k} vexga{some[0]} x{k} y{k} z{k} vexga{some[1]} q{k}.", 1), (f"w{k} vexga{some[2]} y{k} z{k} lomde{some[3]} r{k}.", 0), (f"lomde{some[0]} s{k} lomde{some[1]} t{k}.", 0)]
        rows += [(f"m{k} idiot n{k} o{k} p{k}.", 1)] * 2 + [(f"vexga{some[1]} t{k} calm.", 0), (f"calm {'here there'.split()[k % 2]} p{k}.", 0), (f"nothing{some[0]} p{k}.", 0)]
    s = T.train(rows).scores(["a vexgawix b c vexgazul", "vexgawix a b c", "lomdewix a lomdezul", "an idiot", "nothing"])
    assert (s[[0, 3]] > 0.5).all() and (s[[1, 2, 4]] < 0.5).all()


def test_toxicity_recall_on_held_out_rows_of_each_language(spark):
    sf = "/root/testdata/sf0.1"
    rows, pairs, text = held(spark, T.score, "toxic", sf)
    insults = "trash pathetic loser worthless disgusting idiot scum moron clown stupid".split()
    for i, r in rows.items():
        n = sum(text[i].lower().split().count(w) for w in insults)
        assert r.predicted == 1 if n > 2 else True
    lang = {r.doc_id: r.lang for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "lang").collect()}
    for name in ("en", "fr", "de", "es"):
        assert np.mean([r.predicted for r, y in pairs if y == 1 and lang[r.doc_id] == name]) >= 0.8
        assert np.mean([r.predicted for r, y in pairs if y == 0 and lang[r.doc_id] == name]) <= 0.02


def test_cotraining_on_held_out_rows(spark):
    _, pairs, _ = held(spark, C.score, "quality")
    assert np.mean([r.predicted == y for r, y in pairs]) > 0.9
    assert np.mean([r.kept for r, y in pairs if y == 1]) > 0.95


def test_cotraining_query_matches_plain_scoring(spark, sf):
    """Every row's scores again, by plain counting of n-grams and lines."""
    d, lab = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    m = C.fit(d, lab)
    got = {r.doc_id: r for r in C.score(d, lab).collect()}
    sigmoid = lambda z: 1 / (1 + math.exp(-z))
    for r in d.collect():
        raw = r.text.lower().encode()
        grams = Counter((int.from_bytes(raw[i : i + 3], "big") * 0x9E3779B97F4A7C15 % 2**64) >> 54 for i in range(len(raw) - 2))
        size = math.sqrt(sum(math.log1p(n) ** 2 for n in grams.values())) or 1e-9
        text = sum(8 / size * math.log1p(n) * m.text_w[k] for k, n in grams.items()) + m.text_w[-1]
        lines = r.text.split("\n")
        long = [len(x) for x in lines]
        facts = [math.log1p(len(r.text)), math.log1p(len(lines)), math.log1p(sum(long) / len(long)), math.log1p(max(long)), len(set(lines)) / len(lines), 1]
        page = m.page_w[zlib.crc32(r.lang.encode()) % 32] + m.page_w[32 + zlib.crc32(r.source.encode()) % 32] + sum(x * w for x, w in zip(facts, m.page_w[-6:]))
        one, two = (max(-12, min(12, c[0] * z + c[1])) for z, c in ((text, m.text_cal), (page, m.page_cal)))
        row = got[r.doc_id]
        assert abs(row.text_score - sigmoid(one)) < 1e-6 and abs(row.page_score - sigmoid(two)) < 1e-6
        assert abs(row.score - sigmoid(m.blend @ [one, two, 1])) < 1e-6 and row.kept == (row.score >= 0.5)


def test_cotraining_ties_and_repeats(spark):
    """Equal texts with unlike labels and repeated ids: equal rows score alike, whatever their order."""
    rows = [(k, "same words here " * 9, "en", "s") for k in range(40)] + [(40 + k, f"other {k} $$", "en", "t") for k in range(40)]
    lab = spark.createDataFrame([(k, k % 2) for k in range(40)] + [(40 + k, 0) for k in range(30)], "doc_id long, quality int")
    schema = "doc_id long, text string, lang string, source string"
    a = {r.doc_id: r.score for r in C.score(spark.createDataFrame(rows, schema).repartition(3), lab).collect()}
    b = {r.doc_id: r.score for r in C.score(spark.createDataFrame(rows[::-1], schema), lab).collect()}
    assert len({round(a[k], 9) for k in range(40)}) == 1 and all(abs(a[k] - b[k]) < 1e-6 for k in a)


def test_cotraining_reads_every_unlabelled_row(spark, monkeypatch):
    n = 3000
    rows = [(k, f"good plain words {k} stand here" if k % 2 else f"$$ ## {k} @@ !!", "en", ("g" if k % 2 else "b")) for k in range(n)]
    d = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string").repartition(5)
    lab = spark.createDataFrame([(k, k % 2) for k in range(200)], "doc_id long, quality int")
    want = [k for k in range(200, n) if zlib.crc32(str(k).encode()) % 5]
    assert sorted(r.doc_id for r in C.unlabelled(d, lab).collect()) == want
    seen, total = [], C._total
    monkeypatch.setattr(C, "_total", lambda *a: seen.append(total(*a)) or seen[-1])
    C.fit(d, lab)
    assert seen[0].sum() == 2 * len(want)
    size = C.TEXT_DIMS + 1
    taught = [(x[size], x[-2]) for x in seen if len(x) < 2 * C.BOUND]
    assert min(taught[0]) > 0.02 * len(want) and min(taught[-1]) > min(taught[0])


def test_cotraining_sums_match_one_pass(spark):
    rng = np.random.default_rng(2)
    texts = [" ".join(rng.choice(["aa", "bcd", "efg", "$$", "hi"], 30)) for _ in range(200)]
    pool = C.pool_views(spark.createDataFrame([(k, t, "en", "s") for k, t in enumerate(texts)], "doc_id long, text string, lang string, source string").repartition(3))
    a, b = C._views([(t, "en", "s") for t in texts])
    wa, wb = rng.normal(size=a.shape[1]), rng.normal(size=b.shape[1]) / 9
    done = [(wa, wb, [(-200, 200), (-100, 100)])]
    got = C._total(pool, len(wa) + len(wb) + 4, C._sums(done, wa / 9, wb / 9))
    want = C._sums(done, wa / 9, wb / 9)(a, b)
    assert np.allclose(got, want, rtol=0.1, atol=0.05 * np.abs(want).max())


def test_edge_cases(spark):
    s = "doc_id int, text string, lang string, source string, score string, held_out int"
    d = spark.createDataFrame([(1, None, None, None, "a", 1), (None, "idiot", "en", "s", None, None), (2, "x " * 60000, "en", "s", "", 0), (2, "x " * 60000, "en", "s", "", 0)], s)
    lab = spark.createDataFrame([(1, 1, 0), (1, 0, 1), (None, 1, 1), (7, None, None)], "doc_id int, quality int, toxic int")
    for fn in (T.score, C.score):
        assert fn(d, lab).count() == 4
        assert fn(d, lab.limit(0)).count() == 4 and fn(d.limit(0), lab).collect() == []
