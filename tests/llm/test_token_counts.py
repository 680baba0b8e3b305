from hypothesis import given, settings
from hypothesis import strategies as st
from tokenizers import Tokenizer

from cubelens.llm import token_counts as T

LIB = Tokenizer.from_file(T.default_path())
COUNTER = T.Counter(open(T.default_path()).read())


def lib(text):
    return len(LIB.encode(text or "", add_special_tokens=False).ids)


def test_whole_words_are_proven():
    assert len(COUNTER.whole) > 30000 and all(len(LIB.encode(w, add_special_tokens=False).ids) == 1 for w in list(COUNTER.whole)[:500])


@settings(max_examples=500, deadline=None)
@given(st.lists(st.one_of(st.text(max_size=6), st.sampled_from(["the", "The", "don't", "I'LL", " ", "\n", "123", "!!!", "é", "ÀÉ", "ß", "İ", "é", "ﬁ", "<|endoftext|>", "<|END", "日本", "\x1c", "\x85", "😀", "'s"])), max_size=12).map("".join))
def test_counts_equal_the_library(text):
    text = text.encode("utf-8", "ignore").decode()
    assert COUNTER.count(text) == lib(text)


def test_one_odd_character_does_not_send_the_whole_text():
    words = " ".join(["It\u2019s", "5\u20ac", "\u2014", "caf\u00e9", "\u65e5\u672c\u8a9e", "na\u0308ive", "<|endoftext|>x", "a\u3000b", "\u03a3\u03a3", "the\u0301", "\U0001f600"])
    seen = []
    c = T.Counter(open(T.default_path()).read())
    encode = c._encode
    c._encode = lambda w: seen.append(w) or encode(w)
    assert c.count(words + " plain words") == lib(words + " plain words")
    assert max(map(len, seen)) < 20 and {"na\u0308ive", "<|endoftext|>x"} <= set(seen)
    for ch in "\u2019\u20ac\u2014\u65e5\u03b1\u0436":
        assert not c.odd.search(ch)


@settings(max_examples=500, deadline=None)
@given(st.text(alphabet=st.characters(exclude_categories=["Cs"]), max_size=40))
def test_any_characters(text):
    assert COUNTER.count(text) == lib(text)


def test_query_and_edges(spark, sf):
    d = spark.read.parquet(f"{sf}/documents.parquet")
    src = {r.doc_id: r.text for r in d.collect()}
    for r in T.count_tokens(d).collect():
        assert (r.n_bytes, r.n_tokens, r.over_limit) == (len(src[r.doc_id].encode()), lib(src[r.doc_id]), lib(src[r.doc_id]) > 2048)
    s = "doc_id int, text string, n_tokens string"
    e = spark.createDataFrame([(1, None, "x"), (None, "", None), (2, "a" * 200000, ""), (2, "a" * 200000, "")], s)
    got = sorted((str(r.doc_id), r.n_tokens) for r in T.count_tokens(e).collect())
    assert got == [("1", 0), ("2", lib("a" * 200000)), ("2", lib("a" * 200000)), ("None", 0)]
    assert T.count_tokens(e.limit(0)).collect() == []


def test_memory_is_bounded():
    c = T.Counter(open(T.default_path()).read(), limit=5)
    words = [f"zqx{k}w" for k in range(40)]
    assert c.count(" ".join(words)) == lib(" ".join(words)) and 0 < len(c.known) <= c.limit
