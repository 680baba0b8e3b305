import hashlib
import random
import re
import string

from hypothesis import given, settings
from hypothesis import strategies as st

from cubelens.llm import secrets as S

KW = "|".join("".join(f"[{c}{c.upper()}]" if c.isalpha() else c for c in w) for w in ("password", "passwd", "secret", "token")) + "|[aA][pP][iI]_?[kK][eE][yY]"
BASE = {
    "assign": re.compile(rf"""({KW})["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""),
    "access": re.compile("AKIA[A-Z0-9]+"),
    "hex": re.compile("[0-9a-f]+"),
}
MACHINE = S.compile_rules()


def brute(text):
    out = []
    for n, (k, r) in enumerate(BASE.items()):
        for m in r.finditer(text or ""):
            if len(m[2]) >= 6 if k == "assign" else len(m[0]) >= (20 if k == "access" else 24):
                out.append((m.start(), n, m.end(), k))
    return [(k, a, b) for a, _, b, k in sorted(out)]


def base(text):
    return [s for s in S.spans_of(text, MACHINE) if s[0] in S.BASE_KINDS]


PIECES = st.sampled_from(["token", "TOKEN", "passwd", "Password", "secret", "api_key", "apikey", "=", ":", " ", "  ", '"', "'", "==", "abc", "abcdef", "é", "ſ", "K", "AKIA", "AKIAABCDEFGH", "0123456789", "0123456789abcdef01234567", "f" * 23, "\n", "-", "x", "ghp_", "eyJ", "a" * 40, ".", "://", "http", ":b@"])


@settings(max_examples=600, deadline=None)
@given(st.lists(PIECES, max_size=14).map("".join))
def test_base_spans_match_regular_expressions(text):
    assert base(text) == brute(text)


def test_known_texts():
    for t in ["", None, "token=token: abcdef", "token==abcdef", "password:token=abcdef", "secret: ab token: abcdef", "f" * 24, "AKIAAKIA" + "A" * 12, "é" * 50 + "token = 'abcdefg", "token = " + "a" * 5000]:
        assert base(t) == brute(t)
    extra = {s[0] for s in S.spans_of("-----BEGIN RSA PRIVATE KEY----- ghp_" + "a" * 36 + " xoxb-1234567890-abcdef https://u:pw@h", MACHINE)}
    assert extra >= {"private_key", "forge_token", "chat_token", "url_login"}


def test_automaton_is_small_and_minimal():
    assert MACHINE.any.n_states < 5000 and MACHINE.any.width < 80


def test_query_and_masking(spark):
    d = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    rows = {r.doc_id: r for r in S.secret_report(d).collect()}
    n = 0
    for r in d.collect():
        want = brute(r.text)
        got = rows[r.doc_id]
        assert (got.n_assign, got.n_access, got.n_hex) == tuple(sum(s[0] == k for s in want) for k in BASE)
        assert got.base_sha256 == hashlib.sha256(",".join(f"{k}:{a}:{b}" for k, a, b in want).encode()).hexdigest()
        n += len(want)
    assert n
    left = S.mask_secrets(d)
    assert left.schema == d.schema and left.count() == d.count()
    for r in left.collect():
        assert not brute(r.text) and r.n_chars == len(r.text)


def test_edge_cases(spark):
    s = "doc_id int, text string, spans string, kind int"
    rows = [(1, None, "a", 1), (None, "token=abcdef", None, None), (1, None, "a", 1), (2, "", "", 2), (3, "x token='0123456789abcdef0123456789' y", "", 0)]
    d = spark.createDataFrame(rows, s)
    got = sorted((str(r.doc_id), r.n_assign, r.n_hex, r.spans) for r in S.secret_report(d).collect())
    assert got == [("1", 0, 0, ""), ("1", 0, 0, ""), ("2", 0, 0, ""), ("3", 1, 1, "assign:2:35,hex:9:35"), ("None", 1, 0, "assign:0:12")]
    assert [r.text for r in S.mask_secrets(d).orderBy("spans", "doc_id").collect()][-1] is None
    assert "x [SECRET]' y" in [r.text for r in S.mask_secrets(d).collect()]
    assert S.secret_report(d.limit(0)).collect() == [] and S.mask_secrets(d.limit(0)).collect() == []


def test_shortest_match_beyond_any_window():
    token = "eyJ" + "a" * 300 + "." + "b" * 900 + "." + "c" * 43
    login = "https://" + "u" * 300 + ":" + "p" * 300 + "@"
    for text, kind in ((token, "web_token"), (login, "url_login")):
        for behind in ("", " and the text goes on " + "x y " * 300):
            assert (kind, 3, 3 + len(text)) in S.spans_of("at " + text + behind, MACHINE)
    for text in ("token" + " " * 300 + "= abcdefgh and on " + "x y " * 300, "secret =" + " " * 5000 + "'abcdefgh' " + "x y " * 300):
        assert base(text) == brute(text) != []


def test_private_keys_are_masked_to_their_last_character(spark):
    rng = random.Random(4)
    body = ["".join(rng.choices(string.ascii_letters + string.digits + "+/", k=64)) for _ in range(25)] + ["Qx9/kA=="]
    begin, end = "-----BEGIN RSA PRIVATE KEY-----", "-----END RSA PRIVATE KEY-----"
    head = "Proc-Type: 4,ENCRYPTED\nDEK-Info: AES-256-CBC,0123ABCD\n\n"
    keys = [
        "\n".join([begin, *body, end]),
        "\r\n".join([begin, *body, end]),
        "\\n".join([begin, *body, end]),
        f"{begin}\n{head}" + "\n".join([*body, end]),
        "\\n\" +\n \"".join([begin, *body, end]),
        " ".join([begin, *body, end]),
        "\n".join([begin, *body]),
        "\\n".join([begin, *body]),
        "\n".join([begin, *body[:9], "Qx9kAB"]),
        f"{begin}\n{head}" + "\n".join(body),
        begin + end,
        begin,
    ]
    for key in keys:
        for behind in ("", ". It was found, see é.", "\n\nThe text goes on. " + "x y " * 300, " " + keys[0]):
            spans = [s for s in S.spans_of("é in " + key + behind, MACHINE) if s[0] == "private_key"]
            assert spans[0] == ("private_key", 5, 5 + len(key)), (key, behind)
            assert len(spans) == 1 + (keys[0] in behind)
    d = spark.createDataFrame([(k, "see " + t + "\n\nthe end") for k, t in enumerate(keys)], "doc_id long, text string")
    assert {r.text for r in S.mask_secrets(d).collect()} == {"see [SECRET]\n\nthe end"}
    assert S.spans_of(begin + " marks a key in plain words, " + "x y " * 300, MACHINE) == [("private_key", 0, len(begin))]
    assert len(S.spans_of((begin + " and words ") * 2000, MACHINE)) == 2000
