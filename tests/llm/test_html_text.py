import html
import random
import re
import zlib

import numpy as np

from cubelens.llm import html_text as H


def wanted(page):
    """The article of a generated page, by cutting its known markup."""
    m = re.search(r"<article>(.*?)</article>", page, re.S)
    body = m[1] if m else page[page.index("<article>") + 9 :].split("<footer")[0]
    parts = re.split(r"</?(?:p|h1|article)>", body)
    return "\n".join(t for b in parts if (t := " ".join(html.unescape(re.sub("</?b>", "", b.replace("<br>", " "))).split())))


def test_query_on_generated_pages(spark, sf):
    d = spark.read.parquet(f"{sf}/pages.parquet")
    src = {r.page_id: r for r in d.collect()}
    rows = H.extract(d).collect()
    assert len(rows) == len(src)
    for r in rows:
        assert r.text == wanted(src[r.page_id].html) and r.n_chars == len(r.text) and r.url == src[r.page_id].url


def test_best_run_matches_brute_force():
    rng = random.Random(1)
    for _ in range(200):
        x = np.array([rng.randint(-4, 4) for _ in range(rng.randint(0, 12))], float)
        a, z = H.best_run(x)
        best = max((x[i:j].sum() for i in range(len(x)) for j in range(i + 1, len(x) + 1)), default=0)
        assert x[a:z].sum() == max(best, 0)


W = H.default_weights() | {"li": -0.35, "a": -0.7, "div": -1.0}


def test_weights_decide(spark, sf):
    """Other weights give other texts; the mark of an article is not looked at."""
    rows = spark.read.parquet(f"{sf}/pages.parquet").collect()
    w = H.learn(spark.read.parquet(f"{sf}/pages.parquet"))
    dear = H.Weights(dict.fromkeys(w.tags, -50.0), w.names)
    free = H.Weights(dict.fromkeys(w.tags, -0.0001))
    assert w.tags["div"] < w.tags["p"] and zlib.crc32(b"ad") % H.NAME_BUCKETS in w.names
    apart = 0
    for r in rows:
        text, div = H.main_text(r.html, w), r.html.replace("<article>", "<div>").replace("</article>", "</div>")
        assert H.main_text(div, w) == text
        assert H.main_text(r.html, dear) != text
        unnamed = div.replace(' class="ad"', "")
        apart += H.main_text(unnamed, free) != H.main_text(unnamed, w)
    assert apart > len(rows) / 4


def test_region_is_the_best_run():
    """On small pages of plain blocks the text is that of the best of all runs."""
    rng = random.Random(4)
    for _ in range(300):
        blocks = [(rng.choice(["p", "div", "li", "h2"]), rng.randint(0, 9)) for _ in range(rng.randint(1, 7))]
        page = "".join(f"<{t}>{' '.join(f'w{i}x{k}' for k in range(n))}</{t}>" for i, (t, n) in enumerate(blocks))
        w = {t: -rng.choice([0.02, 1.0, 3.0]) for t in ("p", "div", "li", "h2")}
        score = lambda a, z: sum(n for _, n in blocks[a:z]) + 2 * sum(w[t] for t, _ in blocks[a:z]) - w[blocks[a][0]] - w[blocks[z - 1][0]]
        best = max((score(a, z), z - a, -a) for a in range(len(blocks)) for z in range(a + 1, len(blocks) + 1) if blocks[a][1] and blocks[z - 1][1]) if any(n for _, n in blocks) else None
        got = [i for i in range(len(blocks)) if f"w{i}x0" in H.main_text(page, w)]
        if best is None:
            assert got == []
        else:
            a, z = min(got), max(got) + 1
            assert abs(score(a, z) - best[0]) < 1e-6


def test_broken_markup_and_names_of_text():
    cases = {
        "<p class='x>one two</p>": "one two",
        "<p>a b</p><p class=\"y>c d": "a b\nc d",
        "<p>1 < 2 and 3 <4</p>": "1 < 2 and 3 <4",
        "<article><p>a b c</p><p class='share-price'>the price rose</p><p id='reply'>they said so</p></article>": "a b c\nthe price rose\nthey said so",
        "<p>one two</p></3 x><p>three four</p>": "one two\nthree four",
        "<body><header><h1>Site</h1></header><div><header><h1>Head line</h1></header><p>a b c</p></div></body>": "Head line\na b c",
        "<div><header><ul><li>x</li></ul><h2>Site name</h2></header><p>a b c</p></div>": "a b c",
    }
    for page, text in cases.items():
        assert H.main_text(page, W) == text, page


def test_structures():
    cases = {
        "<main><p>x y z</p><section class='comments'><p>a reader says a lot of words</p></section></main>": "x y z",
        "<body><div id=menu>m</div><div id=content><h1>T one</h1><p>para one two three</p><ul><li>item a</li></ul><div class='ad-box'>buy</div><p>last words here and the many others that go on to the end of it</p></div></body>": "T one\npara one two three\nitem a\nlast words here and the many others that go on to the end of it",
        "<article><p>a&amp;b &lt;c&gt; &copy &#233;</p><script>var x='<p>no</p>'</script><form><p>mail</p></form><p>d\n\t e<br>f</p></article>": "a&b <c> © é\nd e f",
        "<article><p>one<p>two<aside>no</aside><header><h1>three</h1></header></article><header>no</header>": "one\ntwo\nthree",
        "<p hidden>no</p><p>yes it is</p>": "yes it is",
        "plain text only": "plain text only",
        "<script>if (a<b) {}": "",
        "<p title='a>b'>q</p>": "q",
    }
    for page, text in cases.items():
        assert H.main_text(page, W) == text, page


def test_content_under_names_like_boilerplate():
    cases = {
        "<div class='has-sidebar'><article><p>a b c</p></article><div class='sidebar'>no</div></div>": "a b c",
        "<div id='page' class='site no-sidebar'><article><p>a b c</p></article></div>": "a b c",
        "<article><div class='post-header'><h1>Head line</h1></div><p>a b c</p></article>": "Head line\na b c",
        "<article><div class='header'><h1>Head line</h1></div><p>a b c</p></article>": "Head line\na b c",
        "<article><section id='related-work'><p>others did</p></section><section id='search-algorithms'><p>we find</p></section></article>": "others did\nwe find",
        "<form id='aspnetForm'><main><p>a b c</p></main></form>": "a b c",
        "<div class='sidebar widget'><article><p>a b c d</p></article></div><p>x</p>": "a b c d",
        "<div class='modal'><p>most of the words of all stand here</p><div class='ads'>buy</div></div><div>x</div>": "most of the words of all stand here",
        "<article><p>a b c</p></article><div class='comments'><article><p>a reader says many more words</p></article></div>": "a b c",
        "<article><p>a b c</p></article><div class='related-posts'><article><p>d e f g h</p></article></div>": "a b c",
        "<article><p>a b</p><figure><img src=x><figcaption>what it shows</figcaption></figure></article>": "a b\nwhat it shows",
        "<article><p>so <math><semantics><mrow><mi>x</mi><mo>=</mo><mn>1</mn></mrow><annotation>x=1</annotation></semantics></math> holds</p></article>": "so x=1 holds",
        "<article><p>a b</p><div class='cookie-banner'>no</div><div class='ad-box'>no</div><div class='navBar'>no</div><div class='site-footer'>no</div></article>": "a b",
    }
    for page, text in cases.items():
        assert H.main_text(page, W) == text, page


def test_edge_cases(spark):
    s = "page_id int, url string, html string, text string"
    d = spark.createDataFrame([(1, None, None, "t"), (None, "u", "", None), (2, "u", "<p>" * 3000 + "deep", ""), (2, "u", "<p>" * 3000 + "deep", ""), (3, "u", "<div>" * 5000 + "x " * 50000, "")], s)
    got = {(r.page_id, r.n_chars) for r in H.extract(d).collect()}
    assert got == {(1, 0), (None, 0), (2, 4), (3, 99999)}
    assert H.extract(d).count() == 5 and H.extract(d.limit(0)).collect() == []
