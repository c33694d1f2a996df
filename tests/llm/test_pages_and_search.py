"""URL filters, HTML extraction and exact search against brute force."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from nodeweave.llm import html, topk, urls

URLS = [None, "", "no scheme", "http://WWW.Example.com/en/1", "http://example.com/en", "http://a.example.com/en/x?q", "http://x.net/es/a#b", "http://x.net/de", "http://net/fr/", "https://www.casino-win.example.org/de/5", "http://cheappills.example.org/", "http://dailynews.example.org/en", "http://b.com", "http://b.com/", "ftp://x.com:80/a://b", "http://É.COM/ä", "://com/", "http://examplecom/en/"]


def brute(url):
    if url is None or "://" not in url:
        return "", "", None, None
    rest = url.split("://", 1)[1]
    cut = min([rest.find(c) for c in "/?#" if c in rest], default=len(rest))
    host = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in rest[:cut])
    path = rest[cut:]
    path = path[: min([path.find(c) for c in "?#" if c in path], default=len(path))]
    fits = [(len(h + p), h + p, v) for v, h, p in urls.RULES if (host == h or host.endswith("." + h)) and path.startswith(p)]
    best = max(fits, default=(0, None, None))
    return host, path, best[1], best[2]


def test_rules(spark):
    pages = spark.createDataFrame([(i, u, "x", "y") for i, u in enumerate([*URLS, URLS[3]])], "page_id long, url string, host string, verdict string")
    rows = {r["page_id"]: r for r in urls.judge(pages).collect()}
    assert len(rows) == len(URLS) + 1
    model = urls.NameModel()
    for i, u in enumerate(URLS):
        host, path, rule, verdict = brute(u)
        want = verdict or ("block" if model.log_odds(host, path) > 0 else "allow")
        assert (rows[i]["host"], rows[i]["path"], rows[i]["rule"], rows[i]["verdict"]) == (host, path, rule, want)
    assert rows[9]["verdict"] == "block" and rows[10]["verdict"] == "block" and rows[11]["verdict"] == "allow" and rows[0]["verdict"] == "allow"
    assert urls.judge(pages.limit(0)).count() == 0


def test_weights_are_naive_bayes():
    """Log odds from the counts of labelled words, by hand."""
    import math

    blocked, allowed = "casino-win big-win", "daily-news city"
    model = urls.NameModel(blocked, allowed, prior=0.3, smooth=0.5)
    words = {"casino", "win", "big", "daily", "news", "city"}
    b = {w: ["casino", "win", "big", "win"].count(w) for w in words}
    a = {w: ["daily", "news", "city"].count(w) for w in words}
    odds = lambda ws: math.log(0.3 / 0.7) + sum(math.log((b[w] + 0.5) / (4 + 3)) - math.log((a[w] + 0.5) / (3 + 3)) for w in ws if w in words)
    for host, path, want in (("casinowin.net", "/", ["casino", "win"]), ("www.bigcity.org", "/news/x.html", ["big", "city", "news"]), ("zzz.org", "/", [])):
        assert math.isclose(model.log_odds(host, path), odds(want))


def test_dictionary_is_counted_over_all_pages(spark):
    pages = spark.createDataFrame([(1, "http://tinyhouse.org/a", "<p>Tiny house, tiny</p><script>var tiny=1</script>"), (2, None, None), (3, "http://x.org/", "<b class='house'>HOUSE &amp; caf\u00e9</b>")], "page_id long, url string, html string")
    assert urls.corpus_words(pages) == {"tiny": 2, "house": 2, "caf\u00e9": 1}
    model = urls.NameModel(counts=urls.corpus_words(pages))
    assert model.segment("tinyhouse") == ("tiny", "house") and model.segment("housecaf\u00e9") == ("house", "caf\u00e9")


def test_hosts_of_blocked_trades(spark):
    pages = spark.createDataFrame([(i, f"http://{h}/de/1", "<p>words of a page</p>") for i, h in enumerate(("blog.adult-cams.example.net", "freebets.example.org", "gardenrecipes.example.org", "zorblax.example.org"))], "page_id long, url string, html string")
    assert [r["verdict"] for r in urls.judge(pages).orderBy("page_id").collect()] == ["block", "block", "allow", "allow"]


@settings(max_examples=60, deadline=None)
@given(st.text(alphabet="abcinosw", max_size=9))
def test_viterbi_is_the_best_split(text):
    model = urls.NameModel("casino win", "cow is son")

    def cost(parts):
        total, before = 0.0, False
        for p in parts:
            if p in model.cost:
                total, before = total + model.cost[p], False
            else:
                total += 2.0 * len(p) + (0 if before else np.log(10 * model.total))
                before = True
        return total

    def splits(s):
        if not s:
            yield []
        for i in range(1, len(s) + 1):
            for rest in splits(s[i:]):
                yield [s[:i], *rest]

    got = model.segment(text)
    assert "".join(got) == text
    assert abs(cost(got) - min(map(cost, splits(text)))) < 1e-9


PAGE = """<html><head><title>T</title><style>p{}</style><script>var t="</p>";</script></head><body class="has-sidebar"><header><h1>Site</h1></header>
<nav><ul><li><a href="/">Home</a></li></ul></nav><div class="cookie-notice"><p>We use cookies, many, many cookies.</p></div>
<div id="wrap"><article><h1>Title &amp; more</h1><p><b>One, two, <i>thr</i>ee.<br><p>Four
   five &#233;.</p><form><p>Mail</p></form><ul><li>item one<li>item two</ul><script>x</script><div class="ad">Buy</div><!-- no --></article>
<aside>Side, side, side.</aside><section id="comments"><p>First, I say, comment, long, long, long, long, long.</p></section></div><footer>&copy; me</footer></body></html>"""


def test_extraction():
    assert html.extract(PAGE) == "Title & more One, two, three. Four five é. item one item two"
    assert html.extract(None) == "" and html.extract("") == "" and html.extract("<script>x</script>") == ""
    assert html.extract("just text, no tags &lt;") == "just text, no tags <"
    assert html.extract("<div><p>Short one, yes.</p><p>a < b and c > d</p></div>") == "Short one, yes. a < b and c > d"
    plain = "<body><div class=menu><a href=x>Home</a></div><div><h2>Head</h2><div><p>" + "A long paragraph, with commas, and words. " * 20 + "</p><p>Tail.</p></div></div><div class='footer'>x</div></body>"
    got = html.extract(plain)
    assert got.startswith("Head") and got.endswith("Tail.") and "Home" not in got


@settings(max_examples=80, deadline=None)
@given(st.text(alphabet=st.sampled_from("<>/ap divbr\"'=!-&;x\n"), max_size=120))
def test_extraction_never_fails(source):
    assert isinstance(html.extract(source), str)


def test_extraction_query(spark):
    big = "<p>" + "word, " * 100_000 + "</p>"
    pages = spark.createDataFrame([(1, "u", PAGE, "x"), (1, "u", PAGE, "x"), (2, None, None, "x"), (3, "u", big, "x")], "page_id long, url string, html string, text string")
    rows = sorted(html.main_texts(pages).collect(), key=lambda r: r["page_id"])
    assert [r["n_chars"] for r in rows] == [len(r["text"]) for r in rows] and rows[0] == rows[1] and rows[2]["text"] == "" and rows[3]["n_chars"] == 599_999
    assert html.main_texts(pages.limit(0)).count() == 0


def brute_top(vectors, queries, k):
    out = []
    for q, v in queries:
        best = sorted((-(np.dot(v, w)), i) for i, w in vectors if i != q and len(w) == len(v))[:k]
        out += [(int(q), n + 1, int(i), int(-s)) for n, (s, i) in enumerate(best)]
    return sorted(out)


def test_top_k_against_brute_force(spark, monkeypatch):
    rng = np.random.default_rng(0)
    x = rng.normal(size=(300, 16)) / 4
    x[100:150] = x[7]  # a group of equal vectors, with ties
    rows = [(i, [float(np.float32(t)) for t in v], 0) for i, v in enumerate(x)]
    rows += [(300, None, 0), (350, [float("nan")] * 16, 0), (400, [None] + [0.1] * 15, 0), (450, [float("inf")] * 16, 0), (500, [0.1] * 8, 0), (550, [], 0)]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<float>, score int").repartition(4)
    monkeypatch.setattr(topk, "BASE_ROWS", 64)
    monkeypatch.setattr(topk, "QUERY_ROWS", 4)
    monkeypatch.setattr(topk, "BATCH", 3)
    q = topk.quantised(frame)
    got = sorted(tuple(r) for r in topk.top_k(q, q.filter("vec_id % 50 = 0"), 5).collect())
    ints = [(i, np.floor(256 * np.array(v, dtype=np.float32).astype(float)).astype(int)) for i, v, _ in rows if v and None not in v and np.isfinite(np.array(v, dtype=float)).all()]
    assert got == brute_top(ints, [t for t in ints if t[0] % 50 == 0], 5)
    assert topk.top_k(q.limit(0), q.limit(0), 5).count() == 0


@pytest.mark.parametrize("scale", [1.0, 1e4, 1e7, 1e12])
def test_top_k_of_large_components(spark, monkeypatch, scale):
    """Any finite component is served: scores beyond a long are held at its ends, ranks are by exact values."""
    rng = np.random.default_rng(2)
    x = rng.normal(size=(150, 6)).astype(np.float32)
    x[::7] *= np.float32(scale)
    x[5, 0] = 3e38
    rows = [(i, [float(t) for t in v]) for i, v in enumerate(x)]
    monkeypatch.setattr(topk, "BASE_ROWS", 40)
    q = topk.quantised(spark.createDataFrame(rows, "vec_id long, embedding array<float>").repartition(3))
    got = sorted(tuple(r) for r in topk.top_k(q, q.filter("vec_id % 50 = 0"), 5).collect())
    ints = {i: [max(-(1 << 52), min(1 << 52, int(np.floor(256 * t)))) for t in v] for i, v in rows}
    want = []
    for a in (0, 50, 100):
        scored = sorted((-sum(s * t for s, t in zip(ints[a], v, strict=True)), i) for i, v in ints.items() if i != a)[:5]
        want += [(a, n + 1, i, max(-(1 << 63), min((1 << 63) - 1, -s))) for n, (s, i) in enumerate(scored)]
    assert got == want


@settings(max_examples=40, deadline=None)
@given(st.integers(1, 60), st.integers(1, 6), st.integers(1, 7), st.integers(0, 999))
def test_index_is_exact(n, dims, k, seed):
    rng = np.random.default_rng(seed)
    v = rng.integers(-300, 300, (n, dims))
    ids = rng.permutation(1000)[:n]
    got = topk.ImpactIndex(ids, v).top(v[: min(n, 5)], ids[: min(n, 5)].tolist(), k)
    for j, (a, b) in enumerate(got):
        want = sorted((-int(v[j] @ v[i]), int(ids[i])) for i in range(n) if ids[i] != ids[j])[:k]
        assert [(-int(s), int(i)) for i, s in zip(a, b, strict=True)] == want
