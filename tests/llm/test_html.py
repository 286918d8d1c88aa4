import random

import numpy as np

from setanon.llm import html as hx


def test_blocks():
    page = '<title>T &amp</title><script>var t="</p>";</script><nav><ul><li><a href=x>a<li>b</ul></nav><!-- <p>no --><article class="x y"><h1>H&eacute;<br>z</h1><p><b>one\n two<br><p>three</p>tail</article><footer>&copy; f'
    got = [(".".join(b.path[-1:]), b.text) for b in hx.blocks(page)]
    assert got == [("title", "T &"), ("li", "a"), ("li", "b"), ("h1", "Hé z"), ("p", "one two"), ("p", "three"), ("article.x.y", "tail"), ("footer", "© f")]
    assert hx.blocks(None) == hx.blocks("") == hx.blocks("<p></p><!-- open") == []


def test_gradients_equal_differences():
    rnd = np.random.default_rng(0)
    net = hx.Net(3, 1, width=4)
    net.p = {k: v.astype(np.float64) for k, v in net.p.items()}
    x, n, y = rnd.normal(size=(3, 5, 4)), np.asarray([5, 2, 3]), rnd.integers(0, 2, (3, 5)).astype(float)
    _, g = net.gradients(x, n, y)
    for k, v in net.p.items():
        for at in list(np.ndindex(v.shape))[:: max(1, v.size // 6)]:
            old = v[at]
            v[at] = old + 1e-3
            up = net.gradients(x, n, y)[0]
            v[at] = old - 1e-3
            down = net.gradients(x, n, y)[0]
            v[at] = old
            assert abs((up - down) / 2e-3 - g[k][at]) < 2e-3, k


def test_padding_does_not_matter():
    net, rnd = hx.Net(4, 2, width=6), np.random.default_rng(1)
    seqs = [rnd.normal(size=(k, 6)).astype(np.float32) for k in (1, 7, 4)]
    both = net.forward(*hx.padded(seqs))
    for i, s in enumerate(seqs):
        assert np.allclose(both[i, : len(s)], net.forward(*hx.padded([s]))[0], atol=1e-5)


def test_query_on_given_pages(spark):
    pages = spark.read.parquet("/root/testdata/sf0.01/pages.parquet").select("page_id", "url", "html")
    net = hx.train(pages)
    got = {r.page_id: r for r in hx.extract(pages, net).collect()}
    rows = pages.collect()
    assert len(got) == len(rows)
    for r in rows:
        items = hx.blocks(r.html)
        want = hx.main_text(items, np.asarray([hx.taught(b) for b in items]))
        assert got[r.page_id].text == want and got[r.page_id].n_chars == len(want)
    rnd, wrong, total = random.Random(8), 0, 0
    made = [hx.blocks(hx.variant(r.html, rnd)) for r in rows]
    for b, k in zip(made, hx.labelled(net, made, hx.Vectors())):
        wrong += sum(hx.taught(x) != y for x, y in zip(b, k))
        total += len(b)
    assert wrong < 0.01 * total
    odd = spark.createDataFrame([(1, None, None, "k"), (1, "u", "", "k"), (None, "u", "<nav>x</nav>" * 3000, "k")], "page_id long, url string, html string, text string")
    assert [(r.text, r.n_chars) for r in hx.extract(odd, net).collect()] == [("", 0)] * 3
    assert hx.extract(odd.limit(0), hx.train(odd.limit(0))).count() == 0


S = (
    "The committee met on Tuesday to discuss the budget for the coming year, and members agreed on most points.",
    "Several residents spoke about the new road. They asked for more time to read the plans before the vote.",
    "A final decision is expected next month, according to the chair of the committee.",
)
PARAGRAPHS = "".join(f"<p>{x}</p>" for x in S)
MENU = '<ul><li><a href="/a">Home</a></li><li><a href="/b">News</a></li><li><a href="/c">Sport</a></li></ul>'
#: Hand-made layouts and the article in each; none is made by the operator's own generators.
LAYOUTS = {
    "nameless divs": (f'<html><head><title>T</title></head><body><div class="a1">{MENU}</div><div class="b2"><h1>Budget talks</h1>{PARAGRAPHS}</div><div class="c3"><p>© 2024 Example Ltd</p></div></body></html>', ["Budget talks", *S]),
    "table": (f'<html><body><table><tr><td width=120><a href="/a">Home</a><br><a href="/b">News</a></td><td><h1>Budget talks</h1><p>{S[0]}</p><p>{S[1]}</p></td></tr></table></body></html>', ["Budget talks", *S[:2]]),
    "misleading class": (f'<html><body><nav>{MENU}</nav><article><h1>Shares</h1><p>{S[0]}</p><div class="share-price">{S[1]}</div><p>{S[2]}</p></article><footer>© x</footer></body></html>', ["Shares", *S]),
    "reader comments": (f'<html><body><div class="menu">{MENU}</div><main><h1>Budget talks</h1>{PARAGRAPHS}</main><section id="comments"><div class="comment"><p>{S[1]}</p></div><article class="comment-body"><p>{S[0]}</p></article></section></body></html>', ["Budget talks", *S]),
    "notice": (f'<body><div class="cookie-notice"><p>We use cookies to improve this site. Accept?</p><button>OK</button></div><div id=page>{MENU}<div class=c9><h2>Budget talks</h2>{PARAGRAPHS}</div></div></body>', ["Budget talks", *S]),
    "bare": (f"<h1>Budget talks</h1>{PARAGRAPHS}", ["Budget talks", *S]),
    "divs for paragraphs": (f'<body><div class="x"><div class="y"><a href=1>One</a> <a href=2>Two</a></div><div class="y"><div><h1>Budget talks</h1></div><div>{S[0]}</div><div>{S[1]}</div><div>{S[2]}</div></div><div class="y"><a href=3>Privacy</a> <a href=4>Imprint</a></div></div></body>', ["Budget talks", *S]),
}


def test_layouts_without_role_names(spark):
    net = hx.train(spark.read.parquet("/root/testdata/sf0.01/pages.parquet"))
    for name, (page, want) in LAYOUTS.items():
        items = hx.blocks(page)
        got = [b.text for b, k in zip(items, hx.labelled(net, [items], hx.Vectors())[0]) if k]
        assert got == want, name


def test_quotes_count_only_in_attribute_values():
    assert [b.text for b in hx.blocks("<p class=it's>Hello there.</p><p>It's fine</p>")] == ["Hello there.", "It's fine"]
    assert [(b.path[-1], b.text) for b in hx.blocks("<div data-class='x' class=\"a>b\">one</div><p title='no end>two")] == [("div.a>b", "one"), ("p", "two")]


def test_sample_is_bounded_and_distinct(spark):
    rows = [(i, "u", "<article><p>A sentence that is the same.</p></article>") for i in range(300)] + [(i, "u", f"<article><p>{i}</p></article>") for i in range(300, 320)]
    seen = []
    keep, hx.fit = hx.fit, lambda pages, opt: seen.append(pages)
    try:
        hx.train(spark.createDataFrame(rows, "page_id long, url string, html string"), hx.Options(max_pages=15))
    finally:
        hx.fit = keep
    assert len(seen[0]) == len(set(seen[0])) == 15
