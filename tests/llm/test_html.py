import random

from cyclefold.llm import html


def text_of(page, template=frozenset()):
    return html.extract(html.parse(page), set(template))


def test_declared_parts_go():
    page = """<!DOCTYPE html><html><head><title>T</title><style>p{}</style></head><body class="has-sidebar">
    <header><h1>Site</h1></header><nav><ul><li><a href=x>Home</a></ul></nav><div class="cookie-notice">Accept?</div>
    <main><article class=post><header><h1>The  &amp; title</h1></header><p>One <b>bold</b>&nbsp;word<br>two<p>Three &lt;3 a<b>c</b>d
    <script>var t="</p>";</script><aside>Also</aside><form><input value="a>b"></form><div class="ad box">Buy</div>
    <ul><li>x<li>y</ul><section id="comments"><article><p>First! a very long comment that is longer than all the rest of this page
    and goes on and on and on for a while</article></section></article></main><!-- <p>no</p> --><div hidden class="newsletter">Sign</div><footer>&copy;</footer>"""
    assert text_of(page) == "The & title\nOne bold word two\nThree <3 acd\nx\ny"
    assert text_of("<p>adder</p><div class='reader'>shared text</div><div class='share'>no</div>") == "adder\nshared text"
    assert text_of("plain a < b text &amp; more") == "plain a < b text & more"
    for nothing in ("", "<", "<script>", "<!-- x", "<div></div>", "<nav>only</nav>"):
        assert text_of(nothing) in ("", "<")


def test_templates_by_host_counts(spark):
    draw = random.Random(2)
    words = lambda n: " ".join("".join(draw.choice("abcdefgh") for _ in range(5)) for _ in range(n))
    rows, want = [], {}
    for i in range(12):
        body = words(30)
        top = "<div><p>Our shop</p><a href=/>Top</a></div>" if i < 8 else f"<div><p>{words(4)}</p></div>"
        host = "a.example" if i < 8 else "b.example"
        note = words(3) if i else "We deliver everywhere"
        rows.append((i, f"http://{host}/p{i}", f"<body>{top}<div><p>{body}</p></div><div><p>{note}</p></div>"))
        want[i] = (body if i < 8 else html.extract(html.parse(top), set()) + "\n" + body) + "\n" + note
    article = "<body><div class=x>Rarely</div><article><h1>Same</h1><p>text of copies</p></article>"
    for i in range(20, 30):  # many copies of one article are no template
        rows.append((i, "http://c.example/", article))
        want[i] = "Same\ntext of copies"
    for i in range(40, 50):  # a paragraph that recurs inside articles is content, a container is template
        rows.append((i, "https://U@D.example:80/x", f"<article><p>Licence line.</p><div><b>Rate us</b></div><p>{(w := words(9))}</p></article>"))
        want[i] = f"Licence line.\n{w}"
    rows += [(90, "http://a.example/", None), (90, "http://a.example/", None), (91, None, "<p>x</p>"), (None, "", "<p>y</p>")]
    want |= {90: "", 91: "x", None: "y"}
    pages = spark.createDataFrame([(*r, 7) for r in rows], "page_id long, url string, html string, hashes int")
    got = html.main_text(pages).collect()
    assert len(got) == len(rows)
    for r in got:
        assert r.text == want[r.page_id] and r.n_chars == len(r.text), (r, want[r.page_id])
    assert html.main_text(pages.limit(0)).count() == 0


def test_hostile_pages():
    for page in ("<div>" * 20_000 + "x", "<p>" * 20_000, "<a b='" * 5000, "<" * 50_000, "<!--" * 20_000, "<li><ul>" * 5000 + "x", "</p>" * 2000):
        html.extract(html.parse(page), set())
        html.candidates(html.parse(page))


def test_article_content_is_not_told_by_compound_names():
    page = "<article><h2 class='related-work'>Related work</h2><p class='related-work'>Others did so.</p><p class='notice-board'>Boards.</p><section class='share-price'><p>Prices rose.</p></section><div class='share'>Tweet</div><div class='comment-list'><p>First!</p></div><p>End.</p></article>"
    assert text_of(page) == "Related work\nOthers did so.\nBoards.\nPrices rose.\nEnd."


def test_sites_without_declared_parts(spark):
    """Nothing says what is template: no article, no roles, no telling names. Only repetition on the host does."""
    draw = random.Random(5)
    words = lambda n: " ".join("".join(draw.choice("abcdefgh") for _ in range(5)) for _ in range(n))
    rows, want = [], {}
    for site in range(4):
        top, side, end = (f"<div class=x{draw.randrange(99)}><p>{words(6)}</p><ul><li>{words(1)}<li>{words(2)}</ul></div>" for _ in range(3))
        for i in range(9):
            page, body = site * 100 + i, [words(draw.randrange(5, 40)) for _ in range(draw.randrange(1, 5))]
            rows.append((page, f"https://s{site}.example/{i}", f"<html><body>{top}<div>{side}<div>{''.join(f'<p>{b}</p>' for b in body)}</div></div>{end if i % 2 else ''}{end}</body></html>"))
            want[page] = "\n".join(body)
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    got = html.main_text(pages).collect()
    assert {r.page_id: r.text for r in got} == want
    assert all(r.n_template >= 3 for r in got)
    alone = html.main_text(pages.filter("page_id % 100 < 4")).collect()  # four pages are no template
    assert all(r.n_template == 0 and len(r.text) > len(want[r.page_id]) for r in alone)


def test_hosts_of_many_templates_go_page_by_page(spark, monkeypatch):
    pages = spark.read.parquet("/root/testdata/sf0.1/pages.parquet")
    whole = sorted(map(tuple, html.main_text(pages).collect()), key=str)
    assert sum(r[4] for r in whole) > 0
    monkeypatch.setattr(html, "HOST_LIST", 0)
    assert sorted(map(tuple, html.main_text(pages).collect()), key=str) == whole


def test_what_some_articles_of_a_large_site_share_stays(spark):
    table = "<table><tr><td>Units<td>Metres</table>"
    rows = [(i, "http://a.example/", f"<article><p>text number {i} of this large site with some words</p>{table if i % 8 == 0 else ''}<div><b>Rate us</b></div></article>") for i in range(64)]
    got = html.main_text(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()
    for r in got:
        assert r.text == f"text number {r.page_id} of this large site with some words" + ("\nUnits\nMetres" if r.page_id % 8 == 0 else "")
