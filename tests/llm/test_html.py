"""Extraction from the given pages (by a plain rule for their one layout), from made pages, and edge cases."""

import html
import random
import re
import time

import pytest

from boxmdl.llm import html_text

SF = "/root/testdata/sf0.001"


def text(page, recurring=frozenset()):
    return html_text.main_text(html_text.parse(page), recurring)


def test_given_pages(spark):
    got = {r.page_id: r for r in html_text.op3_site_template_removal(spark, SF).collect()}
    pages = spark.read.parquet(f"{SF}/pages.parquet").collect()
    assert len(got) == len(pages)
    for p in pages:
        inner = re.search(r"<article>(.*)</article>", p.html, re.S)[1]
        blocks = [" ".join(html.unescape(re.sub(r"<[^>]*>", "", x)).split()) for x in re.split(r"</?(?:p|h1)>", inner)]
        expected = "\n".join(b for b in blocks if b)
        assert got[p.page_id].text == expected and got[p.page_id].n_chars == len(expected) and got[p.page_id].url == p.url


@pytest.mark.parametrize(
    ("page", "expected"),
    [
        ("<p>a &lt;b&gt;&nbsp;c<br>d</p>tail", "a <b> c d\ntail"),
        ("<p>one<p>two<ul><li>x<li>y <b>z</b></ul>", "one\ntwo\nx\ny z"),
        ("<nav>menu</nav><div class='side-bar sidebar'>s</div><div id=comments>c</div><div class=x>t</div>", "t"),
        ("<article>a<aside>no</aside><div class='ad-box'>no</div><p>b</p></article><div>other</div>", "a\nb\nother"),
        ("<article><div class='article-header'><h1>Title</h1></div><p>Body.</p><section id='related-work'><p>Others did.</p></section></article>", "Title\nBody.\nOthers did."),
        ("<article><header><h1>Title</h1></header><p>Body</p><footer>no</footer></article><header>no</header>", "Title\nBody"),
        ("<div class='site-header'>no</div><main><div class='header'><h1>T</h1></div><div class='cookie-banner'>no</div><p class='social alert'>kept</p><div id='comments'>no</div></main>", "T\nkept"),
        ("<div class='notice-period railway'>kept</div><div class='main-nav'>no</div><ul role='navigation'><li>no</ul><form><p>no</form>", "kept"),
        ("<p title='a > b' x=it's>one</p><p y=\"never closed>two</p>", "one\ntwo"),
        ("<main><h1>T</h1><script>if (a < b) x('</p>')</script>text<!-- <p>no</p> --></main>", "T\ntext"),
        ("<table><tr><td>1<td>2<tr><td>3</table>", "1\n2\n3"),
        ("a<span hidden>no</span>b<div style='display: none'>no</div>c", "ab\nc"),
        ("no markup at all", "no markup at all"),
        ("unclosed <b>bold <p>next <i", "unclosed bold\nnext"),
        ("<div class='download headline'>kept</div>", "kept"),
        ("", ""),
    ],
)
def test_made_pages(page, expected):
    assert text(page) == expected


def test_deep_nesting_and_length():
    assert text("<div>" * 5000 + "deep" + "</div>" * 5000) == "deep"
    assert len(text("<p>" + "word " * 200_000)) == 999_999


@pytest.mark.parametrize(
    "page",
    ["<a x " * 200_000, "<a x=\"" * 150_000, "<a x='b' " * 100_000 + ">", "<div>" * 200_000, "<button><p>" + "<div>" * 100_000, "<b>" * 200_000 + "</i>" * 100_000, "<b><div>" + "<i>" * 150_000 + "</b>" * 100_000, "<p " + "x" * 1_000_000 + " class=a>t", "<!-- " * 200_000, "= " * 500_000 + "<p =" + " " * 500_000 + ">t", "</p>" * 150_000, "<table><tr><td>" * 60_000, "<script>" * 120_000, "&amp;" * 200_000],
    ids=str.__len__,
)
def test_long_pages_take_linear_time(page):
    began = time.monotonic()
    root = html_text.parse(page)
    html_text.page_subtrees(root)
    text(page)
    assert time.monotonic() - began < 10  # a second or two each; quadratic work would take hours


def plain_recurring(pages, least, share, many):
    """Subtrees to delete by host, counted page by page."""
    seen, held = {}, {}
    for host, page in pages:
        for kind, digest, subtrees in html_text.page_subtrees(html_text.parse(page)):
            if (host, kind, digest) not in seen:
                seen[host, kind, digest] = subtrees
    for (host, kind, _), subtrees in seen.items():
        held[host, None] = held.get((host, None), 0) + (kind == "page")
        for x in subtrees:
            held[host, x] = held.get((host, x), 0) + 1
    return {(host, x) for (host, x), n in held.items() if x is not None and n >= least and (n >= share * held[host, None] or n >= many)}


def test_templates_by_counting_alone(spark):
    """Hosts without article, tags or class names that tell anything: what recurs goes, the rest stays."""
    rng = random.Random(4)
    words = lambda n: " ".join(rng.choice("ab cde fgh ijk lmno pq rstu vw xyz".split()) + str(rng.randrange(999)) for _ in range(n))
    rows, expected = [], {}
    for h in range(4):
        top, side, end = words(5), [words(3) for _ in range(3)], words(4)
        for i in range(30):
            body = [words(12) for _ in range(rng.randrange(1, 4))]
            extra = side[i % 3]
            page = f"<div class=a1><div>{top}</div><div><p>{'</p><p>'.join(body)}</p></div><div><span>{extra}</span></div><div>{end}</div></div>"
            rows.append((1000 * h + i, f"http://h{h}.example/{i}", page))
            expected[1000 * h + i] = "\n".join(body)
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    for bound in (10**6, 0):
        got = {r.page_id: r.text for r in html_text.extract(pages, broadcast_rows=bound).collect()}
        assert got == expected
    hosts = [(u.split("/")[2], p) for _, u, p in rows]
    counted = {(r.host, r.subtree) for r in html_text.recurring_subtrees(pages, "html", "url").collect()}
    assert counted == plain_recurring(hosts, html_text.LEAST_PAGES, html_text.SHARE, html_text.MANY_PAGES)


def test_templates_are_found_by_repetition(spark):
    def page(i):
        return f"<div class=x><div>Site name<b>tagline</b></div><div><p>story {i} has words</p></div><div>All rights of site</div></div>"

    rows = [(i, f"https://Host.example/{i}", page(i), 5) for i in range(12)] + [(100 + i, f"http://other.example/{i}", page(0), 5) for i in range(12)]
    rows += [(200, None, None, 5), (201, "no host", page(1), 5), (201, "no host", page(1), 5)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string, host int")
    for bound in (1000, 0):
        got = {r.page_id: r.text for r in html_text.extract(pages, broadcast_rows=bound).collect()}
        assert all(got[i] == f"story {i} has words" for i in range(12))
        assert got[100] == "Site name tagline\nstory 0 has words\nAll rights of site".replace("name ", "name")  # copies of one page
        assert got[200] == "" and got[201].startswith("Site")
    assert html_text.extract(pages.limit(0)).count() == 0


def test_templates_inside_articles_and_text_beside_them(spark):
    def page(i):
        return f"<h1>Title {i}</h1><article><p>story {i} has <b>bold</b> words</p><ul><li>same</li><li>item {i}</li></ul><p class=x>Licence of the site</p></article><div>body {i}</div>"

    rows = [(i, f"https://host.example/{i}", page(i)) for i in range(12)]
    rows += [(100 + i, "https://copies.example/", f"<article><p>one story of many words</p><p>told again</p></article><div>{i}</div>") for i in range(12)]
    rows += [(200 + i, "https://cards.example/", f"<article>Read more</article><div>a longer body of page {i}</div>") for i in range(12)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    got = {r.page_id: r.text for r in html_text.extract(pages).collect()}
    for i in range(12):
        assert got[i] == f"Title {i}\nstory {i} has bold words\nsame\nitem {i}\nbody {i}"
        assert got[100 + i] == f"one story of many words\ntold again\n{i}"
        assert got[200 + i] == f"a longer body of page {i}"


def test_a_template_of_part_of_a_large_host(spark):
    rows = [(i, "https://large.example/", f"<p>story {i}</p>" + "<div>notice</div>" * (i < 30)) for i in range(400)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    for many, expected in ((30, "story 0"), (31, "story 0\nnotice")):
        got = {r.page_id: r.text for r in html_text.extract(pages, many_pages=many).collect()}
        assert got[0] == expected and got[399] == "story 399"
