import random
import re
import time

import pytest

from blockgraph.llm import html_text
from blockgraph.llm.html_text import Page, Tree, extract, main_text, paragraph_points

BODY = "<p>First, a sentence that runs on.</p><p>Second &amp; last,\n  with <b>bold</b> text.</p>"
WANT = "First, a sentence that runs on.\nSecond & last, with bold text."


@pytest.mark.parametrize("page,want", [
    (None, ""), ("", ""), ("   ", ""), ("plain text", "plain text"),
    (f"<html><body><nav><a href=x>Home</a></nav><article>{BODY}</article><footer>c</footer></body></html>", WANT),
    (f"<body><div class='header'>Top</div><div id=content>{BODY}</div><div class=sidebar><p>Side, bar, text.</p></div></body>", WANT),
    (f"<body><div class='post-body'>{BODY}</div><section id=comments><p>I, a reader, say a lot of things, really.</p></section>", WANT),
    (f"<body><header><h1>Site</h1></header><main><article><h1>Title</h1>{BODY}<form><p>Mail, please</p></form></article></main>", "Title\n" + WANT),
    (f"<body><article>{BODY}<script>var a='<p>x</p>'</script><style>p{{}}</style><!-- <p>no</p> --></article>", WANT),
    ("<body><article><p><b>One<br><p>Two<p>Three &lt;x&gt; &copy;</article>", "One\nTwo\nThree <x> ©"),
    (f"<body><article>{BODY}<p>cut o", WANT + "\ncut o"),
    (f"<body><article>{BODY}<p class='a", WANT),
    (f"<body><div class=cookie-notice><p>We use cookies, yes, many, of them.</p></div><div>{BODY}</div>", WANT),
    (f"<body><div class='main-menu'><ul><li>Home, sweet home</li></ul></div><div class='content has-sidebar'>{BODY}</div><div class='main-footer'>Foot, note.</div></body>", WANT),
    (f"<body><div id='page'><div class='page-header'>Site</div><div class='entry'><div class='entry-header'><h1>T</h1></div>{BODY}<div class='post-comments'><p>Well, I never, said, a reader.</p></div></div></div>", "T\n" + WANT),
    (f"<body><article>{BODY}<div class='ad-slot'>Buy, now</div><div class='related-posts'><a href=x>More</a></div><aside>Note</aside><p>End.</p></article>", WANT + "\nEnd."),
    ("<body><div><p>One, two, three.</p></div><div><p>Four, five, six.</p></div><div><a href=a>x</a> <a href=b>y</a> <a href=c>z</a></div>", "One, two, three.\nFour, five, six."),
    ("<body><article><ul><li>a<li>b</ul>3 < 4</article>", "a\nb\n3 < 4"),
    # several articles, and an article in parts
    (f"<body><main><article>{BODY}</article><article><h2>Next</h2><p>Third, here.</p></article></main>", WANT + "\nNext\nThird, here."),
    (f"<body><div><div>{BODY}</div></div><section><div><p>Later, in another place.</p></div></section>", WANT + "\nLater, in another place."),
    # names that say something else
    (f"<body><article>{BODY}<div class='restaurant-menu'><p>Soup of the day.</p></div><p class='notice-period'>Three months.</p><div class=share-price>Up.</div></article>", WANT + "\nSoup of the day.\nThree months.\nUp."),
    (f"<body><div class='content-comments-off'>{BODY}</div><div class='notice'>We have moved.</div><form><p>Search, here.</p></form>", WANT),
    (f"<body><form action=x><div class=story>{BODY}<p><a href=a>All of this is a link.</a></p></div><div class=side-bar><a href=a>A</a></div></form>", WANT + "\nAll of this is a link."),
    # markup that is not what it seems
    (f"<body><article><svg class=i/>{BODY}<svg><text>no</text></svg><object>no</object><p>End.</p></article>", WANT + "\nEnd."),
    ("<body><article><p>a</b></i></p><p>b</p></div></ul></article>", "a\nb"),
])
def test_pages(page, want):
    assert main_text(page) == want


def test_given_pages(spark):
    df = spark.read.parquet("/root/testdata/sf0.001/pages.parquet")
    got = {r.page_id: r for r in extract(df).collect()}
    for r in df.collect():
        body = r.html.split("<article>")[1].split("</article>")[0]
        import html

        want = [re.sub(r"\s+", " ", html.unescape(re.sub(r"</?b>", "", x))).strip() for x in re.split(r"</?p>|</?h1>|<br>", body.split("<footer>")[0])]
        assert got[r.page_id].text == "\n".join(x for x in want if x)
        assert got[r.page_id].n_chars == len(got[r.page_id].text)
    assert len(got) == df.count()


def test_empty(spark):
    assert extract(spark.createDataFrame([], "page_id long, url string, html string, text int")).collect() == []


def reference(page):
    """The method by its definition, on a tree of dicts, quadratic."""
    page = Page(page)
    tree = Tree(page)
    kids = {x: [y for y in range(len(page.tag)) if page.parent[y] == x] for x in range(len(page.tag))}
    mine = {x: [(t, n) for t, o, n in tree.lines if o == x] for x in kids}
    below = lambda x: [y for k in kids[x] for y in below(k)] + [x]
    own = lambda x: tree.worth[x]

    def total(x):
        out = 0.0
        for y in below(x):
            for t, _ in mine[y]:
                up, level, w = y, -1 if tree.leaf[y] else 0, 0.5 if page.tag[y] in html_text.HEADS else 1
                while up != x:
                    w *= own(up)
                    level += tree.block[up] or up == y
                    up = page.parent[up]
                if not (tree.leaf[x] and y == x):
                    out += w * paragraph_points(t) * 0.5 ** max(level, 0)
        return out

    return [total(x) for x in kids], tree


def test_points_by_definition():
    for page in (f"<body><div>{BODY}<div><p>x, y<nav><p>a, b, c</nav></div>loose, text</div><section class=comments>{BODY}", f"<main><article><h1>T, t</h1>{BODY}<ul><li>a<li>b, c</ul></article><aside>{BODY}</aside></main>"):
        want, tree = reference(page)
        assert [0 if leaf else t for t, leaf in zip(tree.total, tree.leaf)] == pytest.approx([0 if leaf else w for w, leaf in zip(want, tree.leaf)])


def made_page(rng):
    """A page without article or main, and its text."""
    words = "river stone window light garden paper music winter road house".split()
    sentence = lambda: " ".join(rng.choice(words) for _ in range(rng.randint(6, 20))).capitalize() + rng.choice([".", ", indeed.", ", or so, they said."])
    text = lambda: " ".join(sentence() for _ in range(rng.randint(1, 4)))
    want, body = ["Title of it"], ["<h1>Title of it</h1>"]
    for _ in range(rng.randint(3, 8)):
        t = text()
        want.append(t)
        body.append(rng.choice([f"<p>{t}", f"<p>{t}</p>", f"<div><p>{t}</p></div>", f"<blockquote>{t}</blockquote>", f"<p class='lead-in'>{t}</p>", f"<div class='fish-menu'><p>{t}</p></div>"]))
        body.append(rng.choice(["", "", f"<div class='ad-box'>{sentence()}</div>", "<script>if (a < b) x('<p>')</script>", f"<aside>{text()}</aside>", "<ul class=share><li><a href=a>Mail</a><li><a href=b>Print</a></ul>"]))
    links = "".join(f"<li><a href='/{i}'>{rng.choice(words)}</a></li>" for i in range(5))
    inner = "".join(body)
    for _ in range(rng.randint("-" in inner, 3)):  # a doubtful name needs a container to stand in
        inner = f"<div{rng.choice(['', ' class=wrap', ' id=content'])}>{inner}</div>"
    before = rng.choice([f"<nav><ul>{links}</ul></nav>", f"<div id='top-menu'><ul>{links}</ul></div>", f"<header><h1>Site</h1><p>{sentence()}</p></header>", f"<ul>{links}</ul>"])
    after = rng.choice([f"<div class='comments'><p>{text()}</p><p>{text()}</p></div>", f"<footer>{text()}</footer>", f"<div class=sidebar><h3>More</h3><p>{text()}</p></div>", f"<div class='cookie-banner'>{text()}</div>", f"<div class='weather-widget'><p>{text()}</p></div>", f"<div class='about-author'>{sentence()}</div>"]) if "<div" in inner else ""
    return f"<html><head><title>no</title></head><body>{before}{inner}{after}{before}</body></html>", "\n".join(want)


def test_made_pages():
    rng = random.Random(4)
    wrong = [(p, w) for p, w in (made_page(rng) for _ in range(300)) if main_text(p) != w]
    assert not wrong, wrong[0]


def test_scores_decide(monkeypatch):
    rng = random.Random(5)
    pages = [made_page(rng)[0] for _ in range(50)]
    right = [main_text(p) for p in pages]
    for name, constant in (("weight", lambda self, x: 1.0), ("value", lambda self, x, inside: 1.0)):
        with monkeypatch.context() as m:
            m.setattr(Tree, name, constant)
            assert sum(main_text(p) != r for p, r in zip(pages, right)) > 10, name


@pytest.mark.parametrize("page,n", [
    ("<div>" * 100_000 + "deep", 4), ("<div><p>a, b.</p>" * 50_000, 50_000 * 6 - 1), ("<p>x</p>" + "</b></i></ul></p>" * 50_000, 1), ("<div><b>x" + "<i>" * 50_000 + "</b>" * 50_000, 1),
    ("<ul>" + "<div>" * 30_000 + "<li>a</li>" * 30_000, 59_999), ("<a title='x\">y" * 50_000, None), ("<" * 100_000, 100_000), ("<p>" + "word, " * 500_000, 2_999_999),
])
def test_deep_and_long(page, n):
    began = time.perf_counter()
    got = main_text(page)
    assert n is None or len(got) == n
    assert time.perf_counter() - began < 30


def test_extra_columns(spark):
    df = spark.createDataFrame([(1, "u", None, "x"), (1, "u", "<p>Hi.</p>", "y"), (None, None, "<p>Hi.</p>", None)], "page_id long, url string, html string, text string")
    assert sorted(map(tuple, extract(df).collect()), key=str) == [(1, "u", "", 0), (1, "u", "Hi.", 3), (None, None, "Hi.", 3)]
