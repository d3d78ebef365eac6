import html
import math
import re

import pytest

from treefacts.llm import html_text


@pytest.mark.parametrize(("page", "want"), [
    (None, ""), ("", ""), ("plain words", "plain words"), ("<p>a&amp;b &eacute;<b>c</b>d<br>e", "a&b écd e"), ("<body><nav><a>x</a></nav><article><h1>T</h1><p>one  two\n three<p>four</article><footer>f</footer>", "T one two three four"),
    ("<article><p>short.</p><ul><li>a<li>b</ul></article><div class='comments'><p>" + "reader words " * 50 + "</div>", "short. a b"), ("<script>var a='<p>no</p>'</script><p>yes</p><!-- <p>no --><style>p{}</style>", "yes"),
    ("<div id=main><div class='sidebar'>s</div><form><p>f</p></form><p>body text, long enough to win here.</p></div><div class=cookie-notice>c</div>", "body text, long enough to win here."), ("<p>cut <a href='x", "cut"), ("<article><p>x</p><aside>y</aside><p>z</p></article>", "x z"),
    ("<div class='page has-sidebar'><header>site</header><article><header class='entry-header'><h1>T</h1></header><p>x</p></article><div class=sidebar>s</div></div>", "T x"), ("<article class=post><p>a</p></article><section class='comments'><article class=comment><p>b</p></article></section>", "a"),
])
def test_small_pages(page, want):
    assert html_text.main_text(page) == want


def test_given_pages(spark, tiny):
    pages = spark.read.parquet(f"{tiny}/pages.parquet")
    source = {r.page_id: r.html for r in pages.collect()}

    def article(page):
        inner = re.search(r"<article>(.*?)(?:</article>|\Z)", page, re.S)[1]
        inner = re.sub(r"</?b>", "", re.sub(r"</?(?:p|h1|br)[^>]*>", " ", inner))
        return " ".join(html.unescape(re.sub(r"<[^>]*\Z", "", inner)).split())

    rows = html_text.extract(pages).collect()
    assert len(rows) == len(source)
    assert all(r.text == article(source[r.page_id]) and r.n_chars == len(r.text) for r in rows)


def test_densities_choose_the_text_of_a_page_without_article():
    links = "".join(f"<div><a href=/{i}>link {i}</a></div>" for i in range(30))
    text = "".join(f"<p>{'sentence with words, ' * 12}</p>" for _ in range(5))
    got = html_text.main_text(f"<body><div>{links}</div><div><div><h2>Title</h2>{text}</div></div><div>{links}</div></body>")
    assert got.startswith("Title sentence") and "link" not in got


def test_several_articles_and_prose_in_named_blocks():
    first, second = "first story words, " * 20, "second story, longer " * 40
    page = f"<body><nav><a>n</a></nav><article class=post><h2>A</h2><p>{first}</p></article><article class=post><h2>B</h2><p>{second}</p></article><div class=ad>buy</div></body>"
    assert html_text.main_text(page) == f"A {first.strip()} B {second.strip()}"
    assert html_text.main_text(f"<article><h1>T</h1><p>one</p><div class='related-work'><p>{first}</p></div><div class='ad-slot'>buy</div></article>") == f"T one {first.strip()}"


def plain_density(node, links):
    """Density of a node from its own subtree alone, counted anew."""
    def count(x):
        kids = [k for k in x.children if isinstance(k, html_text.Node) and not k.cut]
        chars, tags, link_chars, link_tags = sum(len(" ".join(t.split())) for t in x.children if isinstance(t, str)), len(kids), 0, 0
        for k in kids:
            c, t, lc, lt = count(k)
            chars, tags, link_chars, link_tags = chars + c, tags + t, link_chars + lc, link_tags + lt
        return (chars, tags, chars, tags + 1) if x.name == "a" else (chars, tags, link_chars, link_tags)

    c, t, lc, lt = count(node)
    if not c:
        return 0.0
    base = math.log(c / max(1, c - lc) * lc + links * c + math.e)
    return c / max(1, t) * math.log(c / max(1, lc) * max(1, t) / max(1, lt)) / math.log(base)


def test_densities_match_brute_force():
    import random

    rng = random.Random(3)

    def make(depth):
        if depth == 0 or rng.random() < 0.2:
            return "".join(rng.choice("abcde") for _ in range(rng.randint(1, 60)))
        tag = rng.choice(["div", "p", "section", "a", "span", "b"])
        return f"<{tag}>" + " ".join(make(depth - 1) for _ in range(rng.randint(1, 4))) + f"</{tag}>"

    for _ in range(60):
        root = html_text.parse("<body>" + "".join(make(4) for _ in range(4)) + "</body>")
        found = html_text.nodes(root)
        body = next(x for x in found if x.name == "body")
        html_text.weigh(found, body)
        links = body.link_chars / max(1, body.chars)
        for x in found:
            base = math.log(x.chars / max(1, x.chars - x.link_chars) * x.link_chars + links * x.chars + math.e) if x.chars else 0
            if x.chars and base > 1:
                assert math.isclose(x.density, plain_density(x, links), abs_tol=1e-9)
            kids = [k.density for k in x.children if isinstance(k, html_text.Node) and not k.cut]
            assert math.isclose(x.sum, sum(kids) or (x.density if x.chars else 0), abs_tol=1e-9)


def test_deep_pages_and_odd_tables(spark, none):
    import time

    start = time.time()
    assert html_text.main_text("<div>" * 20_000 + "deep text" + "</div>" * 20_000) == "deep text"
    assert time.time() - start < 5
    rows = [(1, None, None, "x", 5), (None, "u", "", "x", 5), (2, "u", "<p>a</p>", "x", 5), (2, "u", "<p>a</p>", "x", 5)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string, text string, n_chars long")
    assert sorted(r.text for r in html_text.extract(pages).collect()) == ["", "", "a", "a"]
    assert html_text.extract(pages.limit(0)).count() == 0
