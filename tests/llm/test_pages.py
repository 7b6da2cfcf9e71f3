"""Raw elements, formulas and plain pages; pages in layouts and names that the trees do not learn from."""

import random

import pytest
from pyspark.sql import functions as F

from trainscape.llm import html_extract

RAW = ["<script>var a = '<p>no</p>';</script>", "<script src=/js/>var a = 1;</script>", '<script src="x.js"/>var a = 1;</script>', "<style>p {}</style >", "<svg><title>no</title></svg>", "<svg/>", "<select><option>no</select>", "<iframe>no</iframe\n>", "<template><p>no</p></template>", "<textarea>no</textarea x>"]
LONG = "Words of the article go on for a while, so that it is plainly the main text here."


def runs(page):
    todo, found = [html_extract.parse_blocks(page)], []
    while todo:
        n = todo.pop()
        found += [n.text] if n.text is not None else []
        todo += reversed(n.kids)
    return found


@pytest.mark.parametrize("raw", RAW)
def test_text_and_tag_after_a_raw_element_stay(raw):
    assert runs(f"<p>Before it {raw} words after it</p>") == ["Before it words after it"]
    assert runs(f"{raw}Loose words. <p>x</p>") == ["Loose words.", "x"]
    root = html_extract.parse_blocks(f'{raw}<div class="comments">x</div>')
    assert root.kids[0].tag == "div" and root.kids[0].groups


@pytest.mark.parametrize("raw", RAW)
def test_given_pages_with_raw_elements_in_the_article(spark, raw):
    rows = [r["html"] for r in spark.read.parquet("/root/testdata/sf0.001/pages.parquet").collect()]
    trees = html_extract.learn_trees()
    want = html_extract.main_texts(rows, trees)
    assert html_extract.main_texts([r.replace("<p>", f"{raw}<p>") for r in rows], trees) == want


def test_formulas_objects_and_noscript_are_text():
    page = f"<article><p>{LONG} <math><mi>x</mi><mo>=</mo><mn>2</mn><annotation>x=2</annotation></math> holds.</p><object><p>{LONG}</p></object><noscript><p>{LONG}</p></noscript></article>"
    assert html_extract.main_texts([page], html_extract.learn_trees()) == [f"{LONG} x=2 holds. {LONG} {LONG}"]


def test_plain_long_and_tied_pages(spark):
    trees = html_extract.learn_trees()
    assert html_extract.main_texts(["just words &amp; more\n of them", " ", "<!-- x -->"], trees) == ["just words & more of them", "", ""]
    long = "<article>" + f"<p>{LONG}</p>" * 20_000 + "</article>"
    rows = [(1, "u", long), (1, "u", long), (2, None, None), (None, None, "")]
    got = html_extract.extract_main_text(spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("text", F.lit("x"))).collect()
    assert [r["n_chars"] for r in got] == [20_000 * (len(LONG) + 1) - 1] * 2 + [0, 0]
    nodes, x = html_extract.node_features(html_extract.parse_blocks("<div><p>one</p></div>"))
    assert html_extract.decode(nodes, x[:, 0] * 0) == []


NAMES = {
    "menu": ["topbar-links", "site-nav", "l-nav", "mainmenu", "hauptmenue", "breadcrumb-trail"], "side": ["rail-right", "side-col", "c-related", "read-next", "most-read widget-box"],
    "ad": ["ad-box", "sponsor-unit", "promo-tile"], "notice": ["gdpr-bar", "cookie-bar", "newsletter-box"], "talk": ["reader-comments", "comments-area", "discussion-thread"],
    "foot": ["page-foot", "site-footer", "colophon legal"], "main": ["story-copy", "c-article__text", "post-text", "entry", "txt", "prose"],
}


def other_page(seed):
    """A page whose names, nesting and furniture differ from the pages that the trees learn from; its main text."""
    r = random.Random(seed)
    said = []

    def prose(low, high):
        return " ".join(r.choice("Ein kurzer langer Satz about rivers and towns wird hier gesagt dans la ville of the old".split()) for _ in range(r.randint(low, high))) + "."

    def box(kind, inner, tags=("div", "section")):
        tag = r.choice(tags)
        return f'<{tag} data-k="1" class="{r.choice(NAMES[kind])}">{inner}</{tag}>'

    def items(n):
        return "<ul>" + "".join(f'<li class="it"><a href="#{i}"><span>{prose(1, 3)}</span></a></li>' for i in range(n)) + "</ul>"

    def main(low, high):
        said.append(prose(low, high))
        return said[-1]

    body = [f"<h1 class=hl>{main(3, 9)}</h1>"] if r.random() < 0.8 else []
    for _ in range(r.randint(2, 9)):
        body.append(r.choice(["<p class=para>{}</p>", "<p>{}</p>", "<h3>{}</h3>", "<figure><figcaption>{}</figcaption></figure>", "<blockquote>{}</blockquote>"]).format(main(6, 90)))
        if r.random() < 0.2:
            body.append(r.choice([box("ad", f"<p>{prose(3, 30)}</p>"), "<script>var q = 1;</script>", "<form><p>" + prose(2, 8) + "</p></form>"]))
    art = "".join(body)
    art = r.choice([f"<article class=c>{art}</article>", f"<main><div>{art}</div></main>", box("main", art), f"<div id=page><div class=col>{box('main', art)}</div></div>"])
    parts = [box("menu", items(r.randint(3, 8)), ("nav", "div")), *(f() for f in (lambda: box("notice", f"<p>{prose(5, 25)}</p>"), lambda: box("ad", prose(3, 20))) if r.random() < 0.5), art]
    parts += [f() for f in (lambda: box("talk", "".join(f"<div class=c1><p>{prose(4, 40)}</p></div>" for _ in range(3))), lambda: box("side", f"<h4>{prose(1, 3)}</h4>{items(4)}", ("aside", "div"))) if r.random() < 0.6]
    parts.append(box("foot", f"<p>{prose(4, 15)}</p>{items(2)}", ("footer", "div")))
    return "<html><body>" + "\n".join(parts) + "</body></html>", " ".join(said)


def test_pages_of_other_layouts():
    made = [other_page(s) for s in range(300)]
    got = html_extract.main_texts([p for p, _ in made], html_extract.learn_trees())
    exact = sum(g == w for g, (_, w) in zip(got, made))
    print(f"exact: {exact} of 300")
    assert exact >= 240
