"""Main text of pages that were written by hand, in layouts that the training pages do not have, and of odd pages."""

import random
import time

import pytest

from overlapgraph.llm import crf, html_main


@pytest.fixture(scope="module")
def model():
    return html_main.train()


#: (page, its main text as a reader would copy it)
PAGES = [
    (
        """<!doctype html><html lang=en><head><meta charset=utf-8><title>Tides</title><link rel=stylesheet href=a.css></head>
<body class="single-post"><header class="site-header"><a class="logo" href="/">The Harbour Log</a>
<nav class="main-navigation"><ul class="menu"><li><a href="/">Home</a><li><a href="/boats">Boats</a><li><a href="/tides">Tides</a></ul></nav></header>
<main id="content"><article class="post"><h1 class="entry-title">How the tide tables are made</h1>
<div class="entry-content"><p>Every harbour has its own <em>tide table</em>, and every table begins with a gauge.</p>
<p>The gauge is read for a year. Its record is then split into some forty waves, each with a period that the moon or the sun prescribes.</p>
<h2>From waves to tables</h2><p>Adding the waves up again gives the height of the water at any hour.</p></div></article>
<section id="comments" class="comments-area"><h2>2 comments</h2><ol><li class="comment"><p>Great article, thank you!</p></li><li class="comment"><p>My harbour has no gauge at all.</p></li></ol></section></main>
<aside class="sidebar"><h3>Related posts</h3><ul><li><a href="/1">Knots that hold</a><li><a href="/2">Painting a hull</a></ul></aside>
<footer class="site-footer"><p>&copy; 2019 The Harbour Log. All rights reserved.</p></footer></body></html>""",
        "How the tide tables are made Every harbour has its own tide table, and every table begins with a gauge. The gauge is read for a year. Its record is then split into some forty waves, each with a period that the moon or the sun prescribes. From waves to tables Adding the waves up again gives the height of the water at any hour.",
    ),
    (
        """<html><body><div id=wrap><div id=navbar><a href=/>Start</a> | <a href=/a>Archive</a> | <a href=/k>Contact</a></div>
<div class="cookie-banner" role="dialog"><p>We use cookies to make this site better.</p><button>Accept</button></div>
<div class="story"><h1>Brot ohne Hefe</h1><p>Man nimmt 500&nbsp;g Mehl, etwas Salz und lauwarmes Wasser.<p>Der Teig ruht &uuml;ber Nacht &#8211; l&auml;nger schadet nicht.
<ul><li>500 g Mehl</li><li>10 g Salz</li><li>350 ml Wasser</li></ul><p>Gebacken wird bei gro&szlig;er Hitze.</div>
<div class="ad-slot">Jetzt neu: der Backofen, der alles kann.</div><div id=footer>Impressum</div></div></body></html>""",
        "Brot ohne Hefe Man nimmt 500\xa0g Mehl, etwas Salz und lauwarmes Wasser. Der Teig ruht über Nacht – länger schadet nicht. 500 g Mehl 10 g Salz 350 ml Wasser Gebacken wird bei großer Hitze.",
    ),
    (
        """<HTML><HEAD><TITLE>x</TITLE><SCRIPT>document.write("<p>not text</p>")</SCRIPT></HEAD><BODY><ARTICLE><H1>İstanbul'da sabah</H1>
<P>İlk vapur İskele'den altıda kalkar; İİİİİİİİİİİİİİİİİİİİİİİİİİİİİİİİ diye öter.</P><SCRIPT type="text/javascript">var a = 1 < 2;</Script>
<P>İkinci vapur yarım saat sonra gelir ve herkes çay içer.</P><STYLE>p { color: red }</STYLE></ARTICLE><FOOTER>Tüm hakları saklıdır</FOOTER></BODY></HTML>""",
        "İstanbul'da sabah İlk vapur İskele'den altıda kalkar; İİİİİİİİİİİİİİİİİİİİİİİİİİİİİİİİ diye öter. İkinci vapur yarım saat sonra gelir ve herkes çay içer.",
    ),
    (
        """<body><nav><a href=1>One</a><a href=2>Two</a></nav><article><header><h1>A page with hidden parts</h1></header>
<p style="text-decoration:none; margin: 0">The style of this paragraph hides nothing at all.</p>
<div style="display: none">This box is hidden and was never read by anyone.</div><div hidden>Neither was this one, of course.</div>
<blockquote><p>Nothing is as hidden as what lies in the open.</p></blockquote><pre>x = 1
y = 2</pre><form action=/subscribe><label>Your address</label><input name=mail><button>Subscribe</button></form></article><footer>Legal notice</footer>""",
        "A page with hidden parts The style of this paragraph hides nothing at all. Nothing is as hidden as what lies in the open. x = 1 y = 2",
    ),
    (
        """<body><div class="header"><div class="logo">Wire</div></div><div class="main-content"><div class="article-body"><div>Boxes hold the text of this page.</div>
<div><div><div>Some of them stand inside others, as old editors made them.</div></div></div><div>Still it is one article from its first to its last box.</div></div>
<div class="share"><a href=x>Share</a> <a href=y>Tweet</a></div><div class="newsletter"><p>Subscribe to our newsletter.</p></div></div><div class="copyright">Copyright 2020 Wire</div></body>""",
        "Boxes hold the text of this page. Some of them stand inside others, as old editors made them. Still it is one article from its first to its last box.",
    ),
]


@pytest.mark.parametrize("page,text", PAGES, ids=range(len(PAGES)))
def test_pages_written_by_hand(model, page, text):
    assert html_main.main_text(page, model) == text


def test_accuracy_on_other_composed_pages(model):
    rng, right, n = random.Random(99), 0, 0
    for _ in range(300):
        page, labels = html_main.labelled_page(rng)
        blocks = html_main.leaf_blocks(page, model)
        got = crf.viterbi(html_main.own_features(blocks), model, [b.node.emit for b in blocks])
        # the shared sums and the features spelt out are the same field
        assert got == crf.viterbi(html_main.block_features(blocks), model)
        right, n = right + sum(a == b for a, b in zip(got, labels, strict=True)), n + len(labels)
    assert right / n > 0.985


@pytest.mark.parametrize("unit,n", [('<div class="c{}">word {}.', 30_000), ("<b><p>{}{}", 30_000), ("<svg>{}{}", 30_000), ("<td>{}</td></span>{}", 30_000), ("<div><li>{}</ul>{}", 30_000), ('<a "{}\'{}', 30_000)])
def test_time_grows_with_the_length_of_a_page(model, unit, n):
    took = []
    for m in (n // 4, n):
        page = "<article>" + "<div>" * (m // 2) + "".join(unit.format(i, i) for i in range(m))
        start = time.process_time()
        html_main.main_text(page, model)
        took.append(time.process_time() - start)
    assert took[1] < 12 * took[0] + 0.5


def test_pages_without_text(model):
    for page in ("", " \n", "<html>", "<script>x", "<!-- only a comment", "<p>", "&#x110000;&nbsp", "<" * 100):
        assert isinstance(html_main.main_text(page, model), str)
