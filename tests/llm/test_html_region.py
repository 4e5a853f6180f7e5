"""The region follows the scores, whatever marks a page has; parsing is linear; nothing but furniture is left out."""

import time

from rangebound.llm import html_extract as H

STORY = "It rained for days in the north and rivers rose quickly over the plain."


def test_weights_decide_the_region():
    page = f"<body><div>one two three four five six seven eight nine ten</div><article><p>{STORY}</p></article></body>"
    assert H.extract(page, H.Weights()) == STORY
    assert H.extract(page, H.Weights(outside=1.0)) == f"one two three four five six seven eight nine ten {STORY}"
    assert H.extract(page, H.Weights(against=frozenset(["p"]), outside=1.0)).startswith("one two") and STORY not in H.extract(page, H.Weights(against=frozenset(["p"]), outside=1.0))


def test_pages_without_marks():
    page = f"""<html><head><title>T x</title></head><body><div id="cookie-consent">We use cookies accept all</div><div class="top-bar"><a href="/">Home</a> <a href="/n">News</a></div>
<div class="layout"><div class="content"><h1>Rain</h1><p>{STORY}</p><div class="advert">Buy boots now at a very special price today only for you and your friends</div><ul><li>one fact about rain</li><li>two facts about rivers</li></ul><blockquote>We are wet.</blockquote><p>End.</p></div>
<div class="sidebar"><h3>Popular</h3><ul><li>other story about something else entirely</li></ul></div></div>
<div class="comments"><h2>3 comments</h2><p>I think that this is a great story about rain and boots</p></div><div id="footer">Copyright 2020 all rights reserved by us</div></body></html>"""
    want = f"Rain {STORY} one fact about rain two facts about rivers We are wet. End."
    assert H.extract(page, H.Weights()) == want
    assert H.extract(page.replace('<div class="content">', "").replace("End.</p></div>", "End.</p>"), H.Weights()) == want


def test_what_is_learned():
    counts = {"#word": (900, 300), "p": (80, 5), "h1": (10, 1), "div": (3, 60), "@div.blurb": (0, 120), "@p": (850, 40), "@div": (900, 300), "@li": (40, 30)}
    w = H.learn(counts)
    assert w.against == {"div.blurb"} and w.word > 0 > w.tags["p"] > w.tags["div"] and w.outside < 0
    blurb = "<div class='blurb'>" + "words of another page " * 10 + "</div>"
    page = f"<body>{blurb}<div><p>{STORY}</p></div></body>"
    assert H.extract(page, w) == STORY and blurb[20:40] in H.extract(page, H.Weights())


def test_all_text_of_the_region_stays():
    page = "<article><p>We show <math>a b</math> and <span class='tags'>kept words</span> then <div class='related-work'>more here</div> <object>fallback</object> 1 < 2 end</p><nav>menu</nav></article>"
    assert H.extract(page, H.Weights()) == "We show a b and kept words then more here fallback 1 < 2 end"
    assert H.extract('<p title="a > b">one</p><p class=x>two &lt;b&gt;</p><!-- no --><![CDATA[no]]><p data-x=\'"\'>three', H.Weights()) == "one two <b> three"


def test_malformed_pages_of_a_megabyte():
    start = time.time()
    for page in ('<body><p>some words <a href="x>word ' * 40_000, "<p>a <a href='x\">w</a> " * 50_000, "<div>" * 150_000 + "x " * 10, "< <a <b <c " * 100_000, "<!-- " * 200_000, "<script>" * 100_000):
        H.extract(page, H.Weights())
    assert time.time() - start < 60
