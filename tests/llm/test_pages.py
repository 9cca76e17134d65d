"""Main text of pages that the tree has not seen, and of broken ones."""

import time

import pytest

from tilestar.llm import html

M = html.MARK
#: Held out: blocks of main text begin with the mark.
PAGES = {
    "div": f"<html><body><div class='nav'><a href=/>Home</a><a href=/b>Blog</a></div><div class='post'><h2>{M}Ten days in the hills</h2><p>{M}We walked.</p><ul><li>{M}Pack light</li><li>{M}Bring water</li></ul>"
    f"<p>{M}On the third day the rain stopped and we could see the whole valley for the first time since we had set out.</p></div><div class='comments'><p>Lovely trip, thanks for sharing it with all of us here.</p></div>"
    "<div id='footer'>All rights reserved</div></body></html>",
    "article": f"<header><a href=/>Site</a></header><article><h1>{M}Bread</h1><p>{M}Flour, water, salt.</p><h2>{M}Bake</h2><ol><li>{M}Mix it all and let it rest for a night in a cool place</li><li>{M}Bake</li></ol></article>"
    "<aside><h3>More</h3><a href=/x>Rolls</a></aside><footer>Imprint</footer>",
    "wrapped": f"<div class='layout with-sidebar'><div class='content'><h1>{M}Tides</h1><p>{M}The sea comes twice a day.</p><p>{M}It is the moon that pulls it, and the sun helps a little when both stand in one line.</p></div>"
    "<div class='sidebar'><p>This blog is about the sea and nothing else, written by someone who lives close to it.</p></div></div>",
    "plain": f"<h1>{M}A list</h1><ul><li>{M}one</li><li>{M}two</li></ul><p>{M}That is all.</p>",
    "cookie": f"<div id='cookie-banner'>This site uses cookies so that it can remember what you like.</div><main><p>{M}Short text.</p><table><tr><td>{M}a</td><td>{M}1</td></tr></table></main><form><label>Name</label><button>Send</button></form>",
    "reset": f"<div class='no-sidebar'><div class='header-nav'><a href=/>Up</a></div><div class='widget-area'><article><h1>{M}Inside</h1><p>{M}An article is main text even where a theme puts it into an odd place.</p></article></div></div>",
    "remarks": f"<main><article><h1>{M}Oak</h1><p>{M}Oaks grow slowly and live long, and their wood is hard.</p></article></main><section class='comments'><article><p>My oak is older than yours, I think, and it still bears fruit.</p></article></section>",
}


def test_blocks_of_unseen_pages():
    hit = kept = main = 0
    for page in PAGES.values():
        marked = [b[0].startswith(M) for b in html.blocks(page)]
        got = [html.leaf(html.TREE, f) >= 0.5 for f in html.features(html.blocks(page.replace(M, "")))]
        hit, kept, main = hit + sum(a and b for a, b in zip(marked, got, strict=True)), kept + sum(got), main + sum(marked)
    assert hit / kept >= 0.95 and hit / main >= 0.95, (hit, kept, main)


def test_heads_and_items_outside_a_main_element():
    got = html.extract(PAGES["div"].replace(M, "")).split("\n")
    assert got[0] == "Ten days in the hills" and "Pack light" in got and "Bring water" in got and "All rights reserved" not in got


@pytest.mark.parametrize("unit", ["<a ", '<a ="', "<b ='>'", "</p", "<p", "<!", "<!--", "<script", "<script>", "</script", "<div>", "<div></p>", '<a href="x>', "&amp", "< ", "<title>"])
def test_broken_markup_takes_time_in_proportion(unit):
    began = time.perf_counter()
    html.extract(unit * (1_000_000 // len(unit)))
    assert time.perf_counter() - began < 8  # quadratic: hours


def test_tags_that_do_not_end_are_text():
    assert html.extract("<p>one two three four five six <b and a < b") == "one two three four five six <b and a < b"
    assert html.extract("<p title='a > b'>x is one of the letters</p>") == "x is one of the letters"
    assert html.extract('<p title="a > b>x is one of the letters</p>') == "b>x is one of the letters"
    assert html.extract(None) == "" and html.extract("<p>&eacute;t&#233;&nbsp; is\n summer</p>") == "été is summer"
