"""Extraction held against pages whose article is known."""

import random
import time

import pytest

from placeminer.llm import extract
from placeminer.llm.extract import Page

LONG = "This is the running text of the article, which goes on for a while. "


@pytest.mark.parametrize("mark", ['class="side-by-side"', 'class="post notice-board"', 'class="content has-sidebar"', 'class="post comments-open"', 'id="no-sidebar"', 'class="legal-news"'])
@pytest.mark.parametrize("tag", ["article", "main", "div"])
def test_words_inside_classes_do_not_lose_the_article(tag, mark):
    page = f'<body><nav>Home About</nav><div class="site-header">The site of sites, with a long claim about itself.</div><{tag} {mark}><p>{LONG * 3}</p><p>Short end.</p></{tag}><div class="cookie-banner">We use cookies to make this site work for you and for us.</div></body>'
    assert Page(page).text() == f"{(LONG * 3).strip()}\nShort end."


def test_comments_stay_out_however_long_they_are():
    many = "".join(f'<article class="comment"><p>{LONG}</p></article>' for _ in range(50))
    assert Page(f'<article><p>{LONG}</p></article><section class="comments">{many}</section>').text() == LONG.strip()
    assert Page(f'<article><p>{LONG * 4}</p></article>{many[:many.index("</article>") + 10]}').text() == (LONG * 4).strip()


def test_only_the_chosen_container_of_a_path():
    page = Page(f"<body><div><p>{LONG * 5}</p></div><div><p>Read this teaser, too.</p></div></body>")
    path = page.containers[page.best()[0]].path
    assert page.text(path) == (LONG * 5).strip()
    parts = Page(f'<body><div><p>{LONG * 5}</p></div><div class="ad">{LONG}</div><div><p>{LONG * 3}</p></div></body>')
    assert parts.text(path) == f"{(LONG * 5).strip()}\n{(LONG * 3).strip()}"


def test_marked_inline_elements_end_at_their_own_close():
    assert Page(f'<p>{LONG}<span class="ad"><span>buy</span> now</span>It ends.</p>').text() == f"{LONG}It ends."
    assert Page(f'<div><p>{LONG}<span class="ad">buy</p><p>Second {LONG}<span>x</span></p></div>').text() == f"{LONG.strip()}\nSecond {LONG}x"


@pytest.mark.parametrize("inner", ["<div>", '<div class="a b">', "<section><span>", "<div><select>", '<span class="ad">', "<div><p>", "</x><div>"])
def test_very_deep_pages_take_time_in_proportion(inner):
    began = time.time()
    page = Page("<body><p>Lead text.</p>" + inner * 100_000 + LONG + "</div>" * 50_000)
    assert page.best()[0] >= 0 and time.time() - began < 20
    assert len({c.path for c in page.containers}) <= 200_002


def test_known_articles_among_random_frames(spark):
    """A plain version: pages are built around an article, which must come back as it was."""
    rng = random.Random(4)
    frames = ["<nav><a href='/'>Home</a> <a href='/b'>More</a></nav>", "<header>Site name of some length, with a claim.</header>", '<div class="sidebar"><p>Other things that one might read here some day.</p></div>', "<script>if (a < b) { x('<p>') }</script>", "<footer>All rights reserved by whoever holds them.</footer>", '<div role="alert">A notice that the site has terms of use.</div>', "<!-- <p>old</p> -->", "<form><p>Sign up for what we send around every week.</p></form>"]
    rows, want = [], {}
    for k in range(200):
        blocks = [" ".join(rng.choice(["word", "Größe", "1 < 2 & 3", "naïve", "中文"]) for _ in range(rng.randrange(12, 30))) + "." for _ in range(rng.randrange(1, 6))]
        escaped = [b.replace("&", "&amp;").replace("<", "&lt;").replace("ö", "&ouml;") for b in blocks]
        body = "".join(f"<{t}>\n {b.replace(' ', '  ', 2)} </{t}>" for b, t in ((b, rng.choice(["p", "h2", "blockquote"])) for b in escaped))
        tag = rng.choice(["article", "main", 'div class="post"'])
        page = f"<html><body>{''.join(rng.sample(frames, 4))}<{tag}>{body}</{tag.split()[0]}>{''.join(rng.sample(frames, 4))}</body></html>"
        rows.append((k, f"http://h{k % 5}.org/{k}", page))
        want[k] = "\n".join(blocks)
    got = {r["page_id"]: r["text"] for r in extract.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert got == want


def test_clashing_columns_and_repeated_rows(spark):
    df = spark.createDataFrame([(1, "http://a/1", f"<p>{LONG}</p>", "t", "h", 5)] * 3 + [(None, None, None, None, None, None)], "page_id long, url string, html string, text string, host string, path int")
    out = extract.extract(df)
    assert out.columns == ["page_id", "url", "text", "n_chars"] and sorted(r["n_chars"] for r in out.collect()) == [0, *[len(LONG.strip())] * 3]
