import random
import time

import public_tokenizers as P
import pytest
from tokenizers import Tokenizer, models, pre_tokenizers

from overlapix.llm import html_extract as H
from overlapix.llm import unigram_count as U
from tests.llm.helpers import EDGES, docs_frame

VOCAB = P.path("piece_bpe_32k.model")

PAGE = """<!DOCTYPE html><html><head><title>T</title><style>p{}</style><script>var t="</p><article>x";</script></head>
<body class="has-sidebar"><header><p>Site name and a slogan that is long enough to look like a paragraph of text</p></header><nav><ul><li><a href="/a">A</a></li></ul></nav>
<div class="cookie-notice">We use cookies on this site, please agree to all of them right now, thank you very much.</div>
<article class="post"><header><h1>Title &amp; more</h1></header><p><b>First   para<br><p>Second&nbsp;one &lt;tag&gt;.</p><div class="ad">Buy now</div><p>Wh.</p>
<form><input><label>Your name</label></form><section id="comments"><article class="comment">Nice text!</article></section></article>
<aside>Other things to read</aside><footer>&copy; someone</footer>"""

PLAIN = "<html><body><div id=menu><a href=x>Home</a></div><div><a href=1>One</a> <a href=2>Two</a></div><p>" + "Long running text here. " * 10 + "</p><p>Short.</p><p>" + "More running text. " * 9 + "</p><p>&copy; 2024 Someone</p><div class='comments'><p>" + "I think so too, good text. " * 9 + "</p></div></body></html>"


def test_article():
    assert H.main_text(PAGE) == "Title & more First para Second one <tag>. Wh."


def test_without_article():
    assert H.main_text(PLAIN) == ("Long running text here. " * 10 + "Short. " + "More running text. " * 9).strip()


@pytest.mark.parametrize("html", [None, "", "<", "<p", "no markup at all" * 9, "<div class='ad'>never closed <p>" + "text of the page goes on. " * 9, "<a title='x>y'>" + "z" * 200, "</p></article>", "<article>" * 50])
def test_odd_pages(html):
    out = H.main_text(html)
    assert isinstance(out, str)
    if html and "never closed" in html:
        assert "text of the page" in out


def test_windows_decide_between_articles():
    """A teaser beside the story goes, for its windows stay below the level; without windows it would stay."""
    page = "<article><h2>Other story</h2><p>Read it.</p></article><article><h1>Story</h1>" + "<p>Running text of the story itself.</p>" * 9 + "</article><article><p>More</p></article>"
    story = "Story " + " ".join(["Running text of the story itself."] * 9)
    assert H.main_text(page) == story
    level, H.SURGE = H.SURGE, 1e-9
    try:
        assert H.main_text(page) == "Other story Read it. " + story + " More"
    finally:
        H.SURGE = level


def slow_regions(sizes, level):
    """Surge and dive from the definition: every window sum, every run of positive ones."""
    padded = [*sizes, *[0] * H.WINDOW]
    sums = [sum(padded[j] for j in range(i - H.WINDOW + 1, i + 1) if j >= 0) for i in range(len(padded))]
    out, i = [], 0
    while i < len(sums):
        if not sums[i]:
            i += 1
            continue
        j = i
        while j < len(sums) and sums[j]:
            j += 1
        if max(sums[i:j]) >= level > 0:
            out.append((i, max(k for k in range(i, j) if padded[k]) + 1))
        i = j
    return out


def test_surge_and_dive_by_brute_force():
    rng = random.Random(8)
    for _ in range(3000):
        sizes = [rng.choice([0, 0, 0, 1, 5, 40, 90]) for _ in range(rng.randrange(25))]
        level = rng.choice([0, 1, 30, 80])
        assert list(H.regions(sizes, level)) == slow_regions(sizes, level)


def test_pages_without_their_article_tag(spark):
    """The windows find the same text where the pages name no article."""
    html = [r.html for r in spark.read.parquet("/root/testdata/sf0.01/pages.parquet").collect()]
    same = [H.main_text(h) == H.main_text(h.replace("<article>", "<div>").replace("</article>", "</div>")) for h in html]
    assert sum(same) >= 0.95 * len(same), sum(same) / len(same)


@pytest.mark.parametrize("unit", ["<div class=ad>", "<div class=ad><p>", "<p class=ad>x", "<a class=share href='x>", "<!--", "<script>", "<span class=ad>", "</div>", "<li class=menu><ul>", "<article>"])
def test_long_odd_pages_are_quick(unit):
    start = time.time()
    H.main_text(unit * (1_000_000 // len(unit)))
    assert time.time() - start < 4


def test_rows_that_repeat_and_columns_that_clash(spark):
    rows = [(1, "u", PAGE, "t", 7), (1, "u", PAGE, "t", 7), (2, None, None, "t", 7), (None, "v", PLAIN, None, None)]
    df = spark.createDataFrame(rows, "page_id bigint, url string, html string, text string, n_chars int")
    got = sorted(map(tuple, H.extract(df).collect()), key=repr)
    assert len(got) == 4 and got[0] == got[1] and got[0][2] == H.main_text(PAGE) and (2, None, "", 0) in got
    assert H.extract(df.limit(0)).count() == 0


def test_pages_table(spark):
    pages = spark.read.parquet("/root/testdata/sf0.001/pages.parquet")
    rows = H.extract(pages).collect()
    assert len(rows) == pages.count() and all(r.n_chars == len(r.text) > 0 for r in rows)
    by = {r.page_id: r.html for r in pages.collect()}
    for r in rows:
        foot = by[r.page_id].split("<footer>")[-1].split("&middot; ")[-1].split("</footer>")[0]
        assert not r.text.endswith(foot) and "track(" not in r.text and "<" not in r.text
    odd = spark.createDataFrame([(None, None, None), (1, "u", "")], "page_id bigint, url string, html string")
    assert [tuple(r)[2:] for r in H.extract(odd).collect()] == [("", 0), ("", 0)]


def library(pieces, byte_fallback=True):
    tok = Tokenizer(models.Unigram(pieces, 0, byte_fallback))
    tok.pre_tokenizer = pre_tokenizers.Metaspace(replacement=U.SPACE, prepend_scheme="always", split=True)
    return tok


def test_counts_equal_library(spark):
    tok, tool = library(U.read_pieces(VOCAB)), U.counter(VOCAB)
    rows = [r.text for r in spark.read.parquet("/root/testdata/sf0.001/documents.parquet").collect()]
    rng = random.Random(2)
    rows += ["".join(rng.choice("aeé t▁ \n中\U0001f600<0x41>") for _ in range(rng.randrange(30))) for _ in range(2000)]
    for t in rows:
        assert tool.count(t) == len(tok.encode(t, add_special_tokens=False).ids), ascii(t[:80])


def test_ties_and_unknowns():
    rng = random.Random(4)
    pieces = [("<unk>", 0.0), *((p, -rng.choice([1.0, 2.0, 1.5, 0.5])) for p in ["▁", "a", "b", "aa", "ab", "ba", "aab", "abb", "▁a", "▁ab", "bb", "bab", "aba"])]
    tok, tool = library(pieces, False), U.UnigramCounter(pieces, False)
    for _ in range(4000):
        t = "".join(rng.choice("aab bxy") for _ in range(rng.randrange(14)))
        assert tool.count(t) == len(tok.encode(t, add_special_tokens=False).ids), t


def test_edge_rows(spark):
    got = U.token_counts(docs_frame(spark, EDGES), VOCAB).collect()
    assert len(got) == len(EDGES) and got[0].n_tokens == got[1].n_tokens == 0
    assert U.token_counts(docs_frame(spark, []), VOCAB).count() == 0
