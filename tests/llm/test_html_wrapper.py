"""Wrappers and main texts of made and given pages."""

import html
import json
import random
import re
import time

import pytest
from mjoin.llm import html_wrapper as H
from mjoin.llm.common import load
from pyspark.sql import functions as F

FULL = """<!DOCTYPE html><html><head><title>T &amp; t</title><style>p > a {{}}</style><script>if (a < b) "</p>"</script></head><body>
<!-- <p>not this</p> --><div class="cookie-notice"><p>We use cookies</p><button>OK</button></div>
<header class="site-header"><div>Brand</div><nav><ul><li><a href="/">Home</a><li><a href="/x">More</a></ul></nav></header>
<div id="content"><{tag} class="post-{n}"><header><h1>Title {n}</h1></header>
<p>First&nbsp;para {n}
 with <b>bold</b>ness &lt;kept&gt;<br>and a break<p>Second para {n}.</p>
<ul><li>One {n}<li>Two</ul><div class="ad"><p>Buy now</p></div><form><label>Mail</label><input></form>
<table><tr><td>cell {n}<td>b</table><blockquote>Quote {n} &#233;&copy;</blockquote></{tag}>
<section id="comments"><h2>Comments</h2><article class="comment"><p>Nice post {n}!</p></article></section></div>
<aside><p>Related stuff</p></aside><footer><p>&copy; 2024</p></footer><noscript>enable</noscript></body></html>"""


def want(n):
    return f"Title {n}\nFirst para {n} with boldness <kept> and a break\nSecond para {n}.\nOne {n}\nTwo\ncell {n}\nb\nQuote {n} é©"


def texts(spark, rows):
    frame = spark.createDataFrame(rows, "page_id bigint, url string, html string, tree string, host int")
    assert H.extract(frame).columns == ["page_id", "url", "text", "n_chars"]
    got = H.extract(frame).collect()
    assert len(got) == len(rows) and all(r["n_chars"] == len(r["text"]) for r in got)
    return {r["page_id"]: r["text"] for r in got}


@pytest.mark.parametrize("tag", ["article", "main", "div"])
def test_main_text_of_full_pages(spark, tag):
    rows = [(n, f"https://u@h.example:80/{n}", FULL.format(n=n, tag=tag), "x", 1) for n in range(7)]
    got = texts(spark, rows)
    for n in range(7):
        # outside an article, a header is the page's own
        assert got[n] == want(n) if tag != "div" else want(n).split("\n", 1)[1] == got[n]


def test_a_part_apart_leaves_others_at_its_path(spark):
    """One hidden paragraph, or a box of comments, says nothing about other blocks of the same path."""
    rows = [(n, f"http://h/{n}", f"<article><h1>T{n}</h1>{'<p hidden>secret</p>' if n == 3 else ''}<p>Body {n}.</p><p style='display:none'>x</p></article>", "", 0) for n in range(6)]
    rows += [(10 + n, f"http://g/{n}", f"<div class='box' id='body'><p>Body {n}.</p></div><div class='box' id='comments'><p>Nice {n}</p></div>", "", 0) for n in range(6)]
    got = texts(spark, rows)
    for n in range(6):
        assert got[n] == f"T{n}\nBody {n}." and got[10 + n] == f"Body {n}."


LOOSE = {
    "<body class='has-sidebar'><p>{}</p><div class='sidebar'><p>Other</p></div></body>": "{}",
    "<body><div class='post no-sidebar'><p>{}</p></div><div class='share'><p>Share</p></div></body>": "{}",
    "<article class='post comments-open'><h1>T</h1><p>{}</p></article><div class='comments'><p>Nice</p></div>": "T\n{}",
    "<main class='search-results share'><p>{}</p><article class='post comments-open'><p>b</p></article></main>": "{}\nb",
    "<article><h1>T</h1><div class='post no-sidebar'><p>{}</p></div><div class='ad'><p>Buy</p></div></article>": "T\n{}",
    "<article><section data-title='Hidden gems'><p>{}</p></section></article>": "{}",
    "<article><div data-hidden='false' data-id='comments' data-class='ad'><p>{}</p></div></article>": "{}",
    "<article><p>{}</p><p HIDDEN>x</p><p aria-hidden=true>x</p><p class=ad>x</p></article>": "{}",
    "<article><p>{}</p></article><section id='comments'><article class='comment'><p>" + "long " * 40 + "</p></article></section>": "{}",
}


def test_loose_words_keep_articles(spark):
    rows = [(n, f"http://h{n}/", page.format("The body of the page"), "", 0) for n, page in enumerate(LOOSE)]
    got = texts(spark, rows)
    assert [got[n] for n in range(len(LOOSE))] == [w.format("The body of the page") for w in LOOSE.values()]


def test_odd_pages(spark):
    long = "<p>" + "word " * 40_000 + "</p>"
    rows = [(1, "http://a/1", None, None, None), (2, "http://a/2", "", "", 0), (3, None, "plain text & more", "", 0), (4, "not a url", "<p>x</p><p>y", "", 0), (4, "not a url", "<p>x</p><p>y", "", 0), (5, "http://b/", f"<article>{long}</article>", "", 0)]
    rows += [(6, "http://c/", "<article><p>a</div></p>b<!-- open", "", 0), (7, "http://d/", "<" * 3000 + '"' * 3001, "", 0), (None, "http://e/", "<main>m</main>", "", 0)]
    rows += [(8, "http://f/", "<html><head><title>t</title><body><p>no end of the head</p>", "", 0)]
    got = texts(spark, rows)
    assert got[1] == got[2] == "" and got[3] == "plain text & more" and got[4] == "x\ny" and got[6] == "a\nb" and got[None] == "m"
    assert got[8] == "no end of the head"
    assert len(got[5]) == 199_999
    assert H.extract(spark.createDataFrame([], "page_id bigint, url string, html string")).count() == 0


def test_given_pages(spark, sf):
    pages = load(spark, sf, "pages")
    got = {r["page_id"]: r["text"] for r in H.extract(pages).collect()}
    for r in pages.collect():
        inner = re.search(r"<article>(.*)</article>", r["html"], re.S).group(1)
        parts = [" ".join(html.unescape(re.sub(r"<[^>]+>", "", p.replace("<br>", " "))).split()) for p in re.split(r"</?(?:p|h1)>", inner)]
        assert got[r["page_id"]] == "\n".join(p for p in parts if p)


@pytest.mark.parametrize("page", ["<div>" * 100_000 + "deep", "<svg>" * 100_000 + "x", "<iframe>" * 50_000, "<!" * 200_000, "<a " * 200_000, "<a 'x\">" * 60_000, "<!--" * 100_000, "</p>" * 100_000, "<div class=ad>" * 60_000 + "x", "<div></span>" * 50_000, "<p>x<li>" * 30_000, "<x y='" * 50_000 + ">"])
def test_hostile_pages_stay_linear(page):
    began = time.time()
    blocks, folded = H.parse(page)
    json.dumps(folded)
    assert time.time() - began < 20
    assert page[-4:] != "deep" or [b["text"] for b in blocks] == ["deep"]


def test_many_unlike_children_are_aligned_in_bounded_time():
    rng = random.Random(0)
    pages = ["".join(f"<{rng.choice(['p', 'ul', 'h2', 'pre', 'hr', 'table'])}>x" for _ in range(3000)) for _ in range(2)]
    a, b = map(tree, pages)
    began = time.time()
    both = H.align(a, b)
    assert time.time() - began < 20
    assert set(H.slot_marks(a)) | set(H.slot_marks(b)) <= set(H.slot_marks(both))


def test_the_wrapper_decides_about_hinted_parts(spark):
    """A varying part that is named like an advert stays where every page of the host has it, and goes where only some do."""
    part = "<div class='promo'><p>Part {n} of this very series</p></div>"
    page = "<article><h1>Title {n}</h1><p>{n} long body of an article with many words in it</p>{part}<p>The end, {n}.</p></article>"
    rows = [(n, "http://always/", page.format(n=n, part=part.format(n=n))) for n in range(6)]
    rows += [(10 + n, "http://sometimes/", page.format(n=n, part=part.format(n=n) if n % 2 else "")) for n in range(6)]
    frame = spark.createDataFrame(rows, "page_id bigint, url string, html string")
    got = {r["page_id"]: r["text"] for r in H.extract(frame).collect()}
    for n in range(6):
        ends = f"Title {n}\n{n} long body of an article with many words in it", f"The end, {n}."
        assert got[n] == f"{ends[0]}\nPart {n} of this very series\n{ends[1]}" and got[10 + n] == "\n".join(ends)
    # without alignment, the first tree stands for all pages, and what is dropped changes
    parsed = H.parsed_pages(frame)
    slots, aligned = H.slot_statistics(parsed.select("host", "blocks")), H.infer_wrappers(parsed.select("host", "tree"))
    first = parsed.groupBy("host").agg(F.max_by("tree", F.length("tree")).alias("wrapper")).join(aligned.select("host", "n_pages"), "host")
    dropped = lambda wrappers: {r["host"]: r["dropped"] for r in H.content_paths(slots, wrappers).collect()}
    assert dropped(aligned) == {"always": [], "sometimes": ["article/div.promo/p"]} != dropped(first)


def test_text_that_never_changes_is_template(spark):
    rows = [(n, f"http://h/{n}", f"<div id='a'><div class='box'><p>Body {n} of the page</p><p>same</p></div><div class='note'><p>Read on</p></div></div>") for n in range(5)]
    got = [r["text"] for r in H.extract(spark.createDataFrame(rows, "page_id bigint, url string, html string")).orderBy("page_id").collect()]
    assert got == [f"Body {n} of the page\nsame" for n in range(5)]


def tree(page):
    return H.parse(page)[1]


def test_alignment_gives_optional_and_repeated_groups():
    a = tree("<div><h1>a</h1><p>x</p></div>")
    b = tree("<div><h1>b</h1><p>x</p><p>y</p><p>z</p></div>")
    c = tree("<div><h1>c</h1><table><tr><td>1</td></tr></table><p>x</p></div>")
    wrapper = H.align(H.align(a, b), c)
    assert H.expression(wrapper) == "<div> <h1> # </h1> (<table> <tr> <td> # </td> </tr> </table>)? (<p> # </p>)+ </div>"
    assert all(H.covers(wrapper, t) for t in (a, b, c))
    assert not H.covers(wrapper, tree("<div><p>x</p></div>")) and not H.covers(a, b)
    assert H.expression(H.fold(["", "", [["dt", "", []], ["dd", "", []]] * 3])) == "(<dt> </dt> <dd> </dd>)+"
    for left in (a, b, c):
        for right in (a, b, c):
            both = H.align(left, right)
            assert H.covers(both, left) and H.covers(both, right)


def test_wrappers_of_hosts(spark):
    rows = [(n, f"http://h/{n}", f"<div><h1>t</h1>{'<p>x</p>' * (n % 3 + 1)}{'<hr>' * (n % 2)}</div>") for n in range(20)]
    parsed = H.parsed_pages(spark.createDataFrame(rows, "page_id bigint, url string, html string"))
    found = H.infer_wrappers(parsed, fan_in=2).collect()
    assert len(found) == 1 and found[0]["n_pages"] == 20 and found[0]["n_trees"] == 2
    wrapper = json.loads(found[0]["wrapper"])
    assert H.expression(wrapper) == "<div> <h1> # </h1> (<p> # </p>)+ </div>"
    assert set(H.slot_marks(wrapper)) == {"div/h1", "div/p"}


def test_wrappers_in_many_parts(spark):
    """However the trees of a host are parted, the wrapper covers all of them."""
    pages = [f"<div>{''.join(f'<{t}>x</{t}>' for k, t in enumerate(('h1', 'p', 'table', 'ul', 'pre')) if n >> k & 1)}</div>" for n in range(32)]
    parsed = H.parsed_pages(spark.createDataFrame([(n, "http://h/", p) for n, p in enumerate(pages)], "page_id bigint, url string, html string"))
    for fan_in in (3, 1000):
        found = H.infer_wrappers(parsed, fan_in).collect()
        assert len(found) == 1 and found[0]["n_pages"] == 32 and found[0]["n_trees"] == 32
        wrapper = json.loads(found[0]["wrapper"])
        assert all(H.covers(wrapper, tree(p)) for p in pages)
        assert set(H.slot_marks(wrapper)) == {f"div/{t}" for t in ("h1", "p", "table", "ul", "pre")}
