"""WARC archives and main text."""

import base64
import gzip
import hashlib

import pytest
from pyspark.sql import functions as F

from gembed.llm import html_text, warc

PAGES = "page_id long, url string, html string, digest string, first long, refers_to long, file string"


@pytest.fixture(scope="module")
def pages(spark):
    rows = [(1, "http://www.a.example.com/x?q=1#f", "<p>one</p>"), (2, "http://b.example.com", "<p>one</p>"), (7, "http://a.example.com/x?q=1", "<p>two é😀</p>\r\n\r\n"), (3, None, None), (4, "", ""), (5, "http://b.example.com/ y", "<p>one</p>"), (6, "ftp://c", "x" * 200_000), (9, "http://a.example.com/x?q=1", "third")]
    return spark.createDataFrame([(*r, "d", 1, 2, "f") for r in rows], PAGES).repartition(3)


def test_round_trip_of_all_records(spark, pages):
    rows = [(r["page_id"], (r["html"] or "").encode()) for r in pages.collect()]
    largest = {}
    for i, p in rows:
        largest[p] = max(i, largest.get(p, i))
    got = {r["page_id"]: r for r in warc.round_trip(pages).collect()}
    assert len(got) == len(rows)
    for i, p in rows:
        r = got[i]
        assert (r["payload_bytes"], r["payload_digest"]) == (len(p), base64.b32encode(hashlib.sha1(p).digest()).decode())
        assert (r["record_type"], r["refers_to"]) == (("response", None) if largest[p] == i else ("revisit", largest[p]))
    assert all(r["record_type"] == "response" for r in warc.round_trip(pages, min_bytes=100).collect())
    assert warc.round_trip(pages.where("false")).count() == 0


def test_look_up_through_both_levels(pages):
    archive = warc.write_archive(pages, block_lines=2, file_bytes=500)
    assert archive.directory.count() >= 3
    found = warc.look_up(archive, "http://a.example.com/x?q=1")
    assert sorted(f["id"] for f in found) == [1, 7, 9]
    assert next(f for f in found if f["id"] == 7)["payload"] == "<p>two é😀</p>\r\n\r\n".encode()
    assert warc.look_up(archive, "http://nowhere.example/") == []
    opened = warc.Directory(archive)
    for r in pages.collect():
        if r["url"]:
            same = [p["page_id"] for p in pages.collect() if warc.url_key(p["url"]) == warc.url_key(r["url"])]
            assert sorted(f["id"] for f in opened.look_up(r["url"])) == sorted(same)
    assert [f["id"] for f in warc.look_up(archive, "http://b.example.com/ y")] == [5]


def test_keys_and_records():
    assert warc.url_key("https://www.Sub.Example.com:81/A?b#c") == "com,example,sub:81)/a?b"
    r = warc.record_bytes(3, "http://e/\r\nX: 1", b"abc", None)
    assert warc.parse_record(gzip.decompress(gzip.compress(r)))["payload"] == b"abc" and b"\r\nX: 1" not in r
    with pytest.raises(ValueError):
        warc.parse_record(r[:-6])


def test_weights_find_the_labelled_content():
    assert all(html_text.main_text(p) == t for p, t in html_text.labelled_pages())


LONG = " ".join(f"word{i}" for i in range(60))


@pytest.mark.parametrize(
    "page,text",
    [
        (None, ""),
        ("", ""),
        ("<p></p>", ""),
        (f"<body><article><h1>A &amp; B</h1><p>{LONG}</p><p>End.</p></article><footer>f</footer>", f"A & B\n{LONG}\nEnd."),
        (f"<article><p>x<b>y</b>  z&nbsp;q<br>r</p><p>{LONG}<script>if (a < b) {{ '</p>' }}</script></p></article>", f"xy z q r\n{LONG}"),
        (f"<main><p>{LONG}</p><aside>no</aside><div class='cookie-notice'>no</div><form><p>no</p></form><section id='comments'><p>nice post {LONG}</p></section></main>", LONG),
        (f"<nav><a href='/'>home</a></nav><div class='sidebar'><p>{LONG}</p></div><article><ul><li>one<li>two {LONG}</ul></article>", f"one\ntwo {LONG}"),
        (f"<article><p>{LONG}<!-- <p>hidden</p> --></p><div class='ad'>buy</div><p>more &lt;tags&gt; &#233;</p></article>", f"{LONG}\nmore <tags> é"),
        (f"<body><div class='content'><p>{LONG}</p><p>two</p></div><div class='footer'>f</div>", f"{LONG}\ntwo"),
        (f"<article><p>{LONG}</p><table><tr><td>a<td>b</table></article><style>p{{}}", f"{LONG}\na\nb"),
    ],
)
def test_main_text(page, text):
    assert html_text.main_text(page) == text


@pytest.mark.parametrize(
    "page,text",
    [
        (f"<body><h1>Title</h1><p>{LONG}</p><p>End.</p></body>", f"Title\n{LONG}\nEnd."),
        (f"<h1>Title</h1><p>Short.</p><p>{LONG}</p><p>The end.</p>", f"Title\nShort.\n{LONG}\nThe end."),
        (f"<html><body><ul><li><a href='/'>home page</a><li><a href='/x'>news</a></ul><h1>Title</h1><p>{LONG}</p><aside><p>{LONG} {LONG}</p></aside><p>{LONG} z</p><p>End.</p><footer>f</footer></body></html>", f"Title\n{LONG}\n{LONG} z\nEnd."),
        (f"<body><p>{LONG}</p><div class='ad'>{LONG} {LONG}</div><ul><li>one<li>two</ul><p><a href='/'>all links here</a></p></body>", f"{LONG}\none\ntwo"),
        (f"<body><ul><li>{LONG}</ul><div class='advert'>{LONG} {LONG}</div><p>End.</p></body>", f"{LONG}\nEnd."),
        (f"<body><section><h2>A</h2><p>{LONG}</p></section><section><h2>B</h2><p>{LONG}</p></section><section><p>C</p></section></body>", f"A\n{LONG}\nB\n{LONG}\nC"),
    ],
)
def test_main_text_directly_in_the_body(page, text):
    assert html_text.main_text(page) == text


def test_best_run_equals_all_runs():
    import random

    r = random.Random(3)
    for _ in range(300):
        blocks = [html_text.Block("x", n := r.randrange(1, 9), r.randrange(n + 1), r.random() < 0.2, 0, r.randrange(4), r.randrange(4)) for _ in range(r.randrange(12))]
        w = html_text.Weights(1.0, r.choice((0.0, -1.0, -2.0)), -2.0, r.choice((-1.0, -2.0, -4.0)), r.choice((0.0, -0.5, -1.0)))

        def total(a, b, blocks=blocks, w=w):
            return sum(html_text.gain(x, w) + (html_text.cost(x, w) if i else 0) for i, x in enumerate(blocks[a : b + 1]))

        every = {(a, b): total(a, b) for a in range(len(blocks)) for b in range(a, len(blocks))}
        lo, hi = html_text.best_run(blocks, w)
        best = max(every.values(), default=0.0)
        assert (hi < lo and best <= 0) or every[lo, hi] == best


def test_the_weights_decide_on_held_out_pages():
    held = [(*html_text.blocks_of(p), t) for p, t in html_text.labelled_pages(seed=7)]
    best = html_text.quality(html_text.fitted(), held)
    assert best > 0.97
    for other in (html_text.Weights(1, 0, 0, 0, 0), html_text.Weights(1, 1, 1, 1, 1), html_text.Weights(1, 0, -2, 0, 0)):
        assert html_text.quality(other, held) < best - 0.02, other


@pytest.mark.parametrize(
    "page",
    ['<a "' * 400_000, "<div>x" * 100_000, "<head>" * 200_000, '<a x=">" ' * 200_000, "<div>" * 600 + "<dt></dt>" * 100_000, "<svg>a" * 200_000, "<" * 1_000_000, "<!--" * 400_000, "<div>" * 1000 + "</section>" * 150_000, "<p>" + "word " * 400_000],
    ids=["quotes", "deep", "head", "values", "lists", "svg", "angles", "comments", "ends", "words"],
)
def test_long_and_hostile_pages_take_linear_time(page):
    import time

    at = time.process_time()
    text = html_text.main_text(page)
    assert time.process_time() - at < 8
    if page.startswith("<p>"):
        assert text.count("word") == 400_000


@pytest.mark.parametrize(
    "page,text",
    [
        ("<p>one two three</p><svg><path></p><p>four five six seven</p>", "one two three\nfour five six seven"),
        (f"<article><p>{LONG}</p><iframe src=x><p>five six</p><noscript><p>six</p><object><p>seven</p></article>", f"{LONG}\nfive six\nsix\nseven"),
        (f"<article><p>{LONG}</p><svg><text>no</text></svg><object>no<p>no</p></object><p>yes</p><select><option>no</select></article>", f"{LONG}\nyes"),
        (f"<article><div class='social-science'>{LONG}</div><div id='tags-content'>ten</div><div class='ad-box'>no</div><div class='site-footer'>no</div></article>", f"{LONG}\nten"),
        (f"<article><header><h1>Title</h1><p>by me</p></header><p>{LONG}</p></article>", f"Title\n{LONG}"),
        (f"<article><p>a </> b </ c> d < e <1> {LONG}</p><p title='it\"s'>f</p></article>", f"a b d < e <1> {LONG}\nf"),
    ],
)
def test_nothing_is_lost_after_unclosed_elements(page, text):
    assert html_text.main_text(page) == text


def test_repeated_rows_each_give_a_row(spark, pages):
    twice = pages.union(pages)
    assert html_text.extract(twice).count() == twice.count()
    assert warc.round_trip(twice).count() == twice.count()


def test_given_pages(spark):
    pages = spark.read.parquet("/root/testdata/sf0.001/pages.parquet")
    got = html_text.extract(pages.withColumn("text", F.lit("clash")))
    assert got.count() == pages.count() and got.where("n_chars != length(text) or n_chars = 0").isEmpty()
    joined = got.join(pages.select("page_id", "html"), "page_id")
    assert joined.where("text like '%<%' and html not like '%&lt;%'").isEmpty()
    assert html_text.extract(pages.where("false")).count() == 0
