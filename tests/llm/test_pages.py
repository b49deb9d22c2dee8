"""Main text and archive derivatives on hand-made pages."""

import base64
import gzip
import hashlib
import json

import pytest

from cubedensity.llm import mainhtml, warc

BODY = "<p>First, one.</p><p>Second &amp; last,\n  with <b>bold</b>text.</p>"
SIDE = {
    "nav": "<nav><ul><li><a href='/x'>Menu</a></li></ul></nav>",
    "header": "<header><a href='/'>Site</a> top</header>",
    "footer": "<footer>&copy; foot</footer>",
    "aside": "<aside><p>Side, note, here, there.</p></aside>",
    "ad": '<div class="ad">Buy, now, cheap, things.</div>',
    "cookie": '<div id="cookie-notice"><p>We use cookies, many, of them.</p><button>OK</button></div>',
    "form": "<form><label>Mail</label><input><textarea>t</textarea></form>",
    "script": '<script>var t="</p><p>no</p>";</script><style>p{}</style><noscript>off</noscript>',
    "comments": '<section class="comments"><p>Nice, text, indeed, I, say.</p></section>',
    "comment": "<!-- <p>hidden</p> -->",
    "hidden": "<div style='display: none'><p>hid, den</p></div>",
}
TEXT = "First, one. Second & last, with boldtext."


@pytest.mark.parametrize("name", SIDE)
@pytest.mark.parametrize("place", ["before", "after", "in"])
@pytest.mark.parametrize("holder", ["<article>{}</article>", "<main>{}</main>", "<div class='content'>{}</div>", '<div id="wrap"><div>{}</div></div>'])
def test_parts_beside_the_article(name, place, holder):
    inner = holder.format(SIDE[name] + BODY if place == "in" else BODY)
    page = f"<!DOCTYPE html><html><head><title>T</title></head><body>{SIDE[name] if place == 'before' else ''}{inner}{SIDE[name] if place == 'after' else ''}</body></html>"
    assert mainhtml.extract(page) == TEXT


def test_text_rules():
    assert mainhtml.extract("<article><h1>Head</h1><p><b>One<br><p>Two</p></article>") == "Head One Two"
    assert mainhtml.extract("<article><p>a<i>b</i>c&nbsp;&nbsp;d &#8364; &lt;x&gt;</p><ul><li>e<li>f</ul></article>") == "abc d € <x> e f"
    assert mainhtml.extract("<article><header><h1>T</h1><p>by me</p></header><p>x</p></article>") == "T x"
    assert mainhtml.extract("<div><p>only</p></div>") == "only"
    assert mainhtml.extract("plain < text") == "plain < text"
    assert mainhtml.extract("<article><table><tr><td>1<td>2<tr><td>3</table></article>") == "1 2 3"
    for empty in (None, "", "<html></html>", "<script>x", "<!-- x", "<p", "</p></div>"):
        assert mainhtml.extract(empty) in ("", "<p")
    assert mainhtml.extract("<p>a>b \"q\" it's</p>") == "a>b \"q\" it's"
    assert mainhtml.extract('<article><p title="a>b">ok</p></article>') == "ok"


def test_deep_and_long_pages():
    assert mainhtml.extract("<div>" * 50_000 + "<p>deep</p>") == "deep"
    long = " ".join(f"w{i}," for i in range(100_000))
    assert mainhtml.extract(f"<nav>x</nav><article><p>{long}</p></article>") == long


def test_link_lists_lose_to_prose():
    links = "".join(f"<p><a href='/{i}'>a link, with, commas, {i}</a></p>" for i in range(30))
    assert mainhtml.extract(f"<body><div class='x'>{links}</div><div class='y'>{BODY}</div></body>") == TEXT


def test_best_container_keeps_prose_siblings():
    page = f"<body><div><div class='part'>{BODY * 4}</div><p>A last line, outside of it.</p><div><a href='/'>x</a></div></div></body>"
    assert mainhtml.extract(page) == " ".join([TEXT] * 4) + " A last line, outside of it."


def test_main_text_rows(spark):
    rows = [(1, "u", f"<article>{BODY}</article>"), (1, "u", f"<article>{BODY}</article>"), (2, None, None), (None, "v", "")]
    df = spark.createDataFrame(rows, "page_id bigint, url string, html string").selectExpr("*", "1 as text", "2 as n_chars")
    got = [tuple(r) for r in mainhtml.main_text(df).collect()]
    assert sorted(got, key=str) == sorted([(1, "u", TEXT, len(TEXT))] * 2 + [(2, None, "", 0), (None, "v", "", 0)], key=str)
    assert mainhtml.main_text(df.limit(0)).count() == 0


PAGE = '<html><head><title>A &amp; B</title><script>x</script></head><body><p>One<br>two</p><a href="/a?b&amp;c">l</a><img src=i.png></body></html>'


def test_derivatives(spark, tmp_path):
    rows = [(1, "http://x/", PAGE), (2, None, None), (3, "http://y/é", "é")]
    pages = spark.createDataFrame(rows, "page_id bigint, url string, html string")
    responses = warc.responses(pages)
    assert responses.select("record_id").distinct().count() == 3
    made = warc.derive(responses)
    got = {(r.type, r.response_id): r for r in made.collect()}
    assert len(got) == 6
    sources = {r.record_id: r for r in responses.collect()}
    for (kind, rid), r in got.items():
        payload = (sources[rid].payload or "").encode()
        sha = lambda b: "sha1:" + base64.b32encode(hashlib.sha1(b).digest()).decode()
        assert r.refers_to == rid and f"WARC-Refers-To: {rid}" in r.header and f"WARC-Type: {kind}" in r.header
        assert r.payload_digest == sha(payload) and r.block_digest == sha(r.block.encode()) and r.length == len(r.block.encode())
        assert f"Content-Length: {r.length}" in r.header and f"WARC-Block-Digest: {r.block_digest}" in r.header
        assert ("WARC-Target-URI" in r.header) == (sources[rid].url is not None)
    first = next(k for k, r in sources.items() if r.url == "http://x/")
    assert got["conversion", first].block == "One\ntwo\nl"
    data = json.loads(got["metadata", first].block)
    assert data["title"] == "A & B" and data["status"] == "HTTP/1.1 200 OK"
    assert {"name": "Content-Length", "value": str(len(PAGE))} in data["headers"]
    assert data["links"] == [{"path": "a@href", "url": "/a?b&c"}, {"path": "img@src", "url": "i.png"}]
    assert sorted(r.target for r in warc.links(made).collect()) == ["/a?b&c", "i.png"]
    assert [tuple(r) for r in made.orderBy("record_id").collect()] == [tuple(r) for r in warc.derive(warc.responses(pages)).orderBy("record_id").collect()]

    warc.write_records(made, str(tmp_path / "out"))
    data = b"".join(gzip.decompress(p.read_bytes()) for p in sorted((tmp_path / "out").glob("*.gz")))
    seen = 0
    while data:
        head, data = data.split(b"\r\n\r\n", 1)
        assert head.startswith(b"WARC/1.0")
        size = int(head.split(b"Content-Length: ")[1])
        assert hashlib.sha1(data[:size]).digest() == base64.b32decode(head.split(b"WARC-Block-Digest: sha1:")[1][:32])
        assert data[size : size + 4] == b"\r\n\r\n"
        data, seen = data[size + 4 :], seen + 1
    assert seen == 6
    assert warc.derive(warc.responses(pages.limit(0))).count() == 0


def test_ends_are_found_after_letters_that_grow_in_lower_case():
    page = "<body><article><p>" + "İ" * 40 + "</p><SCRIPT>x</SCRIPT><p>kept, here.</p><p>Kept, there.</p></article></body>"
    got = mainhtml.extract(page)
    assert "kept, here." in got and "Kept, there." in got


def random_tree(rng, depth=0):
    """(tag, class, children): well-formed trees of containers, paragraphs and links."""
    if depth == 4 or depth and rng.random() < 0.2:
        words = " ".join(rng.choice(["one,", "two", "three", "four,", "five"]) for _ in range(rng.randint(0, 60)))
        link = ("a", "", [words]) if rng.random() < 0.3 else None
        return ("p", "", [link] if link else [words])
    tag = rng.choice(["div", "section", "div", "blockquote", "article"])
    return (tag, rng.choice(["", "", "", "x", "sidebar"]), [random_tree(rng, depth + 1) for _ in range(rng.randint(1, 4))])


def written(node):
    tag, mark, items = node
    return f"<{tag}{f' class={mark}' if mark else ''}>" + "".join(x if isinstance(x, str) else written(x) for x in items) + f"</{tag}>"


def brute_choice(top):
    """The rule of the docstring, worked out from each container down."""

    def text(node):
        return sum(len(" ".join(x.split())) if isinstance(x, str) else text(x) for x in node[2])

    def linked(node):
        return text(node) if node[0] == "a" else sum(linked(x) for x in node[2] if not isinstance(x, str))

    def marked(node):
        return node[1] == "sidebar" and node[0] != "article"

    def own(node):  # characters and commas that are no link's and no deeper block's
        parts = [x for x in node[2] if isinstance(x, str)]
        return sum(len(" ".join(x.split())) for x in parts), sum(x.count(",") for x in parts)

    def points(node, above, beside):
        """What a container gets: ``above`` is how many steps it is over the node looked at."""
        beside = beside or marked(node)
        size, commas = own(node)
        step = above - (node[0] in ("p", "blockquote"))
        mine = (1 + commas + min(3.0, size / 100)) / 2**step if size and 0 <= step < mainhtml.STEPS and node[0] != "a" else 0.0
        return mine * (mainhtml.BESIDE if beside else 1) + sum(points(x, above + 1, beside) for x in node[2] if not isinstance(x, str) and x[0] != "a")

    found = []

    def visit(node, line, beside):
        score = points(node, 0, beside)
        share = linked(node) / text(node) if text(node) else 0
        found.append((score * (1 - share), node, line))
        for x in node[2]:
            if not isinstance(x, str) and x[0] != "a":
                visit(x, [*line, node], beside or marked(node))

    visit(top, [], False)
    return found


def test_choice_against_brute_force():
    import random

    rng, chosen, scored = random.Random(5), 0, 0
    for _ in range(300):
        top = ("body", "", [random_tree(rng) for _ in range(3)])
        found = brute_choice(top)
        order = mainhtml.parse(written(top))
        mainhtml.score(order)
        got = [(mainhtml.worth(n), n.tag) for n in order if n.tag not in ("#root", "a")]
        assert [t for _, t in got] == [n[0] for _, n, _ in found]
        assert [w for w, _ in got] == pytest.approx([w for w, _, _ in found])
        most = max(w for w, _, _ in found)
        if not most:
            continue
        best, line = next((n, p) for w, n, p in found if w == most)
        order = mainhtml.parse(written(top))
        kept = mainhtml.article(order)
        around = next((n for n in [best, *reversed(line)] if n[0] in ("article", "main")), None)
        worth = {id(n): w for w, n, _ in found}
        if around is not None and worth[id(around)] >= mainhtml.AROUND * most:
            assert [n.tag for n in kept] == ["article"]
        else:
            assert best[0] in [n.tag for n in kept]
        chosen += 1
        scored += mainhtml.text_of(kept) != mainhtml.text_of([order[0]])
    assert chosen > 200 and scored > 100  # without the scores the texts would be others


def test_scores_choose_where_no_word_marks_a_part():
    links = "".join(f"<li><a href='/{i}'>Section {i}</a></li>" for i in range(40))
    teaser = "<div><a href='/a'>Read this, and this, and that</a> <a href='/b'>or that, too</a></div>"
    page = f"<body><div><ul>{links}</ul></div><div><div>{BODY * 5}</div></div>{teaser}<div>Made by us</div></body>"
    assert mainhtml.extract(page) == " ".join([TEXT] * 5)
    everything = mainhtml.text_of([mainhtml.parse(page)[0]])
    assert "Section 7" in everything and "Made by us" in everything


def test_a_page_inside_a_form_is_read():
    page = f"<body><form id='form1'><div><a href='/'>Home</a></div><div class='c'>{BODY * 3}</div></form></body>"
    assert mainhtml.extract(page) == " ".join([TEXT] * 3)


BAD = {
    "nested inline": "<b>x",
    "stray ends": "<div></span>",
    "open quotes": '<a "',
    "open values": '<a x="',
    "hidden ends": '<a x=">" ',
    "fenced blocks": "<div>",
    "comments": "<!--",
    "scripts": "<script>",
    "titles": "<title>",
    "names": "<a",
    "signs": "<",
    "false ends": "</scriptx",
    "headers": "<header><h1>",
}


@pytest.mark.parametrize("name", BAD)
def test_bad_pages_take_linear_time(name):
    import time

    def seconds(size):
        page = ("<p><button>" if name == "fenced blocks" else "<script>" if name == "false ends" else "") + BAD[name] * (size // len(BAD[name]))
        began = time.process_time()
        mainhtml.extract(page)
        warc.read(page)
        return time.process_time() - began

    seconds(20_000)
    assert seconds(1_000_000) < 8 * max(0.15, seconds(250_000))  # four times the page, not sixteen times the time


def test_responses_that_differ_have_ids_that_differ(spark):
    rows = [(1, None, "x"), (None, "1", "x"), (1, "", "x"), (1, "1", None), (1, "1", ""), (1, "1", "y"), (1, "1", "y")]
    pages = spark.createDataFrame(rows, "page_id bigint, url string, html string").selectExpr("*", "1 as record_id", "2 as payload", "3 as block")
    made = warc.responses(pages)
    assert made.select("record_id").distinct().count() == len(set(rows))
    assert warc.derive(made).select("record_id").distinct().count() == 2 * len(set(rows))


def test_dates_and_addresses(spark):
    pages = spark.createDataFrame([(1, "http://x/a b\r\nWARC-Type: fake", "p", "2025-05-05T05:05:05Z")], "page_id bigint, url string, html string, at string")
    for r in warc.derive(warc.responses(pages, date=pages["at"])).collect():
        assert r.date == "2025-05-05T05:05:05Z" and "WARC-Date: 2025-05-05T05:05:05Z" in r.header
        assert "WARC-Target-URI: http://x/a%20b%0D%0AWARC-Type:%20fake\r\n" in r.header and r.header.count("WARC-Type") == 2


def test_raw_elements_do_not_lower_the_page():
    import time

    from cubedensity.llm.markup import LOWER, tokens

    page = "<body><SCRIPT>x</ſcript></Script ><p>" + "ü" * 3_000_000 + "</p><style>y"
    began = time.process_time()
    page.translate(LOWER)
    lowering = time.process_time() - began
    began = time.process_time()
    found = list(tokens(page))
    assert time.process_time() - began < lowering / 2
    assert found[2] == ("raw", "script", "x</ſcript>") and found[-1] == ("raw", "style", "y")
