"""HTML rendering: cases by hand, and random pages whose visible words are known."""

from __future__ import annotations

import random
from html.parser import HTMLParser
from pathlib import Path

import pytest

from eigenlake.llm import htmltext

SF = Path("/root/testdata/sf0.001")


@pytest.mark.parametrize(
    "source,text",
    [
        ("<html><head><title>x</title><p>Hello</p></html>", "Hello"), ("<head><meta charset=u><div>Seen</div>", "Seen"), ("<head>words</head> more", "words more"), ("<head><script>1</script><body>b</body>", "b"),
        ("<head><template><div>no</div></template><title>no</title></head>yes", "yes"), ("<p>a<head>b", "ab"),
        ("<div style='visibility:hidden'>a<b style='visibility:visible'>b</b>c</div>d", "b\nd"), ("<style>.h{visibility:hidden}.v{visibility:visible}</style><ul class=h><li>a<li class=v>b</ul>", "- b"),
        ("<div style='display:none'><b style='display:block;visibility:visible'>no</b></div>yes", "yes"), ("<p hidden>a</p><p hidden style='display:block'>b</p>", "b"), ("<div style='visibility:hidden'><p style='visibility:inherit'>a</div>b", "b"),
        ("<table><tr><td rowspan=2>a<td>b<tr><td>c</table>", "a  b\n   c"), ("<table><tr><td>a<td rowspan=0>b<tr><td>cc<tr><td>d<td>e</table>", "a   b\ncc\nd      e"), ("<table><tr><td colspan=2>aaaa<td>b<tr><td>c<td>d<td>e</table>", "aaaa  b\nc  d  e"),
        ("<table><tr><td>" + "w" * 60 + "<td>a<tr><td>b<td>c</table>", "w" * 60 + "  a\nb  c"), ("<table><tr><td>a<td>" + "w" * 60 + "<tr><td>bb<td>c</table>", "a   " + "w" * 60 + "\nbb  c"),
        ("<div><table><tr><td>a</div>b<td>c</table>d</div>", "ab  c\n\nd"), ("<div>" * 300 + "<i hidden>secret</i>" + "<i style='display:none'>secret</i>" + "<b>x</b>", "x"), ("<blockquote>" * 3 + "q", "      q"),
        ("<ul><li>" * 60 + "deep" + "</ul>" * 60 + "end", "- " * htmltext.NESTED + "deep\n\nend"),
    ],
)
def test_cases(source, text):
    assert htmltext.render(source) == text


class Page:
    """A random page, its source, and the words a reader sees, in order.

    `shown` is False under hidden visibility, which children may lift, and None where nothing has a place.
    """

    def __init__(self, seed: int):
        self.rng, self.seen, self.n = random.Random(seed), [], 0
        head = self.rng.choice(["", "<head><title>no</title><style>.gone{display:none} .veil{visibility:hidden}</style>", "<!doctype html><html><head><meta a=b><style>.gone{display:none}.veil{visibility:hidden}</style></head><body>"])
        self.styled = "style" in head
        self.source = head + self.blocks(4, True)

    def words(self, shown: bool | None) -> str:
        out = []
        for _ in range(self.rng.choice([1, 1, 3])):
            self.n += 1
            out.append(f"w{self.n}")
        if shown:
            self.seen += out
        return self.rng.choice([" ", "\n", "  "]).join(out)

    def inline(self, depth: int, shown: bool | None) -> str:
        kind = self.rng.randrange(6) if depth else 0
        if kind < 2:
            return self.words(shown) + " "
        if kind == 2:
            return "<b>" + self.inline(depth - 1, shown) + "</b> "
        if kind == 3:
            return f"<i hidden>{self.inline(depth - 1, None)}</i> "
        if kind == 4:
            return "<br><!-- no --><script>no()</script>"
        style, inner = self.rng.choice([("hidden", False), ("visible", True)])
        inner = None if shown is None else inner
        return f"<span style='visibility:{style}'>{self.inline(depth - 1, inner)}</span> "

    def blocks(self, depth: int, shown: bool | None) -> str:
        return "".join(self.block(depth, shown) for _ in range(self.rng.choice([1, 2, 3])))

    def block(self, depth: int, shown: bool | None) -> str:
        kind = self.rng.randrange(9) if depth else 0
        close = self.rng.random() < 0.5
        if kind < 2:
            return "<p>" + self.inline(2, shown) + ("</p>" if close else "")
        if kind == 2:
            return "<div>" + self.blocks(depth - 1, shown) + "</div>"
        if kind == 3:
            return "<ul>" + "".join("<li>" + self.blocks(depth - 1, shown) + ("</li>" if close else "") for _ in range(2)) + "</ul>"
        if kind == 4:
            rows = ["<tr>" + "".join(f"<td rowspan={self.rng.choice([1, 1, 2])}>{self.inline(1, shown)}" + ("</td>" if close else "") for _ in range(2)) for _ in range(2)]
            return "<table>" + "".join(rows) + "</table>"
        if kind == 5:
            return "<blockquote>" + self.blocks(depth - 1, shown) + "</blockquote>"
        if kind == 6 and self.styled:
            return f"<section class='x gone'>{self.blocks(depth - 1, None)}</section>"
        if kind == 7 and self.styled:
            return f"<div class=veil>{self.inline(2, shown and False)}<em style='visibility:visible'>{self.words(None if shown is None else True)}</em></div>"
        return "<pre>" + self.words(shown) + "</pre>"


@pytest.mark.parametrize("seed", range(60))
def test_random_pages_keep_the_visible_words(seed):
    page = Page(seed)
    got = [w for w in htmltext.render(page.source).split() if w not in ("-", "*")]
    # Cells of several lines stand side by side, so only the words of pages without tables keep their order.
    assert (sorted(got) == sorted(page.seen)) if "<table" in page.source else (got == page.seen)


class Plain(HTMLParser):
    """All text outside what is never shown, by the standard library's tokenizer."""

    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.words, self.deep = [], 0

    def handle_starttag(self, tag, attrs):
        self.deep += tag in ("script", "style", "title", "noscript", "template")

    def handle_endtag(self, tag):
        self.deep -= tag in ("script", "style", "title", "noscript", "template")

    def handle_data(self, data):
        if not self.deep:
            self.words += data.split()


def test_given_pages_hold_the_words_of_a_plain_reading(spark):
    if not SF.exists():
        pytest.skip("no test tables here")
    pages = spark.read.parquet(f"{SF}/pages.parquet")
    sources = {r.page_id: r.html for r in pages.collect()}
    for r in htmltext.extract(pages).collect():
        plain = Plain()
        plain.feed(sources[r.page_id] or "")
        got = [w for w in r.text.split() if w != "-" and not (w[:-1].isdigit() and w.endswith("."))]
        if "hidden" not in sources[r.page_id] and "display" not in sources[r.page_id]:
            assert sorted(got) == sorted(w for w in plain.words if w != "-" and not (w[:-1].isdigit() and w.endswith("."))), r.page_id


def test_edges(spark):
    rows = [(1, "<p>a", "x"), (1, "<p>a", "x"), (None, "b", None), (2, None, "y"), (3, "", "z"), (4, "<p>" + "word " * 300_000, "l")]
    pages = spark.createDataFrame(rows, "page_id long, html string, text string")
    got = sorted((str(r.page_id), r.text[:9]) for r in htmltext.extract(pages).collect())
    assert got == [("1", "a"), ("1", "a"), ("2", ""), ("3", ""), ("4", "word word"), ("None", "b")]
    assert htmltext.extract(pages.limit(0)).collect() == [] and htmltext.extract(pages).columns == ["page_id", "text"]
