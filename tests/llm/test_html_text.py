import time
from html.parser import HTMLParser

import pyarrow.parquet as pq
import pytest

from wdsum.llm import html_text as H


def test_blocks_lists_and_cells():
    page = """<!doctype html><title>no</title><body><h1>A &amp;  B</h1><p>one<p>two <b>bo</b>ld<br>next
    <ul><li>x<li>y<ol start=3><li>p<li>q</ol><li hidden>gone</ul>
    <table><tr><th>Name<th>Count</tr><tr><td>Ann<td>3<tr><td>Bartholomew<td>14</table>
    <pre>
  a
    b</pre><div style="display: none">no</div><div>last</div><script>x = "<p>no</p>"</script>"""
    assert H.visible_text(page) == "A & B\n\none\n\ntwo bold\nnext\n\n- x\n- y\n  3. p\n  4. q\n\nName         Count\nAnn          3\nBartholomew  14\n\n  a\n    b\n\nlast"


def test_spans_of_cells():
    page = "<table><tr><td rowspan=2>a<td>b<td>c</tr><tr><td colspan=2>d e f g</tr><tr><td>h<td>i<td>j</table>"
    assert H.visible_text(page) == "a  b  c\n   d e f g\nh  i  j"


def test_broken_markup_never_fails():
    for page in (None, "", "<", "<p", "a<b", "1 < 2 & 3", "</p></div>x", "<table>stray<tr>t<td>c", "<ul>loose<li>i", "<div>" * 5000 + "deep", "<a href='x>y", "<!-- open", "&#x110000; &bogus;", "<td>alone"):
        text = H.visible_text(page)
        assert ("deep" in text) == ("deep" in (page or ""))
    assert H.visible_text("1 < 2 & 3") == "1 < 2 & 3"
    assert H.visible_text("</p></div>x") == "x"
    assert H.visible_text("<table>stray<tr>t<td>c") == "stray\nt\nc"


def test_implied_rows_and_strays_of_sections():
    assert H.visible_text("<table><thead><th>A<th>B</thead><tbody><tr><td>1<td>22</table>") == "A  B\n1  22"
    assert H.visible_text("<table><tbody><td>x</td><td>y</td></tbody><tfoot><td>z</tfoot></table>end") == "x  y\nz\n\nend"
    assert H.visible_text("<table><td>a<td>b<tr><td>c<td>d</table>") == "a  b\nc  d"
    assert H.visible_text("<table><tbody>loose<tr><td>x</table>") == "loose\nx"
    assert H.visible_text("<table><tbody><form><tr><td>x<td>y</tr><tr><td>z</tr></form></tbody></table>") == "x  y\nz"
    assert H.visible_text("<table><tr><form><td>x<td>y</form></tr></table>") == "x  y"
    assert H.visible_text("<table><tbody><div>d</div><tr><td>x</table>") == "d\nx"
    assert H.visible_text("<table><caption>cap<td>x</table>") == "cap\nx"
    assert H.visible_text("<table><colgroup>odd<tr><td>x</table>") == "odd\nx"
    assert H.visible_text("<table><tbody hidden>no<td>no</tbody><tbody><td>x<table><tbody><td>in</table>y</table>") == "x\n\nin\n\ny"
    assert "deep" in H.visible_text("<div>" * 198 + "<table><tbody><td>deep")


def test_text_of_drawings_and_formulas():
    assert H.visible_text("a <svg><title>no</title><defs><text>no</text></defs><g><text>b</text><text>c<tspan>d</tspan></text></g></svg> e") == "a b cd e"
    assert H.visible_text("<math><mi>x</mi><mo>=</mo><mfrac><mn>1</mn><mn>2</mn></mfrac><annotation>no</annotation></math>") == "x= 1 2"
    assert H.visible_text("<svg><title/><path/><text/></svg>kept<svg><g><p>out") == "kept\n\nout"
    assert H.visible_text("<svg hidden><text>no</text></svg><pre>a <svg><text>b</text></svg></pre>") == "a b"


def test_ends_of_tags():
    assert H.visible_text('<p title="x>hello</p>') == "hello"
    assert H.visible_text("<p title='a>b' data-x=1>hello <b class=\"c>d\">bold</b>") == "hello bold"
    assert H.visible_text('<a x"y>one</a> <a b = "c>d">two</a> <a b=c"d>three</a>') == "one two three"
    assert H.visible_text("<p>kept <!-- a > b --> on<!doctype html>ly <b unfinished") == "kept only"
    assert H.visible_text('<script>x = "</scripty>"</script a="b">seen') == "seen"


@pytest.mark.parametrize("part", ["<a ", "<a b='x> ", '<a b="x> c', "<a b='c\" ", "</script ", "<!--", "<a =", "&", "<td>", "<b>", "<p>x"])
def test_a_page_of_a_megabyte_takes_linear_time(part):
    for page in (part * ((1 << 20) // len(part)) + '"', "<script>" + part * ((1 << 20) // len(part)), "<!-- x -->" + part * ((1 << 20) // len(part)) + "'>"):
        began = time.process_time()
        H.visible_text(page)
        assert time.process_time() - began < 20


class Words(HTMLParser):
    """All words outside unseen elements, by the standard library's parser."""

    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.words, self.off = [], 0

    def handle_starttag(self, tag, attrs):
        self.off += tag in ("script", "style", "title")

    def handle_endtag(self, tag):
        self.off -= tag in ("script", "style", "title")

    def handle_data(self, data):
        if not self.off:
            self.words += data.split()


def test_every_visible_word_of_real_pages_is_there():
    t = pq.read_table("/root/testdata/sf0.01/pages.parquet").to_pylist()
    for r in t:
        p = Words()
        p.feed(r["html"])
        got = [w for line in H.visible_text(r["html"]).split("\n") for w in line.split() if w != "-"]
        assert "".join(w for w in p.words if w != "-") == "".join(got)


def test_query_form(spark):
    df = spark.createDataFrame([(1, "<p>a", "t"), (1, "<p>a", "t"), (None, None, None), (2, "", "x")], "page_id long, html string, text string")
    assert sorted((r.page_id or 0, r.text, r.n_lines) for r in H.extract(df).collect()) == [(0, "", 0), (1, "a", 1), (1, "a", 1), (2, "", 0)]
    assert H.extract(df.limit(0)).count() == 0
