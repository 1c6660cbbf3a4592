"""Operator 6: worked layouts, hostile input and every given page."""

import re

import pytest

from widefeat.llm.common import read_table
from widefeat.llm.html_render import extract_text, html_to_text
from widefeat.llm.queries import queries

CASES = {
    None: None,
    "": "",
    "plain  text\n here": "plain text here",
    "<p>a<p>b": "a\n\nb",
    "<div>a<div>b</div>c</div>": "a\nb\nc",
    "x<br>y<br><br>z": "x\ny\n\nz",
    "<ul><li>a<li>b<ul><li>c</ul></ul>": "- a\n- b\n  - c",
    "<ol start=3><li>a</li><li>b</li></ol>": "3. a\n4. b",
    "<table><tr><th>k<th>value<tr><td>long key<td>1</table>": "k         value\nlong key  1",
    "<table><td>a<td>b</table>": "a  b",
    "<pre>\n a\n  b</pre>": " a\n  b",
    "<h1>T</h1><p>x": "T\n\nx",
    "<title>t</title><style>p{}</style><script>var t='</p>';</script>see": "see",
    "<p style='display: none'>no</p><p hidden>no</p><i aria-hidden=true>no</i>yes": "yes",
    "a &amp; b&nbsp;&copy; &#65;&bogus;": "a & b © A&bogus;",
    "<!-- c --><!doctype html>x<": "x<",
    "<b>bold <i>both</b> rest</i>": "bold both rest",
    "<a href=\"a>b\">link</a>": "link",
    "<textarea><b>raw</b></textarea>": "<b>raw</b>",
    "1 < 2 and <3": "1 < 2 and <3",
    "</p></div>x": "x",
    "<script>never closed": "",
    "<dl><dt>t<dd>d</dl>": "t\nd",
}


@pytest.mark.parametrize("source", CASES)
def test_layout(source):
    assert html_to_text(source) == CASES[source]


def test_hostile():
    assert html_to_text("<div>" * 5000 + "deep") == "deep"
    assert html_to_text("<table><tr><td>" * 300 + "x").strip() == "x"
    assert html_to_text("<" * 3000).count("<") == 3000
    assert len(html_to_text("<p>word " * 20_000).split()) == 20_000


def test_pages(spark, small_dir):
    pages = {r.page_id: r.html for r in read_table(spark, small_dir, "pages").collect()}
    got = queries()["op6_layout_text"](spark, small_dir).collect()
    assert {r.page_id for r in got} == set(pages)
    import html

    for r in got:
        seen = re.sub(r"(?s)<(script|style|title).*?</\1>|<!--.*?-->", "", pages[r.page_id])
        words = html.unescape(re.sub(r"<[^>]*>", " ", seen)).split()
        assert [w for w in r.text.split() if w != "-"] == [w for w in words if w != "-"]


def test_odd_rows(spark):
    rows = spark.createDataFrame([(None, None, None, "x"), (1, "u", "", "x"), (1, "u", "<p>a", "x"), (1, "u", "<p>a", "x")], "page_id long, url string, html string, text string")
    assert sorted(str(r.text) for r in extract_text(rows).collect()) == ["", "None", "a", "a"]
    assert extract_text(rows.limit(0)).count() == 0
