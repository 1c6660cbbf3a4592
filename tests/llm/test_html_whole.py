"""Operator 6 loses no visible text: long tags, malformed tables, deep pages."""

import time

import pytest

from widefeat.llm.html_render import html_to_text

LONG = "A" * 200_000


def test_long_tags():
    assert html_to_text(f'a <img src="data:image/png;base64,{LONG}" alt="a > b"> c') == "a a > b c"
    assert html_to_text(f"<p data-x='{LONG}' hidden>no</p>yes") == "yes"
    assert html_to_text(f'<a title="{LONG}>link</a>') == "link"


@pytest.mark.parametrize("part", ["<a '>'", "<a \"", "<a 'x' \"y\"", "<a", "<a '\">"])
def test_tags_take_linear_time(part):
    began = time.monotonic()
    html_to_text(part * 60_000)
    assert time.monotonic() - began < 20


@pytest.mark.parametrize("source, want", {
    "<table><tr><form><td>X</td><td>Y</td></form></tr></table>": "X  Y",
    "<table>before<tr><td>X</td></tr></table>": "before\nX",
    "<table><tr>loose<td>X</td></tr></table>after": "loose\nX\nafter",
    "<table><tbody><div>apart</div><tr><td>X</td></tr></tbody></table>": "apart\nX",
    "<table><tr><div>apart<td>X<td>Y</table>": "apart\nX  Y",
    "<table><colgroup>c<col></colgroup><tr><td>X</table>": "c\nX",
    "<table><tr><table><tr><td>X</table><td>Y": "X\nY",
    "<math><mi>x</mi><mo>=</mo><mn>1</mn></math>": "x=1",
    "<svg><title>t</title><g><text>drawn</text></g></svg>": "drawn",
    "<map><p>mapped</p></map>": "mapped",
    "<select><optgroup label=g><option>one<option>two</select>": "g\none\ntwo",
}.items())
def test_text_outside_cells(source, want):
    assert [x.rstrip() for x in html_to_text(source).split("\n") if x.strip()] == want.split("\n")


@pytest.mark.parametrize("depth", [150, 197, 198, 199, 200, 201, 5000])
def test_deep_pages(depth):
    deep = "<div>" * depth
    assert html_to_text(f"{deep}<table><tr><td>x</table>") == "x"
    assert html_to_text(f"{deep}<script>code()</script><style>p</style><b hidden>no</b>x") == "x"
    assert html_to_text(f"<ul hidden>{'<ul>' * depth}<li>no</ul>no{'</ul>' * depth}yes") == "yes"
    assert html_to_text("<div>" + "<table><tr><td>" * depth + "x").strip() == "x"
    assert html_to_text("<ul><li>" * depth + "x").split()[-1] == "x"
