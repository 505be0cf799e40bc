"""Pages whose layout is worked out by hand."""

import pytest
from pyspark.sql import functions as F

from zbox.llm.html_layout import extract, render

PAGES = {
    "rowspan": ("<table><tr><td rowspan=2>A<td>b<td>c<tr><td>dddd<td>e</table>", "A  b     c\n   dddd  e"),
    "rowspan and colspan": ("<table><tr><th colspan=2 rowspan=2>head<th>x<tr><td>y<tr><td>1<td>2<td>3</table>", "head  x\n      y\n1  2  3"),
    "rowspan to the end": ("<table><tr><td rowspan=0>A<td>1<tr><td>2<tr><td>3</table>", "A  1\n   2\n   3"),
    "wide characters": ("<table><tr><td>漢字<td>x<tr><td>abcde<td>y</table>", "漢字   x\nabcde  y"),
    "marks": ("<table><tr><td>é<td>x<tr><td>abc<td>y</table>", "é    x\nabc  y"),
    "class rule": ("<style>.x{display:none} /* .y{display:none} */</style><p class='a x'>no<p class=y>yes", "yes"),
    "id, name and descendant rules": ("<style>#q,nav a{display : none}</style><div id=q>no</div><nav>menu <a>no</a></nav><a>yes</a>", "menu\nyes"),
    "later and stronger rules": ("<style>p{display:none}p.s{display:block}.t{display:none}.t{display:block}</style><p>no<p class=s>one<p class=t>two", "one\n\ntwo"),
    "important": ("<style>.k{display:none!important}</style><p class=k style='display:block'>no<p style='display:none'>no<p>yes", "yes"),
    "media rules do not count": ("<style>@media print{p{display:none}}@import 'x';b{display:none}</style><p>yes <b>no</b>", "yes"),
    "visible again": ("<div style='visibility:hidden'>no <span style='visibility:visible'>yes</span> no</div>", "yes"),
    "closed and open details": ("<details><summary>more</summary>no</details><details open><summary>S</summary>body</details>", "more\nS\nbody"),
    "drawing": ("<p>a<svg><title>no</title><g><text>12 %</text><text>x</text></g></svg>b", "a 12 % x b"),
    "buttons": ("<input type=submit value=Send><input type=text value=no>", "Send"),
}


@pytest.mark.parametrize("case", PAGES)
def test_page(case):
    html, want = PAGES[case]
    assert render(html) == want


def test_deep_parts_keep_their_breaks():
    deep = render("<ul><li>" * 150 + "one<li>two <img alt=pic><table><tr><td>a</td><td>b</td></table>")
    assert [x.strip("- ") for x in deep.split("\n")][-4:] == ["one", "two pic", "a", "b"]


def test_extract_on_odd_rows(spark):
    rows = [(1, "<title>t</title>a"), (1, "<title>t</title>a"), (None, None), (2, ""), (3, "<p>w " * 200_000)]
    df = spark.createDataFrame(rows, "page_id bigint, html string").withColumns({"Title": F.lit("own"), "TEXT": F.lit("own"), "url": F.lit("u")})
    got = extract(df)
    assert got.columns == ["page_id", "url", "title", "text"]
    found = sorted(((r.page_id, r.title, r.text) for r in got.collect()), key=str)
    assert found.count((1, "t", "a")) == 2 and (None, "", "") in found and (2, "", "") in found
    assert next(t for p, _, t in found if p == 3).count("w") == 200_000
    assert extract(df.limit(0)).count() == 0
