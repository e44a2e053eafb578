"""Main text: what is never in it, markup that is broken, time, and rows of any id."""

import time

import pytest

from slicelink.llm import htmltext

PROSE = "The river rose in the night, and by the morning the lower fields stood under water. Nobody in the village had seen it come so far, not even the oldest of them."
LONG_ITEM = "Read everything about our products, our prices and our people, in a long and friendly overview of all that we do, day by day."


@pytest.fixture(scope="module")
def text():
    model = htmltext.default_model()
    return lambda source: htmltext.extract(source, model)


def page(inner, before="", after=""):
    return f"<html><head><title>t</title></head><body>{before}<article><h1>High water</h1><p>{PROSE}</p>{inner}<p>{PROSE}</p></article>{after}</body></html>"


WANT = f"High water\n{PROSE}\n{PROSE}"


@pytest.mark.parametrize("junk", [
    f"<nav><ul><li>{LONG_ITEM}</li><li><p>{LONG_ITEM}</p></li></ul></nav>", f"<nav><div><div><p>{LONG_ITEM}</p></div></div></nav>", f"<form><div><p>{LONG_ITEM}</p><label>{LONG_ITEM}</label></div></form>",
    f"<button><span><b>{LONG_ITEM}</b></span></button>", f"<noscript><p>{LONG_ITEM}</p></noscript>", f"<select><option>{LONG_ITEM}</option></select>", f"<svg><text>{LONG_ITEM}</text></svg>", "<script>var a = '<p>" + LONG_ITEM + "</p>';</script>",
])
def test_never_at_any_depth(text, junk):
    assert text(page("", before=junk)) == WANT
    assert text(page(junk)) == WANT
    assert text(page("", after=junk)) == WANT


def test_a_form_around_the_page_and_open_heads(text):
    inner = page("").split("<body>")[1].replace("</body></html>", "")
    assert text(f"<html><body><form action=x>{inner}</form></body></html>") == WANT
    assert text(f"<html><head><title>t</title><meta charset=utf-8><body>{inner}") == WANT


@pytest.mark.parametrize("bad, shown", [('<a href="x>', ""), ("<a href='x>", ""), ("<a title=it's>", ""), ('<b class">', ""), ("<p don't>", ""), ("</ >", ""), ("<!-- a > b -->", ""), ("<? php ?>", ""), ('<i title="a > b">', ""), ("1 < 2", "1 < 2")])
def test_broken_markup_never_shows(text, bad, shown):
    got = text(f"<article><h1>High water</h1><p>{PROSE}</p><p>{PROSE}{bad}</p></article>".replace("<article>", "<article>"))
    assert got == WANT + shown
    got = text(f"<article><h1>High water</h1><p>{PROSE}</p><p>{bad}{PROSE}</p></article>")
    assert got == f"High water\n{PROSE}\n{shown}{PROSE}"


@pytest.mark.parametrize("unit", ["<a ", "</b>", "<b>", "<div>", "<p>", "</p>", "<a href=\"", "<a href='x\" ", "<li>", "<b><p>", "<script>", "</script ", "<!--", "x=", "<i a=", "&amp", "<title>", "<b></i>"])
def test_time_is_linear(text, unit):
    text(unit * 100)
    took = []
    for n in (4000, 16000):
        t = time.time()
        text("<div>" + unit * n)
        took.append(time.time() - t)
    assert took[1] < 10 * max(took[0], 0.1)


def test_rows_of_any_id(spark):
    html = page("")
    rows = [(1, "u", html), (1, "u", html), (None, None, html), (2, "u", None), (None, "v", "")]
    got = sorted(((x.page_id, x.url, x.text, x.n_chars) for x in htmltext.main_text(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()), key=repr)
    assert got == sorted([(1, "u", WANT, len(WANT)), (1, "u", WANT, len(WANT)), (None, None, WANT, len(WANT)), (2, "u", "", 0), (None, "v", "", 0)], key=repr)
