"""Markup that the parser has to get through without losing or adding text."""

import time

import pytest

from harvestgrid.llm import html_gbt as h


def runs(source):
    page = h.Page(source)
    return [(page.tag[n], t) for n, t, _ in page.runs]


@pytest.mark.parametrize("size", [10, 5_000, 1_000_000])
@pytest.mark.parametrize("quote", ['"', "'"])
@pytest.mark.parametrize("fill", ["a", "x > y ", "<p>no</p>"])
def test_long_quoted_values(size, quote, fill):
    value = (fill * size)[:size]
    source = f"<img src={quote}{value}{quote}><p class={quote}a{quote}>Hello</p><p class={quote}b{quote}>World</p>"
    assert runs(source) == [("p", "Hello"), ("p", "World")]


def test_quotes_elsewhere():
    assert runs("<p title=it's>don't <b>it's</b></p>") == [("p", "don't it's")]
    assert runs('<p class="a"">say "x" and "y"</p>') == [("p", 'say "x" and "y"')]
    assert runs('<a href=/x?q="b>c</a> "d" <p>e</p>') == [("html", 'c "d"'), ("p", "e")]
    assert runs('<p class="a>never closed</p><p>b</p>') == [("p", "never closed"), ("p", "b")]
    assert runs("<p class = 'a>b' id=c>d</p>") == [("p", "d")]


def test_broken_markup_is_linear():
    for source in ('<p a="' * 100_000, "<a <a " * 100_000, "<p a='>x" * 100_000, "<p>ok</p>" + "<i b=\"" * 100_000):
        start = time.monotonic()
        h.Page(source)
        assert time.monotonic() - start < 20


@pytest.mark.parametrize("tag", ["<svg class=icon/>", "<svg viewBox='0 0 1 1' />", "<math/>", "<button>", "<select>", "<noscript>", "<template>", "<svg>", "<button>Menu", "<select><option>one", "<svg><path d='M0'/><text>no</text>"])
def test_open_elements_end_where_the_text_begins(tag):
    article = "<article><p>One.</p><p>Two.</p></article>"
    assert runs(tag + article) == [("p", "One."), ("p", "Two.")]
    assert runs(f"<div>{tag}</div>{article}<button>ok</button><p>Three.</p>") == [("p", "One."), ("p", "Two."), ("p", "Three.")]


def test_hidden_elements_nest():
    assert runs("<p>a <svg><svg><text>no</text></svg><text>nor this</text></svg>b</p>") == [("p", "a b")]
    assert runs("<p>a <button><div>no</div></button>b <a href=x>c</a></p>") == [("p", "a b c")]
    assert runs("<div>a <noscript></div><p>no</noscript>b</div>c") == [("div", "a b"), ("html", "c")]
    assert runs("<p>a<svg><title>no</title><foreignObject><div>no</div></foreignObject></svg> b</p>") == [("p", "a b")]
    assert runs("<template><template><p>no</p></template><p>no</p></template><p>a</p>") == [("p", "a")]
    assert runs("<select><option>1<option>2</select>a<svg><title/></svg><p>b</p>") == [("html", "a"), ("p", "b")]
    assert runs("<ul><li>a<button><ul><li>no</ul></button><li>b</ul>") == [("li", "a"), ("li", "b")]


def test_formulas_are_text():
    assert runs("<p>so <math><mi>x</mi><mo>=</mo><mn>1</mn></math> holds</p>") == [("p", "so x=1 holds")]


def test_only_raw_text_runs_to_the_end():
    for name in ("script", "style", "textarea", "title"):
        assert runs(f"<p>a</p><{name}><p>no</p>") == [("p", "a")]
    assert runs("<p>a</p><iframe src=x><p>b</p>") == [("p", "a"), ("p", "b")]
