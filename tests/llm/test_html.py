"""Main text of pages whose articles are split or carry misleading names."""

import pytest

from waypath.llm.html_extract import best_path, extract_one, parse

NAV = "<nav><a href=/a>Home</a></nav>"
END = "<footer>Imprint</footer>"
P = ["The first part says what happened. " * 4, "The second part says why it did so, at length. " * 9, "The third part says what comes next. " * 5]
P = [p.strip() for p in P]


def page(body):
    return f"<html><body>{NAV}{body}{END}</body></html>"


def both(body):
    html = page(body)
    own = extract_one(html)
    assert extract_one(html, best_path(parse(html))[0]) == own
    return own


SPLIT = {
    "sections": f"<article><h1>Head</h1><div class=intro><p>{P[0]}</p></div><section class=body><p>{P[1]}</p></section><section class=more><p>{P[2]}</p></section></article>",
    "one long section": f"<article><h1>Head</h1><div class=intro><p>{P[0]}</p></div><section class=body><p>{P[1]}</p></section><section class=more><p>{P[2]}</p></section></article>".replace(P[1], " ".join([P[1]] * 40)),
    "divs": f"<div class=page><h1>Head</h1><div class=intro><p>{P[0]}</p></div><div class=text><p>{P[1]}</p></div><div class=more><p>{P[2]}</p></div></div>",
    "deep": f"<main><h1>Head</h1><div class=x><div class=y><section class=a><p>{P[0]}</p></section><section class=b><p>{P[1]}</p></section></div></div><div class=z><p>{P[2]}</p></div></main>",
}


@pytest.mark.parametrize("name", SPLIT)
def test_all_parts_of_a_split_article(name):
    want = "\n".join(["Head", *P])
    assert both(SPLIT[name]) == (want.replace(P[1], " ".join([P[1]] * 40)) if name == "one long section" else want)


@pytest.mark.parametrize("tag", ["article", "div class=post"])
def test_an_article_around_a_large_table(tag):
    cells = [f"value {i}" for i in range(300)]
    rows = "".join(f"<tr><td>{c}</td></tr>" for c in cells)
    got = both(f"<{tag}><h1>Head</h1><p>{P[0]}</p><table>{rows}</table><p>{P[2]}</p></{tag.split()[0]}>")
    assert got.split("\n") == ["Head", P[0], *cells, P[2]]


def test_a_wrapper_and_links_stay_out():
    got = both(f"<div class=outer><ul><li><a href=/b>Other things to read here</a></li></ul><article><h1>Head</h1><p>{P[0]}</p></article><div class=note>Copyright</div></div>")
    assert got == f"Head\n{P[0]}"


@pytest.mark.parametrize("tag", ["div class='content with-sidebar'", "div id='page' class='no-sidebar'", "section class='related-work'", "div class='content sidebar-right'", "div class='sidebar'", "div class='comments'"])
def test_a_name_does_not_cut_the_article(tag):
    body = f"<h1>Head</h1><p>{P[0]}</p><p class='side-note'>{P[1]}</p><p>{P[2]}</p>"
    want = "\n".join(["Head", *P])
    assert both(f"<{tag}>{body}</{tag.split()[0]}>") == want
    assert both(f"<{tag}><article>{body}</article></{tag.split()[0]}>") == want
    assert both(f"<{tag}>{body.replace('h1', 'h2')}</{tag.split()[0]}>") == want


def test_a_headline_in_a_header_stays():
    assert both(f"<article><div class='article-header'><h1>Head</h1></div><div class=header><h1>More</h1></div><p>{P[0]}</p></article>") == f"Head\nMore\n{P[0]}"


@pytest.mark.parametrize("cls", ["ad", "site-footer", "sidebar left", "comment-list", "google-ad", "ad-300x250"])
def test_what_is_named_junk_stays_out(cls):
    junk = f"<div class='{cls}'><p>{P[2]}</p></div>"
    assert both(f"{junk}<article><h1>Head</h1><p>Short.</p></article>") == "Head\nShort."
    assert both(f"<div class=text><p>{P[0]}</p><p>{P[1]}</p></div>{junk}") == f"{P[0]}\n{P[1]}"


def test_a_page_of_named_junk_alone_is_not_empty():
    assert extract_one(page("<div class=notice>Closed today</div>")) == "Closed today"
    assert extract_one(page("<div hidden>Closed today</div>")) == ""
