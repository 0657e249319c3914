"""Extraction from pages written by hand after layouts met on the web, each with the text to extract; hostile pages take linear time."""

import time

import pytest

from quadinv.llm import html_extract
from quadinv.llm.html_extract import Dom

P1 = "The river rose two metres in a single night, and by morning the lower town stood under water. Boats went from door to door."
P2 = "Officials had been warned the week before. No one, they said later, had believed the figures; the models had been wrong twice in spring."
P3 = "Repairs will take until autumn, the council expects. A fund for those without insurance opens on Monday, and volunteers are asked to register."
SHORT = "It rained again."
MENU = '<ul><li><a href="/">Home</a></li><li><a href="/news">News</a></li><li><a href="/sport">Sport</a></li><li><a href="/about">About us</a></li></ul>'
LINKS = '<ul><li><a href="/1">Bridge closed for repairs</a></li><li><a href="/2">Market moves to the hill</a></li><li><a href="/3">Ferry adds a boat</a></li></ul>'

LAYOUTS = {
    "header in article": (
        f"<body><nav>{MENU}</nav><article><header><h1>Flood in the town</h1></header><p>{P1}</p><p>{P2}</p></article><footer><p>&copy; 2021 The Paper</p></footer></body>",
        ["Flood in the town", P1, P2],
    ),
    "entry-header": (
        f'<body><div id="page"><header id="masthead" class="site-header"><a href="/">My blog</a></header><div id="content"><article class="post hentry"><div class="entry-header"><h1 class="entry-title">Flood</h1></div><div class="entry-content"><p>{P1}</p><p>{P2}</p><p>{SHORT}</p></div></article></div><aside id="secondary" class="widget-area"><h3>Recent</h3>{LINKS}</aside><footer id="colophon">Proudly made</footer></div></body>',
        ["Flood", P1, P2, SHORT],
    ),
    "header, aside and footer in article after a menu": (
        f"<body><nav>{MENU}</nav><article><header><h1>Flood</h1></header><p>{P1}</p><aside><h3>Related</h3>{LINKS}</aside><p>{P2}</p><footer><a href='/t'>rivers</a> <a href='/w'>weather</a></footer></article></body>",
        ["Flood", P1, P2],
    ),
    "copyright in a plain div": (
        f'<body><div class="nav">{MENU}</div><div class="content"><h1>Flood</h1><p>{P1}</p><p>{P2}</p></div><div>&copy; 2020 Example Ltd. All rights reserved.</div></body>',
        ["Flood", P1, P2],
    ),
    "table layout": (
        f"<body><table><tr><td width=150><a href='/'>Home</a><br><a href='/n'>News</a><br><a href='/s'>Sport</a><br><a href='/c'>Contact</a></td><td><h1>Flood</h1><p>{P1}</p><p>{P2}</p></td></tr></table></body>",
        ["Flood", P1, P2],
    ),
    "hashed classes": (
        f'<body><div class="css-1x2y3z"><div class="css-9a8b7c">{MENU}</div><div class="css-0d1e2f"><h1 class="css-77aa11">Flood</h1><p class="css-aa00bb">{P1}</p><p class="css-aa00bb">{P2}</p><p class="css-aa00bb">{P3}</p></div><div class="css-5f5f5f">{LINKS}</div></div></body>',
        ["Flood", P1, P2, P3],
    ),
    "plain divs": (
        f"<body><div>{MENU}</div><div><h1>Flood</h1><p>{P1}</p><p>{P2}</p><p>{P3}</p></div><div>{LINKS}</div></body>",
        ["Flood", P1, P2, P3],
    ),
    "main with sidebar, form and cookie notice": (
        f'<body><div class="cookie-banner"><p>We use cookies to improve your visit. By staying you agree.</p><button>OK</button></div><header class="header"><a href="/">Paper</a><form role="search"><input name="q"><button>Search</button></form></header><main><h1>Flood</h1><p>{P1}</p><div class="ad">Buy our boats now, cheap.</div><p>{P2}</p></main><aside class="sidebar">{LINKS}</aside><div class="newsletter"><form><label>Your mail</label><input><button>Join</button></form></div></body>',
        ["Flood", P1, P2],
    ),
    "reader comments": (
        f'<body><nav>{MENU}</nav><article><h1>Flood</h1><p>{P1}</p><p>{P2}</p></article><section id="comments" class="comments"><h3>2 comments</h3><ol class="comment-list"><li class="comment"><b>Ann</b><p>I saw it myself, terrible. The whole street was gone.</p></li><li class="comment"><p>Thanks for the report, stay safe.</p></li></ol></section><footer>Contact</footer></body>',
        ["Flood", P1, P2],
    ),
    "lists, quotes and code": (
        f"<body><header><a href='/'>Docs</a></header><nav>{MENU}</nav><main><h1>How to pump</h1><p>{P1}</p><h2>Steps</h2><ol><li>Open the valve fully before you start.</li><li>Prime the pump with clean water.</li></ol><blockquote><p>{SHORT}</p></blockquote><pre>pump --start</pre><p>{P2}</p></main><footer>&copy; Docs</footer></body>",
        ["How to pump", P1, "Steps", "Open the valve fully before you start.", "Prime the pump with clean water.", SHORT, "pump --start", P2],
    ),
    "tags left open, references": (
        f"<body><div class=menu>{MENU}</div><div class=article><h1>Caf&eacute; &amp; flood</h1><p>{P1}<p><b>{P2}</b><br>{SHORT}<p>{P3}</div><div class=footer>Imprint</div>",
        ["Café & flood", P1, f"{P2} {SHORT}", P3],
    ),
    "script, style, hidden markup": (
        f"<html><head><title>T</title><style>p{{}}</style></head><body><script>var a='<p>no</p>';</script><nav>{MENU}</nav><article><h1>Flood</h1><!-- <p>not this</p> --><p>{P1}</p><noscript>Turn on scripts</noscript><p>{P2}</p><iframe src=x>no</iframe></article></body></html>",
        ["Flood", P1, P2],
    ),
    "article alone": (f"<article><p>{P1}</p></article>", [P1]),
    "labels of training pages mean nothing": (f'<body><nav data-y="1">{MENU}</nav><article data-y="0"><h1 data-y="x">Flood</h1><p data-y="12.5">{P1}</p><p data-y=0>{P2}</p></article></body>', ["Flood", P1, P2]),
}


@pytest.fixture(scope="module")
def model():
    return html_extract.fit()


@pytest.mark.parametrize("name", LAYOUTS)
def test_layout(model, name):
    page, want = LAYOUTS[name]
    assert model.text(page) == " ".join(want)


N = 200_000
HOSTILE = {
    "nested blocks": "<div>" * N + "x",
    "nested blocks in a cell in a paragraph": "<p><table><td>" + "<div>" * N,
    "stray end tags": "<div>" * (N // 2) + "</x></b></li>" * (N // 2),
    "nested lists": "<ul><li>" * (N // 2) + "x",
    "inline left open": "<b>" * N + "</div>" * 1000,
    "names without an end": ("<" + "a" * 100) * 2000,
    "angle brackets": "<" * N,
    "an end far away": ("<a " * 60_000) + ">",
    "quotes left open": "<p class='x\">" * 20_000 + "<p title=\"" * 10_000,
    "one quote": "<p \"" + "<p>x</p>" * 20_000,
    "comment left open": "<!--" + "<p>" * N,
    "script left open": "<script>" * 40_000,
    "references": "&amp" * N + "&#x" * 1000,
}


@pytest.mark.parametrize("name", HOSTILE)
def test_reading_takes_linear_time(name):
    began = time.perf_counter()
    dom = Dom(HOSTILE[name])
    assert len(dom.tag) == len(dom.parent) and time.perf_counter() - began < 15


def test_deep_page_is_judged_in_linear_time(model):
    began = time.perf_counter()
    model.text("<div>" * 50_000 + "deep")
    assert time.perf_counter() - began < 20
