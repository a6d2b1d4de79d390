"""Main-text extraction on pages written by hand, on hostile markup, and the fit against a numerical gradient."""

import time

import numpy as np
import pytest

from tricount.llm import extraction

A = "The river rose slowly through the night, and by morning the lower fields were under a foot of brown water."
B = "Farmers moved their cattle to the hills while volunteers filled sandbags along the road to the old bridge."
C = "Officials said the level should begin to fall on Thursday, provided that no more rain comes from the west."
MENU = '<ul><li><a href="/">Home</a></li><li><a href="/news">News</a></li><li><a href="/sport">Sport</a></li></ul>'

#: (page, blocks of its main text), none of them from the layout generator.
PAGES = {
    "bare body": (f"<body><p>{A}</p></body>", [A]),
    "no body": (f"<p>{A}<p>{B}", [A, B]),
    "unknown class": (f'<html><body><div class="zz"><p>{A}</p></div></body></html>', [A]),
    "unknown class, more": (f'<body><nav>{MENU}</nav><div class="qx-12"><h1>Flood in the valley</h1><p>{A}</p><p>{B}</p></div><footer>&copy; 2020 The Paper</footer></body>', ["Flood in the valley", A, B]),
    "comments in the name of main": (f'<body><main class="with-comments"><h1>Flood</h1><p>{A}</p></main></body>', ["Flood", A]),
    "sidebar in the class of main": (f'<body><div id="main-content" class="sidebar-left"><p>{A}</p><p>{B}</p></div></body>', [A, B]),
    "article with table, pre and comments": (
        f'<body><div class="k9"><h1>Water levels</h1><p>{A}</p><table><tr><th>Day</th><th>Level</th></tr><tr><td>Monday</td><td>3.1 m</td></tr></table><pre>level = 3.1</pre><p>{B}</p></div><div class="comments"><p>I saw it too, it was terrible.</p><p>Stay safe all.</p></div></body>',
        ["Water levels", A, "Day", "Level", "Monday", "3.1 m", "level = 3.1", B],
    ),
    "article in article element": (f'<body><header><a href="/">Logo</a></header><article><h1>Flood</h1><p>{A}</p><blockquote>{B}</blockquote></article><aside><h3>Most read</h3><ul><li><a href="/1">One</a></li></ul></aside></body>', ["Flood", A, B]),
    "advert inside": (f'<body><article><p>{A}</p><div class="ad">Buy our new boots now, they are the best boots.</div><p>{B}</p></article></body>', [A, B]),
    "newsletter form inside": (f'<body><main><p>{A}</p><form class="newsletter"><label>Your address</label><input name="m"><button>Send</button></form><p>{B}</p></main></body>', [A, B]),
    "cookie notice": (f'<body><div id="cookie-banner"><p>We use cookies to improve this site.</p><button>Accept</button></div><div><h1>Flood</h1><p>{A}</p></div></body>', ["Flood", A]),
    "rights at the end": (f"<body><h1>Flood</h1><p>{A}</p><p>{B}</p><div>&copy; 2021 Valley Press</div></body>", ["Flood", A, B]),
    "links on top": (f'<body><div><a href="/">Home</a> | <a href="/a">About</a> | <a href="/c">Contact</a></div><h1>Flood</h1><p>{A}</p><p>{B}</p></body>', ["Flood", A, B]),
    "reader comments as articles": (f'<body><article class="post"><p>{A}</p><p>{B}</p></article><section id="comments"><article class="comment"><p>Well said, I agree.</p></article></section></body>', [A, B]),
    "sidebar content": (f'<body><div class="sidebar-content"><p>Our shop has new mugs.</p></div><div class="post-body"><p>{A}</p><p>{C}</p></div></body>', [A, C]),
    "script, style and comment": (f'<head><style>p{{margin:0}}</style></head><body><!-- {B} --><script>document.write("<p>{B}</p>")</script><article><p>{A}</p></article></body>', [A]),
    "references": ("<body><article><p>Salt &amp; pepper &#8212; caf&eacute; &lt;b&gt; was the name of the small place near the old market in town.</p></article></body>", ["Salt & pepper — café <b> was the name of the small place near the old market in town."]),
    "white space": ("<body><article><p>  One\n\n two\t three&nbsp;&nbsp;four five six seven eight nine ten eleven twelve.  </p></article></body>", ["One two three four five six seven eight nine ten eleven twelve."]),
    "unclosed inline": (f"<body><article><p><b>{A}<br><p>{B}</article><footer>Imprint</footer></body>", [A, B]),
    "list in the article": (f"<body><article><h1>Packing list</h1><p>{A}</p><ul><li>Two warm blankets for each person.</li><li>A torch and some batteries.</li></ul></article></body>", ["Packing list", A, "Two warm blankets for each person.", "A torch and some batteries."]),
    "layout table": (f"<body><table><tr><td><p>{A}</p><p>{B}</p></td></tr></table></body>", [A, B]),
    "misleading body": (f'<body class="has-sidebar comments-open"><div class="wrapper"><h1>Flood</h1><p>{A}</p><p>{C}</p></div></body>', ["Flood", A, C]),
    "link in prose": (f'<body><div class="t3"><p>{A} <a href="/map">See the map</a> for the roads that are still open today.</p><p>{B}</p></div></body>', [f"{A} See the map for the roads that are still open today.", B]),
    "hidden": (f'<body><article><p>{A}</p><p style="display:none">{B}</p><div hidden>{C}</div></article></body>', [A]),
    "nothing but a menu": (f"<body><nav>{MENU}</nav><footer>&copy; me</footer></body>", []),
    "long attribute": (f'<body><article data-x={"y" * 50_000}><p>{A}</p></article></body>', [A]),
    "quotes without values": (f'<body><article "><p " \'>{A}</p></article></body>', [A]),
}


@pytest.mark.parametrize("name", PAGES)
def test_pages_by_hand(name):
    page, want = PAGES[name]
    assert extraction.default_model().text(page) == "\n".join(want)


@pytest.mark.parametrize("page", ['<a "' * 250_000, "<a <b " * 160_000, "<div>x" * 60_000, "<b>" * 60_000 + "<div></div>" * 60_000, "<! " * 300_000, "<div>" * 60_000 + "</x>" * 60_000, "<td>" * 60_000, '<x =" ' * 160_000, "<!--" * 250_000, "word " * 200_000], ids=range(10))
def test_hostile_pages_take_linear_time(page):
    began = time.time()
    extraction.blocks(page)
    assert time.time() - began < 10


def test_a_megabyte_of_open_quotes():
    began = time.time()
    assert extraction.blocks('<a "' * 262_144) == []
    assert time.time() - began < 1


def test_fit_climbs_the_likelihood():
    """At the end of the fit the slope of the penalised likelihood is near zero, by finite differences."""
    rng = np.random.default_rng(2)
    pages = [([[f"f{k}" for k in range(4) if rng.random() < 0.5] + ["bias"] for _ in range(5)], [int(rng.random() < 0.5) for _ in range(5)]) for _ in range(30)]
    crf = extraction.fit(pages, rounds=3000)
    size = sum(len(p[0]) for p in pages)

    def value(w, move, start):
        total = 0.0
        for found, gold in pages:
            e = [sum((w[crf.index[f]] for f in fs), np.zeros(2)) for fs in found]
            f = start + e[0]
            path = start[gold[0]] + e[0][gold[0]]
            for k in range(1, len(e)):
                f = np.logaddexp(f[0] + move[0], f[1] + move[1]) + e[k]
                path += move[gold[k - 1], gold[k]] + e[k][gold[k]]
            total += path - np.logaddexp(*f)
        return total / size - 0.02 / 20 * ((w**2).sum() + (move**2).sum())

    base = [crf.state.copy(), crf.move.copy(), crf.start.copy()]
    for which in range(3):
        for at in np.ndindex(base[which].shape):
            up, down = [x.copy() for x in base], [x.copy() for x in base]
            up[which][at] += 1e-4
            down[which][at] -= 1e-4
            assert abs(value(*up) - value(*down)) / 2e-4 < 2e-3
