"""Main-text extraction with a linear-chain conditional random field over the leaf blocks of a page.

A page becomes a sequence of leaf blocks: stretches of text between block-level tags, with the open elements around
them. Features of a block are its ancestor tags, words of their class, id and role attributes, and properties of its
text (length, links, punctuation, words of notices). The chain has two states, main text and the rest; its weights are fitted by maximum
likelihood on labelled pages that a layout generator writes, and the best sequence is found by Viterbi. Many of these
pages have no element that tells where the article is, or names that mislead, so that text alone has to tell.

Scanning is linear in the page: a tag is read once, and of the open elements only counts and last places are kept.

Defined results: a null or empty page, or one without main text, gives an empty text; comments, scripts, styles and
other raw-text elements never give text; unclosed and stray tags are tolerated; what follows a tag that never ends is
part of that tag; repeated rows give equal results; an empty table gives an empty table; other columns are ignored.
"""

from __future__ import annotations

import html
import random
import re
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
from pyspark.sql import DataFrame

from .common import arrow_map

# Element names by their role in parsing.
RAW = frozenset("script style noscript template iframe object svg math textarea select title head".split())
CDATA = frozenset("script style textarea title iframe noscript".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
INLINE = frozenset("a abbr acronym b bdi bdo big br cite code data dfn em font i img ins del kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split())
CLOSES_P = frozenset("address article aside blockquote details div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr main menu nav ol p pre section table ul".split())

# Elements whose names are features, and those that end an open item of their kind.
KNOWN = frozenset("html body main article section div p ul ol li dl dt dd table tbody thead tr td th caption pre code blockquote figure figcaption h1 h2 h3 h4 h5 h6 nav header footer aside form fieldset label button menu dialog details summary address center address span font hgroup".split())
SAME = {"li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "td": ("td", "th"), "th": ("td", "th"), "tr": ("tr",), "option": ("option",)}
HOLDERS = ("ul", "ol", "dl", "table", "select")

_OPEN = re.compile(r"<(?:!--|!\[CDATA\[|[!?]|/?[A-Za-z]|/)")
_NAME = re.compile(r"[^\s/>]+")
#: The rest of a tag: a quote counts only after an equals sign.
_REST = re.compile(r"""[^>=]*+(?:=(?:\s*+(?:"[^"]*"|'[^']*'))?[^>=]*+)*+>""")
_ATTR = re.compile(r"""(?:^|[\s"'])(class|id|role|itemprop)\s*+=\s*+(?:"([^"]*)"|'([^']*)'|([^\s"'>]+))""", re.I)
_HIDDEN = re.compile(r"""(?:^|\s)(?:hidden(?:[\s=]|$)|aria-hidden\s*+=\s*+["']?true|style\s*+=\s*+["'][^"']*display\s*:\s*none)""", re.I)
_NAMES = re.compile(r"[A-Za-z]+")
_CAMEL = re.compile(r"(?<=[a-z])(?=[A-Z])")

# Groups of words in class, id and role attributes, by what they tell about an element.
HINTS = {
    "main": "article content entry post story main body text prose maincontent markdown",
    "menu": "nav navigation menu menubar breadcrumb breadcrumbs pagination pager toc tabs skip sitemap links navbar topbar",
    "head": "header masthead banner logo hero branding",
    "foot": "footer foot copyright legal colophon imprint",
    "side": "sidebar aside complementary widget rail related recommended recommendations popular trending more teaser",
    "note": "notice cookie cookies consent gdpr alert popup modal overlay toast announcement warning disclaimer paywall",
    "advert": "ad ads advert adverts advertisement sponsor sponsored promo promotion promoted dfp adsense commercial",
    "talk": "comment comments disqus reply replies respond discussion thread reviews reader readers",
    "form": "form newsletter signup subscribe subscription search login contact",
    "share": "share sharing social follow tweet facebook byline author meta tags tag category date",
}
_HINT = {w: k for k, ws in HINTS.items() for w in ws.split()}
# First and last words of names that say how a page is set, not what an element is; words of notices and the like.
MODIFIERS = frozenset("with has have no not without is show hide enable supports".split())
STATES = frozenset("fixed sticky open opened closed enabled disabled visible".split())
CUES = frozenset("cookie cookies subscribe newsletter copyright rights reserved login log sign advertisement sponsored share tweet menu search privacy terms accept reply comment comments".split())
_ODD_TAGS = frozenset("nav footer aside form header menu button dialog".split())


def _hints(name: str, attrs: str) -> tuple[str, ...]:
    """What an element's names tell: groups of HINTS, or "torn" where one name says main text and another does not."""
    main, odd = False, set()
    for m in _ATTR.finditer(attrs):
        for token in (m[2] or m[3] or m[4] or "").split():
            words = [w.lower() for w in _NAMES.findall(_CAMEL.sub(" ", token))]
            if words and (words[0] in MODIFIERS or words[-1] in STATES):
                continue
            found = {_HINT[w] for w in words if w in _HINT}
            if found - {"main"}:
                odd |= found - {"main"}
            elif found:
                main = True
    if name in ("html", "body", "main"):
        return ()
    if main and odd:
        return ("torn",)
    return ("main",) if main else tuple(sorted(odd))


@dataclass
class Block:
    """A leaf block: its text, the share of it inside links, its own block element, the known tags and the hints around it, and which signal is innermost."""

    text: str
    linked: float
    own: str
    tags: frozenset[str]
    hints: frozenset[str]
    inner: str


class _Open:
    """The open elements, with the places of each name, of block elements and of elements that tell something."""

    def __init__(self):
        self.stack: list[tuple[str, tuple[str, ...], bool]] = []
        self.places: dict[str, list[int]] = {}
        self.solid: list[int] = []
        self.signals: list[tuple[int, str]] = []
        self.hints: dict[str, int] = {}
        self.hidden = self.links = 0

    def push(self, name: str, attrs: str, off: bool) -> None:
        hints, at = _hints(name, attrs), len(self.stack)
        self.stack.append((name, hints, off))
        self.places.setdefault(name, []).append(at)
        if name not in INLINE:
            self.solid.append(at)
        for h in hints:
            self.hints[h] = self.hints.get(h, 0) + 1
        odd = name in _ODD_TAGS or set(hints) - {"main", "torn"}
        if odd or name in ("article", "main") or "main" in hints:
            self.signals.append((at, "odd" if odd else "main"))
        self.hidden += off
        self.links += name == "a"

    def pop(self, to: int) -> None:
        while len(self.stack) > to:
            name, hints, off = self.stack.pop()
            at = len(self.stack)
            self.places[name].pop()
            if not self.places[name]:
                del self.places[name]
            if self.solid and self.solid[-1] == at:
                self.solid.pop()
            if self.signals and self.signals[-1][0] == at:
                self.signals.pop()
            for h in hints:
                self.hints[h] -= 1
                if not self.hints[h]:
                    del self.hints[h]
            self.hidden -= off
            self.links -= name == "a"

    def last(self, names: tuple[str, ...]) -> int:
        """The place of the innermost element of one of the names, or -1."""
        return max((self.places[n][-1] for n in names if n in self.places), default=-1)


def blocks(page: str | None) -> list[Block]:
    """The leaf blocks of a page in their order; white space is one space, character references are decoded."""
    page = page or ""
    out: list[Block] = []
    now = _Open()
    parts: list[str] = []
    linked: list[str] = []

    def flush():
        text = " ".join(html.unescape("".join(parts)).split())
        if text:
            inside = len(" ".join(html.unescape("".join(linked)).split()))
            own = now.stack[now.solid[-1]][0] if now.solid else "none"
            tags = frozenset(t for t in now.places if t in KNOWN)
            out.append(Block(text, min(1.0, inside / len(text)), own, tags, frozenset(now.hints), now.signals[-1][1] if now.signals else "none"))
        parts.clear()
        linked.clear()

    def words(piece):
        if piece and not now.hidden:
            parts.append(piece)
            if now.links:
                linked.append(piece)

    at = 0
    while True:
        m = _OPEN.search(page, at)
        words(page[at : m.start()] if m else page[at:])
        if not m:
            break
        begins, at = m[0], m.end()
        if begins in ("<!--", "<![CDATA["):
            mark = "-->" if begins == "<!--" else "]]>"
            end = page.find(mark, at)
            if begins != "<!--":
                words(html.escape(page[at : end if end >= 0 else len(page)]))
            at = end + 3 if end >= 0 else len(page)
            continue
        if begins in ("<!", "<?", "</"):
            end = page.find(">", at)
            at = end + 1 if end >= 0 else len(page)
            continue
        named = _NAME.match(page, at - 1)
        rest = _REST.match(page, named.end())
        if not rest:  # the tag never ends
            break
        name, attrs, at = named[0].lower(), rest[0][:-1], rest.end()
        if begins.startswith("</"):
            depth = now.last((name,))
            if name not in INLINE:
                flush()
            if depth >= 0 and (name not in INLINE or not now.solid or now.solid[-1] < depth):
                now.pop(depth)
            continue
        if name == "br" or name == "img":
            words(" ")
            continue
        if name not in INLINE:
            flush()
            if name in CLOSES_P:
                if now.solid and now.stack[now.solid[-1]][0] == "p":
                    now.pop(now.solid[-1])
            elif name in SAME:
                depth = now.last(SAME[name])
                if depth > now.last(HOLDERS):
                    now.pop(depth)
        if name in VOID or attrs.endswith("/"):
            continue
        if name in CDATA:
            end = re.compile(rf"</{name}[\s/>]", re.I).search(page, at)
            stop = page.find(">", end.start()) + 1 if end else len(page)
            at = stop or len(page)
            continue
        if name == "body" and "head" in now.places:
            now.pop(now.places["head"][0])
        now.push(name, attrs, name in RAW or bool(_HIDDEN.search(attrs)))
    flush()
    return out


def block_features(b: Block, place: int, n: int) -> list[str]:
    """Names of the features that hold for a block."""
    tags = b.tags - {"html", "body"}
    count = b.text.count(" ") + 1
    size = "1" if count < 2 else "4" if count < 5 else "10" if count < 11 else "25" if count < 26 else "more"
    links = "all" if b.linked > 0.9 else "half" if b.linked > 0.4 else "some" if b.linked > 0 else "none"
    stop = "stop" if b.text[-1] in ".!?…\"”»" else "nostop"
    out = ["bias", f"own={b.own}", f"len={size}", f"linked={links}", stop, f"inner={b.inner}"]
    out += [f"in={t}" for t in tags] + [f"hint={h}" for h in b.hints]
    if "©" in b.text or "\xae" in b.text:
        out.append("sign")
    if count < 30 and not CUES.isdisjoint(_NAMES.findall(b.text.lower())):
        out.append("cue")
    odd = b.hints - {"main", "torn", "head", "share"}
    oddtag = tags & _ODD_TAGS
    if odd:
        out.append("odd")
    if oddtag:
        out.append("oddtag")
    if not odd and not oddtag and not b.hints & {"head", "share"}:
        out += ["free", f"free:len={size}", f"free:{stop}", f"free:linked={links}"]
        if not tags & {"article", "main"} and "main" not in b.hints:
            out += ["outside", f"outside:own={b.own}", f"outside:{size}:{stop}", f"outside:linked={links}"]
    if b.inner == "main" and b.own in ("h1", "h2", "h3"):
        out.append("heading")
    return out


@dataclass(frozen=True)
class Crf:
    """Weights of features by state (0 rest, 1 main text) and of transitions; start weights are the row of no state."""

    index: dict[str, int]
    state: np.ndarray
    move: np.ndarray
    start: np.ndarray

    def best(self, found: list[list[str]]) -> list[int]:
        """The best states by Viterbi."""
        get, w = self.index.get, self.state
        back = []
        a = b = 0.0
        (m00, m01), (m10, m11) = self.move.tolist()
        for k, names in enumerate(found):
            ids = [i for i in map(get, names) if i is not None]
            e0, e1 = (w[ids].sum(axis=0)).tolist() if ids else (0.0, 0.0)
            if k == 0:
                a, b = self.start[0] + e0, self.start[1] + e1
                continue
            f0, f1 = b + m10 > a + m00, b + m11 > a + m01
            a, b = (b + m10 if f0 else a + m00) + e0, (b + m11 if f1 else a + m01) + e1
            back.append((f0, f1))
        if not found:
            return []
        now = int(b > a)
        out = [now]
        for f in reversed(back):
            now = int(f[now])
            out.append(now)
        return out[::-1]

    def text(self, page: str | None) -> str:
        found = blocks(page)
        states = self.best([block_features(b, k, len(found)) for k, b in enumerate(found)])
        return "\n".join(b.text for b, s in zip(found, states, strict=True) if s)


def fit(pages: list[tuple[list[list[str]], list[int]]], rounds: int = 100, ridge: float = 0.02) -> Crf:
    """Maximum likelihood with a ridge, by gradient ascent with momentum; all pages are padded to one length and run together."""
    names = sorted({f for found, _ in pages for x in found for f in x})
    index = {f: i for i, f in enumerate(names)}
    pages = [p for p in pages if p[0]]
    n, t = len(pages), max(len(p[0]) for p in pages)
    y = np.zeros((n, t), dtype=int)
    live = np.zeros((n, t), dtype=bool)
    for i, (_, states) in enumerate(pages):
        y[i, : len(states)], live[i, : len(states)] = states, True
    size = int(live.sum())
    flat = np.zeros((size, len(names)))
    for row, fs in zip(flat, (fs for found, _ in pages for fs in found), strict=True):
        row[[index[f] for f in fs]] = 1
    w, move, start = np.zeros((len(names), 2)), np.zeros((2, 2)), np.zeros(2)
    speed = [np.zeros_like(w), np.zeros_like(move), np.zeros_like(start)]
    gold = np.eye(2)[y]
    pair = live[:, 1:]
    gold_move = np.einsum("ntj,ntk->jk", gold[:, :-1] * pair[..., None], gold[:, 1:] * pair[..., None])

    def lse(v, axis):
        return np.logaddexp(v.take(0, axis), v.take(1, axis))  # two states

    for r in range(rounds):
        e = np.zeros((n, t, 2))
        e[live] = flat @ w
        f, b = np.zeros((n, t, 2)), np.zeros((n, t, 2))
        f[:, 0] = start + e[:, 0]
        for k in range(1, t):
            f[:, k] = np.where(live[:, k, None], lse(f[:, k - 1, :, None] + move, 1) + e[:, k], f[:, k - 1])
        for k in range(t - 2, -1, -1):
            b[:, k] = np.where(live[:, k + 1, None], lse(move + (e[:, k + 1] + b[:, k + 1])[:, None, :], 2), 0)
        z = lse(f[:, -1], 1)
        p = np.exp(np.clip(f + b - z[:, None, None], -60, 0))
        joint = np.exp(np.clip(f[:, :-1, :, None] + move + (e[:, 1:] + b[:, 1:])[:, :, None, :] - z[:, None, None, None], -60, 0)) * pair[..., None, None]
        grads = (flat.T @ (gold - p)[live] / size - ridge * w / 10, (gold_move - joint.sum(axis=(0, 1))) / size - ridge * move / 10, (gold - p)[:, 0].sum(axis=0) / size)
        for g, s, v in zip(grads, speed, (w, move, start), strict=True):
            s *= 0.9
            s += g
            v += 1.0 * s
    return Crf(index, w, move, start)


# Labelled pages -------------------------------------------------------------------------------------------------

_M, _R = 1, 0


class _Layouts:
    """Writes labelled pages: a list of (html, state or None) whose texts, in order, are the gold blocks."""

    def __init__(self, seed: int):
        self.rng = random.Random(seed)

    def pick(self, *xs):
        return self.rng.choice(xs)

    def word(self):
        return "".join(self.pick("ra", "to", "mi", "en", "al", "or", "est", "un", "le", "der", "sch", "ció") for _ in range(self.rng.randrange(1, 4)))

    def words(self, a, b, stop=True):
        text = " ".join(self.word() for _ in range(self.rng.randrange(a, b + 1))).capitalize()
        style = self.rng.random()
        if style < 0.08:
            text = text.upper()
        elif style < 0.16:
            text = " ".join(w + self.pick("###", "***", "%%%", "$$$", "!!") for w in text.split())
        elif style < 0.2:
            text = text.replace(" ", " | ")
        return text + self.pick(".", ".", ".", "!", "?") * stop

    def some(self, chance):
        return self.rng.random() < chance

    def menu(self):
        items = [self.words(1, 3, False) for _ in range(self.rng.randrange(3, 8))]
        body = [("<ul>", None)] + [x for w in items for x in ((f'<li><a href="/{w}">{w}</a></li>', _R),)] + [("</ul>", None)]
        return self.wrap(body, self.pick("<nav>|</nav>", '<div class="menu">|</div>', '<div id="top-nav">|</div>', '<ul class="breadcrumb">|</ul>', '<nav class="main-navigation">|</nav>', '<div role="navigation">|</div>'))

    def wrap(self, body, tags):
        a, b = tags.split("|")
        return [(a, None), *body, (b, None)]

    def name(self):
        """A name that tells nothing."""
        return self.pick("zz", "x1", "wrap", "col", "row", "inner", "box", "grid", "css", "block", "c2", "view", "lay") + self.pick("", "-a", "-7", "_in", "-left") if self.some(0.7) else self.word()

    def rest(self, kind):
        if kind == "menu":
            return self.menu()
        tags = {
            "head": ("<header>|</header>", '<div class="site-header">|</div>', '<div id="masthead">|</div>'),
            "foot": ("<footer>|</footer>", '<div class="footer">|</div>', '<div id="site-footer">|</div>'),
            "side": ("<aside>|</aside>", '<div class="sidebar">|</div>', '<div id="right-rail" class="widget">|</div>', '<section class="related-posts">|</section>', '<aside class="sidebar">|</aside>', '<div class="sidebar-content">|</div>'),
            "note": ('<div class="cookie-notice">|</div>', '<div id="consent-banner">|</div>', '<div class="alert notice">|</div>', '<div class="notice">|</div>', '<div role="dialog" class="popup">|</div>'),
            "advert": ('<div class="ad">|</div>', '<div class="advert">|</div>', '<div class="sponsored">|</div>', '<aside class="promo">|</aside>', '<div id="ad-slot">|</div>', '<div class="ads">|</div>'),
            "talk": ('<section class="comments">|</section>', '<div id="comments">|</div>', '<ol class="comment-list">|</ol>', '<div class="comment">|</div>', '<div class="user-comments">|</div>', '<article class="comment">|</article>', '<div class="comment-body">|</div>'),
            "form": ("<form>|</form>", '<form class="newsletter">|</form>', '<div class="signup"><form>|</form></div>', '<form id="search">|</form>'),
            "share": ('<div class="share-buttons">|</div>', '<div class="social">|</div>', '<ul class="tags">|</ul>'),
        }[kind]
        body = []
        for _ in range(self.rng.randrange(1, 4)):
            if kind == "foot" and self.some(0.5):
                body.append((f"<p>&copy; {self.words(2, 8)}</p>", _R))
            elif kind == "form":
                body.append((f"<label>{self.words(1, 4, False)}</label><input><button>", _R))
                body.append((f"{self.words(1, 2, False)}</button>", _R))
            elif kind == "share":
                body.append((f'<li><a href="#">{self.words(1, 2, False)}</a></li>', _R))
            else:
                tag = self.pick("p", "div", "p", "li", "h3")
                body.append((f"<{tag}>{self.words(2, 30)}</{tag}>", _R))
        return self.wrap(body, self.pick(*tags))

    def unnamed(self):
        """What is no main text in elements whose names tell nothing: rows of links, lines of rights, words of notices."""
        kind = self.pick("links", "links", "rights", "cue")
        if kind == "links":
            row = self.pick(" | ", " ", " &middot; ").join(f'<a href="/{k}">{self.words(1, 3, False)}</a>' for k in range(self.rng.randrange(2, 7)))
            return self.wrap([(row, _R)], f'<div class="{self.name()}">|</div>')
        if kind == "rights":
            return self.wrap([(f"&copy; {self.words(1, 6, False)}", _R)], self.pick("<div>|</div>", "<p>|</p>", f'<div class="{self.name()}">|</div>'))
        cue = self.pick("Share", "Log in", "Subscribe", "Accept cookies", "Privacy", "Advertisement", "Search", "Menu")
        return self.wrap([(self.pick(cue, f'<a href="#">{cue}</a>'), _R)], self.pick("<div>|</div>", f'<div class="{self.name()}">|</div>'))

    def table(self):
        cell = lambda: self.words(1, 4, False) if self.some(0.7) else self.words(4, 20)
        rows = [[(f"<{t}>{cell()}</{t}>", _M) for t in (["th"] * 3 if k == 0 and self.some(0.5) else ["td"] * 3)] for k in range(self.rng.randrange(2, 5))]
        return [("<table>", None), *(x for row in rows for x in (("<tr>", None), *row, ("</tr>", None))), ("</table>", None)]

    def main(self):
        body = []
        if self.some(0.85):
            h = f"<h1>{self.words(1, 12, self.some(0.3))}</h1>"
            if self.some(0.12):
                body += [("<header>", None), (h, _M), *([(f'<p class="byline">{self.words(2, 5, False)}</p>', _R)] if self.some(0.5) else []), ("</header>", None)]
            else:
                body.append((h, _M))
        for _ in range(self.rng.randrange(1, 10)):
            kind = self.rng.random()
            text = self.words(8, 60) if self.some(0.75) else self.words(1, 8)
            if kind < 0.64:
                body.append((f"<p>{text}</p>" if self.some(0.8) else f"<p><b>{text}<br></b></p>", _M))
            elif kind < 0.7:
                body.append((f"<div>{self.words(12, 60)}</div>", _M))
            elif kind < 0.77:
                body.append((f"<{(t := self.pick('h2', 'h3', 'h4'))}>{self.words(1, 6, False)}</{t}>", _M))
            elif kind < 0.82:
                body.append((f"<blockquote>{text}</blockquote>", _M))
            elif kind < 0.88:
                body += [("<ul>", None), *((f"<li>{self.words(1, 14)}</li>", _M) for _ in range(3)), ("</ul>", None)]
            elif kind < 0.91:
                body.append((f"<pre>{self.words(3, 30, False)}</pre>", _M))
            elif kind < 0.94:
                body += self.table()
            elif kind < 0.96:
                body += [("<figure><img>", None), (f"<figcaption>{self.words(3, 12)}</figcaption>", _M), ("</figure>", None)]
            else:
                body.append((f'<p><a href="#">{self.words(2, 6)}</a> {self.words(8, 20)}</p>', _M))
            if self.some(0.1):
                body += self.rest(self.pick("advert", "note", "form", "share", "side", "talk"))
        if self.some(0.15):
            body += self.rest("talk")
        if self.some(0.45):
            told = ("<article>|</article>", "<article>|</article>", "<main>|</main>", '<div class="content">|</div>', '<div id="main-content">|</div>', '<div class="post-body">|</div>', '<main><article class="entry">|</article></main>', '<div class="article-text">|</div>', '<section class="story">|</section>')
            return self.wrap(body, self.pick(*told))
        if self.some(0.25):  # names that mislead
            torn = ('<main class="with-comments">|</main>', '<div id="main-content" class="sidebar-left">|</div>', '<div class="content has-sidebar">|</div>', '<article class="post no-comments">|</article>', '<div id="content" class="comments-open">|</div>', '<main class="sidebar-right">|</main>', '<div class="entry tag-news category-world">|</div>')
            return self.wrap(body, self.pick(*torn))
        plain = ("|", "|", "<div>|</div>", f'<div class="{self.name()}">|</div>', f'<div class="{self.name()}"><div id="{self.name()}">|</div></div>', f'<section class="{self.name()}">|</section>', "<center>|</center>", "<table><tr><td>|</td></tr></table>")
        return self.wrap(body, self.pick(*plain))

    def page(self):
        """The page and its gold states by block."""
        body = []
        for kind in ("head", "menu", "note", "advert"):
            if self.some(0.4):
                body += self.rest(kind)
        if self.some(0.25):
            body += self.unnamed()
        body += self.main()
        if self.some(0.3):
            body += self.unnamed()
        for kind in ("talk", "side", "share", "form", "advert", "foot"):
            if self.some(0.35):
                body += self.rest(kind)
        if self.some(0.3):
            body = self.wrap(body, self.pick('<div class="wrapper">|</div>', '<div id="page">|</div>', '<div class="container">|</div>', '<div class="page header-fixed">|</div>', f'<div class="{self.name()}">|</div>'))
        source = "<html><head><title>" + self.words(1, 5) + "</title></head>" + self.pick("<body>", "<body>", '<body class="has-sidebar single-post">') + "".join(h for h, _ in body) + "</body></html>"
        return source, [s for _, s in body if s is not None]


def labelled_pages(n: int = 700, seed: int = 11) -> list[tuple[str, list[int]]]:
    """Pages with the gold state of each leaf block; the same for every call."""
    writer = _Layouts(seed)
    return [writer.page() for _ in range(n)]


@lru_cache(maxsize=1)
def default_model() -> Crf:
    pages = []
    for source, gold in labelled_pages():
        found = blocks(source)
        if len(found) != len(gold):
            raise ValueError("a labelled page has other blocks than labels")
        pages.append(([block_features(b, k, len(found)) for k, b in enumerate(found)], gold))
    return fit(pages)


def extract(pages: DataFrame, model: Crf | None = None) -> DataFrame:
    """page_id, url, text and n_chars (code points) of every page."""
    held = pages.sparkSession.sparkContext.broadcast(model or default_model())

    def rows(ids, urls, sources):
        texts = [held.value.text(s) for s in sources]
        return {"page_id": ids, "url": urls, "text": texts, "n_chars": [len(t) for t in texts]}

    return arrow_map(pages.select("page_id", "url", "html"), "page_id long, url string, text string, n_chars long", rows)
