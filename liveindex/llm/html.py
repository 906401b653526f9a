"""Main text of web pages: flat text blocks classified by a small decision tree.

A page is cut into blocks at block-level tags. The tree sees each block's words and link density, those of its
neighbours, its words against the page's largest block, and how strongly the markup around it speaks: a container
named as menu, advert, comment .. counts the less the more of the page it holds, as a page's wrapper often carries
such names too. The tree is grown by Gini gain from a small table of labelled pages, given or made by a rule.

Tags are read in one pass over the page, so that the time grows with its length whatever it holds.
"""

from __future__ import annotations

import re
from collections.abc import Iterable, Iterator
from functools import lru_cache
from html import unescape
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

_NAME = re.compile(r"[a-zA-Z][^\s/>]*")
_PLAIN = re.compile(r"""[^>"'<]*>""")
_BETWEEN = re.compile(r"[\s/]*")
_ATTRIBUTE = re.compile(r"""([^\s/>=]+)(?:\s*=\s*("[^"]*"|'[^']*'|[^\s>"'][^\s>]*))?""")
# Elements of the page's language by how they act here.
_RAW = frozenset("script style textarea title iframe noframes noembed noscript template xmp".split())
_SKIPPED = frozenset("svg object canvas select button datalist audio video".split())
_BLOCK = frozenset("address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol optgroup option p pre section summary table tbody td tfoot th thead tr ul".split())
_NOISE = frozenset("nav aside footer menu dialog".split())
_FORM = frozenset("form fieldset".split())
_HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
_NAMED = frozenset("article aside center details div dl footer form header li main menu nav ol p section table td tr ul".split())
_NOISY = re.compile(
    r"ads?|adverts?|advertisements?|advertising|adslot|adbox|sponsor(?:ed|s)?|promos?|promotions?|banners?|menus?|nav|navbar|navigation|sidebars?|footer|header|masthead|cookies?|consent|gdpr|notices?|popups?|modal|overlay"
    r"|comments?|commentlist|respond|reply|replies|disqus|share|sharing|social|related|recommended|recommendations|subscribe|subscription|newsletters?|breadcrumbs?|widgets?|pagination|pager|toolbar|login|signup|search|searchbox|copyright|disclaimer|complementary|contentinfo")
_SAYS = re.compile(r"[a-z]+|[A-Z]+(?![a-z])|[A-Z][a-z]*|\d+")
_DENIES = frozenset("no not has with without is hide".split())

FEATURES = ("words", "links", "words_before", "links_before", "words_after", "links_after", "relative", "element", "named", "form", "article", "page_has_article", "heading", "hidden")


def tags(html: str) -> Iterator[tuple[int, int, str, bool, dict[str, str]]]:
    """(begin, end, name, closing, attributes) of a page's tags, in order; the name is "" for comments and the like, and
    "#" for an element whose content is no text, which is left out whole. What begins like a tag at the page's end
    and is never closed is left out too."""
    at, size = 0, len(html)
    while (begin := html.find("<", at)) >= 0:
        closing = html.startswith("/", begin + 1)
        name = _NAME.match(html, begin + 1 + closing)
        if not name:
            if html.startswith("<!--", begin):
                end = html.find("-->", begin + 4 if not html.startswith("<!-->", begin) else begin + 2)
                at = size if end < 0 else end + 3
            elif html[begin + 1 : begin + 2] in ("!", "?", "/"):
                end = html.find(">", begin)
                at = size if end < 0 else end + 1
            else:  # a sign of the text
                at = begin + 1
                continue
            yield begin, at, "", False, {}
            continue
        word, has = name[0].lower(), {}
        plain = _PLAIN.match(html, name.end())
        if plain:
            at = plain.end()
            said = html[name.end() : at - 1]
            if said and not said.isspace():
                has = {m[1].lower(): m[2] or "" for m in _ATTRIBUTE.finditer(said)}
        else:
            at = name.end()
            while (at := _BETWEEN.match(html, at).end()) < size and html[at] != ">":
                found = _ATTRIBUTE.match(html, at)
                if found:
                    has.setdefault(found[1].lower(), (found[2] or "").strip("\"'"))
                    at = found.end()
                else:
                    at += 1
            at = min(size, at + 1)
        if word in _RAW and not closing:
            end = re.compile(f"</{word}(?=[\\s/>])", re.I).search(html, at)
            stop = html.find(">", end.end()) if end else -1
            at = stop + 1 if stop >= 0 else size
            word = "#"
        yield begin, at, word, closing, has


def _says_noise(has: dict[str, str]) -> bool:
    """Whether a class, id or role names something beside the text, as a word that no word before it denies."""
    for key in ("class", "id", "role"):
        for item in has.get(key, "").split():
            before = ""
            for word in map(str.lower, _SAYS.findall(item)):
                if before not in _DENIES and _NOISY.fullmatch(word):
                    return True
                before = word
    return False


class _Container:
    """An element that speaks for noise: words before it and up to its end, and whether a title or article is in it."""

    __slots__ = ("begin", "end", "titled")

    def __init__(self, begin: int) -> None:
        self.begin, self.end, self.titled = begin, None, False

    def strength(self, words: int, titles: int) -> float:
        """1 if the page's titles and articles are elsewhere; else what it leaves of the page's words."""
        if not self.titled and titles:
            return 1.0
        return 1 - ((words if self.end is None else self.end) - self.begin) / max(words, 1)


#: What holds for text: element, container of each kind (element, named, form), article, hidden, label of training pages.
_OPEN = ("", None, None, None, 0, 0, None)


def blocks(html: str) -> list[tuple[str, list[float], str | None]]:
    """(text, features, label) of a page's blocks; the label is that of a data-y attribute, for training pages.

    Text of scripts, styles, comments and other elements that hold no prose is left out. Blocks without words are none."""
    out: list[list] = []
    stack: list[tuple[tuple, tuple]] = []  # what holds inside, and the containers that the element itself opened
    text: list[str] = []
    linked: list[str] = []
    state = _OPEN
    words = titles = articles = 0
    link, skip, skipped, closes = False, "", 0, {}
    at = 0

    def close() -> None:
        nonlocal text, linked, words
        if text:
            found = unescape("".join(text)).split()
            if found:
                share = len(unescape(" ".join(linked)).split()) / len(found) if linked else 0.0
                out.append([" ".join(found), len(found), min(1.0, share), state])
                words += len(found)
        text, linked = [], []

    def leave(depth: int) -> None:
        nonlocal state
        for _, own in stack[depth:]:
            for c in own:
                c.end = words
        del stack[depth:]
        state = stack[-1][0] if stack else _OPEN

    for begin, end, name, closing, has in chain(tags(html), [(len(html), len(html), "", True, {})]):
        if begin > at and not skip:
            text.append(html[at:begin])
            if link:
                linked.append(html[at:begin])
        at = end
        if skip:
            if name == skip:
                skipped += -1 if closing else 1
                skip = skip if skipped else ""
            continue
        if name == "#":
            text.append(" ")
        elif name in _SKIPPED and not closing:
            if name not in closes:
                closes[name] = max((m.start() for m in re.finditer(f"</{name}(?=[\\s/>])", html, re.I)), default=-1)
            text.append(" ")
            if begin < closes[name]:  # one that is never closed holds nothing
                skip, skipped = name, 1
        elif closing:
            if name == "a":
                link = False
            elif name in _BLOCK:
                close()
                depth = next((k for k in range(len(stack) - 1, -1, -1) if stack[k][0][0] == name), None)
                if depth is not None:
                    leave(depth)
                    link = False
        elif name == "a":
            link = True
        elif name in ("br", "img", "input"):
            text.append(" ")
        elif name in _BLOCK:
            close()
            depth = len(stack)
            while depth and (top := stack[depth - 1][0][0]) in ("p", "dt", "dd", "option", *_HEADINGS) and (name not in ("dt", "dd") or top in ("dt", "dd", "p")) and not (top == "dd" and name in ("ul", "ol", "div", "table")):
                depth -= 1
            if depth and (name == "li" and stack[depth - 1][0][0] == "li" or name in ("td", "th") and stack[depth - 1][0][0] in ("td", "th") or name == "tr" and stack[depth - 1][0][0] == "tr"):
                depth -= 1
            leave(depth)
            _, element, named, form, article, hidden, label = state
            own: list[_Container] = []

            def opened(own=own) -> _Container:
                own.append(_Container(words))
                return own[-1]

            noisy = name in _NAMED and bool(has) and _says_noise(has) and not (article and name == "header")
            main = (name in ("article", "main") or has.get("role") == "main" or has.get("itemprop") == "articleBody") and not noisy
            if name in _NOISE or name == "header" and not article:
                element = opened()
            if noisy:
                named = opened()
            if name in _FORM:
                form = opened()
            if main or name == "h1":
                titles += 1
                articles += main
                for _, others in stack:
                    for c in others:
                        c.titled = True
            if main:
                article = 1
            if has:
                if "hidden" in has or has.get("aria-hidden") == "true" or "display:none" in has.get("style", "").replace(" ", "").lower():
                    hidden = 1
                label = has.get("data-y", label)
            state = (name, element, named, form, article, hidden, label)
            if name != "hr":
                stack.append((state, tuple(own)))
            link = False
    close()
    leave(0)
    largest = max((n * (1 - share) for _, n, share, s in out if s[1] is s[2] is s[3] is None), default=0) or max((n for _, n, _, _ in out), default=1)
    none = ["", 0, 0.0]
    rows = []
    for k, (block, n, share, (name, element, named, form, article, hidden, label)) in enumerate(out):
        before, after = (out[k - 1] if k else none), (out[k + 1] if k + 1 < len(out) else none)
        strength = [0.0 if c is None else c.strength(words, titles) for c in (element, named, form)]
        rows.append((block, [n, share, before[1], before[2], after[1], after[2], min(1.0, n / largest), *strength, article, float(articles > 0), float(name in _HEADINGS), hidden], label))
    return rows


def labelled_pages(pages: int = 600, seed: int = 11) -> list[str]:
    """Pages made by a rule, whose blocks carry their label in data-y (1 main text, 0 not): the default labelled table.

    A page has a body of paragraphs, headings and lists in an article, a wrapper of some name, a form or nothing, and
    around and inside it menus, adverts, notices, sidebars, comments and footers with and without names that say so."""
    rng = np.random.default_rng(seed)
    pick = lambda *some: some[int(rng.integers(len(some)))]
    prose = lambda n: " ".join(f"w{k}" for k in range(max(1, int(n))))
    links = lambda n: " ".join(f"<a href=x>{prose(rng.integers(1, 4))}</a>" for _ in range(n))
    low = lambda: prose(rng.integers(2, 45))

    def noise(said: str) -> str:
        return pick(f"<div class='{said}' data-y=0>{low()}</div>", f"<section id={said} data-y=0><h3>{prose(2)}</h3><p>{low()}</p><p>{low()}</p></section>", f"<div class='box {said}' data-y=0><p>{low()}</p>{links(2)}</div>")

    def plain() -> str:
        return pick(f"<div data-y=0>{links(3)}</div>", f"<ul data-y=0>{''.join(f'<li>{links(1)}</li>' for _ in range(4))}</ul>", f"<div data-y=0>{links(2)} {prose(2)}</div>", f"<div data-y=0><p>{links(1)}</p><p>{links(2)}</p></div>")

    def body(scale: float) -> str:
        out = []
        for k in range(int(rng.integers(3, 9))):
            out.append(f"<p>{prose(scale * rng.integers(6, 60))}" + pick("</p>", "</p>", ""))
            if rng.random() < 0.25:
                out.append(pick(f"<h2 id=related-work>{prose(3)}</h2><p>{prose(scale * 30)}</p>", f"<ul><li>{prose(4)}</li><li>{prose(scale * 9)}</li></ul>", f"<p>{prose(scale * 20)} {links(1)} {prose(8)}</p>", f"<blockquote>{prose(scale * 15)}</blockquote>", f"<p>{prose(2)}</p>", f"<table><tr><td>{prose(2)}</td><td>{prose(1)}</td></tr></table>"))
        return "".join(out)

    out = []
    for k in range(pages):
        said = lambda: pick("ad", "advert", "menu", "sidebar", "cookie-notice", "comments", "share", "related", "newsletter", "breadcrumb", "siteFooter", "promo", "widget", "search", "social")
        text = body(pick(0.15, 0.5, 1.0, 1.0, 2.0))
        # A heading in a container that is no article does not tell the page's title from that of the site.
        title = pick(f"<h1>{prose(6)}</h1>", f"<h1>{prose(6)}</h1>", "")
        inside = "".join(noise(said()) for _ in range(int(rng.integers(0, 3)))) + pick("", f"<aside data-y=0>{low()}</aside>", f"<form data-y=0><p>{low()}</p></form>", f"<div hidden data-y=0>{low()}</div>")
        kind = k % 6
        if kind < 2:
            tag = pick("article", "main")
            last = pick("", "", f"<p>{prose(rng.integers(1, 90))}</p>")
            middle = f"<{tag} data-y=1>{pick('', '<header>')}{title}{pick(text, text, prose(30))}{inside}{last}</{tag}>"
        elif kind == 2:
            middle = f"<div class='{pick('page no-sidebar', 'post has-header', 'content with-sidebar', 'wrapper')}' data-y=1>{title}{text}</div>"
        elif kind == 3:
            middle = f"<form action=x data-y=1>{title}<div>{text}</div></form>"
        elif kind == 4:
            middle = f"<div class='{pick('layout sidebar', 'banner', 'search')}' data-y=1>{title}{text}{text}</div>"
        else:
            middle = f"<div data-y=1>{title}{text}</div>"
        around = [pick("<nav data-y=0><ul>" + "".join(f"<li>{links(1)}</li>" for _ in range(5)) + "</ul></nav>", f"<header data-y=0><p>{prose(4)}</p></header>", plain(), "") if kind != 4 else ""]
        after = "".join(pick(noise(said()), plain(), f"<footer data-y=0>{low()}</footer>", f"<aside data-y=0><p>{low()}</p></aside>", "") for _ in range(int(rng.integers(0, 4)))) if kind != 4 else ""
        if kind < 2:  # beside an article even long prose is not the text
            after += pick("", f"<div data-y=0><p>{prose(30)}</p></div>", f"<div class=comments data-y=0><article><p>{prose(40)}</p></article><article><p>{prose(25)}</p></article></div>")
        out.append(f"<body>{''.join(around)}{noise(said()) if rng.random() < 0.4 and kind != 4 else ''}{middle}{after}")
    return [*out, *(f"<body><p data-y=1>{prose(n)}</p><p data-y=1>{prose(n)}</p><p data-y=1>{prose(n + 2)}</p>" for n in (3, 4, 8, 30)), f"<body><div data-y=1>{prose(34)}</div>"]


def labelled(pages: Iterable[str]) -> tuple[np.ndarray, np.ndarray]:
    """Features and labels of the labelled blocks."""
    rows = [b for page in pages for b in blocks(page) if b[2] is not None]
    return np.array([b[1] for b in rows], float).reshape(-1, len(FEATURES)), np.array([b[2] == "1" for b in rows], bool)


def grow(x: np.ndarray, y: np.ndarray, depth: int = 8, least: int = 3) -> tuple:
    """A tree as nested (feature, threshold, at most, above); a leaf is a share of main text, of `least` blocks or more."""
    share = float(y.mean()) if y.size else 0.0
    if depth == 0 or share in (0.0, 1.0) or y.size < 2 * least:
        return (share,)
    best = None
    for f in range(x.shape[1]):
        order = np.argsort(x[:, f], kind="stable")
        values, hits = x[order, f], np.cumsum(y[order])
        cut = np.flatnonzero(values[1:] != values[:-1])
        cut = cut[(cut + 1 >= least) & (y.size - cut - 1 >= least)]
        if not cut.size:
            continue
        n, m = cut + 1, y.size - cut - 1
        low, high = hits[cut], hits[-1] - hits[cut]
        impurity = low * (1 - low / n) + high * (1 - high / m)
        k = int(impurity.argmin())
        if best is None or impurity[k] < best[0] - 1e-12:
            best = float(impurity[k]), f, float((values[cut[k]] + values[cut[k] + 1]) / 2)
    if best is None or best[0] >= y.size * share * (1 - share) - 1e-12:
        return (share,)
    low = x[:, best[1]] <= best[2]
    return best[1], best[2], grow(x[low], y[low], depth - 1, least), grow(x[~low], y[~low], depth - 1, least)


@lru_cache(1)
def tree() -> tuple:
    """The tree of the default labelled table."""
    return grow(*labelled(labelled_pages()))


def is_main(node: tuple, features: list[float]) -> bool:
    while len(node) > 1:
        node = node[2] if features[node[0]] <= node[1] else node[3]
    return node[0] >= 0.5


def main_text(html: str | None, node: tuple) -> str:
    return "\n".join(text for text, features, _ in blocks(html or "") if is_main(node, features))


#: Most labelled pages that the driver takes to grow a tree from.
MOST_LABELLED = 2000


def extract_main_text(df: DataFrame, html: str = "html", into: str = "text", labels: DataFrame | None = None, most_labelled: int = MOST_LABELLED) -> DataFrame:
    """df without its html, with the main text of each page: blocks in page order, one to a line.

    labels: a table with a column html of pages whose blocks are labelled by data-y attributes, of which the
    most_labelled first ones by text grow the tree; without it the pages of labelled_pages do.

    Null and empty pages have an empty text. Each row is read alone and whole, in time that grows with its length:
    repeated rows get equal texts, an empty table gives an empty result, and a column already named like the new one
    is replaced.
    """
    kept = [f for f in df.schema if f.name != html and f.name.lower() != into.lower()]
    node = tree() if labels is None else grow(*labelled(r[0] or "" for r in labels.select("html").orderBy("html").limit(most_labelled).collect()))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                texts = pa.array([main_text(h.as_py(), node) for h in part.column(html)], pa.string())
                yield pa.RecordBatch.from_arrays([*[part.column(f.name) for f in kept], texts], names=[*[f.name for f in kept], into])

    return df.mapInArrow(run, T.StructType([*kept, T.StructField(into, T.StringType())]))
