"""Main text of web pages by the maximum-scoring run of tokens (operator 4).

A page becomes a list of tokens: tags score below zero; words score by the elements and
class names around them and by the texture of their block (prose, a scrap, mostly links),
as often as such words were content in labelled pages. One linear scan finds the run of
tokens with the highest sum; of its words those in surroundings that are mostly not
content (adverts, notices, comments within an article) are left out. Within an article or
main element the run is extended to all other content of that element, so that lists of
links at its edges stay.

A stretch that is left out anyway costs the run little where the element that holds it
also holds paragraphs (OWN_COST at most), else up to OTHER_COST.

The weights are smoothed log-odds counted on the labelled pages of
`labelled_pages()`, whose content lies between two marker comments.

A null or empty page gives an empty text; broken markup (unclosed elements, a page
that breaks off, '<' in the text or in a script) is read as browsers do, as far as text
goes; elements nested deeper than DEEPEST become siblings, as there. Repeated rows give
repeated rows; null page_id or url stay null; no rows give no rows.
"""

from __future__ import annotations

import html
import math
import re
from collections import Counter
from collections.abc import Iterator
from itertools import groupby

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corefold.llm.common import slices, text_or_empty

# Element names by their part in the HTML standard.
VOID = frozenset("area base br col embed hr img input link meta source track wbr".split())
RAW = frozenset("script style noscript template textarea title iframe svg select".split())
INLINE = frozenset("a abbr b bdi bdo cite code data dfn em font i kbd label mark q s samp small span strike strong sub sup time tt u var wbr".split())
CLOSED_BY = {"li": ("li",), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "option": ("option",)}
CLOSES_P = frozenset("address article aside blockquote div dl fieldset footer form h1 h2 h3 h4 h5 h6 header hr main nav ol p pre section table ul".split())

_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)>|<(/?)([a-zA-Z][^\s/>]*)([^>]*)(?:>|\Z)|<[!?][^>]*>", re.S)
_RAW_END = {name: re.compile(rf"</{name}(?=[\s/>])[^>]*(?:>|\Z)", re.I) for name in RAW}
_NAMES = re.compile(r"(?:class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))", re.I)
_WORD = re.compile(r"[A-Za-z]+")
_SENTENCE = re.compile(r"[.!?:;。！？…][\"'”’»)]*$")
#: Fixed value: the deepest nesting of browsers' parsers.
DEEPEST = 512
#: Elements whose words make the element that holds them one of content.
PARAGRAPHS = frozenset("p h1 h2 h3 h4 h5 h6 ul ol dl pre blockquote table figure".split())
#: What one left-out stretch takes from a run at most, among paragraphs and elsewhere.
OWN_COST, OTHER_COST = 5.0, 60.0
#: Words from which on a block is prose, whatever it ends with.
LONG = 12
BEGIN, END = "<!--content-->", "<!--/content-->"


def _features(name: str, attributes: str) -> tuple[str, ...]:
    found = [name]
    if "=" in attributes:
        for groups in _NAMES.findall(attributes):
            found += ["." + w.lower() for w in _WORD.findall("".join(groups))]
    return tuple(dict.fromkeys(found))


class Element:
    """An open element: its features and those of all it lies in."""

    __slots__ = ("name", "parent", "depth", "context", "names", "holds", "judged")

    def __init__(self, name: str, parent: Element | None, features: tuple[str, ...]):
        self.name, self.parent = name, parent
        self.depth = parent.depth + 1 if parent else 0
        self.context: tuple[str, ...] = (*parent.context, *(f for f in features if f not in parent.context)) if parent else ()
        self.names: frozenset[str] = parent.names | {name} if parent else frozenset()
        self.holds = False  # a paragraph of content, so far
        self.judged: tuple[float, bool] | None = None

    def block(self) -> Element:
        """The innermost element around that is not inline."""
        here = self
        while here.name in INLINE and here.parent:
            here = here.parent
        return here


def tokens(page: str) -> Iterator[tuple[str, object, Element]]:
    """('text', string, innermost open element), ('tag', name, ...) or ('mark', comment, ...)."""
    here = Element("", None, ())
    at = 0
    while m := _TOKEN.search(page, at):
        if m.start() > at:
            yield "text", page[at : m.start()], here
        at = m.end()
        if m[0].startswith("<!--"):
            yield "mark", m[0], here
            continue
        name = (m[2] or m[5] or "").lower()
        if not name:
            continue
        if m[1] or m[4]:
            if name in here.names:
                while here.name != name:
                    here = here.parent
                here = here.parent
        else:
            if name in CLOSES_P and "p" in here.names:
                up = here
                while up.name in INLINE:
                    up = up.parent
                if up.name == "p":
                    here = up.parent
            elif name in CLOSED_BY and here.name in CLOSED_BY[name]:
                here = here.parent
            attributes = m[3] or m[6] or ""
            if name in RAW:  # nothing in it is markup; only its own end tag ends it
                yield "tag", name, here
                if not attributes.endswith("/") or name in ("script", "style", "textarea", "title"):
                    end = _RAW_END[name].search(page, at)
                    at = end.end() if end else len(page)
                    yield "tag", "/" + name, here
                continue
            if name not in VOID and not attributes.endswith("/"):
                here = Element(name, here if here.depth < DEEPEST else here.parent, _features(name, attributes))
        yield "tag", ("/" if m[1] or m[4] else "") + name, here
    if at < len(page):
        yield "text", page[at:], here


Block = list[tuple[str, object, Element]]


def blocks(page: str) -> Iterator[tuple[str, Block]]:
    """(texture, tokens) of each block: what stands between two tags that are not inline; '' for such tags themselves."""
    inner = lambda t: t[0] == "text" or t[0] == "tag" and t[1].strip("/") in INLINE
    for together, found in groupby(tokens(page), key=inner):
        if not together:
            yield from (("", [t]) for t in found)
            continue
        found = list(found)
        words = linked = 0
        last = ""
        for kind, value, here in found:
            if kind == "text" and (n := len(value.split())):
                words += n
                linked += n * ("a" in here.names)
                last = value
        yield "links" if 2 * linked > words else "prose" if words >= LONG or _SENTENCE.search(last.rstrip()) else "scrap", found


class Weights:
    """Scores of tags, and of words by surroundings and by their block's texture."""

    def __init__(self, tag: dict[str, float], near: dict[str, float], texture: dict[str, float], base: float):
        self.tag, self.near, self.texture, self.base = tag, near, texture, base

    def word(self, here: Element) -> tuple[float, bool]:
        """A word's score: base, or less where an open element is one that mostly holds no content.

        And whether a word there is content if the run has it: links lower the score,
        as menus are made of them, but a link within content is content.
        """
        if here.judged is None:
            worst = min((self.near.get(f, 0.0) for f in here.context), default=0.0)
            block = min((self.near.get(f, 0.0) for f in here.context if f not in INLINE), default=0.0)
            kept = self.base + min(0.0, block) > 0
            here.judged = self.base + min(0.0, worst) if kept else -0.3, kept
        return here.judged


def fit(pages: list[str]) -> Weights:
    """Log-odds, smoothed by one half, over labelled pages."""
    inside: Counter = Counter()
    outside: Counter = Counter()
    tag_in: Counter = Counter()
    tag_out: Counter = Counter()
    texture_in: Counter = Counter()
    texture_out: Counter = Counter()
    for page in pages:
        within = False
        for texture, found in blocks(page):
            for kind, value, here in found:
                if kind == "mark":
                    within = value == BEGIN or within and value != END
                elif kind == "tag":
                    (tag_in if within else tag_out)[value] += 1
                elif n := len(str(value).split()):
                    (texture_in if within else texture_out)[texture] += n
                    for f in here.context:
                        (inside if within else outside)[f] += n
    odds = lambda a, b: math.log((a + 0.5) / (b + 0.5))
    near = {f: 2 * odds(inside[f], outside[f]) for f in set(inside) | set(outside)}
    tag = {t: min(-0.1, odds(tag_in[t], tag_out[t]) / 8 - 0.1) for t in set(tag_in) | set(tag_out)}
    usual = odds(sum(texture_in.values()), sum(texture_out.values()))
    texture = {t: max(-0.5, min(0.5, (odds(texture_in[t], texture_out[t]) - usual) / 4)) for t in set(texture_in) | set(texture_out)}
    return Weights(tag, near, texture, 1.0)


def labelled_pages() -> list[str]:
    """Pages of common make-up; what is content lies between the markers."""
    s = "Some plain words of a sentence that goes on for a while, as they do."
    links = "".join(f'<li><a href="/{i}">{w}</a></li>' for i, w in enumerate("Home News About Contact More".split()))
    head = f"<html><head><meta charset='utf-8'><title>{s}</title><style>p{{}}</style></head><body>"
    menu = f'<nav class="menu"><ul>{links}</ul></nav><div class="breadcrumb breadcrumbs">{s}</div>'
    top = f'<header class="banner masthead" role="banner"><div class="logo tagline">{s}</div>{menu}</header>'
    side = f'<aside class="sidebar"><h3>{s}</h3><ul class="related recommended popular">{links}</ul><div class="widget">{s}</div></aside>'
    ads = f'<div class="ad ads advert advertisement sponsor sponsored promo adsense">{s}</div>'
    notices = f'<div class="cookie cookies consent notice popup modal overlay gdpr newsletter subscribe alert" role="dialog">{s}</div>'
    form = f"<form><label>{s}</label><button>{s}</button></form>"
    talk = f'<section class="comments comment disqus replies respond"><ol><li><p>{s}</p></li><li><p>{s}</p></li></ol></section>'
    share = f'<div class="share social sharing">{s}</div><div class="pagination pager">{s}</div>'
    foot = f'<footer class="footer copyright" role="contentinfo"><p>&copy; {s}</p></footer><div class="footer">{s}</div></body></html>'
    body = f"<h1>{s}</h1><p>{s} <b>{s}</b> <i>{s}</i> <em>{s}</em> <strong>{s}</strong> <span>{s}</span><br>{s}</p><h2>{s}</h2><p>{s} <a href='/x'>one</a> {s} <code>{s}</code></p>" * 6
    rich = f"<h1>{s}</h1><p>{s}</p><ul><li>{s}</li><li>{s}</li></ul><ol><li>{s}</li></ol><blockquote><p>{s}</p></blockquote><pre>{s}</pre><table><tr><th>{s}</th><td>{s}</td></tr></table><figure><figcaption>{s}</figcaption></figure><h3>{s}</h3><p>{s}</p>" * 6
    mark = lambda x: BEGIN + x + END
    return [
        f"{head}{menu}{ads}<article>{mark(body)}</article>{foot}",
        f"{head}{top}<main><article>{mark(rich)}</article></main>{side}{foot}",
        f"{head}{notices}{top}<div class='content'>{mark(body)}{share}</div>{talk}{foot}",
        f"{head}{top}{side}<main>{mark(rich)}{form}</main>{ads}{foot}",
        f"{head}{menu}<div id='main' class='post entry'>{mark(body)}{ads}{mark(rich)}</div>{talk}{share}{foot}",
        f"{head}{form}{menu}<section>{mark(body)}</section>{side}{notices}{foot}",
    ]


_WEIGHTS: list[Weights] = []


def default_weights() -> Weights:
    if not _WEIGHTS:
        _WEIGHTS.append(fit(labelled_pages()))
    return _WEIGHTS[0]


def _container(items: list, begin: int, end: int) -> Element | None:
    """The innermost article or main element around all kept words of a run."""
    around: Element | None = None
    for _, add, here, kept in items[begin:end]:
        if not kept or add.isspace():
            continue
        if around is None:
            around = here
            continue
        while around.depth > here.depth:
            around = around.parent
        while here.depth > around.depth:
            here = here.parent
        while around is not here:
            around, here = around.parent, here.parent
    while around is not None and around.name not in ("article", "main"):
        around = around.parent
    return around


def _lies_in(here: Element, around: Element) -> bool:
    while here.depth > around.depth:
        here = here.parent
    return here is around


def extract(page: str | None, weights: Weights | None = None) -> str:
    """The main text of one page."""
    weights = weights or default_weights()
    items: list[tuple[float, str, Element, bool]] = []  # score, what it adds to the text, where, whether it adds words
    best, best_from, best_to = 0.0, 0, 0
    running, since, spent = 0.0, 0, 0.0
    for texture, found in blocks(page or ""):
        lift = weights.texture.get(texture, 0.0)
        for kind, value, here in found:
            if kind == "mark":
                continue
            each, kept = weights.word(here)
            if kind == "tag":
                score, words = weights.tag.get(value, -0.3), False
                add = "" if value.strip("/") in INLINE - {"br"} else " "
            else:
                text = html.unescape(value)
                n = len(text.split())
                score, add, words = (each + lift if kept else each) * n, text if kept else " ", kept and n > 0
                if words and (block := here.block()).name in PARAGRAPHS or words and block.name in ("li", "td", "th", "dd", "dt"):
                    if block.parent:
                        block.parent.holds = True
            if kept:
                spent = 0.0
            else:  # left out anyway; else an advert would cut an article in two
                top = here
                while top.parent and not weights.word(top.parent)[1]:
                    top = top.parent
                limit = OWN_COST if top.parent and top.parent.holds else OTHER_COST
                score = -min(-score, max(0.0, limit - spent))
                spent -= score
            items.append((score, add, here, words))
            running += score
            if running > best:
                best, best_from, best_to = running, since, len(items)
            if running <= 0:
                running, since = 0.0, len(items)
    if best_to and (around := _container(items, best_from, best_to)) is not None:
        held = [i for i, (_, _, here, words) in enumerate(items) if words and _lies_in(here, around)]
        best_from, best_to = min(best_from, held[0]), max(best_to, held[-1] + 1)
    return " ".join("".join(add for _, add, _, _ in items[best_from:best_to]).split())


def extract_pages(pages: DataFrame, weights: Weights | None = None) -> DataFrame:
    """page_id, url, text, n_chars of every page."""
    weights = weights or default_weights()
    chosen = weights.tag, weights.near, weights.texture, weights.base

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = Weights(*chosen)
        for whole in batches:
            for batch in slices(whole, "html", 4 << 20):
                texts = [extract(p, own) for p in batch.column(2).to_pylist()]
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array(list(map(len, texts)), pa.int64())], names=["page_id", "url", "text", "n_chars"])

    chosen_columns = pages.select(F.col("page_id").cast("long"), "url", text_or_empty("html").alias("html"))
    return chosen_columns.mapInArrow(run, "page_id long, url string, text string, n_chars long")
