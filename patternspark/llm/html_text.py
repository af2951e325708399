"""Main text of web pages by tag-path ratios.

A page becomes its text blocks with their root-to-leaf tag paths; what the markup itself says is no article (menus,
footers, asides, forms, dialogs, scripts, styles, hidden parts; by element or role) has no blocks. Each path gathers
text length, punctuation and number of blocks. Two ratios per path (text per block, punctuation per block) are laid
along the page's blocks, smoothed and fused by their product with a prior of its class names, which is nought for names
of boilerplate (adverts, notices, comments, sharing). Paths at or above a share of the page's mean score, weighted by
length, are content; their blocks name the content nodes: the article or main element around them, elsewhere the deepest
element that holds all of them and the headings right before them. The nodes' blocks are the result, short ones
included, but for those of no score at all.
"""

from __future__ import annotations

import html as entities
import os.path
import re
from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import quoted, slices

_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?\]\]>|<[!?][^>]*>|</([a-zA-Z][^\s/>]*)[^>]*>|<([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)>", re.S)
_ATTR = re.compile(r"([^\s=/>\"']+)(?:\s*=\s*(\"[^\"]*\"|'[^']*'|[^\s>]+))?")
# Fixed values of the HTML standard.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title xmp iframe noembed noframes plaintext".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark nobr q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split())
SPACE = frozenset(["br"])
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
# Elements that are a part of a text and not the whole of it.
PARTS = HEADINGS | frozenset("p li ul ol dl dt dd table thead tbody tfoot tr blockquote pre section figure hgroup".split())
# A start tag (key) ends an open element (values) of the same parent when the end tag was left out.
CLOSES = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}, "body": {"head"}}
ENDS_P = frozenset("address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre search section table ul".split())
BOUNDS = frozenset("ul ol dl table div section article main body aside nav header footer form td th".split())
# Boilerplate by element, by role, and by whole words of class or id.
DROP = frozenset("head title script style noscript template iframe object embed svg canvas audio video nav aside footer form button select option optgroup textarea input fieldset legend dialog menu search noembed noframes datalist map".split())
ROLES = frozenset("navigation banner contentinfo complementary search form dialog alertdialog alert menu menubar toolbar tablist".split())
CUES = frozenset(
    """ad ads adv advert adverts advertisement advertising adsense adslot adbox banner banners sponsor sponsored sponsors promo promos promoted promotion
    nav navbar navigation navi menu menus submenu breadcrumb breadcrumbs topbar toolbar pager pagination toc skip skiplink header masthead footer colophon
    sidebar sidebars sidenav aside rail widget widgets cookie cookies consent gdpr notice notices notification alert popup modal overlay lightbox paywall
    newsletter subscribe subscription signup login signin search searchbox form comment comments commentlist reply replies respond disqus discussion feedback
    share sharing social follow related recommended recommendations trending popular tags""".split()
)
COMMENT_CUES = frozenset("comment comments commentlist reply replies respond disqus discussion".split())
KEEPERS = frozenset("html body main article".split())
#: A class that only says what a layout has beside its content, and words that make a header the article's own.
BESIDE = frozenset("with has no without".split())
OWN = frozenset("article post entry content story body main text page-title title headline".split())
_WORDS = re.compile(r"[A-Z]?[a-z]+|[A-Z]+|\d+")
_PUNCT = re.compile(r"[.,;:!?…、。，¿¡]")
_HIDDEN = re.compile(r"display\s*:\s*none|visibility\s*:\s*hidden", re.I)


def _attrs(raw: str) -> dict[str, str]:
    return {k.lower(): entities.unescape(v.strip("\"'")) for k, v in reversed(_ATTR.findall(raw))} if raw and not raw.isspace() else {}


def _cued(names: str) -> set[str]:
    """Cue words among class and id names."""
    out = set()
    for name in names.split():
        words = {w.lower() for w in _WORDS.findall(name)} | {w for w in name.lower().split("_") if w}
        if words & BESIDE:
            continue
        found = words & CUES
        out |= found - {"header"} if words & OWN else found
    return out


def _dropped(tag: str, a: dict[str, str], inside_content: bool) -> bool:
    """Whether the markup says that an element is no part of the article."""
    if tag in DROP or tag == "header" and not inside_content:
        return True
    return bool(a) and ("hidden" in a or a.get("aria-hidden") == "true" or a.get("role", "").lower() in ROLES or bool(_HIDDEN.search(a.get("style", ""))))


def _named(tag: str, a: dict[str, str]) -> bool:
    """Whether an element's class or id names boilerplate."""
    if not ("class" in a or "id" in a):
        return False
    found = _cued(f"{a.get('class', '')} {a.get('id', '')}")
    return tag == "article" and bool(found & COMMENT_CUES) if tag in KEEPERS else bool(found)


@dataclass(frozen=True)
class Block:
    """``nodes``: element numbers from the root, ``path``: their tags; ``named``: some class or id says boilerplate."""

    nodes: tuple[int, ...]
    path: str
    text: str
    named: bool


def blocks(page: str) -> list[Block]:
    """Blocks of text in page order."""
    out: list[Block] = []
    stack: list[tuple[str, int, bool, bool, bool]] = []  # tag, number, dropped, inside article or main, named
    text: list[str] = []
    at, count, owner = 0, 0, ()

    def flush() -> None:
        if text:
            if joined := " ".join(entities.unescape("".join(text)).split()):
                out.append(Block(tuple(n for _, n, _ in owner), "/".join(t for t, *_ in owner), joined, any(x for *_, x in owner)))
            text.clear()

    def said(piece: str) -> None:
        nonlocal owner
        if piece and not (stack and stack[-1][2]):
            if not text:
                owner = tuple((t, n, x) for t, n, *_, x in stack if t not in INLINE)
            text.append(piece)

    def close(k: int) -> None:
        if any(t not in INLINE for t, *_ in stack[k:]):
            flush()
        del stack[k:]

    pos = 0
    while m := _TOKEN.search(page, pos):
        said(page[pos:m.start()])
        pos = m.end()
        if name := m[1]:
            name = name.lower()
            for k in range(len(stack) - 1, -1, -1):
                if stack[k][0] == name:
                    close(k)
                    break
                if name in INLINE and stack[k][0] not in INLINE:
                    break
            else:
                if name in ("p", "br"):
                    flush()
        elif name := m[2]:
            name, raw = name.lower(), m[3] or ""
            if name in SPACE:
                said(" ")
                continue
            gone = bool(stack and stack[-1][2])
            if name not in INLINE:
                if name in ENDS_P or name in CLOSES:
                    for k in range(len(stack) - 1, -1, -1):
                        t = stack[k][0]
                        if t in CLOSES.get(name, ()) or (t == "p" and name in ENDS_P):
                            close(k)
                            if name != "tr":
                                break
                        elif t in BOUNDS:
                            break
                flush()
                gone = bool(stack and stack[-1][2])
            if name in VOID or (raw.endswith("/") and name in ("svg", "path", "use", "rect", "circle")):
                if name in ("hr", "img"):
                    said(" ")
                continue
            count += 1
            inside = bool(stack and stack[-1][3]) or name in ("article", "main")
            a = {} if gone else _attrs(raw)
            drop = gone or _dropped(name, a, bool(stack and stack[-1][3])) or name in INLINE and _named(name, a)
            if drop and not gone:
                flush() if name not in INLINE else None
            stack.append((name, count, drop, inside, not drop and _named(name, a)))
            if name in RAW:
                end = re.compile(rf"</{name}(?=[\s/>])[^>]*>", re.I).search(page, pos)
                said(page[pos:end.start() if end else len(page)])
                pos = end.end() if end else len(page)
                close(len(stack) - 1)
    said(page[pos:])
    flush()
    return out


def path_scores(found: list[Block], radius: int = 1, names: bool = True) -> np.ndarray:
    """Fused, smoothed path ratios along the blocks; ``names``: with the prior of class names."""
    chars, marks, number = defaultdict(int), defaultdict(int), defaultdict(int)
    named = np.array([names and b.named for b in found])
    keys = [(b.path, x) for b, x in zip(found, named.tolist())]
    for key, b in zip(keys, found):
        chars[key] += len(b.text)
        marks[key] += len(_PUNCT.findall(b.text))
        number[key] += 1
    ratio = np.array([chars[k] / number[k] for k in keys])
    punct = np.array([(1 + marks[k]) / number[k] for k in keys])
    weight = np.exp(-0.5 * (np.arange(-radius, radius + 1) / max(radius, 1)) ** 2)
    weight /= weight.sum()
    smooth = lambda x: np.convolve(np.pad(x, radius, mode="edge"), weight, mode="valid")
    return np.where(named, 0.0, smooth(ratio) * smooth(punct))


def _content_node(b: Block) -> tuple[int, ...]:
    """Numbers down to the outermost article around a block, else main; empty without either."""
    tags = b.path.split("/")
    for name in ("article", "main"):
        if name in tags:
            return b.nodes[:tags.index(name) + 1]
    return ()


def main_text(page: str | None, *, share: float = 0.8, names: bool = True, scores=path_scores) -> str:
    """The page's article; empty if there is none.

    ``share``: paths are content from this share of the score on that an average character of the page has. ``names``: whether class and id
    names take part. ``scores`` is for ablations.
    """
    if not page or not (found := blocks(page)):
        return ""
    homes = [_content_node(b) for b in found]
    if names and any(homes) and all(b.named for b, h in zip(found, homes) if h):
        names = False  # a name above the article was misread: go by elements, roles and ratios alone
    value = scores(found, names=names)
    if not value.any():
        return ""
    chars = np.array([len(b.text) for b in found])
    picked = np.flatnonzero((value > 0) & (value >= share * float((value * chars).sum() / chars[value > 0].sum()) - 1e-9)).tolist()
    nodes = {homes[i] for i in picked if homes[i]}
    if nodes:
        keep = {i for i, h in enumerate(homes) if h in nodes and value[i] > 0} | set(picked)
        for i in sorted(keep):  # the headings that main has right before its article
            while i and i - 1 not in keep and value[i - 1] > 0 and homes[i - 1] and homes[i][:len(homes[i - 1])] == homes[i - 1] and found[i - 1].path.rsplit("/", 1)[-1] in HEADINGS:
                i -= 1
                keep.add(i)
        return " ".join(found[i].text for i in sorted(keep))
    region, tags = os.path.commonprefix([found[i].nodes for i in picked]), found[picked[0]].path.split("/")
    while True:
        while region and tags[len(region) - 1] in PARTS:  # what is said beside a part belongs to it
            region = region[:-1]
        first = next(i for i, b in enumerate(found) if b.nodes[:len(region)] == region)
        if not (first and value[first - 1] > 0 and found[first - 1].path.rsplit("/", 1)[-1] in HEADINGS):
            break
        region = os.path.commonprefix([region, found[first - 1].nodes])
    return " ".join(b.text for b, v in zip(found, value) if v > 0 and b.nodes[:len(region)] == region)


def extract(pages: DataFrame, *, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """``id, url, text, n_chars`` of every page.

    Null html counts as empty; broken markup is read as browsers do where that is simple (paragraphs and list items
    end by themselves, unknown tags are blocks). Pages are read whole; repeated rows give repeated results; other
    columns are ignored; an empty table gives an empty result.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in (part for whole in batches for part in slices(whole, 2)):
            texts = [main_text(x) for x in b.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["id", "url", "text", "n_chars"])

    kinds = dict(pages.dtypes)
    return pages.select(quoted(id_col).alias("id"), quoted(url_col).alias("url"), quoted(html_col).alias("html")).mapInArrow(run, f"id {kinds[id_col]}, url {kinds[url_col]}, text string, n_chars long")
