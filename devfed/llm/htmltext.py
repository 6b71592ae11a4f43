r"""Main text of web pages by gradient-boosted trees over DOM nodes.

A tolerant parser builds the element tree (implied end tags, void and raw-text elements, stray
end tags). Trees judge every element by subtree density, link density, attribute tokens, depth,
sibling statistics and what its ancestors are. A bottom-up pass then chooses, for each subtree,
the best of "all of it", "none of it" and "each child as is best for it", so that no kept element
lies in a dropped one. Elements that never hold main text (scripts, styles, forms, head) are dropped
before, with all in them.

Attribute tokens (of class, id, role and itemprop) count by what was learned of them: each is hashed into one of TOKENS
places, a place's weight is the log odds with which training elements with such a token were main text, and
trees see the sum, least and most of an element's and of its ancestors' weights. No word list is given.

The model is trained here, on PAGES generated pages of many layouts (a bounded sample whose
labels are known by construction), and sent to the executors as a few small arrays. The trees see weights that
the other half of the pages gave, as they will with tokens of pages that they don't know.

Text: character references are decoded; white space (space, \t, \n, \v, \f, \r) inside a block
becomes one space; blocks are trimmed, empty ones left out, and joined by one \n. Block elements
begin and end blocks; <br> is white space. Defined results: a null or empty page, and one
without main text, gives an empty text; repeated rows are handled one by one; an empty table
gives an empty result; only the named columns are read. U+00A0 and other white space beyond ASCII stays as it is. Time grows with a
page's length, however deep its elements lie. Memory is bounded by a batch of rows and the longest page.
"""

from __future__ import annotations

import functools
import html as entities
import random
import re
import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import gbt

#: Generated pages for training; a bound of the labelled sample.
PAGES, SEED, TREES = 1000, 7, 40
#: Weight of an element's own verdict beside that of its texts (1 each).
CONTAINER = 0.05

# fixed values: elements of HTML by how they are parsed or shown
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript iframe noembed noframes xmp".split())
NEVER = frozenset("head script style noscript template iframe object svg math form button select textarea input option dialog title link meta noembed noframes xmp canvas audio video".split())
BLOCKS = frozenset("address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hgroup hr html legend li main menu nav ol optgroup option p pre section summary table tbody td tfoot th thead tr ul".split())
#: An open p ends where one of these begins.
ENDS_P = BLOCKS - frozenset("caption legend optgroup option summary tbody td tfoot th thead tr html head body".split())
#: An open element of the value's kinds ends where one of the key begins, up to the nearest list or table.
ENDS = {"li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"), "option": ("option",), "thead": ("tr", "td", "th"), "tbody": ("thead", "tbody", "tr", "td", "th"), "tfoot": ("tbody", "tr", "td", "th")}
SCOPES = frozenset("ul ol dl table select div article section main body html aside nav footer header td th".split())

#: Places that attribute tokens are hashed into, and what a place's counts are shrunk by.
TOKENS, SHRINK = 8192, 4.0

_TAG = re.compile(r"""<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>"']++|"[^"]*"|'[^']*'|["'])*+)(?:>|\Z)""", re.S)
_ATTRIBUTE = re.compile(r"""\b(?:class|id|role|itemprop)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+))""", re.I)
_TOKEN = re.compile(r"[a-z]+")
_SPACE = re.compile(r"[ \t\n\x0b\f\r]+")
_PUNCTUATION = re.compile(r"[.,;:!?。，]")

TAGS = ("p", "div", "article", "main", "section", "nav", "aside", "header", "footer", "ul", "li", "a", "h1", "h2", "td", "body", "blockquote", "pre", "figure")
BAD_TAGS, GOOD_TAGS = frozenset(("nav", "aside", "header", "footer", "menu")), frozenset(("article", "main"))


class Page:
    """The element tree of a page in preorder; element 0 is a root above all. parts: (element, text) pieces and (element, None) borders, in order."""

    def __init__(self, source: str) -> None:
        self.tag, self.parent, self.attributes = ["#root"], [-1], [""]
        self.parts: list[tuple[int, str | None]] = []
        self.open: Counter[str] = Counter()
        stack, at, n = [0], 0, len(source)
        while at < n:
            found = _TAG.search(source, at)
            if found is None:
                self._text(stack[-1], source[at:])
                break
            if found.start() > at:
                self._text(stack[-1], source[at : found.start()])
            at, name = found.end(), found[2]
            if name is None:
                if found[0].startswith("<![CDATA["):
                    self._text(stack[-1], found[0][9:].removesuffix("]]>"), False)
                continue
            name = name.lower()
            if found[1]:
                self._end(stack, name)
                continue
            self._implied(stack, name)
            node = len(self.tag)
            self.tag.append(name)
            self.parent.append(stack[-1])
            self.attributes.append(found[3])
            if name in BLOCKS:
                self.parts.append((node, None))
            elif name == "br":
                self.parts.append((stack[-1], " "))
            if name in RAW:
                close = re.compile(rf"</{name}[\s/>]", re.I).search(source, at)
                end = close.start() if close else n
                if name in ("title", "textarea"):
                    self._text(node, source[at:end])
                at = source.find(">", end) + 1 if close else n
                at = at or n
            elif name not in VOID:
                stack.append(node)
                self.open[name] += 1

    def _text(self, node: int, raw: str, decode: bool = True) -> None:
        self.parts.append((node, entities.unescape(raw) if decode and "&" in raw else raw))

    def _end(self, stack: list[int], name: str) -> None:
        if not self.open[name]:
            return
        for k in range(len(stack) - 1, 0, -1):
            own = self.tag[stack[k]]
            if own == name:
                self._close(stack, k)
                return
            # an inline end tag doesn't reach over a block
            if name not in BLOCKS and own in BLOCKS:
                return

    def _close(self, stack: list[int], k: int) -> None:
        while len(stack) > k:
            node = stack.pop()
            self.open[self.tag[node]] -= 1
            if self.tag[node] in BLOCKS:
                self.parts.append((stack[-1], None))

    def _implied(self, stack: list[int], name: str) -> None:
        if name in ENDS_P and self.open["p"]:
            for k in range(len(stack) - 1, 0, -1):
                own = self.tag[stack[k]]
                if own == "p":
                    self._close(stack, k)
                    break
                if own in BLOCKS:
                    break
        for kind in ENDS.get(name, ()):
            if not self.open[kind]:
                continue
            for k in range(len(stack) - 1, 0, -1):
                own = self.tag[stack[k]]
                if own == kind:
                    self._close(stack, k)
                    break
                if own in SCOPES and own not in ENDS[name]:
                    break

    def tokens(self) -> list[tuple[int, list[int]]]:
        """(element, the places of its attributes' distinct tokens) of the elements that have any."""
        out = []
        for i, text in enumerate(self.attributes):
            if "=" in text:
                found = {t for a in _ATTRIBUTE.findall(text) for t in _TOKEN.findall("".join(a).lower())}
                if found:
                    out.append((i, [place_of(t) for t in found]))
        return out

    def features(self, weights: np.ndarray) -> np.ndarray:
        """A row for each element."""
        n = len(self.tag)
        parent = np.array(self.parent)
        own_text, own_stops, own_words = np.zeros(n), np.zeros(n), np.zeros(n)
        for node, text in self.parts:
            if text:
                own_text[node] += len(text.strip())
                own_stops[node] += len(_PUNCTUATION.findall(text))
                own_words[node] += text.count(" ") + 1
        depth, in_link = np.zeros(n), np.zeros(n, bool)
        # sum, least and most of the element's tokens
        token = np.zeros((3, n))
        for i, places in self.tokens():
            own = weights[places]
            token[:, i] = own.sum(), min(own.min(), 0.0), max(own.max(), 0.0)
        tag_good, tag_bad = np.array([t in GOOD_TAGS for t in self.tag], float), np.array([t in BAD_TAGS for t in self.tag], float)
        above = np.zeros((4, n))
        for i, tag in enumerate(self.tag):
            up = self.parent[i]
            in_link[i] = tag == "a"
            if up >= 0:
                depth[i] = depth[up] + 1
                in_link[i] |= in_link[up]
                above[0, i] = min(above[0, up], token[1, up])
                above[1:, i] = np.maximum(above[1:, up], (token[2, up], tag_good[up], tag_bad[up]))
        sums = np.stack([own_text, np.where(in_link, own_text, 0), own_stops, own_words, np.ones(n), np.array([t == "p" for t in self.tag], float), np.array([t == "a" for t in self.tag], float)])
        children, place = np.zeros(n), np.zeros(n)
        for i in range(1, n):
            place[i] = children[parent[i]]
            children[parent[i]] += 1
        for i in range(n - 1, 0, -1):
            sums[:, parent[i]] += sums[:, i]
        text, link, stops, words, nodes, paragraphs, anchors = sums
        up = np.maximum(parent, 0)
        kind = np.stack([np.array([t == k for t in self.tag], float) for k in TAGS])
        return np.column_stack([
            kind.T, np.log1p(text), np.log1p(own_text), link / np.maximum(text, 1), text / nodes, stops / np.maximum(words, 1), text / np.maximum(words, 1), np.log1p(paragraphs), np.log1p(anchors), depth, children,
            place / np.maximum(children[up], 1), children[up], text / np.maximum(text[up], 1), link[up] / np.maximum(text[up], 1), text / max(text[0], 1), token.T, above.T,
        ])

    def keep(self, margin: np.ndarray) -> np.ndarray:
        """Flags of the kept elements: of every subtree all, none, or what is best for each child."""
        n = len(self.tag)
        never = np.zeros(n, bool)
        for i, tag in enumerate(self.tag):
            never[i] = tag in NEVER or (i > 0 and never[self.parent[i]])
        margin = np.where(never, -1e6, np.clip(margin, -6, 6))
        weight = np.full(n, CONTAINER)
        for node, text in self.parts:
            if text and text.strip():
                weight[node] += 1
        # log odds of keeping as against dropping; dropping is the zero
        every, best = margin * weight, np.zeros(n)
        mixed = np.zeros(n)
        for i in range(n - 1, -1, -1):
            mixed[i] = max(margin[i] * (weight[i] - CONTAINER), 0.0) + mixed[i]
            best[i] = max(every[i], 0.0, mixed[i])
            if i:
                every[self.parent[i]] += every[i]
                mixed[self.parent[i]] += best[i]
        out, chosen = np.zeros(n, bool), np.zeros(n, np.int8)
        for i in range(n):
            up = self.parent[i]
            state = chosen[up] if i else 2
            if state == 2:
                state = 1 if every[i] > 0 and every[i] >= mixed[i] else 2 if mixed[i] > 0 else 0
            chosen[i] = state
            out[i] = state == 1 or (state == 2 and margin[i] > 0)
        return out & ~never

    def text(self, kept: np.ndarray) -> str:
        blocks, now = [], []
        for node, text in [*self.parts, (0, None)]:
            if text is None:
                if now and (block := _SPACE.sub(" ", "".join(now)).strip(" ")):
                    blocks.append(block)
                now = []
            elif kept[node]:
                now.append(text)
        return "\n".join(blocks)


@functools.lru_cache(maxsize=1 << 16)
def place_of(token: str) -> int:
    return zlib.crc32(token.encode()) % TOKENS


@dataclass
class Model:
    """Boosted trees and the learned weights of attribute tokens."""

    trees: gbt.Trees
    tokens: np.ndarray

    def margins(self, pages: list[Page]) -> list[np.ndarray]:
        rows = [p.features(self.tokens) for p in pages]
        return np.split(self.trees.margin(np.concatenate(rows)), np.cumsum([len(x) for x in rows])[:-1]) if rows else []


def token_weights(pages: list[Page], labels: list[np.ndarray]) -> np.ndarray:
    """Log odds of main text given a token's place, less those of all elements with tokens; 0 where none was seen."""
    counts = np.zeros((2, TOKENS))
    for page, y in zip(pages, labels, strict=True):
        for i, places in page.tokens():
            counts[int(y[i]), places] += 1
    share = (counts[1].sum() + 1) / (counts.sum() + 2)
    return np.log((counts[1] + SHRINK * share) / (counts[0] + SHRINK * (1 - share))) - np.log(share / (1 - share))


def _words(r: random.Random, n: int) -> str:
    out = []
    while len(out) < n:
        k = r.randint(3, 14)
        words = ["".join(r.choice(("ka", "ten", "or", "el", "mi", "sho", "ver", "u", "and", "the", "re", "in", "lo")) for _ in range(r.randint(1, 4))) for _ in range(k)]
        out += [words[0].capitalize(), *words[1:-1], words[-1] + r.choice(".,..!?")]
    return " ".join(out[: max(n, 1)])


#: What authors call the parts of pages, for generated ones.
NAMES = {
    "menu": "menu nav navbar navigation topnav breadcrumb breadcrumbs crumbs links subnav".split(),
    "side": "sidebar side widget rail related recommended trending more-stories promo-box secondary".split(),
    "ad": "ad ads advert advertisement banner promo sponsored sponsor adslot dfp outbrain".split(),
    "notice": "cookie cookie-notice consent notice alert newsletter signup popup modal share social toast gdpr".split(),
    "comments": "comments comment-list replies respond discussion thread disqus reactions feedback".split(),
    "tags": "tags meta pagination pager byline-links categories filed".split(),
    "head": "header top masthead branding site-header logo".split(),
    "foot": "footer bottom colophon copyright site-footer legal".split(),
    "main": "content article post entry story body main text prose article-body post-content entry-content blog page-content copy".split(),
    "any": "wrapper container row inner box col-8 clearfix wrap block section-1 js-x grid u-mt l-page module".split(),
}


def generate(seed: int) -> tuple[str, list[str]]:
    """A page of a random layout, and its main blocks (marked by construction). Words are invented."""
    r = random.Random(seed)
    some = lambda low, high: _words(r, r.randint(low, high))

    def named(kind: str, always: bool = False) -> str:
        """A class or id for a part of the page, among others that say nothing."""
        if not always and r.random() < 0.25:
            return ""
        own = [r.choice(NAMES[kind])] + [r.choice(NAMES["any"]) for _ in range(r.choice((0, 0, 1, 2)))]
        if r.random() < 0.2:
            own.append("c" + "".join(r.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(5)))
        r.shuffle(own)
        return f' {r.choice(("class", "class", "id"))}="{" ".join(own)}"'

    link = lambda: f'<a href="/{r.randint(1, 999)}">{some(1, 3)}</a>'
    links = lambda: "<ul>" + "".join(f"<li>{link()}</li>" for _ in range(r.randint(2, 9))) + "</ul>"
    main: list[str] = []

    def paragraph() -> str:
        text, tag = some(1, r.choice((4, 12, 40, 160))), r.choice(("p", "p", "p", "p", "p", "h2", "li", "blockquote", "div", "pre"))
        main.append(text)
        shown = text if r.random() < 0.8 else r.choice((f"<b>{text}</b>", f'<a href="/x">{text}</a>', f"<em>{text}</em>", f"<span{named('any')}>{text}</span>", f"<strong><i>{text}</strong>"))
        return f"<ul><li>{shown}</li></ul>" if tag == "li" else f"<{tag}>{shown}" + (f"</{tag}>" if tag != "p" or r.random() < 0.8 else "")

    def furniture() -> str:
        kind = r.randrange(9)
        if kind == 0:
            return r.choice((f"<nav{named('menu')}>{links()}</nav>", f"<div{named('menu')}>{links()}</div>", f'<div role="navigation">{link()} {link()}</div>'))
        if kind == 1:
            return f"<aside{named('side')}>{r.choice((links(), f'<p>{some(5, 60)}</p>', f'<h3>{some(1, 3)}</h3>{links()}'))}</aside>"
        if kind == 2:
            return f"<{(tag := r.choice(('div', 'section')))}{named('ad', True)}>{r.choice((some(3, 30), f'<p>{some(3, 30)}</p>', f'<a href=/x>{some(2, 8)}</a>'))}</{tag}>"
        if kind == 3:
            return f"<div{named('notice', True)}><p>{some(4, 30)}</p></div>"
        if kind == 4:
            return f"<form{named('notice')}><label>{some(1, 3)}</label><input type=text><button>{some(1, 2)}</button></form>"
        if kind == 5:
            return f"<{(tag := r.choice(('div', 'section', 'ol')))}{named('comments', True)}><h3>{some(1, 3)}</h3>" + "".join(f"<div{named('comments')}><p>{some(3, 60)}</p></div>" for _ in range(r.randint(1, 6))) + f"</{tag}>"
        if kind == 6:
            return f"<div{named('side', True)}><p>{some(3, 40)}</p>{links()}</div>"
        if kind == 7:
            return f"<script>var a = '{some(3, 9)}';</script>"
        return f"<p{named('tags')}>{link()} | {link()} | {link()}</p>"

    def around(n: int) -> str:
        return "".join(furniture() for _ in range(r.randint(0, n)))

    head = r.choice(("", f"<header{named('head')}><h1>{some(1, 4)}</h1>{links()}</header>", f"<nav>{links()}</nav>", f"<div{named('head', True)}>{link()} {link()}</div>"))
    foot = r.choice(("", f"<footer{named('foot')}>&copy; {some(2, 30)}</footer>", f"<div{named('foot', True)}><p>{some(3, 20)}</p>{links()}</div>"))
    before, after = around(3), around(3)
    title = some(1, 12)
    body = ""
    if r.random() < 0.7:
        main.append(title)
        body = f"<h1>{title}</h1>"
    inside = [paragraph() for _ in range(r.choice((1, 2, 4, 8, 15, 30)))]
    if r.random() < 0.25:
        inside.insert(r.randrange(len(inside) + 1), furniture())
    body += "".join(inside)
    box = r.choice(("<article>{}</article>", "<article{n}>{}</article>", "<main>{}</main>", "<main{n}><article>{}</article></main>", "<div{a}>{}</div>", "<div{a}><div{n}>{}</div></div>", "<section{a}>{}</section>", "<div{a}><div>{}</div></div>"))
    body = box.replace("{n}", named("main")).replace("{a}", named("main", True)).replace("{}", body)
    if r.random() < 0.1 and not after:
        # an end tag that is missing
        body = body[: body.rindex("</")]
    if r.random() < 0.3:
        body = f"<div{named('any', True)}>{body}{around(1)}</div>"
    sheet = r.choice(("", f"<style>.{r.choice(NAMES['main'])}{{color:#{r.randint(100, 999)}}}</style>"))
    return f"{r.choice(('<!DOCTYPE html>', ''))}<html><head><title>{title}</title>{sheet}</head><body>{head}{before}{body}{after}{foot}{r.choice(('</body></html>', ''))}", main


def labelled(page: Page, main: list[str]) -> np.ndarray:
    """1 for the elements whose whole text is main text (each main block is taken once, in order)."""
    n, own = len(page.tag), {}
    for node, text in page.parts:
        if text and text.strip():
            own.setdefault(node, []).append(text)
    wanted = {" ".join(m.split()) for m in main}
    yes, no = np.zeros(n), np.zeros(n)
    for node, texts in own.items():
        hit = " ".join("".join(texts).split()) in wanted and page.tag[node] not in NEVER
        above = node
        while hit and above > 0:
            hit, above = page.tag[above] not in NEVER, page.parent[above]
        (yes if hit else no)[node] += 1
    for i in range(n - 1, 0, -1):
        yes[page.parent[i]] += yes[i]
        no[page.parent[i]] += no[i]
    return (yes > no).astype(float)


@functools.lru_cache(maxsize=2)
def model(pages: int = PAGES, seed: int = SEED) -> Model:
    """Trained on generated pages; the same every time."""
    made = [generate(seed * 100_003 + k) for k in range(pages)]
    read = [Page(source) for source, _ in made]
    labels = [labelled(p, main) for p, (_, main) in zip(read, made, strict=True)]
    # each half is seen with the tokens' weights of the other
    halves = [token_weights(read[1 - k :: 2], labels[1 - k :: 2]) for k in (0, 1)]
    x = [p.features(halves[k % 2]) for k, p in enumerate(read)]
    return Model(gbt.train(np.concatenate(x), np.concatenate(labels), trees=TREES), token_weights(read, labels))


def main_text(source: str, fitted: Model) -> str:
    page = Page(source)
    return page.text(page.keep(fitted.margins([page])[0]))


def extract(pages: DataFrame, id_col: str = "page_id", html_col: str = "html", carry: tuple[str, ...] = ("url",), fitted: Model | None = None) -> DataFrame:
    """One row per row of ``pages``: the id, the carried columns, ``text`` and ``n_chars``. No shuffle."""
    source = pages.select(F.col(f"`{id_col}`").alias("id"), F.col(f"`{html_col}`").cast("string").alias("html"), *(F.col(f"`{c}`").alias(f"c{k}") for k, c in enumerate(carry)))
    fitted = fitted or model()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in (batch.slice(i, 200) for i in range(0, len(batch), 200)):
                read = [Page(x or "") for x in part.column(1).to_pylist()]
                texts = [p.text(p.keep(m)) for p, m in zip(read, fitted.margins(read), strict=True)]
                yield pa.RecordBatch.from_arrays([part.column(0), *part.columns[2:], pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], [id_col, *carry, "text", "n_chars"])

    kinds = [f"`{c}` {source.schema[f'c{k}'].dataType.simpleString()}" for k, c in enumerate(carry)]
    return source.mapInArrow(run, ", ".join([f"`{id_col}` {source.schema['id'].dataType.simpleString()}", *kinds, "text string", "n_chars long"]))
