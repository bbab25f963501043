"""Main text of web pages by inference on the DOM tree.

Every node of the tree is content or not. What is seen of a node (tag, words of
class and id, size and shape of its text) depends on its own state, and its state
on its parent's: a tree-structured graphical model. Both tables of probabilities
are counted from labelled pages. Messages are passed once from the leaves to the
root and once back, which gives each text leaf its exact marginal probability of
being content; leaves above one half are the main text.

White space inside a block becomes one space, blocks are joined by line ends in
page order. Null and empty pages have an empty text. Pages that end early, leave
elements open or close what was never opened are read as far as they go; nesting
of any depth is walked without recursion, and pages of any length are read whole. Rows
are extracted one by one, repeated ids and rows without one included; a leaf at the
threshold itself is text. An empty table gives an empty result. Columns of other names
play no part.

Only scripts and styles are left out for what they are; whatever else a page holds is
judged by the model. It is trained on pages made by rule (`varied_page`): layouts with
and without frame elements, named or not, tables as layout, pages without any frame,
and blocks of every kind inside and outside the article.
"""

from __future__ import annotations

import html
import math
import random
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tplforge.llm.common import byte_slices

# Element names of the markup language by role.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style".split())
#: what these hold is characters and no markup
PLAIN = frozenset("title textarea".split())
BLOCK = frozenset(
    "address article aside blockquote body caption center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hr html legend li main menu nav ol p pre section summary table tbody td tfoot th thead title tr ul".split()
)
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
#: a start tag of the key closes an open element of the values
CLOSES = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}, "body": {"head"}}
SCOPES = frozenset("ul ol dl table tbody thead tfoot select html body div article section main aside nav footer header form td th li blockquote".split())

_TAG = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[(.*?)(?:\]\]>|\Z)|<[!?][^>]*>?|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)>", re.S)
_NAMED = re.compile(r"\b(class|id|role|hidden|data-label)\b(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?", re.I)
_WORDS = re.compile(r"[A-Z]?[a-z]+|[A-Z]+")
_CLOSE = {tag: re.compile(rf"</{tag}[\s/>][^>]*>?|</{tag}>", re.I) for tag in RAW | PLAIN}
_ENDS = re.compile(r"[.!?:;…]['\")\]]*$")


@dataclass
class Tree:
    """Nodes in page order: parent, tag ('' for text), seen features, text, label."""

    parent: list[int] = field(default_factory=list)
    tag: list[str] = field(default_factory=list)
    seen: list[tuple[str, ...]] = field(default_factory=list)
    text: list[str | None] = field(default_factory=list)
    label: list[int | None] = field(default_factory=list)

    def add(self, parent: int, tag: str, seen: tuple[str, ...], text: str | None, label: int | None) -> int:
        for held, x in zip((self.parent, self.tag, self.seen, self.text, self.label), (parent, tag, seen, text, label), strict=True):
            held.append(x)
        return len(self.tag) - 1


def _attributes(raw: str) -> tuple[tuple[str, ...], int | None]:
    if not raw or raw.isspace():
        return (), None
    words, label = [], None
    for m in _NAMED.finditer(raw):
        name, value = m[1].lower(), m[2] or m[3] or m[4] or ""
        if name == "data-label":
            label = int(value == "1")
        elif name == "hidden":
            words.append("attr:hidden")
        else:
            words += [f"name:{w.lower()}" for w in _WORDS.findall(value)]
    return tuple(dict.fromkeys(words)), label


def _text_features(text: str, inside: list[str]) -> tuple[str, ...]:
    n = len(text.split())
    out = ["text:" + ("0" if not n else "1" if n < 2 else "few" if n < 6 else "some" if n < 15 else "many")]
    if n:
        out.append("ends" if _ENDS.search(text.rstrip()) else "open")
    if "a" in inside:
        out.append("in:a")
    return tuple(out)


def parse(page: str) -> Tree:
    t = Tree()
    root = t.add(-1, "#root", (), None, None)
    stack, at, n = [root], 0, len(page)

    def text(raw: str) -> None:
        if raw:
            raw = html.unescape(raw)
            t.add(stack[-1], "", (f"tag:{t.tag[stack[-1]]}>#text", *_text_features(raw, [t.tag[i] for i in stack[-4:]])), raw, None)

    while at < n:
        lt = page.find("<", at)
        if lt < 0:
            text(page[at:])
            break
        m = _TAG.match(page, lt)
        if not m:
            # a bare '<' is text
            nxt = page.find("<", lt + 1)
            nxt = n if nxt < 0 else nxt
            text(page[at:nxt])
            at = nxt
            continue
        text(page[at:lt])
        at = m.end()
        if m[1] is not None:
            text(m[1])
        if not m[3]:
            continue
        tag = m[3].lower()
        if m[2]:
            for i in range(len(stack) - 1, 0, -1):
                if t.tag[stack[i]] == tag:
                    del stack[i:]
                    break
                if t.tag[stack[i]] in ("td", "table") and tag not in BLOCK:
                    break
            continue
        if tag in BLOCK and t.tag[stack[-1]] != "#root":
            # block elements end an open paragraph, with whatever inline elements it has left open
            for i in range(len(stack) - 1, 0, -1):
                if t.tag[stack[i]] == "p":
                    del stack[i:]
                    break
                if t.tag[stack[i]] in BLOCK:
                    break
        if ends := CLOSES.get(tag):
            for i in range(len(stack) - 1, 0, -1):
                if t.tag[stack[i]] in ends:
                    del stack[i:]
                    break
                if t.tag[stack[i]] in SCOPES:
                    break
        words, label = _attributes(m[4])
        node = t.add(stack[-1], tag, (f"tag:{t.tag[stack[-1]]}>{tag}", *words), None, label)
        if tag in RAW or tag in PLAIN:
            close = _CLOSE[tag].search(page, at)
            if tag in PLAIN:
                stack.append(node)
                text(page[at : close.start() if close else n])
                stack.pop()
            else:
                t.add(node, "#raw", (f"tag:{tag}>#raw",), None, 0)
            at = close.end() if close else n
        elif tag not in VOID and not m[4].endswith("/"):
            stack.append(node)
    _shapes(t)
    return t


def _shapes(t: Tree) -> None:
    """Adds to what is seen of block elements how many words they hold and what share of them is in links."""
    n = len(t.tag)
    words, linked = [0] * n, [0] * n
    for i in range(n - 1, 0, -1):
        if not t.tag[i]:
            words[i] = len(t.text[i].split())
        elif t.tag[i] == "a":
            linked[i] = words[i]
        p = t.parent[i]
        words[p] += words[i]
        linked[p] += linked[i]
    for i in range(n):
        if t.tag[i] in BLOCK and t.tag[i] not in ("html", "body", "head"):
            w = words[i]
            size = "none" if not w else "few" if w < 8 else "some" if w < 40 else "many"
            links = "no" if not linked[i] else "little" if 4 * linked[i] < w else "much" if 10 * linked[i] < 9 * w else "all"
            t.seen[i] += (f"words:{size}", f"links:{links}")


@dataclass
class Model:
    """Logarithms: prior of the root, child given parent, feature given state."""

    root: tuple[float, float]
    move: tuple[tuple[float, float], tuple[float, float]]
    feature: dict[str, tuple[float, float]]

    def evidence(self, feature: str) -> tuple[float, float] | None:
        """Logarithms of a feature in either state, if it or its tag alone was met in training."""
        return self.feature.get(feature) or self.feature.get(_alone(feature))

    def marginals(self, t: Tree) -> list[float]:
        """Probability of content of each node, by messages up and down the tree."""
        n = len(t.tag)
        e0, e1 = math.exp(self.root[0]), math.exp(self.root[1])
        (m00, m01), (m10, m11) = ((math.exp(x) for x in row) for row in self.move)
        own0, own1, memo = [0.0] * n, [0.0] * n, {}
        for i, seen in enumerate(t.seen):
            if (u := memo.get(seen)) is None:
                known = [x for f in seen if (x := self.evidence(f)) is not None]
                a, b = sum(k[0] for k in known), sum(k[1] for k in known)
                top = max(a, b)
                u = memo[seen] = (math.exp(a - top), math.exp(b - top))
            own0[i], own1[i] = u
        # up: own holds a node's evidence times the messages of its children; sent is its message to its parent
        sent0, sent1 = [1.0] * n, [1.0] * n
        for i in range(n - 1, 0, -1):
            a, b = own0[i], own1[i]
            s0, s1 = m00 * a + m01 * b, m10 * a + m11 * b
            z = s0 + s1
            s0, s1 = s0 / z, s1 / z
            sent0[i], sent1[i] = s0, s1
            p = t.parent[i]
            x0, x1 = own0[p] * s0, own1[p] * s1
            z = x0 + x1
            own0[p], own1[p] = (x0 / z, x1 / z) if z > 0 else (0.5, 0.5)
        # down: belief of the parent without the child's own message, then through the table
        out = [0.0] * n
        full = [(0.5, 0.5)] * n
        for i in range(n):
            if i:
                f0, f1 = full[t.parent[i]]
                c0, c1 = f0 / sent0[i], f1 / sent1[i]
                d0, d1 = c0 * m00 + c1 * m10, c0 * m01 + c1 * m11
            else:
                d0, d1 = e0, e1
            b0, b1 = d0 * own0[i], d1 * own1[i]
            z = b0 + b1
            b0, b1 = (b0 / z, b1 / z) if z > 0 else (0.5, 0.5)
            full[i] = (max(b0, 1e-300), max(b1, 1e-300))
            out[i] = b1
        return out


def states(t: Tree) -> list[int]:
    """Labels of all nodes: the nearest annotation at or above; none: not content."""
    s = [0] * len(t.tag)
    for i, mine in enumerate(t.label):
        s[i] = mine if mine is not None else (s[t.parent[i]] if i else 0)
    return s


def _alone(feature: str) -> str:
    """A tag below a tag as the tag alone, for pairs that were never seen."""
    return "tag:" + feature.rpartition(">")[2] if feature.startswith("tag:") else feature


def fit(pages: list[str], smooth: float = 0.5, temper: float = 0.25, back: float = 2.0) -> Model:
    """pages: html in which data-label="1" or "0" marks where content begins and ends.

    A tag's probability is that below its parent's tag: in a list of links the links say no more than the list.
    What is seen of a text or of what a block holds (lengths, ends, links) depends on itself several times
    over: its logarithms count for `temper` of their worth.
    """
    feature, of, below, move, root = (Counter(), Counter()), [0, 0], (Counter(), Counter()), Counter(), [1.0, 1.0]
    for page in pages:
        t = parse(page)
        s = states(t)
        root[s[0]] += 1
        for i, seen in enumerate(t.seen):
            if i:
                move[s[t.parent[i]], s[i]] += 1
                below[s[i]][t.tag[t.parent[i]]] += 1
            of[s[i]] += 1
            for f in seen:
                feature[s[i]][f] += 1
                if f.startswith("tag:"):
                    feature[s[i]][_alone(f)] += 1
    log = math.log

    def logs(f: str, y: int) -> float:
        alone = (feature[y][_alone(f)] + smooth) / (of[y] + 2 * smooth)
        if ">" not in f:
            return (1.0 if f.startswith(("tag:", "name:", "attr:")) else temper) * log(alone)
        # below a parent seldom seen in this state, the tag's own share decides
        return log((feature[y][f] + back * alone) / (below[y][f[4:].rpartition(">")[0]] + back))

    table = {f: (logs(f, 0), logs(f, 1)) for f in sorted(feature[0].keys() | feature[1].keys())}
    z = sum(root)
    rows = tuple(tuple(log((move[a, b] + smooth) / (move[a, 0] + move[a, 1] + 2 * smooth)) for b in (0, 1)) for a in (0, 1))
    return Model((log(root[0] / z), log(root[1] / z)), rows, table)


def rendered(t: Tree, p: list[float], threshold: float = 0.5) -> str:
    """The texts of p at or above the threshold, in blocks."""
    blocks: list[list[str]] = [[]]
    # the innermost block element above each node, and a new block whenever that changes or a block ends
    block_of = [0] * len(t.tag)
    last = -1
    for i, tag in enumerate(t.tag):
        if i:
            block_of[i] = i if tag in BLOCK else block_of[t.parent[i]]
        if tag == "br":
            blocks[-1].append(" ")
        if tag in BLOCK or (not tag and block_of[i] != last):
            blocks.append([])
            last = block_of[i]
        if not tag and p[i] >= threshold:
            blocks[-1].append(t.text[i])
    return "\n".join(x for x in (" ".join("".join(b).split()) for b in blocks) if x)


def main_text(page: str | None, model: Model, threshold: float = 0.5) -> str:
    if not page:
        return ""
    t = parse(page)
    return rendered(t, model.marginals(t), threshold)


#: syllables of the made-up words, names of blocks, and words of what sites say beside their articles
_SYLLABLES = "ta ri mo len sur ka vi den po ar es ul ni gre fo hal".split()
_GOOD_NAMES = "content post entry article story main body text page-content post-body entry-content article-body".split()
_PLAIN_NAMES = "wrap box row col inner c1 left block x9 unit grid cell section part".split()
_SIDES = {
    "nav": ("nav", "menu", "navbar", "main-menu", "breadcrumb", "tabs"),
    "ad": ("ad", "ads", "advert", "banner", "sponsor", "promo"),
    "side": ("sidebar", "aside", "widget", "related", "most-read", "teaser"),
    "notice": ("cookie-notice", "notice", "popup", "modal", "consent", "alert"),
    "form": ("search", "newsletter", "subscribe", "login"),
    "share": ("share", "social", "toolbar", "tags"),
    "comments": ("comments", "comment-list", "replies", "discussion"),
    "footer": ("footer", "site-footer", "copyright", "legal"),
    "header": ("header", "site-header", "masthead", "logo"),
}


class _Maker:
    """Pieces of pages, all from one stream of chance."""

    def __init__(self, seed: int):
        self.r = random.Random(seed)

    def word(self) -> str:
        return "".join(self.r.choice(_SYLLABLES) for _ in range(self.r.choice((1, 1, 2, 2, 3))))

    def say(self, least: int, most: int, end: str = ".") -> str:
        return " ".join(self.word() for _ in range(self.r.randint(least, most))).capitalize() + end

    def prose(self) -> str:
        return " ".join(self.say(4, 18) for _ in range(self.r.choice((1, 1, 2, 3, 5))))

    def link(self) -> str:
        return f'<a href="/{self.word()}">{self.say(1, 4, "")}</a>'

    def inline(self, text: str) -> str:
        k = self.r.randrange(9)
        if k < 4:
            tag = ("b", "em", "span", "code")[k]
            return f"<{tag}>{self.say(1, 4, '')}</{tag}> {text}"
        return f"{text} {self.link()} {self.say(2, 9)}" if k == 4 else f"<b>{text}<br>" if k == 5 else text

    def block(self) -> str:
        """A block as it stands in an article."""
        k = self.r.randrange(18)
        if k < 8:
            return f"<p>{self.inline(self.prose())}</p>"
        if k == 8:
            return f"<h{k % 3 + 2}>{self.say(2, 6, '')}</h{k % 3 + 2}>"
        if k == 9:
            return f"<p>{self.say(1, 2, self.r.choice(('.', '', ':')))}</p>"
        if k == 10:
            items = "".join(f"<li>{self.link() if self.r.random() < 0.5 else self.say(1, 14, self.r.choice(('.', '')))}</li>" for _ in range(self.r.randint(2, 5)))
            return f"<ul>{items}</ul>" if self.r.random() < 0.6 else f"<ol>{items}</ol>"
        if k == 11:
            return "<ul>" + "".join(f"<li>{self.link()}</li>" for _ in range(self.r.randint(2, 5))) + "</ul>"
        if k == 12:
            return f"<blockquote><p>{self.prose()}</p></blockquote>" if self.r.random() < 0.5 else f"<blockquote>{self.prose()}</blockquote>"
        if k == 13:
            return "<table>" + "".join(f"<tr><td>{self.word()}</td><td>{self.r.randint(1, 99)}</td></tr>" for _ in range(3)) + "</table>"
        if k == 14:
            return f"<figure><img src='/p'><figcaption>{self.say(2, 9)}</figcaption></figure>"
        if k == 15:
            return f"<p>{self.say(2, 8, '')} <math><mi>x</mi><mo>=</mo><mn>{self.r.randint(1, 9)}</mn></math> {self.say(2, 8)}</p>"
        if k == 16:
            return f"<pre>{self.word()} = {self.r.randint(1, 9)}</pre>" if self.r.random() < 0.5 else f"<object><p>{self.prose()}</p></object>"
        return f"<dl><dt>{self.word()}</dt><dd>{self.say(3, 9)}</dd></dl>" if self.r.random() < 0.5 else f"<div><p>{self.prose()}</p></div>"

    def article(self) -> list[str]:
        k = self.r.choice((1, 1, 1, 2))
        out = [f"<h{k}>{self.say(2, 9, self.r.choice(('', '.', '!')))}</h{k}>"] if self.r.random() < 0.8 else []
        out += [self.block() for _ in range(self.r.randint(1, 7))]
        if self.r.random() < 0.3:
            out += [self.side(self.r.choice(("ad", "share", "side", "form")), inside=True), self.block()]
        if self.r.random() < 0.15:
            out.insert(0, '<noscript data-label="0"><p>' + self.say(4, 9) + "</p></noscript>")
        return out

    def links(self) -> str:
        if self.r.random() < 0.7:
            return "<ul>" + "".join(f"<li>{self.link()}</li>" for _ in range(self.r.randint(3, 7))) + "</ul>"
        return self.r.choice((" ", " | ", "<br>")).join(self.link() for _ in range(self.r.randint(3, 7)))

    def side(self, kind: str, inside: bool = False) -> str:
        """A block that is no part of the article."""
        inner = {
            "nav": lambda: self.links(),
            "ad": lambda: self.r.choice((self.say(4, 20), f"<p>{self.say(3, 9, '!')}</p>{self.link()}", f"<span>{self.word()}</span> {self.link()}")),
            "side": lambda: f"<h3>{self.say(1, 3, '')}</h3>" + self.r.choice((self.links(), f"<p>{self.say(5, 20)}</p>", self.links() + f"<p>{self.say(4, 15)}</p>")),
            "notice": lambda: f"<p>{self.say(6, 25)}</p><button>{self.word()}</button>" if self.r.random() < 0.6 else self.say(6, 25),
            "form": lambda: f"<label>{self.word()}</label><input name='q'><select><option>{self.word()}</option></select><textarea>{self.say(1, 4)}</textarea><p>{self.say(3, 9)}</p><button>{self.word()}</button>",
            "share": lambda: " ".join(f'<a href="#">{self.word()}</a>' for _ in range(3)),
            "comments": lambda: f"<h3>{self.word()}</h3>" + "".join(f'<div class="comment"><p>{self.prose()}</p></div>' if self.r.random() < 0.6 else f'<div class="comment"><b>{self.word()}</b> {self.say(3, 20)}</div>' for _ in range(self.r.randint(1, 3))),
            "footer": lambda: f"<p>&copy; {self.word()}.example.com. {self.say(4, 14)}</p>" if self.r.random() < 0.5 else f"&copy; {self.word()}.example.net &middot; {self.say(3, 9)}\n{self.say(1, 4)}" + (self.links() if self.r.random() < 0.4 else ""),
            "header": lambda: f"<a href='/'>{self.word()}</a><div>{self.say(1, 4, '')}</div>" + (self.links() if self.r.random() < 0.5 else ""),
        }[kind]()
        name = self.r.choice(_SIDES[kind])
        own = {"nav": "nav", "side": "aside", "form": "form", "comments": "section", "footer": "footer", "header": "header"}.get(kind)
        tag = own if own and self.r.random() < 0.6 and not inside else "form" if kind == "form" else "div"
        named = tag == "div" or self.r.random() < 0.4 or tag == "section"
        what = f' {self.r.choice(("class", "class", "id"))}="{name}"' if named else ""
        return f'<{tag} data-label="0"{what}>{inner}</{tag}>'


def varied_page(seed: int) -> str:
    """A page in one of many layouts, made by rule; data-label says what is its main text."""
    m = _Maker(seed)
    r, blocks = m.r, m.article()
    article, kind = "".join(blocks), r.randrange(12)
    if kind < 3:
        frame = f'<article data-label="1">{article}</article>'
        frame = f"<main>{frame}</main>" if r.random() < 0.3 else frame
    elif kind < 6:
        tag, what = r.choice(("div", "div", "main", "section")), f'{r.choice(("class", "id"))}="{r.choice(_GOOD_NAMES)}"'
        frame = f'<{tag} {what} data-label="1">{article}</{tag}>'
        frame = f'<div class="{r.choice(_PLAIN_NAMES)}">{frame}</div>' if r.random() < 0.4 else frame
    elif kind < 8:
        frame = f'<div data-label="1">{article}</div>' if r.random() < 0.5 else f'<div id="{r.choice(_PLAIN_NAMES)}" data-label="1">{article}</div>'
    elif kind == 8:
        frame = f'<table><tr><td data-label="0">{m.links()}</td><td data-label="1">{article}</td></tr></table>'
    elif kind == 9:
        frame = f'<main data-label="1">{article}</main>'
    else:
        # no frame at all: each block for itself
        frame = "".join(x if "data-label" in x else re.sub(r"^<(\w+)", r'<\1 data-label="1"', x) for x in blocks)
    before = "".join(m.side(k) for k in ("header", "nav", "ad", "notice", "share") if r.random() < 0.45)
    after = "".join(m.side(k) for k in ("side", "ad", "comments", "form", "share", "footer", "nav") if r.random() < 0.35)
    if r.random() < 0.15:
        return before + frame + after
    head = f'<head data-label="0"><meta charset="utf-8"><title>{m.say(2, 8, "")}</title><style>p{{margin:0}}</style><script>var t="</p>";</script></head>' if r.random() < 0.8 else ""
    return f'<!DOCTYPE html><html>{head}<body data-label="0">{before}{frame}{after}' + ("</body></html>" if r.random() < 0.8 else "")


def unmarked(page: str) -> str:
    """A labelled page without its labels."""
    return re.sub(r' data-label="[01]"', "", page)


def labelled_pages(n: int = 400) -> list[str]:
    """The pages that the model is fitted on."""
    return [varied_page(seed) for seed in range(n)]


def extract(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", labelled: list[str] | None = None, threshold: float = 0.5) -> DataFrame:
    """page_id, url, text and n_chars of every row; labelled pages default to labelled_pages()."""
    model = fit(labelled_pages() if labelled is None else labelled)
    held = pages.sparkSession.sparkContext.broadcast(model)
    rows = pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).cast("string").alias("url"), F.col(html_col).cast("string").alias("html"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in byte_slices(batches, "html"):
            found = [main_text(x, held.value, threshold) for x in b.column("html").to_pylist()]
            yield pa.record_batch([b.column("page_id"), b.column("url"), pa.array(found, pa.string()), pa.array([len(x) for x in found], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    return rows.mapInArrow(run, "page_id long, url string, text string, n_chars long")
