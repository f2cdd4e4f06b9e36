"""Main text of web pages by a linear-chain conditional random field over DOM leaf blocks.

A page is cut into leaf blocks, the runs of text between block-level tags. A block's features
are the tags, classes, ids and roles of its ancestors, its own length, links and signs, and
a few words; neighbouring blocks are joined by learned transitions. The field is trained on
labelled pages of many layouts that this module composes itself, and decoded by Viterbi.
"""

from __future__ import annotations

import html
import random
import re
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import crf
from . import textvec as tv
from .common import text_batches, text_of

#: Elements by their role in HTML (fixed values).
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
INLINE = frozenset(
    "a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var".split()
)
RAW = frozenset("script style noscript template title textarea iframe object svg math head select button xmp noembed noframes".split())
CLOSES_P = frozenset(
    "address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre search section table ul".split()
)
SIBLINGS = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}

_TOKEN = re.compile(
    r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*>?"
    r"|<(?P<end>/?)(?P<tag>[A-Za-z][^\s/>]*)(?P<attrs>(?:[^>\"']|\"[^\"]*\"|'[^']*')*)>?|[^<]+|<",
    re.S,
)
_ATTR = re.compile(r"""(?P<n>[^\s=/>"']+)(?:\s*=\s*(?:"(?P<a>[^"]*)"|'(?P<b>[^']*)'|(?P<c>[^\s>]+)))?""")
_BLANKS = re.compile(r"[\x20\x09-\x0D]+")
_WORD = re.compile(r"[A-Za-z]+")
_NAME = re.compile(r"[A-Z]?[a-z]+|[A-Z]+|\d+")


_HIDDEN = re.compile(r"(?:^|;)\s*(?:display\s*:\s*none|visibility\s*:\s*hidden)\b", re.I)
#: An end tag of another element does not close these (fixed values).
_WALLS = ("article", "body", "main", "table")


class Node:
    """An element as its blocks see it: equal paths of tags and names are one node, and share its sums.

    ``new`` holds the features that no ancestor has; ``emit`` is the sum of the weights of all features of the path.
    """

    __slots__ = ("parent", "tag", "leaf", "new", "emit", "kids")

    def __init__(self, parent: "Node | None", tag: str, new: tuple, emit: tuple):
        self.parent, self.tag, self.new, self.emit, self.kids = parent, tag, new, emit, {}
        self.leaf = parent.leaf if parent is not None and tag in INLINE else tag


class Stack:
    """The open elements; every question about them is answered without walking down."""

    def __init__(self, model: crf.ChainModel | None):
        self.weights, self.zero = (model.weights, (0.0,) * model.labels) if model else ({}, ())
        self.top = Node(None, "-", (), self.zero)
        self.open: list[tuple[Node, str, list[str]]] = []  # of (node below, tag, features)
        self.at: dict[str, list[int]] = {}
        self.active: dict[str, int] = {}

    def push(self, tag: str, names: frozenset) -> None:
        feats = ([] if tag in INLINE else ["t:" + tag]) + ["n:" + n for n in names]
        new = []
        for f in feats:
            n = self.active.get(f, 0)
            if not n:
                new.append(f)
            self.active[f] = n + 1
        self.open.append((self.top, tag, feats))
        self.at.setdefault(tag, []).append(len(self.open) - 1)
        node = self.top.kids.get((tag, names))
        if node is None:
            emit = self.top.emit
            for f in new:
                got = self.weights.get(f)
                if got is not None:
                    emit = tuple(x + y for x, y in zip(emit, got, strict=True))
            node = self.top.kids[tag, names] = Node(self.top, tag, tuple(new), emit)
        self.top = node

    def last(self, tags) -> int:
        """The place of the innermost open element of these tags, or -1."""
        return max((self.at[t][-1] for t in tags if self.at.get(t)), default=-1)

    def cut(self, place: int) -> None:
        """Close the element at a place and all that are inside it."""
        while len(self.open) > place:
            self.top, tag, feats = self.open.pop()
            self.at[tag].pop()
            for f in feats:
                self.active[f] -= 1


@dataclass
class Block:
    node: Node
    parts: list = field(default_factory=list)
    linked: int = 0
    text: str = ""


@lru_cache(maxsize=4096)
def _names(attrs: str) -> frozenset:
    out = set()
    for m in _ATTR.finditer(attrs):
        key = m["n"].lower()
        value = m["a"] or m["b"] or m["c"] or ""
        if key in ("class", "id", "role", "itemprop", "aria-label"):
            out |= {w.lower() for w in _NAME.findall(value)}
        elif key == "hidden" or key == "aria-hidden" and value == "true" or key == "style" and _HIDDEN.search(value):
            out.add("hidden!")
    return frozenset(out)


@lru_cache(maxsize=64)
def _ending(tag: str) -> re.Pattern:
    return re.compile("</head|<body" if tag == "head" else "</" + tag, re.I)


def leaf_blocks(page: str, model: crf.ChainModel | None = None) -> list[Block]:
    """The page's blocks in order, with text whose blanks are squeezed; blocks without text are left out.

    Unclosed, misnested and unknown tags are taken as browsers take them in the simple cases;
    text inside scripts, styles, titles and controls is no text of the page. Time and memory grow with the
    length of the page, however deep its elements are nested.
    """
    out: list[Block] = []
    stack = Stack(model)
    block: Block | None = None
    links = 0
    at, size = 0, len(page)
    absent: set[str] = set()

    def close() -> None:
        nonlocal block
        if block is not None:
            block.text = _BLANKS.sub(" ", html.unescape("".join(block.parts))).strip(" ")
            if block.text:
                out.append(block)
            block = None

    def end_of(tag: str) -> int:
        """Where the element's end begins, or -1; an end that was not found once is not sought again."""
        if tag in absent:
            return -1
        found = _ending(tag).search(page, at)
        if found is None:
            absent.add(tag)
            return -1
        return found.start()

    while at < size:
        m = _TOKEN.match(page, at)
        at = m.end()
        tag = m["tag"]
        if tag is None:
            piece = m[0]
            if piece.startswith("<!") or piece.startswith("<?"):
                continue
            if block is None:
                if not piece.strip():
                    continue
                block = Block(stack.top)
            block.parts.append(piece)
            if links:
                block.linked += len(piece)
            continue
        tag = tag.lower()
        if m["end"]:
            if tag == "a":
                links = max(0, links - 1)
            if tag not in INLINE:
                close()
            place = stack.last((tag,))
            if place >= 0 and (tag in INLINE or tag in _WALLS or tag == "html" or stack.last(_WALLS) <= place):
                stack.cut(place)
            continue
        if tag in RAW:
            close()
            if tag == "head":
                # the head ends at its end tag or where the body starts
                at = max(at, end_of(tag))
            elif not m["attrs"].endswith("/") or tag in ("script", "style", "title", "textarea"):
                end = end_of(tag)
                if end >= 0:
                    at = page.find(">", end) + 1 or size
                elif tag in ("script", "style", "textarea", "title"):
                    at = size
            continue
        if tag == "br":
            if block is not None:
                block.parts.append(" ")
            continue
        if tag not in INLINE:
            close()
            if tag in CLOSES_P:
                while stack.open and stack.open[-1][1] in INLINE and stack.last(("p",)) >= 0:
                    # an open paragraph ends together with the inline elements in it
                    below = len(stack.open) - 1
                    while below and stack.open[below - 1][1] in INLINE:
                        below -= 1
                    if not below or stack.open[below - 1][1] != "p":
                        break
                    stack.cut(below - 1)
                if stack.open and stack.open[-1][1] == "p":
                    stack.cut(len(stack.open) - 1)
            if tag in SIBLINGS:
                place = stack.last(SIBLINGS[tag])
                if place > stack.last(("ul", "ol", "dl", "table", "select", "menu")):
                    stack.cut(place)
        if tag in VOID:
            continue
        if tag == "a":
            links += 1
        stack.push(tag, _names(m["attrs"]) if m["attrs"] else frozenset())
    close()
    return out


#: Words of boilerplate that a block's text may begin with (fixed values).
CUES = frozenset("copyright cookie cookies subscribe newsletter share comment comments reply advertisement sponsored related login sign privacy terms rights reserved posted menu search".split())


def own_features(blocks: list[Block]) -> list[list[str]]:
    """What each block shows by itself and beside its predecessor, without its ancestors."""
    out = []
    for i, b in enumerate(blocks):
        f = ["bias", "leaf:" + b.node.leaf]
        size = len(b.text)
        share = min(b.linked, size) / size
        f.append("size:" + ("0" if size < 20 else "1" if size < 60 else "2" if size < 150 else "3" if size < 400 else "4"))
        f.append("link:" + ("0" if share == 0 else "1" if share < 0.3 else "2" if share < 0.7 else "3"))
        f.append("stop:" + str(b.text[-1] in ".!?\"”…"))
        if "©" in b.text:
            f.append("sign")
        f += ["w:" + w for w in {w.lower() for w in _WORD.findall(b.text[:200])[:12]} & CUES]
        if i:
            f.append("same:" + str(blocks[i - 1].node is b.node))
        out.append(f)
    return out


def block_features(blocks: list[Block]) -> list[list[str]]:
    """All features, those of the ancestors spelt out: for training, on pages that are not deep."""
    out = own_features(blocks)
    for b, f in zip(blocks, out, strict=True):
        node = b.node
        while node is not None:
            f += node.new
            node = node.parent
    return out


# ---- labelled pages -------------------------------------------------------------------------


def labelled_page(rng: random.Random) -> tuple[str, list[int]]:
    """A page of a random layout, and for each of its leaf blocks 1 (main text) or 0."""
    out, labels = [], []
    words = "alpha river stone light winter market garden letter window music history number people city paper story water house north question".split()

    def phrase(lo: int, hi: int, stop: bool = True) -> str:
        t = " ".join(rng.choice(words) for _ in range(rng.randint(lo, hi))).capitalize()
        return t + (rng.choice(".!?") if stop else "")

    def put(open_tag: str, texts: list[str], label: int, close_tag: str) -> None:
        out.append(open_tag)
        for t in texts:
            out.append(t)
            labels.append(label)
        out.append(close_tag)

    def wrap(name: str, options: list[str], tag: str = "div") -> tuple[str, str]:
        attr = rng.choice(["class", "id"])
        return f'<{tag} {attr}="{rng.choice(options)}">', f"</{tag}>"

    def menu() -> None:
        o, c = rng.choice([("<nav>", "</nav>"), wrap("nav", ["nav", "navbar", "menu", "main-menu", "breadcrumb", "topnav", "navigation"]), wrap("nav", ["menu", "nav"], "ul"), ("<header>", "</header>"), ('<div role="navigation">', "</div>")])
        put(o, [f'<li><a href="/{rng.choice(words)}">{phrase(1, 2, False)}</a></li>' for _ in range(rng.randint(2, 8))], 0, c)

    def head() -> None:
        o, c = rng.choice([("<header>", "</header>"), wrap("h", ["header", "site-header", "masthead", "banner", "logo"])])
        put(o, [f"<div>{phrase(1, 4, False)}</div>"], 0, c)

    def advert() -> None:
        o, c = rng.choice([wrap("ad", ["ad", "ads", "advert", "ad-slot", "advertisement", "sponsored", "promo", "banner-ad"]), wrap("ad", ["ad", "sponsor", "promo"], "aside")])
        put(o, [rng.choice(["", "<p>"]) + phrase(3, 25)], 0, c)

    def notice() -> None:
        o, c = rng.choice([wrap("n", ["notice", "cookie-notice", "cookie", "alert", "consent", "gdpr", "popup", "modal", "disclaimer", "paywall"]), ('<div role="alert">', "</div>"), ('<div role="dialog">', "</div>"), wrap("n", ["notice", "cookie"], "section")])
        put(o, [f"<p>{phrase(5, 25)}"], 0, c)

    def titled(o: str) -> None:
        # a box that is no article may begin with a heading
        if rng.random() < 0.4:
            put(o, [f"<h3>{phrase(1, 5, False)}</h3>" if rng.random() < 0.6 else f"<h2>{phrase(1, 5, False)}</h2>"], 0, "")
        else:
            out.append(o)

    def sidebar() -> None:
        o, c = rng.choice([("<aside>", "</aside>"), wrap("s", ["sidebar", "side", "widget", "related", "recommended", "trending", "popular", "tags", "share", "social", "author-bio", "newsletter", "subscribe"])])
        items = [f'<li><a href="#">{phrase(2, 8, False)}</a></li>' for _ in range(rng.randint(1, 5))] if rng.random() < 0.6 else [f"<p>{phrase(4, 30)}</p>" for _ in range(rng.randint(1, 3))]
        titled(o)
        put("", items, 0, c)

    def form() -> None:
        o, c = ("<form>", "</form>") if rng.random() < 0.6 else ('<form class="search" action="/s">', "</form>")
        put(o, [f"<div><label>{phrase(1, 6, False)}</label><input name=q></div>" for _ in range(rng.randint(1, 3))], 0, c)

    def comments() -> None:
        o, c = rng.choice([wrap("c", ["comments", "comment-list", "disqus", "replies", "responses", "discussion", "user-comments", "comments-area", "comment-section"]), wrap("c", ["comments", "comment"], "section"), wrap("c", ["comments", "comments-area"], "section"), wrap("c", ["comments"], "ol")])
        titled(o)
        put("", [rng.choice(['<div class="comment"><p>', "<p>", '<article class="comment"><p>', "<li>"]) + phrase(4, 60) + "</p></div>" for _ in range(rng.randint(1, 5))], 0, c)

    def hidden() -> None:
        o = rng.choice(['<div style="display:none">', '<div class="x" style="color:red; display: none;">', "<div hidden>", '<div aria-hidden="true">', '<p style="visibility:hidden">'])
        put(o, [phrase(2, 30)], 0, "</p>" if o.startswith("<p") else "</div>")

    def foot() -> None:
        o, c = rng.choice([("<footer>", "</footer>"), wrap("f", ["footer", "site-footer", "bottom", "copyright", "legal", "colophon"])])
        put(o, [rng.choice(["&copy; ", "", "Copyright "]) + phrase(3, 20)], 0, c)

    def body() -> None:
        layers = [("<article>", "</article>")] if rng.random() < 0.55 else []
        if rng.random() < 0.35:
            layers.insert(0, ("<main>", "</main>"))
        if rng.random() < 0.5 or not layers:
            layers.append(wrap("b", ["content", "main-content", "post", "post-body", "entry", "entry-content", "article-body", "story", "text", "body"]))
        if rng.random() < 0.05:
            layers = []
        out.extend(o for o, _ in layers)
        if rng.random() < 0.85:
            box = rng.choice([("", ""), ("", ""), ("<header>", "</header>")]) if layers and layers[-1][0] == "<article>" else ("", "")
            put(box[0], [f"<h1>{phrase(1, 9, False)}</h1>"], 1, box[1])
        for _ in range(rng.choice([1, 1, 2, 3, 5, 8, 12])):
            kind = rng.random()
            if kind < 0.56:
                put(rng.choice(["<p>", "<p>", "<p>", '<p style="text-decoration:none">', '<p style="margin:0;float:none">']), [rng.choice(["", "<b>", "<em>"]) + phrase(1, 90) + rng.choice(["", "<br>" + phrase(1, 20)])], 1, rng.choice(["</p>", ""]))
            elif kind < 0.62:
                # text straight in boxes, one inside the other or side by side
                deep = rng.randint(0, 3)
                put("<section>" + "<div>" * deep if rng.random() < 0.3 else "<div>" * deep, [f"<div>{phrase(1, 60)}</div>" for _ in range(rng.randint(1, 3))], 1, "</div>" * deep)
            elif kind < 0.68:
                put("", [f"<h{rng.randint(2, 4)}>{phrase(1, 7, False)}"], 1, "")
                out.append("</h2>" if "<h2>" in out[-2] else "</h3>" if "<h3>" in out[-2] else "</h4>")
            elif kind < 0.74:
                put("", [f"<h2>{phrase(1, 7, False)}</h2>"], 1, "")
            elif kind < 0.80:
                put("<ul>", [f"<li>{phrase(1, 14)}</li>" for _ in range(rng.randint(1, 4))], 1, "</ul>")
            elif kind < 0.84:
                put("<blockquote>", [f"<p>{phrase(3, 40)}</p>"], 1, "</blockquote>")
            elif kind < 0.87:
                put("<table><tr>", [f"<td>{phrase(1, 4, False)}</td>" for _ in range(rng.randint(1, 5))], 1, "</tr></table>")
            elif kind < 0.89:
                put("<pre>", [phrase(2, 20)], 1, "</pre>")
            elif kind < 0.91:
                put("<figure><img src=x>", [f"<figcaption>{phrase(2, 10)}</figcaption>"], 1, "</figure>")
            elif kind < 0.93:
                put("<p>", [f'{phrase(3, 12)} <a href="/x">{phrase(1, 5, False)}</a> {phrase(2, 12)}'], 1, "</p>")
            else:
                rng.choice([advert, sidebar, form, notice, hidden])()
        if rng.random() < 0.2:
            comments()
        out.extend(c for _, c in reversed(layers))

    out.append(f"<!DOCTYPE html><html><head><title>{phrase(2, 6, False)}</title><style>p{{}}</style></head><body>")
    for part, chance in ((notice, 0.3), (head, 0.4), (menu, 0.8), (advert, 0.5), (sidebar, 0.3), (form, 0.2)):
        if rng.random() < chance:
            part()
    body()
    for part, chance in ((advert, 0.2), (sidebar, 0.4), (comments, 0.4), (form, 0.2), (notice, 0.1), (menu, 0.1), (foot, 0.85)):
        if rng.random() < chance:
            part()
    out.append("</body></html>")
    return "".join(out), labels


def train(pages: int = 1_500, seed: int = 5) -> crf.ChainModel:
    """The field, trained on pages composed with a fixed seed."""
    rng = random.Random(seed)
    seqs, golds = [], []
    while len(seqs) < pages:
        page, labels = labelled_page(rng)
        blocks = leaf_blocks(page)
        if len(blocks) == len(labels):
            seqs.append(block_features(blocks))
            golds.append(labels)
    return crf.train(seqs, golds)


def main_text(page: str, model: crf.ChainModel) -> str:
    """The main text of one page; empty if there is none."""
    blocks = leaf_blocks(page, model)
    labels = crf.viterbi(own_features(blocks), model, [b.node.emit for b in blocks])
    return " ".join(b.text for b, y in zip(blocks, labels, strict=True) if y == 1)


def extract(pages: DataFrame, model: crf.ChainModel, id_col: str = "page_id", html_col: str = "html", keep: tuple = ("url",)) -> DataFrame:
    """One row per input row: id, the columns ``keep``, text, n_chars.

    Null html counts as empty and gives an empty text. Repeated rows give equal rows. Other
    columns are not read, so their names cannot clash.
    """
    shared = pages.sparkSession.sparkContext.broadcast(model)  # some hundred features

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in tv.pieces(batches):
            last = batch.num_columns - 1
            texts = [main_text(t, shared.value) for t in batch.column(last).to_pylist()]
            cols = [*batch.columns[:last], pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())]
            yield pa.RecordBatch.from_arrays(cols, names)

    picked = text_batches(pages).select(id_col, *keep, text_of(html_col).alias("html!"))
    schema = T.StructType([*picked.schema.fields[:-1], T.StructField("text", T.StringType()), T.StructField("n_chars", T.LongType())])
    names = schema.names
    return picked.mapInArrow(run, schema)
