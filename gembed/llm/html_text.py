"""Operator 8: main text of a page by the maximum-scoring run of its tokens.

A page is a line of tokens: words score positive, words in links and every tag negative (tags of the
page's frame more or less than those of running text), and what stands in menus, headers, footers, side
columns, notices, adverts, forms or comments too. One linear scan finds the contiguous run with the
largest sum. The weights are fitted on labelled pages, which are made by rule (``labelled_pages``); they
decide wherever a page's frame has no telltale name. The run's container (the smallest element around
it) then gives all of its content blocks, so that a one-word paragraph at the end of an article isn't
lost to the tags around it. If that is the whole body, the run gives its own blocks, and the body's text
elements that are not mostly links, the containers that the run touches, and sections like those theirs.

Reading a page is linear in its length: every search goes on from where the last one ended, elements
form a tree in page order (so "inside" compares two numbers), and beyond ``MAX_DEPTH`` open elements a
new one replaces the innermost, as browsers do; no text is lost by that. Script-like elements
run to their end tag; one that is never closed hides the text up to the next tag only.

Character references are decoded, white space inside a block becomes one space, blocks are joined by
one line feed. Defined results: null or empty html, and pages without words of content, give the empty
text; null urls stay null; repeated rows each give a row; an empty table gives an empty table; other
columns are ignored.
"""

from __future__ import annotations

import html
import re
from dataclasses import dataclass
from functools import cache

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import mapped

# Element names and the words in class, id and role that mark what is not content.
BLOCKS = frozenset("address article aside blockquote body center dd details dialog dir div dl dt fieldset figcaption figure footer form frameset h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol option p pre section summary table tbody td tfoot th thead tr ul".split())
#: Elements whose content is characters, not markup, and elements whose content a reader never sees.
TEXT_ONLY = frozenset("script style title textarea xmp iframe noframes noembed".split())
HIDDEN = frozenset("noscript template object svg math head select canvas audio video map".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
ASIDE_TAGS = frozenset("nav footer aside form header dialog menu button label fieldset".split())
ASIDE_ROLES = frozenset("navigation banner contentinfo complementary search dialog alert alertdialog menu menubar form note".split())
ASIDE_WORDS = frozenset(
    "ad ads adv advert adverts advertisement advertising adbox adslot banner breadcrumb breadcrumbs byline comment comments commentlist consent cookie cookies disqus dropdown footer "
    "gdpr header login masthead menu menus modal nav navbar navigation newsletter notice notices notification overlay pager pagination paywall popup promo promotion recommended related "
    "reply replies respond share sharing sidebar sidebars signup skip social sponsor sponsored subscribe subscription tags toolbar topbar widget widgets".split()
)
#: Words that may stand beside those in a name without making it another thing ("ad-box", "site-footer"; but not "social-science").
ASIDE_BESIDE = frozenset(
    "a actions area article articles aside author authors avatar badge bar block blocks body bottom box boxes btn button buttons card cards cell center close col column container count desktop "
    "entry field fixed foot form global group head heading holder icon icons id img index inner input item items js label large left level line link links list main message meta mini mobile native "
    "new note open outer page pages panel panels popular post posts primary reader readers region right row rows secondary section sections short side site slot small space stack sticky stories story tab "
    "text thread title toggle top topic ui unit up user users view wrap wrapper zone".split()
)
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
#: Elements that hold an article's text when they stand directly in the body.
TEXT_TAGS = HEADINGS | frozenset("p ul ol dl li dt dd blockquote pre table figure figcaption hgroup center address".split())
#: Tags that belong to running text; the others make a page's frame.
RUNNING = HEADINGS | frozenset("p li blockquote pre br b i em strong u s small sub sup code q cite abbr mark ins del tt kbd samp var time font wbr hr dd dt figcaption".split())
KEEP_TAGS = frozenset(("html", "body", "article", "main"))
#: A block element that opens inside one of these closes it.
_CLOSED_BY_BLOCK = frozenset(("p",))
_SIBLINGS = {"li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"), "option": ("option",)}
_LISTS = {"li": {"ul", "ol", "menu", "dir"}, "dt": {"dl"}, "dd": {"dl"}, "tr": {"table"}, "td": {"table", "tr"}, "th": {"table", "tr"}, "option": {"select"}}
MAX_DEPTH = 512

#: A tag whose quoted attribute values may hold ">", and one that ends at the first ">".
_TAG = re.compile(r"<(/?)([A-Za-z][^\s/>]*+)((?:[^>\"'=]++|=\s*+(?:\"[^\"]*+\"|'[^']*+')?+|[\"'])*+)>")
_PLAIN_TAG = re.compile(r"<(/?)([A-Za-z][^\s/>]*+)([^>]*+)>")
_CLOSERS = re.compile(rf"</({'|'.join(sorted(TEXT_ONLY | HIDDEN))})(?=[\s/>])", re.I | re.A)
_NEXT_TAG = re.compile(r"<[A-Za-z/!]")
_ATTRIBUTE = re.compile(r"(class|id|role|hidden|aria-hidden)\b(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?", re.I)
_WORDS = re.compile(r"[A-Za-z]+")
_CAMEL = re.compile(r"(?<=[a-z])(?=[A-Z])")


@dataclass(frozen=True)
class Weights:
    """Scores of a word, a word in a link, a word in an aside, a tag of the frame, a tag of running text."""

    word: float = 1.0
    link_word: float = -1.0
    aside_word: float = -2.0
    tag: float = -2.0
    running_tag: float = -0.5


@dataclass
class Block:
    """A block's text, its words, those in links, whether in an aside, its element, and the tags before it."""

    text: str
    words: int
    link_words: int
    aside: bool
    at: int
    tags: int
    running_tags: int


class Tree:
    """The elements in page order: name, parent, and the last element inside; element 0 is the root."""

    def __init__(self):
        self.name, self.parent, self.last, self.depth = ["#root"], [0], [0], [0]

    def add(self, name: str, parent: int) -> int:
        self.name.append(name)
        self.parent.append(parent)
        self.last.append(len(self.name) - 1)
        self.depth.append(self.depth[parent] + 1)
        return len(self.name) - 1

    def inside(self, e: int, around: int) -> bool:
        return around <= e <= self.last[around]

    def around(self, a: int, b: int) -> int:
        """The smallest element around two elements."""
        while a != b:
            if self.depth[a] >= self.depth[b]:
                a = self.parent[a]
            else:
                b = self.parent[b]
        return a


def _named_aside(value: str) -> bool:
    """Whether one name of a class or id says aside: one of its words does, and no other contradicts."""
    for name in value.split():
        words = [w.lower() for w in _WORDS.findall(_CAMEL.sub(" ", name))]
        if any(w in ASIDE_WORDS for w in words) and all(w in ASIDE_WORDS or w in ASIDE_BESIDE for w in words):
            return True
    return False


def _is_aside(name: str, attributes: str) -> bool:
    if name in ASIDE_TAGS:
        return True
    if not attributes or name in KEEP_TAGS:
        return False
    for m in _ATTRIBUTE.finditer(attributes):
        key, value = m[1].lower(), m[2] or m[3] or m[4] or ""
        if key == "hidden" or (key == "aria-hidden" and value.lower() == "true"):
            return True
        if key == "role" and value.lower() in ASIDE_ROLES:
            return True
        if key in ("class", "id") and _named_aside(value):
            return True
    return False


class _Reader:
    """Reads one page into blocks and a tree of its block elements."""

    def __init__(self, page: str):
        self.page, self.blocks, self.tree = page, [], Tree()
        self.stack: list[tuple[str, int, bool, bool]] = [("#root", 0, False, False)]  # name, element, aside, hidden
        self.open: dict[str, int] = {}
        self.pieces: list[str] = []
        self.linked: list[str] = []
        self.tags = self.running = self.links = 0
        self.closers: dict[str, list[int]] | None = None

    def end_block(self) -> None:
        if self.pieces:
            text = " ".join(html.unescape("".join(self.pieces)).split())
            if text:
                linked = len(html.unescape(" ".join(self.linked)).split())
                _, at, aside, _ = self.stack[-1]
                self.blocks.append(Block(text, text.count(" ") + 1, linked, aside, at, self.tags, self.running))
                self.tags = self.running = 0
            self.pieces.clear()
        self.linked.clear()

    def take(self, text: str) -> None:
        if self.stack[-1][3]:
            return
        self.pieces.append(text)
        if self.links:
            self.linked.append(text)

    def push(self, name: str, aside: bool, hidden: bool = False) -> None:
        if len(self.stack) >= MAX_DEPTH:
            self.pop()
        _, parent, inherited, unseen = self.stack[-1]
        if name in HEADINGS and inherited and self.title_place():
            inherited = False
        self.stack.append((name, self.tree.add(name, parent), inherited or aside, unseen or hidden))
        self.open[name] = self.open.get(name, 0) + 1

    def title_place(self) -> bool:
        """Whether the innermost aside is the header of an article: headings in it are the article's."""
        marked = [i for i, s in enumerate(self.stack) if s[2]]
        return self.stack[marked[0]][0] == "header" and any(s[0] in ("article", "main") for s in self.stack[: marked[0]])

    def pop(self) -> None:
        name, at, _, _ = self.stack.pop()
        self.open[name] -= 1
        self.tree.last[at] = len(self.tree.name) - 1

    def pop_to(self, depth: int) -> None:
        while len(self.stack) > depth:
            self.pop()

    def close(self, name: str) -> None:
        if self.open.get(name):
            depth = next(i for i in range(len(self.stack) - 1, 0, -1) if self.stack[i][0] == name)
            self.pop_to(depth)
            self.links = 0

    def closer(self, name: str, at: int) -> int | None:
        """Where the next end tag of a script-like or hidden element begins; None if it has none."""
        if self.closers is None:
            self.closers = {}
            for m in _CLOSERS.finditer(self.page):
                self.closers.setdefault(m[1].lower(), []).append(m.start())
            for places in self.closers.values():
                places.reverse()
        places = self.closers.get(name, [])
        while places and places[-1] < at:
            places.pop()
        return places[-1] if places else None

    def opened(self, name: str, attributes: str) -> None:
        """A start tag of a block element."""
        if self.stack[-1][0] in _CLOSED_BY_BLOCK:
            self.pop()
        if any(self.open.get(s) for s in _SIBLINGS.get(name, ())):
            for i in range(len(self.stack) - 1, 0, -1):
                if self.stack[i][0] in _SIBLINGS[name]:
                    self.pop_to(i)
                    break
                if self.stack[i][0] in _LISTS[name]:
                    break
        self.push(name, _is_aside(name, attributes))

    def tag(self, closing: bool, name: str, attributes: str, at: int) -> int:
        """Takes one tag that ends at ``at``; the place to go on from."""
        if name in RUNNING:
            self.running += 1
        else:
            self.tags += 1
        if name in TEXT_ONLY:
            if closing or attributes.rstrip().endswith("/"):
                return at
            end = self.closer(name, at)
            if end is not None:
                over = self.page.find(">", end)
                return len(self.page) if over < 0 else over + 1
            following = _NEXT_TAG.search(self.page, at)
            return following.start() if following else len(self.page)
        if name in HIDDEN:
            if closing:
                self.end_block()
                self.close(name)
            elif not attributes.rstrip().endswith("/") and self.closer(name, at) is not None:
                self.end_block()
                self.push(name, False, True)
            return at
        if name == "a":
            self.links = 0 if closing else 1
        elif name == "br":
            self.take(" ")
        elif name == "hr":
            self.end_block()
        elif name in BLOCKS:
            self.end_block()
            if closing:
                self.close(name)
            else:
                self.opened(name, attributes)
        elif closing:
            if self.stack[-1][0] == name:
                self.end_block()
                self.pop()
        elif name in VOID:
            if name in ("img", "input", "embed"):
                self.take(" ")
        elif _is_aside(name, attributes):
            self.end_block()
            self.push(name, True)
        return at

    def read(self) -> tuple[list[Block], Tree]:
        page, at, pattern = self.page, 0, _TAG
        last = page.rfind(">")
        while True:
            lt = page.find("<", at)
            if lt < 0:
                self.take(page[at:])
                break
            if lt > at:
                self.take(page[at:lt])
            following = page[lt + 1 : lt + 2]
            letter = page[lt + 2 : lt + 3] if following == "/" else following
            named = letter.isascii() and letter.isalpha()
            if following == "!" or following == "?" or (following == "/" and not named):
                at = self.skip(lt)
                continue
            if not named:
                self.take("<")
                at = lt + 1
                continue
            if lt > last:  # a tag cut off by the end of the page
                break
            m = pattern.match(page, lt)
            if m is None and pattern is _TAG:  # a quotation mark that is never closed
                pattern = _PLAIN_TAG
                m = pattern.match(page, lt)
            if m is None:
                self.take("<")
                at = lt + 1
                continue
            at = self.tag(bool(m[1]), m[2].lower(), m[3], m.end())
        self.end_block()
        self.pop_to(1)
        self.tree.last[0] = len(self.tree.name) - 1
        return self.blocks, self.tree

    def skip(self, lt: int) -> int:
        """Past a comment, a declaration or character data; what is never closed ends at the next ">" or the end."""
        page = self.page
        for begin, end in (("<!--", "-->"), ("<![CDATA[", "]]>")):
            if page.startswith(begin, lt):
                over = page.find(end, lt + len(begin))
                if begin != "<!--":
                    self.take(html.escape(page[lt + len(begin) : over if over >= 0 else len(page)], False))
                return over + len(end) if over >= 0 else len(page)
        over = page.find(">", lt)
        return over + 1 if over >= 0 else len(page)


def blocks_of(page: str) -> tuple[list[Block], Tree]:
    """A page's blocks in order, and the elements around them."""
    return _Reader(page).read()


def gain(b: Block, w: Weights) -> float:
    return b.words * w.aside_word if b.aside else (b.words - b.link_words) * w.word + b.link_words * w.link_word


def cost(b: Block, w: Weights) -> float:
    return b.tags * w.tag + b.running_tags * w.running_tag


def best_run(blocks: list[Block], w: Weights) -> tuple[int, int]:
    """First and last block of the run of tokens with the largest sum; (0, -1) if no sum is positive."""
    best, run, start, where = 0.0, 0.0, 0, (0, -1)
    for i, b in enumerate(blocks):
        before = cost(b, w)
        if run + before <= 0:
            run, start = 0.0, i
        else:
            run += before
        run += gain(b, w)
        if run > best:
            best, where = run, (start, i)
    return where


def _in_body(blocks: list[Block], tree: Tree, body: int, lo: int, hi: int) -> list[Block]:
    """The content blocks of a page whose run ``lo`` to ``hi`` has only ``body`` around it."""
    child: list[int] = []
    known: dict[int, int] = {body: body}
    for b in blocks:
        path, e = [], b.at
        while e not in known and tree.inside(e, body):
            path.append(e)
            e = tree.parent[e]
        top = known.get(e, -1)
        for p in reversed(path):
            top = known[p] = p if top == body else top
        child.append(known.get(b.at, -1))
    words: dict[int, int] = {}
    for b, c in zip(blocks, child, strict=True):
        if not b.aside:
            words[c] = words.get(c, 0) + b.words - 2 * b.link_words
    run = [(b, child[i]) for i, b in enumerate(blocks) if lo <= i <= hi and not b.aside and child[i] >= 0]
    touched = {c for _, c in run}
    leaves = {tree.name[c] for b, c in run if b.at == c}
    sections = {tree.name[c] for c in touched} & {"section", "article"}

    def taken(i: int, b: Block) -> bool:
        c = child[i]
        if b.aside or c < 0:
            return False
        if lo <= i <= hi:
            return True
        if c == body or c in touched or tree.name[c] in sections:
            return b.words >= 2 * b.link_words
        return words[c] >= 0 and (tree.name[c] in TEXT_TAGS or (b.at == c and tree.name[c] in leaves))

    return [b for i, b in enumerate(blocks) if taken(i, b)]


def choose(blocks: list[Block], tree: Tree, w: Weights) -> list[Block]:
    """The content blocks: the best run, widened to its container."""
    lo, hi = best_run(blocks, w)
    chosen = [b for b in blocks[lo : hi + 1] if not b.aside]
    if not chosen:
        return []
    inside = tree.around(chosen[0].at, chosen[-1].at)
    e = inside
    while e:
        if tree.name[e] in ("article", "main"):
            inside = e
        e = tree.parent[e]
    if tree.name[inside] in ("p", "li", "blockquote", "pre") or tree.name[inside] in HEADINGS:
        inside = tree.parent[inside]
    while tree.name[inside] in TEXT_TAGS and tree.name[tree.parent[inside]] in ("#root", "html", "body"):
        inside = tree.parent[inside]
    if tree.name[inside] not in ("#root", "html", "body"):
        return [b for b in blocks if not b.aside and tree.inside(b.at, inside)]
    return _in_body(blocks, tree, inside, lo, hi)


def main_text(page: str | None, w: Weights | None = None) -> str:
    """The content blocks of a page, joined by line feeds."""
    return "\n".join(b.text for b in choose(*blocks_of(page or ""), w or fitted()))


def labelled_pages(seed: int = 1) -> list[tuple[str, str]]:
    """Pages made by rule, each with its true content: every frame with every kind of content.

    Some frames name their parts; in the others only words, links and tags tell content from the rest: bars of
    short labels, lists of links inside the content's own column, tables of figures, long menus around a short article.
    """
    word = lambda i, n: " ".join(f"w{seed}y{i}x{k}" for k in range(n))
    links = lambda n, at=90, size=2: "".join(f"<li><a href='/{k}'>{word(at + k, size)}</a></li>" for k in range(n))
    bar = lambda n, at, size=1: "<div>" + "".join(f"<div><span>{word(at + k, size)}</span></div>" for k in range(n)) + "</div>"
    grid = lambda n, at: "<div><table>" + "".join(f"<tr><td>{word(at + k, 1)}</td><td>{k * seed}</td></tr>" for k in range(n)) + "</table></div>"
    cards = lambda n, at: "<div>" + "".join(f"<div><div><a href='/c{k}'>{word(at + k, 4)}</a></div><div><span>{word(at + 50 + k, 3)}</span></div></div>" for k in range(n)) + "</div>"
    bodies = [[word(1, 5), word(2, 60), word(3, 1), word(4, 35)], [word(5, 12), word(6, 9)], [word(7, 8)] + [word(8 + k, 20 + 3 * k) for k in range(12)] + [word(30, 2)], [word(31, 4)] + [word(32 + k, 5 + k) for k in range(6)]]
    frames = [
        "<html><body><nav><ul>{links}</ul></nav><div class='ad'>{ad}</div><article>{content}</article><footer>{foot}</footer></body></html>",
        "<html><body><div><ul>{links}</ul></div><div><div>{content}</div></div><div><ul>{links}</ul></div><p><a href='/x'>{foot}</a></p></body></html>",
        "<body><header><h2>{ad}</h2></header><main>{content}</main><aside>{ad}</aside><div id='comments'><p>{ad}</p></div><form>{foot}</form></body>",
        "<body><ul>{links}</ul>{content}<div class='ad'>{ad}</div><ul>{links}</ul></body>",
        "<body><nav><ul>{links}</ul></nav>{content}<footer>{foot}</footer></body>",
        "<body>" + bar(12, 200) + "<div><div>{content}</div></div>" + bar(25, 300, 2) + "</body>",
        "<body>" + cards(9, 400) + "<div>{content}</div>" + cards(6, 500) + "</body>",
        "<body><div>" + bar(6, 200, 2) + "</div><div>{content}</div>" + grid(14, 600) + "</body>",
        "<body><div><div><ul>" + links(40, 700, 3) + "</ul></div><div>{content}</div><div><ul>" + links(30, 800, 3) + "</ul></div></div></body>",
    ]
    out = []
    for frame in frames:
        for body in bodies:
            content = f"<h1>{body[0]}</h1>" + "".join(f"<p>{b}</p>" for b in body[1:])
            out.append((frame.format(links=links(8), ad=word(70, 14), content=content, foot=word(80, 7)), "\n".join(body)))
    for body in ([word(1, 1), word(2, 60), word(3, 2)], [word(4, 1), word(5, 40), word(6, 45), word(7, 1)]):
        parts = [f"<p>{b}</p>" for b in body[1:]]
        parts.insert(1, f"<aside><p>{word(60, 90)}</p></aside>")
        out.append((f"<body><h1>{body[0]}</h1>{''.join(parts)}<ul>{links(8)}</ul></body>", "\n".join(body)))
    return out


#: The settings that are tried: link words, words of asides, tags of the frame, tags of running text.
GRID = ((0.0, -0.5, -1.0, -2.0), (-2.0, -1.0), (-2.0, -1.0, 0.0, -4.0, -8.0), (-0.5, 0.0, -1.0, -2.0))


def quality(w: Weights, pages: list[tuple[list[Block], Tree, str]]) -> float:
    """Mean word F1 over read pages."""
    total = 0.0
    for blocks, tree, truth in pages:
        got, want = {x for b in choose(blocks, tree, w) for x in b.text.split()}, set(truth.split())
        total += 2 * len(got & want) / max(1, len(got) + len(want))
    return total / max(1, len(pages))


@cache
def fitted() -> Weights:
    """The weights, of the grid, with the highest word F1 on the labelled pages; of equals the middle one."""
    pages = [(*blocks_of(p), truth) for p, truth in labelled_pages()]
    tried = [Weights(1.0, link, aside, tag, running) for link in GRID[0] for aside in GRID[1] for tag in GRID[2] for running in GRID[3]]
    scored = [(quality(w, pages), w) for w in tried]
    top = max(q for q, _ in scored)
    best = sorted((w for q, w in scored if q > top - 1e-9), key=lambda w: (w.tag, w.running_tag, w.link_word, w.aside_word))
    return best[len(best) // 2]


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url, text and n_chars of every page; no shuffle."""
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.coalesce(F.col("html").cast("string"), F.lit("")).alias("html"))
    weights = fitted()

    def run(batch: pa.RecordBatch) -> dict:
        text = [main_text(p, weights) for p in batch.column("html").to_pylist()]
        return {"page_id": batch.column("page_id"), "url": batch.column("url"), "text": text, "n_chars": [len(t) for t in text]}

    return mapped(rows, run, "page_id long, url string, text string, n_chars long")
