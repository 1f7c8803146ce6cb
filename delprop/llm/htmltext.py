"""Main text of web pages by a tree-structured graphical model.

A tolerant reader turns a page into its tree of block elements (inline markup
melts into the text; an inline element that is hidden stays an element of its
own).  Each element is content or boilerplate.  Node
potentials come from tag, class and id words, link density, amount of text,
position and a ``hidden`` attribute or ``display:none`` style, which descendants inherit; edge potentials tie a child to its parent, by the child's kind.
Sum-product messages, upward then downward, give each element's exact
marginal.  Weights maximise the exact likelihood of labelled pages: generated
layouts with articles among menus, headers, footers, sidebars, notices,
adverts, forms and reader comments, in plain and in semantic markup.

The text of content elements, white space folded, goes out block by block in
page order, joined by a line feed.

Text of scripts, styles, templates, frames, drawings (svg), form values and the
source annotations of formulas is not page text and is not read; text for
browsers without scripts is an element like any other.

Edge cases: null or empty html gives an empty text; null ids and urls stay;
malformed, unclosed or cut-off markup is read as far as it goes; repeated rows
stay rows; extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import html
import math
import random
import re
from functools import lru_cache
from itertools import groupby
from operator import itemgetter

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from delprop.llm.common import map_arrow

_VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
_DROP = frozenset("script style template iframe svg select textarea title annotation annotation-xml".split())
_INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var math semantics mrow mi mn mo ms mtext msup msub msubsup mfrac msqrt mroot mover munder munderover mstyle mspace mpadded mfenced".split())
#: Opening one of these ends an open paragraph.
_ENDS_P = frozenset("address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre section table ul li dt dd".split())
#: Opening the key ends an open element of the first set, up to an element of the second.
_SIBLINGS = {
    "li": ({"li"}, {"ul", "ol", "menu", "dir"}), "dt": ({"dt", "dd"}, {"dl"}), "dd": ({"dt", "dd"}, {"dl"}), "tr": ({"tr", "td", "th"}, {"table"}),
    "td": ({"td", "th"}, {"tr", "table"}), "th": ({"td", "th"}, {"tr", "table"}), "tbody": ({"tr", "td", "th", "thead", "tbody"}, {"table"}), "option": ({"option"}, {"select"}),
}
_PIECE = re.compile(r"<!--.*?(?:-->|$)|<(?P<close>/?)(?P<tag>[a-zA-Z][^\s/>]*)(?P<rest>(?:[^>\"']|\"[^\"]*\"|'[^']*')*)(?:>|$)|<[!?][^>]*(?:>|$)|<[^>]*$", re.DOTALL)
_NAMES = re.compile(r"(?:class|id|role|itemprop)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.IGNORECASE)
_ATTRIBUTE = re.compile(r"([^\s\"'=/>]+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?")
_NO_DISPLAY = re.compile(r"(?:^|;)\s*display\s*:\s*none", re.IGNORECASE)

#: Words of class, id and role that the node potentials know, by theme: fixed values.
_THEMES = {
    "menu": "nav menu menubar navigation breadcrumb breadcrumbs toc pager pagination tabs",
    "head": "header masthead head topbar logo brand branding banner",
    "foot": "footer foot bottom copyright colophon legal",
    "side": "sidebar side aside rail widget related recommended popular trending tags",
    "advert": "ad ads advert adverts advertisement sponsor sponsored promo promotion promoted",
    "notice": "notice cookie cookies consent gdpr alert popup modal overlay message",
    "reply": "comment comments reply replies discussion respond disqus thread reader",
    "form": "form subscribe newsletter signup login search contact register",
    "share": "share social sharing follow like tweet",
    "content": "article content main post body entry story text page-content article-body post-content entry-content main-content articlebody",
}
_THEME_OF = {w: t for t, words in _THEMES.items() for w in words.split()}
_TAG_GROUPS = {
    "p": "p", "h1": "head", "h2": "head", "h3": "head", "h4": "head", "h5": "head", "h6": "head", "li": "li", "dt": "li", "dd": "li", "ul": "list", "ol": "list", "dl": "list", "menu": "list", "nav": "nav", "header": "header",
    "footer": "footer", "aside": "aside", "form": "form", "fieldset": "form", "button": "form", "dialog": "aside", "article": "article", "main": "main", "section": "section", "blockquote": "quote", "pre": "quote", "table": "table", "tbody": "table",
    "thead": "table", "tr": "table", "td": "cell", "th": "cell", "figure": "figure", "figcaption": "figure", "body": "root", "html": "root", "#page": "root", "head": "root",
}
_EDGE_KINDS = ("leaf", "list", "box", "marked", "hidden")


class Node:
    __slots__ = ("tag", "parent", "names", "pieces", "links", "children", "size", "own_links", "place", "hidden")

    def __init__(self, tag: str, parent: Node | None, names: str) -> None:
        self.tag, self.parent, self.names = tag, parent, names
        self.pieces: list[str] = []
        self.links = self.own_links = self.size = 0
        self.children: list[Node] = []
        self.place = 0
        self.hidden = False


def _hides(rest: str) -> bool:
    """Whether a tag's attributes, read by name, hide the element."""
    low = rest.lower()
    if "hidden" not in low and "none" not in low:
        return False
    for name, a, b, c in _ATTRIBUTE.findall(rest):
        if name.lower() == "hidden" or (name.lower() == "style" and _NO_DISPLAY.search(a or b or c)):
            return True
    return False


def read_tree(page: str) -> tuple[list[Node], list[tuple[Node, str]]]:
    """Block elements in page order (parents first) and the text blocks as (element, text)."""
    return _read(page)[:2]


def _read(page: str) -> tuple[list[Node], list[tuple[Node, str]], list[tuple[int, bool]]]:
    """As :func:`read_tree`, with each block's line and whether white space parts it from the line's last block."""
    root = Node("#page", None, "")
    nodes, blocks = [root], []
    stack: list[tuple[str, Node]] = [("#page", root)]
    held: list[tuple[Node, str]] = []
    lines: list[tuple[int, bool]] = []
    line = 0
    in_link = 0
    at, end = 0, len(page)

    def flush() -> None:
        nonlocal line
        gap = False
        for owner, run in groupby(held, key=itemgetter(0)):
            raw = html.unescape("".join([x for _, x in run]))
            text = " ".join(raw.split())
            if text:
                owner.size += len(text)
                blocks.append((owner, text))
                lines.append((line, gap or raw[0].isspace()))
                gap = raw[-1].isspace()
            else:
                gap = gap or bool(raw)
        held.clear()
        line += 1

    def close(k: int) -> None:
        nonlocal in_link
        for tag, _ in stack[k:]:
            in_link -= tag == "a"
        if any(tag not in _INLINE for tag, _ in stack[k:]):
            flush()
        del stack[k:]

    def add(text: str) -> None:
        if text:
            held.append((stack[-1][1], text))
            if in_link:
                stack[-1][1].own_links += len(text)

    while at < end:
        hit = _PIECE.search(page, at)
        if hit is None:
            add(page[at:])
            break
        add(page[at : hit.start()])
        at = hit.end()
        tag = hit["tag"]
        if tag is None:
            continue
        tag = tag.lower()
        if hit["close"]:
            for k in range(len(stack) - 1, 0, -1):
                if stack[k][0] == tag:
                    close(k)
                    break
                if tag in _INLINE and stack[k][0] not in _INLINE:
                    break  # a stray inline end tag does not end blocks
            continue
        if tag == "br":
            held.append((stack[-1][1], " "))
            continue
        rest = hit["rest"] or ""
        if tag in _DROP:
            if tag not in _VOID and not rest.endswith("/"):
                at = _skip(page, tag, at)
            continue
        if tag in _VOID:
            if tag == "hr":
                flush()
            continue
        if tag in _ENDS_P:
            for k in range(len(stack) - 1, 0, -1):
                if stack[k][0] == "p":
                    close(k)
                    break
                if stack[k][0] not in _INLINE:
                    break
        if tag in _SIBLINGS:
            ends, limits = _SIBLINGS[tag]
            for k in range(len(stack) - 1, 0, -1):
                if stack[k][0] in limits:
                    break
                if stack[k][0] in ends:
                    close(k)
                    break
        hidden = bool(rest) and _hides(rest)
        if tag in _INLINE:
            if tag == "a":
                in_link += 1
            if not hidden:
                stack.append((tag, stack[-1][1]))
                continue
        else:
            flush()
        parent = stack[-1][1]
        names = " ".join(a or b or c for a, b, c in _NAMES.findall(rest)).lower() if rest else ""
        node = Node(tag, parent, names)
        node.place, node.hidden = len(parent.children), hidden
        parent.children.append(node)
        nodes.append(node)
        stack.append((tag, node))
    flush()
    for node in reversed(nodes):
        node.links += node.own_links
        if node.parent is not None:
            node.parent.links += node.links
    return nodes, blocks, lines


def _skip(page: str, tag: str, at: int) -> int:
    """Where an element whose text never counts ends; nested elements of the same tag are skipped with it."""
    if tag in ("script", "style", "textarea", "title", "template", "iframe"):
        hit = re.compile(rf"</{tag}\s*>", re.IGNORECASE).search(page, at)
        return hit.end() if hit else len(page)
    depth = 1
    for hit in re.compile(rf"<(/?){re.escape(tag)}\b[^>]*>", re.IGNORECASE).finditer(page, at):
        depth += -1 if hit[1] else 1
        if not depth:
            return hit.end()
    return len(page)


@lru_cache(maxsize=1 << 14)
def _themes(names: str) -> tuple[str, ...]:
    words = set(re.split(r"[\s_]+", names)) | set(re.split(r"[^a-z0-9]+", names))
    return tuple(sorted({_THEME_OF[w] for w in words if w in _THEME_OF}))


def _bucket(x: float, edges: tuple[float, ...]) -> int:
    return sum(x >= e for e in edges)


def features(nodes: list[Node]) -> tuple[list[list[str]], list[int], list[str]]:
    """Node features, parent positions (-1 for the root) and edge kinds."""
    number = {id(n): i for i, n in enumerate(nodes)}
    total = [n.size for n in nodes]
    parents = [-1 if n.parent is None else number[id(n.parent)] for n in nodes]
    for i in range(len(nodes) - 1, 0, -1):
        total[parents[i]] += total[i]
    rows, kinds = [], []
    unseen: list[bool] = []
    below: list[str] = []  # nearest marked surroundings of each element's children
    for i, (n, size) in enumerate(zip(nodes, total, strict=True)):
        group, themes = _TAG_GROUPS.get(n.tag, "box"), _themes(n.names)
        around = below[parents[i]] if i else "none"
        below.append(group if group in ("nav", "header", "footer", "aside", "form") else next((t for t in themes if t != "content"), around))
        row = ["bias", "tag " + group, "under " + around, *("theme " + t for t in themes), f"size {_bucket(size, (1, 25, 80, 200, 600))}", f"link {_bucket(n.links / max(size, 1), (0.05, 0.3, 0.6))}"]
        if "content" in themes and len(themes) > 1:
            row.append("theme mixed")
        unseen.append(n.hidden or (i > 0 and unseen[parents[i]]))
        if unseen[i]:
            row.append("hidden")
        rows.append(row)
        kinds.append("hidden" if unseen[i] else "marked" if themes or group in ("nav", "header", "footer", "aside", "form", "article", "main") else "leaf" if group in ("p", "head", "quote", "cell", "figure") else "list" if group in ("li", "list", "table") else "box")
    return rows, parents, kinds


class TreeModel:
    """Binary labels on a tree; scores are log odds of content."""

    def __init__(self) -> None:
        self.node: dict[str, float] = {}
        #: per edge kind: scores of (parent, child) = (0,0), (0,1), (1,0), (1,1)
        self.edge: dict[str, list[float]] = {k: [0.0] * 4 for k in _EDGE_KINDS}

    def messages(self, rows: list[list[str]], parents: list[int], kinds: list[str]) -> tuple[list[float], list[float], list[tuple[float, ...]]]:
        """Node potentials, marginals of content, and joint marginals of each (parent, child) edge, by sum-product."""
        get = self.node.get
        unary = [sum([get(f, 0.0) for f in row]) for row in rows]
        n = len(rows)
        gathered = unary[:]  # log odds from below
        up = [0.0] * n
        for i in range(n - 1, 0, -1):
            a, b, c, d = self.edge[kinds[i]]
            g = gathered[i]
            up[i] = _lse(c, d + g) - _lse(a, b + g)
            gathered[parents[i]] += up[i]
        belief = gathered[:]
        joint: list[tuple[float, ...]] = [()] * n
        for i in range(1, n):
            a, b, c, d = self.edge[kinds[i]]
            above = belief[parents[i]] - up[i]
            belief[i] = gathered[i] + _lse(b, d + above) - _lse(a, c + above)
            g = gathered[i]
            logs = (a, b + g, c + above, d + g + above)
            top = max(logs)
            weights = [math.exp(x - top) for x in logs]
            norm = sum(weights)
            joint[i] = tuple(w / norm for w in weights)
        return unary, [1 / (1 + math.exp(-max(-40.0, min(40.0, b)))) for b in belief], joint

    def fit(self, pages: list[tuple[list[list[str]], list[int], list[str], list[int]]], turns: int = 60, rate: float = 0.4, decay: float = 2e-3) -> TreeModel:
        """Adagrad on the exact likelihood of labelled trees."""
        squares: dict[object, float] = {}
        for _ in range(turns):
            grads: dict[object, float] = {}
            for rows, parents, kinds, labels in pages:
                _, chance, joint = self.messages(rows, parents, kinds)
                for row, p, y in zip(rows, chance, labels, strict=True):
                    for f in row:
                        grads[f] = grads.get(f, 0.0) + y - p
                for i in range(1, len(rows)):
                    if kinds[i] == "hidden":  # says nothing of the element around it: its scores stay zero
                        continue
                    seen = 2 * labels[parents[i]] + labels[i]
                    for k in range(4):
                        key = (kinds[i], k)
                        grads[key] = grads.get(key, 0.0) + (k == seen) - joint[i][k]
            for key, g in grads.items():
                value = self.edge[key[0]][key[1]] if isinstance(key, tuple) else self.node.get(key, 0.0)
                g = g / len(pages) - decay * value
                squares[key] = squares.get(key, 1e-8) + g * g
                value += rate * g / math.sqrt(squares[key])
                if isinstance(key, tuple):
                    self.edge[key[0]][key[1]] = value
                else:
                    self.node[key] = value
        return self


def _lse(a: float, b: float) -> float:
    return a + math.log1p(math.exp(b - a)) if a > b else b + math.log1p(math.exp(a - b))


def labelled_pages(count: int = 160, seed: int = 11) -> list[str]:
    """Generated pages over many layouts; their main texts stand between two control marks."""
    draw = random.Random(seed)

    def words(low: int, high: int) -> str:
        return " ".join("".join(draw.choice("abcdeinorstu") for _ in range(draw.randint(1, 8))) for _ in range(draw.randint(low, high)))

    def link(low: int = 1, high: int = 4) -> str:
        return f'<a href="/{words(1, 1)}">{words(low, high)}</a>'

    def links(tag: str = "ul") -> str:
        return f"<{tag}>" + "".join(f"<li>{link()}</li>" for _ in range(draw.randint(3, 8))) + f"</{tag}>"

    def prose(low: int = 1, high: int = 3) -> str:
        return "".join(f"<p>{words(4, 60)}.</p>" for _ in range(draw.randint(low, high)))

    def name(*themes: str) -> str:
        word = draw.choice(_THEMES[draw.choice(themes)].split())
        return f'{draw.choice(["class", "id", "class"])}="{draw.choice(["", "site-", "js ", "block "])}{word}"'

    def noise(kind: str) -> str:
        if kind == "menu":
            return draw.choice([f"<nav>{links()}</nav>", f'<div {name("menu")}>{links()}</div>', f'<ul {name("menu")}>' + links()[4:], f'<nav {name("menu")}>' + " ".join(link() for _ in range(5)) + "</nav>"])
        if kind == "header":
            body = draw.choice([f"<h1>{words(1, 4)}</h1>", f"<p>{words(2, 9)}</p>", f"<div>{words(2, 5)}</div>", f"<h2>{words(1, 3)}</h2><p>{words(3, 12)}</p>"]) + draw.choice(["", links()])
            return draw.choice([f"<header>{body}</header>", f'<div {name("head")}>{body}</div>'])
        if kind == "footer":
            body = draw.choice([f"&copy; {words(2, 8)}", f"<p>&copy; {words(3, 25)}</p>", prose(1, 2) + links(), f"{words(2, 4)} &middot; {words(4, 12)}"])
            return draw.choice([f"<footer>{body}</footer>", f'<div {name("foot")}>{body}</div>'])
        if kind == "side":
            body = draw.choice([f"<h3>{words(1, 3)}</h3>{links()}", prose(1, 2), f"<h2>{words(1, 2)}</h2>{prose(1, 2)}{links('ol')}"])
            return draw.choice([f"<aside>{body}</aside>", f'<div {name("side")}>{body}</div>', f'<section {name("side")}>{body}</section>'])
        if kind == "advert":
            return f'<{(t := draw.choice(["div", "section", "aside", "div"]))} {name("advert")}>{draw.choice([words(4, 30) + ".", prose(1, 2), f"<p>{words(3, 12)} {link()}</p>"])}</{t}>'
        if kind == "notice":
            return f'<div {name("notice")}>{draw.choice([words(6, 30) + ".", prose(1, 1), f"<p>{words(8, 30)}</p><button>{words(1, 2)}</button>"])}</div>'
        if kind == "reply":
            one = [f'<div {name("reply")}><p>{words(5, 50)}</p></div>', f"<li><p>{words(5, 50)}</p></li>", f"<article><h4>{words(1, 2)}</h4><p>{words(5, 50)}</p></article>"]
            t = draw.choice(["div", "section", "ol", "div"])
            return f'<{t} {name("reply")}>' + f"<h3>{words(1, 2)}</h3>" * (t != "ol") + "".join(draw.choice(one[1:2] if t == "ol" else [one[0], one[2]]) for _ in range(draw.randint(1, 4))) + f"</{t}>"
        if kind == "form":
            body = f"<p>{words(3, 20)}</p><label>{words(1, 3)}</label><input name=q><button>{words(1, 2)}</button>"
            return draw.choice([f"<form>{body}</form>", f'<div {name("form")}><form>{body}</form></div>', f'<div {name("form")}>{prose(1, 1)}</div>'])
        return f'<div {name("share")}>' + " ".join(link(1, 2) for _ in range(4)) + "</div>"

    def mark(text: str) -> str:
        return "\x02" + text + "\x03"

    def block() -> str:
        kind = draw.random()
        if kind < 0.62:
            text = draw.choice([words(3, 70), words(1, 6) + ".", f"<b>{words(2, 9)}.<br>" if draw.random() < 0.5 else words(1, 12), f"{words(4, 20)} {link()} {words(4, 30)}", f"{words(2, 8)} <em>{words(1, 3)}</em>, {words(2, 20)}"])
            return f"<p>{mark(text)}" + draw.choice(["</p>", "</p>", ""])
        if kind < 0.74:
            return f"<{(h := draw.choice(['h2', 'h3', 'h4']))}>{mark(words(1, 7))}</{h}>"
        if kind < 0.84:
            t = draw.choice(["ul", "ol"])
            return f"<{t}>" + "".join(f"<li>{mark(words(2, 20))}</li>" for _ in range(draw.randint(2, 5))) + f"</{t}>"
        if kind < 0.9:
            return f"<blockquote><p>{mark(words(5, 30))}</p></blockquote>"
        if kind < 0.95:
            return "<table>" + "".join(f"<tr><td>{mark(words(1, 4))}</td><td>{mark(words(1, 6))}</td></tr>" for _ in range(3)) + "</table>"
        return f"<figure><img src=x><figcaption>{mark(words(3, 12))}</figcaption></figure>"

    out = []
    before, after = ["menu", "header", "advert", "notice", "form", "share", "side"], ["footer", "side", "advert", "reply", "form", "share", "menu", "notice"]
    for _ in range(count):
        inside = [block() for _ in range(draw.choice([1, 1, 2, 3, 4, 6, 9]))]
        if draw.random() < 0.25:
            inside.insert(draw.randint(0, len(inside)), noise(draw.choice(["advert", "share", "side", "notice", "form"])))
        head = f"<h1>{mark(words(2, 9))}</h1>" if draw.random() < 0.85 else ""
        core = head + "".join(inside)
        core = draw.choice([f"<article>{core}</article>", f"<article>{core}</article>", f"<main>{core}</main>", f"<main><article>{core}</article></main>", f'<div {name("content")}>{core}</div>', f'<div {name("content")}><div>{core}</div></div>', f'<section {name("content")}>{core}</section>', f"<div>{core}</div>"])
        start = "".join(noise(k) for k in draw.sample(before, draw.randint(1, 4)))
        stop = "".join(noise(k) for k in draw.sample(after, draw.randint(1, 4)))
        body = draw.choice([start + core + stop, f'<div class="wrap">{start}{core}{stop}</div>', f'{start}<div id="container">{core}{noise("side")}</div>{stop}'])
        out.append(f"<html><head><title>{words(2, 6)}</title><style>p{{}}</style></head><body>{body}</body></html>")
    return out


def hidden_pages(count: int = 40, seed: int = 13) -> list[str]:
    """Generated pages with hidden paragraphs, boxes and inline elements among their blocks."""
    draw = random.Random(seed)

    def words(low: int, high: int) -> str:
        return " ".join("".join(draw.choice("abcdeinorstu") for _ in range(draw.randint(1, 8))) for _ in range(draw.randint(low, high)))

    def hide() -> str:
        return draw.choice(["hidden", 'hidden=""', 'style="display:none"', "style='color:red; display: none'"])

    out = []
    for page in labelled_pages(count, seed):
        parts = page.split("<p>")
        for k in range(1, len(parts)):
            kind = draw.random()
            if kind < 0.2:
                parts[k - 1] += draw.choice([f"<p {hide()}>{words(4, 60)}.</p>", f"<p {hide()}>{words(4, 40)}", f"<div {hide()}><p>{words(4, 60)}.</p></div>", f"<section {hide()}>{words(4, 30)}</section>"])
            elif kind < 0.35:
                parts[k] = parts[k].replace("\x03</p>", f"\x03 <span {hide()}>{words(1, 12)}</span></p>", 1)
        out.append("<p>".join(parts))
    return out


def _labelled_tree(page: str) -> tuple[list[list[str]], list[int], list[str], list[int]]:
    """Trees of a marked page: text blocks in marks are content; an element is content if most of its text is."""
    nodes, blocks = read_tree(page)
    good, bad = {id(n): 0 for n in nodes}, {id(n): 0 for n in nodes}
    for node, text in blocks:
        marked = "\x02" in text
        for n in _ancestors(node):
            (good if marked else bad)[id(n)] += len(text)
        node.size -= 2 * marked
    rows, parents, kinds = features(nodes)
    return rows, parents, kinds, [int(good[id(n)] > bad[id(n)]) for n in nodes]


def _ancestors(node: Node | None):
    while node is not None:
        yield node
        node = node.parent


@lru_cache(maxsize=2)
def trained(count: int = 160, seed: int = 11) -> TreeModel:
    return TreeModel().fit([_labelled_tree(page) for page in labelled_pages(count, seed) + hidden_pages()])


def main_text(page: str | None, model: TreeModel, threshold: float = 0.5) -> str:
    if not page:
        return ""
    nodes, blocks, lines = _read(page)
    _, chance, _ = model.messages(*features(nodes))
    good = {id(n) for n, p in zip(nodes, chance, strict=True) if p >= threshold}
    out: list[str] = []
    last, parted = -1, False
    for (node, text), (line, gap) in zip(blocks, lines, strict=True):
        parted = line == last and (parted or gap)
        if id(node) in good:
            if out:
                out.append("\n" if line != last else " " if parted else "")
            out.append(text)
            last, parted = line, False
    return "".join(out)


def extract(pages: DataFrame, model: TreeModel | None = None, threshold: float = 0.5) -> DataFrame:
    """(page_id, url, text, n_chars) for every row of ``pages``."""
    model = model or trained()

    def kernel(batch: pa.RecordBatch) -> pa.RecordBatch:
        texts = [main_text(h, model, threshold) for h in batch.column("html").to_pylist()]
        return pa.record_batch([batch.column("page_id"), batch.column("url"), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])

    return map_arrow(pages.select(F.col("page_id").cast("long").alias("page_id"), "url", "html"), kernel, "page_id long, url string, text string, n_chars long")
