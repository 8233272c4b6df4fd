"""Main text of web pages by a minimum cut over each page's blocks.

A page is read into blocks (runs of text between block-level tags) with their place in the DOM. A logistic classifier
gives each block a content cost and a boilerplate cost, which become capacities to the two terminals. Blocks that
follow each other, and blocks next to each other among those of one parent, are joined by smoothness edges whose
capacity falls with their distance in the DOM. The cut of least capacity labels the blocks; max-flow finds it. A block
whose terminal excess is above all its edges together is settled first, which is exact and leaves small graphs.

The classifier is trained here, on pages written by a fixed seed (labelled_pages(), TRAIN_PAGES of them) with known
labels: menus, headers, footers, sidebars, notices, adverts, forms, reader comments, articles, with and without
semantic tags.

Text of a block: character references decoded, white space one space, trimmed; blocks that are content are joined by
\\n in page order. Scripts, styles, templates, frames, form controls, hidden elements, comments, the head and annotations of
formulas never make blocks; formulas, drawings' text and what stands in for media are read like other text. The head
ends at its end tag, or at the first element or text that cannot stand in one; elements whose end tag may be left out
end where it is implied, hidden or not. A button, list of options, text field or the like whose end tag the page lacks
ends at the next block.

Defined results: a null or empty page, or one without content, gives an empty text. Broken or cut-off markup is read as
far as it goes. Repeated rows are read each. Empty tables give empty tables. Other columns are not read.
"""

from __future__ import annotations

import functools
import html as entities
import random
import re
from collections import deque
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import columns

TRAIN_PAGES, SEED, SMOOTH = 300, 11, 0.6

#: HTML element names by their role, and hints in class, id and role.
SKIP = frozenset("head script style template iframe select textarea button option datalist annotation annotation-xml".split())
HEAD = frozenset("head title base basefont bgsound link meta style script noscript noframes template".split())  # what leaves a head open
SCOPE = frozenset("button template object".split())  # implied ends stop here
HIDDEN = 32
RAW = frozenset("script style textarea title noscript iframe".split())
LOOSE = frozenset("button select textarea datalist template iframe annotation annotation-xml".split())  # hidden, and without their end tag no further than a block
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
BLOCK = frozenset("address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol p pre search section summary table tbody tfoot thead tr ul".split())
CHROME = frozenset("nav footer aside form menu dialog fieldset search".split())
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
BAD = re.compile(r"\b(?:ads?|advert\w*|banner|sponsor\w*|promo\w*|cookie\w*|consent|gdpr|notice|alert|sidebar|side|menu|nav\w*|footer|foot|masthead|header|breadcrumbs?|share|social|related|recommend\w*|subscribe|newsletter|popup|modal|overlay|widget|toolbar|login|signup|search|pagination|pager|copyright|legal|tags?|skip|banner|complementary|contentinfo|navigation)\b", re.I)
TALK = re.compile(r"\b(?:comments?|replies|reply|respond|disqus|discussion)\b", re.I)
GOOD = re.compile(r"\b(?:article\w*|content|main|post|entry|story|articlebody|text|body)\b", re.I)
_TOKEN = re.compile(r"""<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*>|<(/?)([A-Za-z][^\s/>]*)((?:[^>"']++|"[^"]*+"|'[^']*+')*+)>|<(/?)([A-Za-z][^\s/>]*)([^>]*)(?:>|\Z)|([^<]+|<)""", re.S)
_ATTR = re.compile(r"""([^\s"'<>/=]+)(?:\s*=\s*("[^"]*"|'[^']*'|[^\s"'=<>`]+))?""")
_SPLIT = re.compile(r"[-_]+|(?<=[a-z])(?=[A-Z])")
#: An element that opens closes an open one of these.
CLOSES = {"li": ("li",), "dd": ("dd", "dt"), "dt": ("dd", "dt"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"), "option": ("option",), "optgroup": ("option",), "button": ("button",), **dict.fromkeys(("thead", "tbody", "tfoot"), ("thead", "tbody", "tfoot", "caption", "tr", "td", "th"))}


class Block:
    __slots__ = ("chrome", "good", "bad", "talk", "article", "linked", "parts", "path", "size", "tag", "text")

    def __init__(self, stack: list):
        self.path = tuple(e[1] for e in stack)
        self.tag = next((e[0] for e in reversed(stack) if e[0] in BLOCK), "")
        flags = stack[-1][2] if stack else 0
        self.article, self.chrome, self.good, self.bad, self.talk = (bool(flags & b) for b in (1, 2, 4, 8, 16))
        self.parts, self.linked, self.text, self.size = [], 0, "", 0


def _flags(tag: str, attrs: str, outer: int) -> tuple[int, bool]:
    """The element's marks with those of its ancestors, and whether it is hidden."""
    f = outer
    if tag in ("article", "main"):
        f |= 1
    elif tag in CHROME or tag == "header" and not outer & 1:
        f |= 2
    hidden = False
    if attrs.strip(" /"):
        for k, v in _ATTR.findall(attrs):
            k, v = k.lower(), v.strip("\"'")
            if k in ("class", "id", "role", "itemprop", "aria-label"):
                v = _SPLIT.sub(" ", v)
                if TALK.search(v):
                    f |= 16
                elif BAD.search(v) and tag not in ("body", "html", "article", "main"):
                    f |= 8
                elif GOOD.search(v):
                    f |= 4
                if k == "role" and v == "main" or k == "itemprop" and v == "article Body":
                    f |= 1
            elif k == "hidden" or k == "style" and re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", v):
                hidden = True
    return f, hidden


def blocks_of(page: str) -> list[Block]:
    stack: list[tuple[str, int, int]] = []  # name, number, marks
    out: list[Block] = []
    now: Block | None = None
    links = number = 0
    at, n, ends = 0, len(page), True  # whether a noscript may still end
    loose: set[int] = set()  # numbers of open elements that have no end tag
    last_end: dict[str, int] = {}  # where the last end tag of a name stands

    def closes(tag: str) -> bool:
        """Whether an end tag follows."""
        if tag not in last_end:
            last_end[tag] = max((m.start() for m in re.finditer(rf"</{tag}\b", page, re.I)), default=-1)
        return last_end[tag] >= at

    def end() -> None:
        nonlocal now
        if now is not None:
            now.text = " ".join("".join(now.parts).split())
            if now.text:
                now.size = len(now.text.split())
                out.append(now)
            now = None

    while at < n:
        m = _TOKEN.match(page, at)
        at = m.end()
        text = m[7]
        top = stack[-1] if stack else ("", 0, 0)
        if text is not None:
            if top[0] == "head" and not text.isspace():
                stack.pop()
                top = stack[-1] if stack else ("", 0, 0)
            if not top[2] & HIDDEN:
                if now is None:
                    if text.isspace():
                        continue
                    now = Block(stack)
                text = entities.unescape(text) if "&" in text else text
                now.parts.append(text)
                if links:
                    now.linked += len(text)
            continue
        closing, tag, attrs = (m[1], m[2], m[3]) if m[2] else (m[4], m[5], m[6])
        if tag is None:
            continue
        tag = tag.lower()
        shown = not top[2] & HIDDEN
        if closing:
            if tag == "a" and shown:
                links = max(0, links - 1)
            if shown and tag not in BLOCK and now is not None and tag in ("td", "th"):
                now.parts.append(" ")
            for k in range(len(stack) - 1, -1, -1):
                if stack[k][0] == tag:
                    del stack[k:]
                    break
                if stack[k][0] in BLOCK and tag not in BLOCK and tag not in ("td", "th", "head") and stack[k][2] & HIDDEN and not (k and stack[k - 1][2] & HIDDEN):
                    break  # an inline end tag does not end a hidden block
            if tag in BLOCK and (shown or not (stack and stack[-1][2] & HIDDEN)):
                end()
            continue
        if top[0] == "head" and tag not in HEAD or tag == "body":
            for k in range(len(stack) - 1, -1, -1):
                if stack[k][0] == "head":
                    del stack[k:]
                    break
        if loose and tag in BLOCK:
            for k, e in enumerate(stack):
                if e[1] in loose:
                    del stack[k:]
                    loose.clear()
                    break
        if tag in RAW and not (tag in LOOSE and not closes(tag)) and (tag != "noscript" or stack and stack[-1][0] == "head"):
            if not attrs.endswith("/"):
                close = re.compile(rf"</{tag}\b[^>]*>", re.I).search(page, at) if tag != "noscript" or ends else None
                ends = ends and (tag != "noscript" or close is not None)
                at = close.end() if close else at if tag == "noscript" else n
            continue
        if tag in BLOCK:
            for k in range(len(stack) - 1, -1, -1):  # a block ends an open paragraph
                if stack[k][0] == "p":
                    del stack[k:]
                    break
                if stack[k][0] in BLOCK or stack[k][0] in SCOPE:
                    break
        for old in CLOSES.get(tag, ()):
            for k in range(len(stack) - 1, -1, -1):
                if stack[k][0] == old:
                    del stack[k:]
                    break
                if stack[k][0] in ("ul", "ol", "dl", "table", "menu") or stack[k][0] in SCOPE:
                    break
        outer = stack[-1][2] if stack else 0
        if not outer & HIDDEN:
            if tag in ("br", "wbr", "td", "th") and now is not None:
                now.parts.append(" ")
            if tag in BLOCK:
                end()
                links = 0 if tag in ("article", "main", "body", "p") else links
        if tag in VOID:
            continue
        if tag in SKIP:
            if not attrs.endswith("/"):
                number += 1
                stack.append((tag, number, outer | HIDDEN))
                if tag in LOOSE and not outer & HIDDEN and not closes(tag):
                    loose.add(number)
            continue
        flags, hidden = _flags(tag, attrs, outer)
        if attrs.endswith("/") and tag not in BLOCK:
            continue
        if hidden:
            flags |= HIDDEN
        number += 1
        links += tag == "a" and not flags & HIDDEN
        stack.append((tag, number, flags))
    end()
    return out


def features(blocks: list[Block]) -> np.ndarray:
    marked = any(b.article for b in blocks)
    rows = []
    for b in blocks:
        chars = max(1, sum(map(len, b.parts)))
        stops = sum(map(b.text.count, ".,!?;:"))
        rows.append((1.0, b.article, marked and not b.article, b.chrome, b.bad, b.talk, b.good and not b.bad, min(1.0, b.linked / chars), min(3.0, np.log1p(b.size) / 2), b.text[-1] in ".!?…。\"”»", b.tag in ("p", "pre", "blockquote"), b.tag in HEADINGS, b.tag in ("li", "tr", "dd", "dt"), min(1.0, stops / max(1, b.size))))
    return np.array(rows, dtype=float).reshape(len(blocks), 14)


def edges_of(blocks: list[Block], smooth: float = SMOOTH) -> dict[tuple[int, int], float]:
    """(i, j): capacity, for neighbours in the page and for neighbours among the blocks of one parent."""
    out: dict[tuple[int, int], float] = {}
    last: dict[int, int] = {}

    def join(i: int, j: int) -> None:
        a, b = blocks[i].path, blocks[j].path
        shared = 0
        for x, y in zip(a, b):
            if x != y:
                break
            shared += 1
        out[i, j] = out.get((i, j), 0.0) + smooth * 0.5 ** max(0, len(a) + len(b) - 2 * shared - 2)

    for j, b in enumerate(blocks):
        if j:
            join(j - 1, j)
        parent = b.path[-2] if len(b.path) > 1 else 0
        if (i := last.get(parent)) is not None and i != j - 1:
            join(i, j)
        last[parent] = j
    return out


def min_cut(excess: np.ndarray, edges: dict[tuple[int, int], float]) -> np.ndarray:
    """True for blocks on the content side; excess: capacity to content minus capacity to boilerplate. Ties go to boilerplate."""
    n = len(excess)
    x = list(map(float, excess))
    near: list[dict[int, float]] = [{} for _ in range(n)]
    for (i, j), c in edges.items():
        near[i][j] = near[i].get(j, 0.0) + c
        near[j][i] = near[j].get(i, 0.0) + c
    side = [None] * n
    todo = deque(range(n))
    while todo:  # settled blocks hand their edges to their neighbours' excess
        i = todo.popleft()
        if side[i] is None and abs(x[i]) >= sum(near[i].values()) and (x[i] or not near[i]):
            side[i] = x[i] > 0
            for j, c in near[i].items():
                x[j] += c if side[i] else -c
                del near[j][i]
                todo.append(j)
            near[i] = {}
    rest = [i for i in range(n) if side[i] is None]
    if rest:
        content = _reachable(rest, x, near)
        for i in rest:
            side[i] = i in content
    return np.array(side, dtype=bool)


def _reachable(nodes: list[int], x: list[float], near: list[dict[int, float]]) -> set[int]:
    """Nodes that the source still reaches after a maximum flow (level graphs and blocking flows)."""
    left = {i: dict(near[i]) for i in nodes}
    source, sink = {i: x[i] for i in nodes if x[i] > 0}, {i: -x[i] for i in nodes if x[i] < 0}
    tiny = 1e-12
    while True:
        level = {i: 0 for i in source if source[i] > tiny}
        q, ends = deque(level), False
        while q:
            i = q.popleft()
            ends = ends or sink.get(i, 0) > tiny
            for j, c in left[i].items():
                if c > tiny and j not in level:
                    level[j] = level[i] + 1
                    q.append(j)
        if not ends:
            return set(level)
        tried = {i: list(left[i]) for i in level}
        for s in [i for i in source if source[i] > tiny]:
            path = [s]
            while source[s] > tiny and path:
                i = path[-1]
                if sink.get(i, 0) > tiny:
                    flow = min([source[s], sink[i], *(left[a][b] for a, b in zip(path, path[1:]))])
                    source[s] -= flow
                    sink[i] -= flow
                    for a, b in zip(path, path[1:]):
                        left[a][b] -= flow
                        left[b][a] += flow
                    path = [s]
                elif tried[i]:
                    j = tried[i][-1]
                    if left[i][j] > tiny and level.get(j) == level[i] + 1:
                        path.append(j)
                    else:
                        tried[i].pop()
                else:
                    path.pop()
                    if path and tried[path[-1]]:
                        tried[path[-1]].pop()


def labelled_pages(pages: int = TRAIN_PAGES, seed: int = SEED) -> list[tuple[str, list[str]]]:
    """(html, texts of its content blocks)."""
    r = random.Random(seed)
    word = lambda: "".join(r.choices("abcdefghijklmnopqrstuvwxyz", k=r.randint(2, 9)))
    words = lambda a, b: " ".join(word() for _ in range(r.randint(a, b)))
    sentence = lambda: words(3, 18).capitalize() + r.choice([".", ".", ".", ", " + words(2, 8) + ".", "!", "?"])
    para = lambda: " ".join(sentence() for _ in range(r.choice([1, 1, 2, 4, 7])))
    out = []
    for _ in range(pages):
        plain = r.random() < 0.4  # no semantic tags
        box = lambda tag, name, inside: f'<div class="{name}">{inside}</div>' if plain or r.random() < 0.3 else f"<{tag}>{inside}</{tag}>"
        menu = lambda: "<ul>" + "".join(f'<li><a href="/{word()}">{words(1, 3)}</a></li>' for _ in range(r.randint(3, 8))) + "</ul>"
        good: list[str] = []

        def own(tag: str, text: str, lead: str = "") -> str:
            good.append(text)
            return f"<{tag}>{lead}{text}</{tag}>"

        body = own("h1", words(3, 9))
        for _ in range(r.randint(1, 9)):
            k = r.random()
            body += own("p", para()) if k < 0.75 else own("h2", words(2, 6)) if k < 0.85 else own("blockquote", sentence()) if k < 0.9 else "<ul>" + "".join(own("li", sentence()) for _ in range(3)) + "</ul>"
            if r.random() < 0.08:
                body += f'<div class="{r.choice(["ad", "advert", "promo", "related-links"])}">{sentence()}</div>'
            if r.random() < 0.05:
                body += f"<aside>{sentence()}</aside>"
        main = r.choice([f"<article>{body}</article>", f"<main>{body}</main>"]) if not plain else f'<div class="{r.choice(["content", "post-body", "entry", "story", "c1"])}">{body}</div>'
        parts = [box("nav", "menu", menu()), main, box("footer", "footer", "&copy; " + words(2, 8))]
        extra = [lambda: f'<div class="{r.choice(["ad", "banner", "sponsored"])}">{sentence()}</div>', lambda: box("header", "header", words(1, 5)), lambda: f'<div id="cookie-notice"><p>{para()}</p></div>', lambda: f"<div><p>{sentence()}</p></div>" if not plain else ""]
        for f in extra:
            if r.random() < 0.5:
                parts.insert(r.choice([0, 1]), f())
        late = [lambda: f'<section class="comments"><h3>{words(1, 2)}</h3>' + "".join(f'<div class="comment"><p>{para()}</p></div>' for _ in range(3)) + "</section>", lambda: box("aside", "sidebar", menu() + f"<p>{sentence()}</p>"), lambda: f"<form><label>{words(1, 4)}</label><p>{sentence()}</p><input></form>"]
        for f in late:
            if r.random() < 0.5:
                parts.insert(len(parts) - 1, f())
        out.append(("<html><head><title>" + words(2, 5) + "</title></head><body>" + "".join(parts) + "</body></html>", good))
    return out


@functools.cache
def trained(pages: int = TRAIN_PAGES, seed: int = SEED) -> tuple[float, ...]:
    """The logistic weights of features()."""
    xs, ys = [], []
    for page, good in labelled_pages(pages, seed):
        b = blocks_of(page)
        left = list(good)
        xs.append(features(b))
        for k in b:
            ys.append(bool(left) and k.text == left[0])
            if ys[-1]:
                left.pop(0)
    x, y = np.concatenate(xs), np.array(ys, dtype=float)
    w = np.zeros(x.shape[1])
    for _ in range(30):  # Newton steps with a small ridge
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        w = w + np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + 0.3 * np.eye(len(w)), x.T @ (y - p) - 0.3 * w)
    return tuple(map(float, w))


def main_text(page: str | None, weights: tuple[float, ...], smooth: float = SMOOTH) -> str:
    blocks = blocks_of(page) if page else []
    if not blocks:
        return ""
    # costs of the two labels are -log p and -log(1 - p); their difference is the classifier's output
    keep = min_cut(features(blocks) @ np.array(weights), edges_of(blocks, smooth))
    return "\n".join(b.text for b, k in zip(blocks, keep) if k)


def extract(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", weights: tuple[float, ...] | None = None, smooth: float = SMOOTH) -> DataFrame:
    """(page_id, url, text)."""
    w = weights or trained()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([b["page_id"], b["url"], pa.array([main_text(x.as_py(), w, smooth) for x in b["html"]], pa.string())], ["page_id", "url", "text"])

    d = columns(pages, page_id=id_col, url=url_col, html=html_col)
    kinds = dict(d.dtypes)
    return d.mapInArrow(run, f"page_id {kinds['page_id']}, url {kinds['url']}, text string")


def query(spark, sf_dir: str) -> DataFrame:
    from pyspark.sql import functions as F

    from .common import table

    return extract(table(spark, sf_dir, "pages")).select("page_id", "url", "text", F.length("text").cast("long").alias("n_chars"))
