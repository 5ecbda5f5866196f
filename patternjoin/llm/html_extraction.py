"""Main text of web pages by minimum-cut labelling.

A page is cut into blocks of text. A logistic classifier over a block's surroundings gives the cost
of calling it content or boilerplate: these become capacities towards the two terminals. Blocks
that follow each other, and blocks close in the DOM, are joined by smoothness edges. The minimum
cut labels all blocks of a page at once.

The classifier is fitted on pages that mark their article: there the blocks inside it, outside of
menus, headers, footers, asides and forms, are content and all others are not. What the marking
itself says (W_IN_CONTENT) is not fitted, the rest is learnt from the other features alone, close to
START where the pages say little.
"""

from __future__ import annotations

import html
import math
import re
from collections import Counter, deque
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import laid

#: Characters of markup that are parsed between two batches.
LAID_CHARS = 2_000_000

VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
#: Elements whose content is never text of the page.
SKIPPED = frozenset("script style template noscript head title svg math canvas object iframe audio video textarea select datalist".split())
RAW_TEXT = frozenset("script style textarea title iframe noscript xmp noembed noframes".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split())
BOILER_TAGS = frozenset("nav footer aside form menu dialog button fieldset".split())
CONTENT_TAGS = frozenset("article main".split())
#: A start tag of the second kind ends an open element of the first.
CLOSES = {"p": frozenset("address article aside blockquote div dl fieldset figure footer form h1 h2 h3 h4 h5 h6 header hr main nav ol p pre section table ul li dd dt".split()),
          "li": frozenset({"li"}), "dt": frozenset({"dt", "dd"}), "dd": frozenset({"dt", "dd"}), "tr": frozenset({"tr", "tbody"}),
          "td": frozenset({"td", "th", "tr"}), "th": frozenset({"td", "th", "tr"}), "option": frozenset({"option"})}

#: Fixed word lists: what names of boilerplate say, and what they may say beside it.
_BOILER_WORDS = frozenset("""nav navbar navigation menu foot footer head header masthead topbar sidebar aside ad ads advert adverts advertisement
sponsor sponsored promo promotion banner cookie cookies consent gdpr notice alert comment comments reply replies respond discussion disqus related
recommended share sharing social breadcrumb breadcrumbs pager pagination newsletter subscribe signup login search popup modal overlay copyright legal
toolbar tags skip""".split())
_NEUTRAL_WORDS = frozenset("""site page global main top bottom left right side bar box block list area section container wrapper wrap inner outer item
items link links button buttons form widget panel row col column content text body thread user reader unit slot space policy message links group""".split())
_PARTS = re.compile(r"[A-Z]?[a-z]+|[A-Z]+|\d+")


def _boiler_name(names: str) -> bool:
    """Some class, id or role consists of boilerplate words, neutral words beside them: search-box, not search-engines."""
    for name in names.split():
        parts = [x.lower() for x in _PARTS.findall(name) if not x.isdigit()]
        if parts and all(x in _BOILER_WORDS or x in _NEUTRAL_WORDS for x in parts) and any(x in _BOILER_WORDS for x in parts):
            return True
    return False


_CONTENT_NAMES = re.compile(r"(?:^|[\s_-])(?:article|content|post|entry|story|main|body|text)(?:$|[\s_-])", re.I)
_HIDDEN = re.compile(r"display\s*:\s*none|visibility\s*:\s*hidden", re.I)
_TAG = re.compile(r"<(?:!--(?P<comment>.*?)(?:-->|$)|!\[CDATA\[(?P<cdata>.*?)(?:\]\]>|$)|[!?][^>]*(?:>|$)"
                  r"|/(?P<end>[a-zA-Z][^\s/>]*)[^>]*(?:>|$)"
                  r"|(?P<start>[a-zA-Z][^\s/>]*)(?P<attrs>(?:[^\"'>]|\"[^\"]*(?:\"|$)|'[^']*(?:'|$))*)(?:>|$))", re.S)
_ATTR = re.compile(r"([^\s=\"'/>]+)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))|([^\s=\"'/>]+)")
_SPACE = re.compile(r"\s+")

#: The classifier's features and the weights it starts from, in the units of the cut's capacities: above zero speaks for content.
FEATURES = ("base", "links", "length", "boiler_tag", "boiler_name", "content_name", "list", "paragraph", "heading")
START = (-1.0, -4.0, 0.8, -9.0, -8.0, 1.5, -0.7, 1.5, 0.8)
W_IN_CONTENT = 5.0
#: Pages that the classifier is fitted on, those of smallest hash; the pull towards START in blocks, and rounds of Newton's method.
SAMPLE_PAGES, PULL, ROUNDS = 2_000, 20.0, 8
#: Ancestors of a block that smoothness looks at, from the block upwards.
NEAR_LEVELS = 12
#: Smoothness of blocks in sequence, and of neighbours among the children of one element.
W_NEXT, W_SIBLING = 0.9, 0.6


@dataclass
class Block:
    text: str
    path: tuple[int, ...]
    parent: int
    features: tuple[float, ...]
    inside: bool

    def score(self, weights: tuple[float, ...]) -> float:
        return W_IN_CONTENT * self.inside + sum(w * x for w, x in zip(weights, self.features, strict=True))


@dataclass
class _Open:
    tag: str
    number: int
    boiler_tag: bool
    boiler_name: bool
    content: bool
    content_name: bool
    skipped: bool
    block: str  # the nearest block-level element
    link: bool
    in_list: bool
    path: tuple[int, ...] = field(default=())


def _attributes(raw: str) -> dict[str, str]:
    out: dict[str, str] = {}
    for m in _ATTR.finditer(raw):
        name = (m[1] or m[5]).lower()
        out.setdefault(name, html.unescape(m[2] or m[3] or m[4] or ""))
    return out


def blocks_of(page: str) -> list[Block]:
    """Blocks of text in page order, with the classifier's features."""
    root = _Open("", 0, False, False, False, False, False, "", False, False)
    stack, out = [root], []
    parts: list[tuple[str, bool]] = []
    number = 0

    def flush(at: _Open) -> None:
        if not parts:
            return
        text = _SPACE.sub(" ", html.unescape("".join(p for p, _ in parts))).strip()
        if text:
            linked = sum(len(p) for p, l in parts if l) / max(1, sum(len(p) for p, _ in parts))
            out.append(Block(text, at.path, at.number, (
                1.0, linked, min(3.0, math.log2(1 + len(text) / 25)), float(at.boiler_tag), float(at.boiler_name), float(at.content_name),
                float(at.in_list), float(at.block in ("p", "pre", "blockquote")), float(at.block in ("h1", "h2", "h3", "h4", "h5", "h6"))), at.content))
        parts.clear()

    at, n = 0, len(page)
    while at < n:
        lt = page.find("<", at)
        top = stack[-1]
        if lt < 0:
            lt = n
        if lt > at and not top.skipped:
            parts.append((page[at:lt], top.link))
        if lt >= n:
            break
        m = _TAG.match(page, lt)
        if m is None:  # a bare "<" is text
            if not top.skipped:
                parts.append(("&lt;", top.link))
            at = lt + 1
            continue
        at = max(m.end(), lt + 1)
        if m["cdata"] is not None:
            if not top.skipped:
                parts.append((m["cdata"].replace("&", "&amp;"), top.link))
        elif m["end"]:
            tag = m["end"].lower()
            if tag == "br":
                flush(top)
                continue
            depth = next((i for i in range(len(stack) - 1, 0, -1) if stack[i].tag == tag), 0)
            # an inline end tag does not reach over the block it stands in
            if depth and tag in INLINE and any(s.tag not in INLINE for s in stack[depth + 1:]):
                for s in stack[depth:]:
                    if tag == "a":
                        s.link = False
                continue
            if depth:
                if tag not in INLINE or stack[depth].skipped or any(s.tag not in INLINE for s in stack[depth:]):
                    flush(top)
                del stack[depth:]
            elif tag not in INLINE:
                flush(top)
        elif m["start"]:
            tag = m["start"].lower()
            if tag == "br" or tag == "hr":
                flush(top)
                continue
            if tag in VOID:
                continue
            inline = tag in INLINE
            if not inline:
                flush(top)
                for i in range(len(stack) - 1, 0, -1):
                    s = stack[i].tag
                    if tag in CLOSES.get(s, ()):
                        del stack[i:]
                        break
                    if s not in INLINE and s not in ("p", "li", "dt", "dd", "tr", "td", "th", "option", "tbody"):
                        break
                top = stack[-1]
            raw = m["attrs"] or ""
            own = _attributes(raw) if raw.strip(" /\n\t") else {}
            name = f"{own.get('class', '')} {own.get('id', '')} {own.get('role', '')}" if own else ""
            hidden = bool(own) and ("hidden" in own or own.get("aria-hidden") == "true" or bool(_HIDDEN.search(own.get("style", ""))))
            boiler_name = hidden or bool(name.strip() and tag not in ("body", "html") and tag not in CONTENT_TAGS and _boiler_name(name))
            is_content = tag in CONTENT_TAGS or own.get("role") in ("main", "article") or own.get("itemprop") == "articleBody"
            nested_comment = tag == "article" and bool(name.strip()) and bool(re.search(r"comment|reply|teaser|card|related|promo|advert", name, re.I))
            number += 1
            entry = _Open(tag, number, top.boiler_tag or tag in BOILER_TAGS or tag == "header",
                          top.boiler_name or boiler_name or nested_comment, top.content or is_content,
                          top.content_name or bool(name.strip() and _CONTENT_NAMES.search(name)), top.skipped or tag in SKIPPED or hidden,
                          top.block if inline else tag, top.link or tag == "a", top.in_list or tag in ("ul", "ol", "dl"), (*top.path[1 - NEAR_LEVELS:], number))
            if inline and entry.skipped == top.skipped and entry.boiler_name == top.boiler_name:
                entry.number, entry.path = top.number, top.path
            elif inline:
                flush(top)
            if raw.endswith("/") and tag not in SKIPPED and tag not in RAW_TEXT and inline:
                continue
            if tag in RAW_TEXT:
                close = re.compile(rf"</{re.escape(tag)}(?=[\s/>])[^>]*(?:>|$)", re.I).search(page, at)
                at = close.end() if close else n
                continue
            stack.append(entry)
    flush(stack[-1])
    return out


def min_cut(scores: list[float], edges: list[tuple[int, int, float]]) -> list[bool]:
    """True where a node stays on the content side of a minimum cut.

    Calling node i boilerplate costs max(0, scores[i]), calling it content max(0, -scores[i]);
    an edge costs its weight when its ends are labelled differently. A node whose own score
    outweighs all its edges has that label in every minimum cut and leaves the network first.
    """
    n = len(scores)
    near: list[dict[int, float]] = [{} for _ in range(n)]
    for a, b, w in edges:
        if a != b:
            near[a][b] = near[a].get(b, 0.0) + w
            near[b][a] = near[b].get(a, 0.0) + w
    score = list(scores)
    label: list[bool | None] = [None] * n
    todo = deque(range(n))
    while todo:
        i = todo.popleft()
        if label[i] is None and abs(score[i]) > sum(near[i].values()):
            label[i] = score[i] > 0
            for j, w in near[i].items():
                score[j] += w if label[i] else -w
                del near[j][i]
                todo.append(j)
            near[i] = {}
    rest = [i for i in range(n) if label[i] is None]
    if rest:
        _max_flow(rest, score, near, label)
    return [bool(x) for x in label]


def _max_flow(rest: list[int], score: list[float], near: list[dict[int, float]], label: list[bool | None]) -> None:
    """Blocking flows over what is left; what the source still reaches is content."""
    place = {i: k for k, i in enumerate(rest)}
    s, t = len(rest), len(rest) + 1
    room: list[dict[int, float]] = [{} for _ in range(len(rest) + 2)]
    for i, k in place.items():
        if score[i] > 0:
            room[s][k], room[k][s] = score[i], 0.0
        else:
            room[k][t], room[t][k] = -score[i], 0.0
        for j, w in near[i].items():
            room[k][place[j]] = w
    while True:
        level = {s: 0}
        queue = deque([s])
        while queue:
            a = queue.popleft()
            for b, r in room[a].items():
                if r > 1e-9 and b not in level:
                    level[b] = level[a] + 1
                    queue.append(b)
        if t not in level:
            break
        left = {a: list(room[a]) for a in level}
        path = [s]
        while path:
            a = path[-1]
            if a == t:
                push = min(room[x][y] for x, y in zip(path, path[1:], strict=False))
                for x, y in zip(path, path[1:], strict=False):
                    room[x][y] -= push
                    room[y][x] = room[y].get(x, 0.0) + push
                path = [s]
                continue
            while left[a]:
                b = left[a][-1]
                if level.get(b) == level[a] + 1 and room[a].get(b, 0.0) > 1e-9:
                    path.append(b)
                    break
                left[a].pop()
            else:
                path.pop()
                if path:
                    left[path[-1]].pop()
    for i, k in place.items():
        label[i] = k in level


def smoothness(blocks: list[Block]) -> list[tuple[int, int, float]]:
    edges, last = [], {}
    for i, b in enumerate(blocks):
        if i:
            a = blocks[i - 1]
            shared = len({*a.path} & {*b.path})  # common ancestors among the nearest
            apart = len(a.path) + len(b.path) - 2 * shared
            edges.append((i - 1, i, W_NEXT / (1 + apart)))
        home = b.path[:-1]
        if home in last:
            edges.append((last[home], i, W_SIBLING))
        last[home] = i
    return edges


def main_text(page: str | None, weights: tuple[float, ...] = START) -> str:
    if not page:
        return ""
    blocks = blocks_of(page)
    if not blocks:
        return ""
    keep = min_cut([b.score(weights) for b in blocks], smoothness(blocks))
    return " ".join(b.text for b, k in zip(blocks, keep, strict=True) if k)


def fit_weights(pages: DataFrame, id_column: str = "page_id", html_column: str = "html", sample_pages: int = SAMPLE_PAGES) -> tuple[float, ...]:
    """Weights of FEATURES from the pages of the sample that mark their article; START where none does.

    Tasks send moments only: for each round the gradient and the curvature of the log-likelihood.
    """
    keyed = pages.select(F.col(html_column).cast("string").alias("html"), F.xxhash64(F.col(id_column), F.col(html_column)).alias("key")).where(
        "html is not null")
    # the keys alone are sorted; pages then stay in their tasks (a page repeated with its id comes with its copies)
    last = keyed.select("key").orderBy("key").limit(sample_pages).agg(F.max("key").alias("key")).first()["key"]
    if last is None:
        return START
    sample = keyed.where(F.col("key") <= last).select("html")

    def features(batches):
        counted: Counter = Counter()
        for batch in batches:
            for page in batch.column(0).to_pylist():
                blocks = blocks_of(page)
                if any(b.inside for b in blocks):
                    for b in blocks:
                        boiler = b.features[3] or b.features[4]
                        counted[(*[round(x, 1) for x in b.features], b.inside and not boiler)] += 1
        rows = list(counted)
        yield pa.RecordBatch.from_arrays(
            [pa.array([list(r[:-1]) for r in rows], pa.list_(pa.float64())), pa.array([r[-1] for r in rows], pa.bool_()),
             pa.array(list(counted.values()), pa.int64())], names=["x", "content", "n"])

    # features are in tenths, so their combinations are bounded: at most 10 x 31 x 2^6 rows, whatever the pages
    rows = sample.mapInArrow(features, "x array<double>, content boolean, n long").groupBy("x", "content").agg(F.sum("n").alias("n")).collect()
    w = start = np.array(START)
    if not rows:
        return START
    x, y, n = np.array([r["x"] for r in rows]), np.array([float(r["content"]) for r in rows]), np.array([float(r["n"]) for r in rows])
    n *= 1_000 / n.sum()  # a thousand blocks' worth of evidence, so that the pull means the same for every sample
    for _ in range(ROUNDS):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        slope = x.T @ (n * (y - p)) - PULL * (w - start)
        bend = (x * (n * p * (1 - p))[:, None]).T @ x + PULL * np.eye(len(w))
        w = w + np.linalg.solve(bend, slope)
    return tuple(float(v) for v in np.round(w, 9))


def extract_text(pages: DataFrame, id_column: str = "page_id", url_column: str = "url", html_column: str = "html",
                 weights: tuple[float, ...] | None = None) -> DataFrame:
    """(page_id, url, text, n_chars), one row for each input row.

    Null and empty pages, and pages without content, give an empty text. Pages are taken whole,
    broken markup included. Null ids and urls and repeated rows pass through; an empty table
    gives no rows; only the three named columns are read. Without `weights` the classifier is
    fitted on the table's own pages.
    """
    weights = fit_weights(pages, id_column, html_column) if weights is None else weights

    def run(batches):
        for batch in batches:
            for part in laid(batch, 2, LAID_CHARS):
                texts = [main_text(p, weights) for p in part.column(2).to_pylist()]
                yield pa.RecordBatch.from_arrays(
                    [part.column(0), part.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())],
                    names=["page_id", "url", "text", "n_chars"])

    return pages.select(F.col(id_column).cast("long").alias("page_id"), F.col(url_column).cast("string").alias("url"),
                        F.col(html_column).cast("string").alias("html")).mapInArrow(
        run, "page_id long, url string, text string, n_chars long")
