"""Main-text extraction by minimum-cut labelling of a page's text blocks.

A tolerant tokenizer turns a page into blocks in page order. A linear classifier gives each block costs for being called
content or boilerplate, which become capacities from the source and to the sink. Neighbouring blocks, and neighbours among
the blocks of one parent element, are joined by smoothness edges. The blocks on the source side of the minimum cut are the
text.
"""

from __future__ import annotations

import html as _html
import re
from collections import defaultdict, deque
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F, types as T

from .common import map_text, table

#: Pages, and blocks of a page, the classifier is fitted on, at most (documented bounds), and the pull towards its prior weights.
TRAIN_PAGES, TRAIN_BLOCKS, PRIOR_PULL = 400, 1000, 0.05
ADJACENT, SIBLING, CLIP = 0.8, 0.8, 8.0

# Element kinds.
_VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
_GONE = frozenset("script style template noscript svg iframe head object audio video canvas title".split())
_RAW = frozenset("script style textarea title noscript iframe".split())
_BLOCK = frozenset("address article aside blockquote body caption center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr html legend li main menu nav ol optgroup option p pre search section select summary table tbody td tfoot th thead tr ul button label textarea".split())
_CLOSES = {
    "li": ({"li"}, {"ul", "ol", "menu"}), "dt": ({"dt", "dd"}, {"dl"}), "dd": ({"dt", "dd"}, {"dl"}), "tr": ({"tr", "td", "th"}, {"table"}), "td": ({"td", "th"}, {"tr", "table"}),
    "th": ({"td", "th"}, {"tr", "table"}), "option": ({"option"}, {"select", "datalist"}),
}
_SCOPE = frozenset("article aside body div footer form header main nav section td th table blockquote li dd button html".split())

# Features of a block and the prior weights of the classifier.
_FLAGS = ["article", "nav", "footer", "header", "aside", "form", "advert", "comments", "notice", "social", "content_class"]
PRIOR = {
    "bias": -0.5, "article": 4.0, "nav": -9.0, "footer": -9.0, "header": -6.0, "aside": -9.0, "form": -9.0, "advert": -9.0, "comments": -10.0, "notice": -9.0, "social": -8.0, "content_class": 1.5,
    "links": -3.0, "length": 0.5, "stop": 0.5, "heading": 0.5, "paragraph": 0.5, "item": -0.3, "copyright": -2.0,
}
_NAMES = list(PRIOR)
_BIT = {n: 1 << i for i, n in enumerate(_FLAGS)}
_BAD = ("nav", "footer", "aside", "form", "advert", "comments", "notice", "social")
_BAD_MASK = sum(_BIT[n] for n in _BAD)
_CONTENT = _BIT["article"] | _BIT["content_class"]
_TAG_FLAG = {"article": "article", "main": "article", "nav": "nav", "menu": "nav", "footer": "footer", "aside": "aside", "form": "form", "select": "form", "button": "form", "textarea": "form", "fieldset": "form", "label": "form", "dialog": "notice", "search": "form"}
_ROLE = {"navigation": "nav", "menu": "nav", "menubar": "nav", "contentinfo": "footer", "complementary": "aside", "search": "form", "form": "form", "dialog": "notice", "alert": "notice", "alertdialog": "notice", "main": "article", "article": "article", "banner": "header"}
_WORDS = {
    "nav": "nav navbar navigation menu menus breadcrumb breadcrumbs topbar toolbar pagination pager",
    "footer": "footer",
    "aside": "sidebar aside widget widgets related recommended recommendations",
    "form": "login signup newsletter subscribe",
    "advert": "ad ads adv advert advertisement advertising banner sponsored promo adsense",
    "comments": "comment comments disqus replies commentlist",
    "notice": "cookie cookies consent notice gdpr paywall",
    "social": "share sharing social",
    "content_class": "content article post entry story body text main",
}
# Words that say little within an article or a content element: they count outside of them only.
_WEAK_WORDS = {
    "nav": "toc",
    "footer": "foot colophon copyright legal",
    "aside": "side more trending popular",
    "form": "form search subscription register",
    "advert": "sponsor promotion promoted",
    "comments": "respond discussion reviews reply",
    "notice": "popup modal overlay alert disclaimer privacy",
    "social": "follow tags",
    "header": "header masthead",
}
_CLASS = {w: n for n, words in _WORDS.items() for w in words.split()}
_WEAK = {w: n for n, words in _WEAK_WORDS.items() for w in words.split()}
_NAME = re.compile(r"<(/?)([a-zA-Z][^\s/>]*)")
_SPECIAL = re.compile(r">|=\s*[\"']")
_ATTR = re.compile(r"([^\s\"'=<>/]++)(?:\s*+=\s*+(\"[^\"]*+\"|'[^']*+'|[^\s>]*+))?")
_UNSEEN = re.compile(r"display\s*:\s*none", re.I)
_SPLIT = re.compile(r"[^a-z]+")
_SPACES = re.compile(r"\s+")
_END = re.compile(r"[.!?…。！？:;\"”»)]$")


def _tags(page: str) -> Iterator[tuple[int, int, bool, str, str]]:
    """(start, end, whether it closes, lower-case name, attributes) of tags; comments and declarations have no name.

    A quoted value may hold any character; where quotes do not close before a tag does, the tag ends at its first ">". Time is
    linear: what a failed look for the end of quoted values has passed is not passed again.
    """
    at, gt, special, dead = page.find("<"), -1, -1, set()

    def quoted_end(start: int) -> int:
        nonlocal special
        if special < start:
            m = _SPECIAL.search(page, start)
            special = m.start() if m else len(page)
        passed, m = [], _SPECIAL.match(page, special)
        while m and page[m.start()] != ">" and m.start() not in dead:
            passed.append(m.start())
            close = page.find(m[0][-1], m.end())
            m = _SPECIAL.search(page, close + 1) if close >= 0 else None
        if m and page[m.start()] == ">":
            return m.start()
        dead.update(passed)
        return -1

    while at >= 0:
        if gt < at:
            gt = page.find(">", at)
            if gt < 0:  # no tag ends any more: only an open comment can follow
                at = page.find("<!--", at)
                if at >= 0:
                    yield at, len(page), False, "", ""
                return
        if page.startswith("<!--", at):
            end = page.find("-->", at + 2)
            end = len(page) if end < 0 else end + 3
            yield at, end, False, "", ""
        elif page.startswith(("<!", "<?"), at):
            end = gt + 1
            yield at, end, False, "", ""
        elif m := _NAME.match(page, at):
            end = quoted_end(m.end())
            end = (gt if end < 0 else end) + 1
            yield at, end, bool(m[1]), m[2].lower(), page[m.end() : end - 1]
        else:
            end = at + 1
        at = page.find("<", end)


def _flags_of(tag: str, attrs: str, memo: dict) -> tuple[int, int]:
    """Flags that an element gives to all blocks inside it (-1: hidden), and those it gives outside of content only."""
    if (known := memo.get((tag, attrs))) is not None:
        return known
    names, weak = {_TAG_FLAG.get(tag), "header" if tag == "header" else None}, set()
    hidden = False
    for m in _ATTR.finditer(attrs) if attrs else ():
        name, value = m[1].lower(), (m[2] or "").strip("\"'").lower()
        if name == "role":
            names.add(_ROLE.get(value))
        elif name in ("class", "id") and tag not in ("html", "body"):
            found = _SPLIT.split(value)
            names.update(map(_CLASS.get, found))
            weak.update(map(_WEAK.get, found))
        elif name == "hidden" or name == "aria-hidden" and value == "true" or name == "style" and _UNSEEN.search(value):
            hidden = True
    out = -1 if hidden else sum(_BIT[n] for n in names if n), sum(_BIT[n] for n in weak - names if n)
    if len(memo) > 4096:
        memo.clear()
    if len(attrs) <= 1024:
        memo[tag, attrs] = out
    return out


def blocks(page: str | None, memo: dict | None = None) -> list[tuple[str, int, str, int, int]]:
    """(text, flags, innermost block element, parent element's number, characters inside links), in page order."""
    page, memo = page or "", {} if memo is None else memo
    out: list[tuple[str, int, str, int, int]] = []
    stack: list[tuple[str, int, int, int]] = [("", 0, 0, 0)]  # element, flags with its ancestors', number, place of the innermost block
    places: dict[str, list[int]] = defaultdict(list)  # where in the stack each element is open
    parts: list[str] = []
    linked = links = gone = number = at = 0

    def flush():
        nonlocal parts, linked
        if parts:
            text = _SPACES.sub(" ", "".join(parts)).strip()
            if text:
                k = stack[-1][3]
                out.append((text, stack[-1][1], stack[k][0], stack[k - 1][2] if k else 0, linked))
            parts, linked = [], 0

    def add(raw: str):
        nonlocal linked
        if raw and not gone:
            text = _html.unescape(raw) if "&" in raw else raw
            parts.append(text)
            if links:
                linked += len(text)

    def close(k: int):
        """Leave the elements from k on."""
        nonlocal gone, links
        while len(stack) > k:
            tag, flags, _, _ = stack.pop()
            places[tag].pop()
            gone -= tag in _GONE or flags < 0
            links -= tag == "a"

    def innermost(tags) -> int:
        return max((places[t][-1] for t in tags if places.get(t)), default=0)

    skip = 0
    for start, end, closes, tag, attrs in _tags(page):
        if start < skip:
            continue
        add(page[max(at, skip) : start])
        at = end
        if not tag:
            continue
        if closes:
            k = innermost((tag,))
            if tag in _BLOCK or k and stack[-1][3] >= k:
                flush()
            if k:
                close(k)
            continue
        if tag == "br":
            parts.append(" ")
            continue
        if tag in _BLOCK:
            flush()
            ends, within = _CLOSES.get(tag, ({"p"}, _SCOPE))
            k = innermost(ends)
            if k and k >= innermost(within):
                close(k)
        if tag in _VOID or attrs.endswith("/"):
            continue
        if tag in _RAW and tag != "textarea":
            found = re.compile(rf"</{tag}\b[^>]*(?:>|\Z)", re.I).search(page, at)
            skip = at = found.end() if found else len(page)
            continue
        own, weak = _flags_of(tag, attrs, memo)
        number += 1
        above = stack[-1][1]
        if own >= 0 and above >= 0:
            if not above & _CONTENT:
                own |= weak
            if own & _BIT["header"] and (above | own) & _BIT["article"]:
                own &= ~_BIT["header"]  # an article's own header holds its title
            flags = above | own
        else:
            flags = -1
        places[tag].append(len(stack))
        stack.append((tag, flags, number, len(stack) if tag in _BLOCK else stack[-1][3]))
        gone += tag in _GONE or flags < 0
        links += tag == "a"
        if tag == "body":
            # an unclosed head ends here
            stack[:] = [stack[0], ("body", flags, number, 1)]
            places.clear()
            places["body"].append(1)
            gone, links = int(flags < 0), 0
    add(page[max(at, skip) :])
    flush()
    return out


def features(found: list[tuple[str, int, str, int, int]]) -> np.ndarray:
    x = np.zeros((len(found), len(_NAMES)))
    x[:, 0] = 1
    for i, (text, flags, tag, _, linked) in enumerate(found):
        for k, n in enumerate(_FLAGS):
            if flags & (1 << k):
                x[i, k + 1] = 1
        k = len(_FLAGS) + 1
        x[i, k : k + 7] = (min(1.0, linked / len(text)), min(6.0, np.log1p(text.count(" ") + 1)), bool(_END.search(text)), tag in ("h1", "h2", "h3", "h4", "h5", "h6"), tag in ("p", "pre", "blockquote"), tag in ("li", "dt", "dd"), "©" in text[:200] or "rights reserved" in text[-200:].lower())
    return x


def min_cut(gain: list[float], edges: list[tuple[int, int, float]]) -> list[bool]:
    """Source side of the minimum cut. gain: capacity from the source (above 0) or to the sink (below 0) of each node;
    edges: undirected capacities. Flow is pushed along shortest augmenting paths, which end at the nearest node that can
    still drain; nodes from which none can be reached are final and not visited again.
    """
    n, spare = len(gain), list(gain)
    links: list[list[list]] = [[] for _ in range(n)]
    for a, b, c in edges:
        forth, back = [b, c, None], [a, c, None]
        forth[2], back[2] = back, forth
        links[a].append(forth)
        links[b].append(back)
    final = [False] * n
    for s in range(n):
        while spare[s] > 1e-12 and not final[s]:
            came: dict[int, list | None] = {s: None}
            queue, drain = deque([s]), -1
            while queue and drain < 0:
                u = queue.popleft()
                for e in links[u]:
                    v = e[0]
                    if e[1] > 1e-12 and v not in came and not final[v]:
                        came[v] = e
                        if spare[v] < -1e-12:
                            drain = v
                            break
                        queue.append(v)
            if drain < 0:
                for u in came:
                    final[u] = True
                break
            flow, v = min(spare[s], -spare[drain]), drain
            while (e := came[v]) is not None:
                flow, v = min(flow, e[1]), e[2][0]
            v = drain
            while (e := came[v]) is not None:
                e[1] -= flow
                e[2][1] += flow
                v = e[2][0]
            spare[s] -= flow
            spare[drain] += flow
    return final


def main_text(page: str | None, weights: np.ndarray, memo: dict | None = None) -> str:
    """Text of the content blocks, joined by empty lines; empty if there is none."""
    found = blocks(page, memo)
    if not found:
        return ""
    gain = np.clip(features(found) @ weights, -CLIP, CLIP).tolist()
    edges, last = [], {}
    for i, b in enumerate(found):
        if i:
            edges.append((i - 1, i, ADJACENT))
        if (j := last.get(b[3], -2)) >= 0:
            edges.append((j, i, SIBLING))
        last[b[3]] = i
    keep = min_cut(gain, edges)
    return "\n\n".join(b[0] for b, k in zip(found, keep) if k)


def train(pages: DataFrame, key: str = "page_id", html: str = "html", train_pages: int = TRAIN_PAGES, train_blocks: int = TRAIN_BLOCKS) -> np.ndarray:
    """Weights fitted on at most train_pages whole pages (picked by a hash of the key) and train_blocks blocks of each, held
    near the prior ones.

    Labels come from landmarks: a block inside an article element and in no boilerplate element is content, a block inside
    a boilerplate element is not; others, and pages without an article, are left out. Each block is learnt twice, with its
    landmarks and without them, so that length, links, punctuation and element have weights of their own where a page has no
    landmarks. Executors make the features; the driver gets those alone.
    """
    w0 = np.array(list(PRIOR.values()))
    picked = pages.select(F.col(html).cast("string").alias("h"), F.xxhash64(key).alias("k")).filter("h IS NOT NULL").orderBy("k", F.xxhash64("h")).limit(train_pages)

    def work(found):
        for _, texts in found:
            xs, ys = [np.zeros((0, len(_NAMES)))], []
            for t in texts:
                seen = blocks(t)
                if any(b[1] & _BIT["article"] for b in seen):
                    sure = [b for b in seen if b[1] & (_BAD_MASK | _BIT["article"])]
                    sure = [sure[i] for i in np.unique(np.linspace(0, len(sure) - 1, min(len(sure), train_blocks)).astype(int))]
                    xs.append(features(sure))
                    ys += [0.0 if b[1] & _BAD_MASK else 1.0 for b in sure]
            x = np.concatenate(xs)
            yield [pa.array(list(x), pa.list_(pa.float64())), pa.array(ys, pa.float64())]

    schema = T.StructType([T.StructField("x", T.ArrayType(T.DoubleType())), T.StructField("y", T.DoubleType())])
    got = map_text(picked, [], "h", schema, work).toArrow()
    if not got.num_rows:
        return w0
    x = np.array(got.column("x").combine_chunks().values).reshape(got.num_rows, -1)
    y = got.column("y").to_numpy()
    order = np.lexsort([*x.T, y])
    x, y = x[order], np.tile(y[order], 2)
    masked = x.copy()
    masked[:, 1 : 1 + len(_FLAGS)] = 0
    x, w = np.concatenate([x, masked]), w0.copy()
    for _ in range(200):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        w -= 0.2 * (x.T @ (p - y) / len(y) + PRIOR_PULL * (w - w0))
    return w


def extract(pages: DataFrame, weights: np.ndarray | None = None, key: str = "page_id", html: str = "html", carry: tuple[str, ...] = ()) -> DataFrame:
    """(key, carried columns, text) for each row. Null, empty and markup-only pages give the empty text; repeated rows
    repeat; an empty table gives no rows; other columns are not read. No shuffle.
    """
    w = train(pages, key, html) if weights is None else weights
    schema = T.StructType([*(T.StructField(f"_{i}", pages.schema[c].dataType) for i, c in enumerate([key, *carry])), T.StructField("text", T.StringType())])

    def work(found):
        memo: dict = {}
        for cols, texts in found:
            yield [*cols, pa.array([main_text(t, w, memo) for t in texts], pa.string())]

    named = pages.select(*(pages[c].alias(f"_{i}") for i, c in enumerate([key, *carry])), pages[html].alias("_html"))
    out = map_text(named, [f"_{i}" for i in range(1 + len(carry))], "_html", schema, work)
    return out.select(*(F.col(f"_{i}").alias(c) for i, c in enumerate([key, *carry])), "text")


def op2_html(spark, sf_dir: str) -> DataFrame:
    found = extract(table(spark, sf_dir, "pages"), carry=("url",))
    return found.select("page_id", "url", "text", F.length("text").cast("long").alias("n_chars"))
