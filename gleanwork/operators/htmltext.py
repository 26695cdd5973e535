"""Main-text extraction, in three forms: plain SQL (regex), visible text (the boilerplate-keeping baseline), and Arrow passes
over a tolerant parser (block density; stop-word density)."""

from __future__ import annotations

from html.parser import HTMLParser

import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F, types as T

from ..profiles import FUNCTION_WORDS
from .gate import decode

DROPPED = ["script", "style", "nav", "header", "footer", "aside", "form", "head"]


def extract_main_text(html: Column, keep_footer: bool = False) -> Column:
    """SQL form: drop boilerplate elements and advert boxes, break at block tags, decode, squeeze white space."""
    t = F.regexp_replace(html, r"(?s)<!--.*?-->", "")
    for tag in DROPPED:
        if not (keep_footer and tag == "footer"):
            t = F.regexp_replace(t, rf"(?is)<{tag}\b.*?</{tag}>", "")
    t = F.regexp_replace(t, r'(?is)<div class="(ad|menu|share)">.*?</div>', "")
    t = F.regexp_replace(t, r"(?i)</?(p|div|h[1-6]|li|ul|ol|br|article|section|footer|tr|table)\b[^>]*>", "\n")
    return _tidy(F.regexp_replace(t, r"<[^>]*>", ""))


def visible_text(html: Column) -> Column:
    """Tags stripped, boilerplate kept: what archive-supplied plain text looks like."""
    t = F.regexp_replace(html, r"(?s)<!--.*?-->", "")
    for tag in ("script", "style", "title"):
        t = F.regexp_replace(t, rf"(?is)<{tag}\b.*?</{tag}>", "")
    t = F.regexp_replace(t, r"(?i)</?(p|div|h[1-6]|li|ul|ol|br|article|section|footer|tr|table|nav)\b[^>]*>", "\n")
    return _tidy(F.regexp_replace(t, r"<[^>]*>", ""))


def _tidy(t: Column) -> Column:
    t = F.regexp_replace(decode(t), r"[ \t\r]+", " ")
    t = F.regexp_replace(t, r" ?\n[ \n]*", "\n")
    return F.regexp_replace(F.regexp_replace(t, r"^[ \n]+", ""), r"[ \n]+$", "")


class _Blocks(HTMLParser):
    """Text blocks with the characters inside links and whether a dropped element surrounds them."""

    BREAKS = frozenset("p div h1 h2 h3 h4 h5 h6 li ul ol br article section tr td table blockquote body main nav header footer aside form".split())
    HIDDEN = frozenset("script style head title noscript".split())
    BOILER = frozenset("nav header footer aside form".split())

    def __init__(self, keep_footer: bool):
        super().__init__(convert_charrefs=True)
        self.out, self.text, self.linked, self.stack = [], [], 0, []
        self.boiler = self.BOILER - {"footer"} if keep_footer else self.BOILER

    def _flush(self):
        text = " ".join("".join(self.text).split())
        if text:
            self.out.append((text, self.linked, any(t in self.boiler or bad for t, bad in self.stack)))
        self.text, self.linked = [], 0

    def handle_starttag(self, tag, attrs):
        if tag in self.BREAKS:
            self._flush()
        if tag not in ("br", "img", "meta", "link", "input", "hr"):
            names = " ".join(v or "" for k, v in attrs if k in ("class", "id")).split()
            self.stack.append((tag, any(n in ("ad", "ads", "menu", "share") for n in names)))

    def handle_endtag(self, tag):
        if tag in self.BREAKS:
            self._flush()
        for i in range(len(self.stack) - 1, -1, -1):
            if self.stack[i][0] == tag:
                del self.stack[i:]
                break

    def handle_data(self, data):
        if not any(t in self.HIDDEN for t, _ in self.stack):
            self.text.append(data)
            if any(t == "a" for t, _ in self.stack):
                self.linked += len(data)


def blocks(html: str | None, keep_footer: bool = False) -> list[tuple[str, int, bool]]:
    p = _Blocks(keep_footer)
    p.feed(html or "")
    p.close()
    p._flush()
    return p.out


def by_density(html: str | None, keep_footer: bool = False, max_links: float = 0.33) -> str:
    """Blocks outside boilerplate elements whose share of linked characters is low."""
    return "\n".join(t for t, linked, boiler in blocks(html, keep_footer) if not boiler and linked / len(t) < max_links)


def by_stopwords(html: str | None, low: float = 0.1, high: float = 0.2, short: int = 70, long: int = 200, max_links: float = 0.2) -> str:
    """Block length, link density and stop-word density: long, dense blocks are text; blocks between follow their neighbours."""
    stop = {w for ws in FUNCTION_WORDS.values() for w in ws}
    kinds, found = [], blocks(html, True)
    for text, linked, _ in found:
        words = text.lower().split()
        density = sum(w.strip(".,;:!?") in stop for w in words) / max(1, len(words))
        if linked / len(text) > max_links:
            kinds.append("bad")
        elif len(text) < short:
            kinds.append("short" if density >= low else "bad")
        elif density >= high:
            kinds.append("good" if len(text) > long else "near")
        else:
            kinds.append("near" if density >= low else "bad")
    good = [i for i, k in enumerate(kinds) if k == "good"]
    first, last = (good[0], good[-1]) if good else (0, -1)
    return "\n".join(t for i, (t, _, _) in enumerate(found) if kinds[i] == "good" or (kinds[i] in ("near", "short") and first - 1 <= i <= last + 1))


def extract(pages: DataFrame, how=by_density, key: str = "page_id", html: str = "html", carry: tuple[str, ...] = (), **options) -> DataFrame:
    """(key, carried columns, text) by one of the parsers, in one Arrow pass; null pages give the empty text."""
    schema = T.StructType([pages.schema[key], *(pages.schema[c] for c in carry), T.StructField("text", T.StringType())])

    def run(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array([how(h, **options) for h in b.columns[-1].to_pylist()], pa.string())], names=[key, *carry, "text"])

    return pages.select(key, *carry, F.col(html).cast("string").alias("_html")).mapInArrow(run, schema)
