"""Rapid target-language gate: decide from the head of a page whether it is worth extracting. Native columns only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from ..functions import textstats as ts
from . import langid

HEAD, TITLE_HEAD = 4096, 65536
LANG = r"(?i)<html\b[^>]*?[\s\"']lang\s*=\s*[\"']?([a-z]+)"
#: Other places of a declaration, asked for by name: xml:lang of the html element, and the content-language meta element.
XML_LANG = r"(?i)<html\b[^>]*?[\s\"']xml:lang\s*=\s*[\"']?([a-z]+)"
META_LANG = r"(?i)<meta\b(?=[^>]*\bhttp-equiv\s*=\s*[\"']?content-language\b)[^>]*?\bcontent\s*=\s*[\"']?([a-z]+)"
TITLE = r"(?is)<title[^>]*>(.*?)</title>"
# The character references that titles commonly hold.
ENTITIES = [("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&nbsp;", " "), ("&amp;", "&")]


def _early(html: Column, size: int, whole: str, pattern: str) -> Column:
    """Group 1 of pattern in the first size characters if these hold the whole element, else in the whole page."""
    head = F.substring(html, 1, size)
    return F.when(head.rlike(whole), F.regexp_extract(head, pattern, 1)).otherwise(F.regexp_extract(html, pattern, 1))


def declared_language(html: Column, also: tuple[str, ...] = ()) -> Column:
    """Primary subtag of the lang attribute of the html element, lower-cased; empty if there is none.

    also: places that are asked where it is missing, in order: "xml:lang" and "content-language".
    """
    found = F.lower(_early(html, HEAD, r"(?i)<html\b[^>]*>", LANG))
    for place in also:
        pattern = {"xml:lang": XML_LANG, "content-language": META_LANG}[place]
        found = F.when(found != "", found).otherwise(F.lower(F.regexp_extract(html, pattern, 1)))
    return found


def declares_language(html: Column, code: str) -> Column:
    return declared_language(html) == code


def decode(text: Column) -> Column:
    for name, char in ENTITIES:
        text = F.replace(text, F.lit(name), F.lit(char))
    return text


def title(html: Column) -> Column:
    """Text of the first title element, decoded, white space as one space; empty if missing."""
    return F.trim(F.regexp_replace(decode(_early(html, TITLE_HEAD, TITLE, TITLE)), r"[ \t\r\n]+", " "))


def title_matches(html: Column, code: str, threshold: float = langid.THRESHOLD) -> Column:
    """The same detector as for body text, on the title; an empty title does not match."""
    t = title(html)
    return (t != "") & langid.is_target(t, code, threshold)


def gate_flag(html: Column, code: str, mode: str = "either", threshold: float = langid.THRESHOLD) -> Column:
    """either (cheap test first), declared, title, or off (everything passes: the slow pipeline)."""
    declared = declares_language(html, code)
    return {
        "either": F.when(declared, F.lit(True)).otherwise(title_matches(html, code, threshold)),
        "declared": declared,
        "title": title_matches(html, code, threshold),
        "off": F.lit(True),
    }[mode]


def held_gate(pages: DataFrame, codes: list[str], mode: str = "either", threshold: float = langid.THRESHOLD, html: str = "html") -> tuple[DataFrame, dict[str, Column]]:
    """pages with the declared language and the title's words held, and a flag for each language over them.

    Each page is searched once, whatever the number of languages; the title is read only where no declaration decides already.
    """
    df = ts.hold(pages, _declared=F.coalesce(declared_language(F.col(html)), F.lit("")) if mode in ("either", "declared") else F.lit(""))
    sure = F.col("_declared") == codes[0] if mode == "either" and len(codes) == 1 else F.lit(False)
    none = F.array().cast("array<string>")
    df = ts.hold(df, _title=F.when(sure, none).otherwise(ts.words(title(F.col(html)))) if mode in ("either", "title") else none)

    def flag(code: str) -> Column:
        if mode == "off":
            return F.lit(True)
        titled = F.coalesce((F.size("_title") > 0) & (langid.score_of(F.col("_title"), code) > threshold), F.lit(False))
        return {"either": (F.col("_declared") == code) | titled, "declared": F.col("_declared") == code, "title": titled}[mode]

    return df, {c: flag(c) for c in codes}


def rapid_gate(pages: DataFrame, code: str, mode: str = "either", html: str = "html") -> DataFrame:
    """The pages that may be in the language; null pages never pass, except with mode off."""
    if mode == "off":
        return pages
    df, flags = held_gate(pages, [code], mode, html=html)
    return df.filter(flags[code]).select(pages.columns)


def gate_view(pages: DataFrame, html: str = "html", key: str = "page_id") -> DataFrame:
    """Pages with the declaration removed for every third id and made wrong for every seventh: a test bed for the gate."""
    wrong = F.translate(F.regexp_extract(F.col(html), r' lang="([a-z]+)"', 1), "edf", "fed")
    h = F.when(F.col(key) % 3 == 0, F.regexp_replace(html, r' lang="[a-z]+"', "")).when(F.col(key) % 7 == 0, F.regexp_replace(F.col(html), F.lit(r' lang="[a-z]+"'), F.concat(F.lit(' lang="'), wrong, F.lit('"')))).otherwise(F.col(html))
    return pages.withColumn(html, h)
