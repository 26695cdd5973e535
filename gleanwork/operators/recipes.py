"""Line, document and paragraph rules of other published corpora, as columns."""

from __future__ import annotations

import re

import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F, types as T

from ..functions import textstats as ts
from ..profiles import FUNCTION_WORDS

ALL_FUNCTION_WORDS = sorted({w for ws in FUNCTION_WORDS.values() for w in ws})
STOPS, EMOJI = frozenset(ALL_FUNCTION_WORDS), re.compile("[\u2600-\u27bf\U0001f300-\U0001faff]")
EMAIL = r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"
FRAGMENT = r"</?[a-zA-Z][^<>]*>|&[a-z]+;"


def keep_terminal_lines(text: Column) -> Column:
    """Lines ending in a terminal mark, perhaps before a closing quote."""
    return F.filter(ts.lines(text), lambda s: s.rlike(r"[.!?\"”]$"))


def drop_short_lines(lines: Column, most: int = 4) -> Column:
    return F.filter(lines, lambda s: F.size(ts.tokens(s)) > most)


def few_sentences(text: Column, least: int = 3) -> Column:
    return F.size(ts.sentences(text)) < least


def c4(text: Column) -> Column:
    """The text after both line rules; null where the document goes."""
    lines = drop_short_lines(keep_terminal_lines(text))
    joined = F.array_join(lines, "\n")
    return F.when(~few_sentences(joined), joined)


def multilingual_rule(text: Column, chars: int = 200, lines: int = 3) -> Column:
    """Kept: long enough and enough lines."""
    return (F.length(text) >= chars) & (F.size(ts.lines(text)) >= lines)


def few_words(text: Column, least: int = 50) -> Column:
    return F.size(ts.tokens(text)) < least


def char_repetition(text: Column, n: int = 10) -> Column:
    """Share of character n-grams at multiples of n that occurred before.

    One scan cuts the text; a substring would be looked for from the text's start each time.
    """
    return repeated(char_chunks(text, n))


def char_chunks(text: Column, n: int) -> Column:
    """Characters 1 to n, n + 1 to 2n and so on, without a shorter rest; a shorter text is one."""
    return F.when(F.length(text) >= n, F.regexp_extract_all(text, F.lit(f"(?s).{{{n}}}"), F.lit(0))).otherwise(F.array(text))


def repeated(parts: Column) -> Column:
    """Share of parts that occurred before."""
    return ts.ratio(F.size(parts) - F.size(F.array_distinct(parts)), F.size(parts))


def word_repetition(text: Column, n: int = 5) -> Column:
    return repeated(ts.ngrams(ts.tokens(text), n))


def _roots(text: str) -> tuple[bool, float, float, float, float]:
    share = lambda a, b: a / b if b else 0.0
    tok, words = re.findall(r"[^ \n\t\r]+", text), re.findall(ts.WORD, text.lower())
    ten = [text[i : i + 10] for i in range(0, max(len(text) - 9, 1), 10)]
    five = max(len(tok) - 4, 0)
    return len(tok) < 50, share(len(ten) - len(set(ten)), len(ten)), share(five - len(set(zip(*(tok[k:] for k in range(5))))), five), share(len(EMOJI.findall(text)), len(text)), share(sum(map(STOPS.__contains__, words)), len(words))


def roots(df: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, few_words, char_repetition, word_repetition, emoji, function_words) of these rules, in one Arrow pass."""
    names = ["few_words", "char_repetition", "word_repetition", "emoji", "function_words"]
    kinds = [pa.bool_(), *[pa.float64()] * 4]
    schema = T.StructType([df.schema[key], T.StructField(names[0], T.BooleanType()), *(T.StructField(c, T.DoubleType()) for c in names[1:])])

    def run(batches):
        for b in batches:
            rows = [(None, 0.0, None, None, None) if t is None else _roots(t) for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array([r[i] for r in rows], kind) for i, kind in enumerate(kinds))], names=[key, *names])

    return df.select(key, F.col(text).cast("string")).mapInArrow(run, schema)


def emoji_share(text: Column) -> Column:
    return ts.class_share(text, r"\x{2600}-\x{27BF}\x{1F300}-\x{1FAFF}")


def function_word_share(text: Column) -> Column:
    w = ts.words(text)
    return ts.ratio(F.size(F.filter(w, lambda x: x.isin(ALL_FUNCTION_WORDS))), F.size(w))


def massive_web(text: Column) -> Column:
    """Published document rules: number and mean length of words, symbols, bullets, ellipses, letters, stop words."""
    w, lines = ts.tokens(text), ts.lines(text)
    n = F.size(w)
    mean = ts.ratio(ts.total_length(w), n)
    symbols = ts.ratio(F.regexp_count(text, F.lit(r"#|…|\.\.\.")), n)
    bullets = ts.ratio(F.size(F.filter(lines, lambda s: s.rlike(r"^\s*[-*•]"))), F.size(lines))
    dots = ts.ratio(F.size(F.filter(lines, lambda s: s.rlike(r"(…|\.\.\.)\s*$"))), F.size(lines))
    letters = ts.ratio(F.size(F.filter(w, lambda s: s.rlike(r"[A-Za-zÀ-ÿœ]"))), n)
    stops = F.size(F.filter(ts.words(text), lambda x: x.isin(ALL_FUNCTION_WORDS)))
    return n.between(50, 100_000) & mean.between(3, 10) & (symbols <= 0.1) & (bullets <= 0.9) & (dots <= 0.3) & (letters >= 0.8) & (stops >= 2)


def clean_lines(text: Column) -> Column:
    """Per-line corrections: mostly upper case, digits only, counters and one-word lines go; null where over 5 % of words go."""
    lines = ts.lines(text)
    upper = lambda s: F.regexp_count(s, F.lit("[A-Z]")) * 2 > F.length(s)
    kept = F.filter(lines, lambda s: ~(upper(s) | s.rlike(r"^[0-9 .,]+$") | s.rlike(r"^[0-9.,]+[kKmM]? (likes|comments|shares|views)$") | (F.size(ts.tokens(s)) <= 1)))
    joined = F.array_join(kept, "\n")
    return F.when(F.size(ts.tokens(joined)) >= 0.95 * F.size(ts.tokens(text)), joined)


def scrub(text: Column) -> Column:
    """E-mail addresses and HTML fragments removed."""
    return F.regexp_replace(F.regexp_replace(text, EMAIL, ""), FRAGMENT, "")


def compare(df: DataFrame, recipes: dict[str, Column | None], text: str = "text") -> DataFrame:
    """(recipe, pages, chars): what each recipe keeps of the same input, in one pass. A recipe gives the kept text or null."""
    aggs = []
    for name, kept in recipes.items():
        c = F.col(text) if kept is None else kept
        aggs += [F.count(c).alias(f"{name}__pages"), F.coalesce(F.sum(F.length(c)), F.lit(0)).alias(f"{name}__chars")]
    one = df.agg(*aggs)
    rows = F.array(*[F.struct(F.lit(n).alias("recipe"), F.col(f"{n}__pages").alias("pages"), F.col(f"{n}__chars").alias("chars")) for n in recipes])
    return one.select(F.explode(rows).alias("r")).select("r.*")
