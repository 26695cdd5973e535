"""Column functions over whole texts: character classes, sentences, lines, words. All run inside the JVM."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, functions as F

from ..profiles import ELLIPSES, HIRAGANA, KANJI, KATAKANA, PUNCTUATION, TERMINATORS, kana_map

SENTENCE = rf"[^{TERMINATORS}\n]+[{TERMINATORS}]*"
WORD = r"[a-zà-öø-ÿœ]+"


def ratio(a: Column, b: Column) -> Column:
    """a / b; 0 where b is 0."""
    return F.when(b == 0, 0.0).otherwise(a / F.when(b == 0, 1).otherwise(b))


def class_share(text: Column, chars: str) -> Column:
    """Share of code points in a regex class; empty text 0."""
    return ratio(F.regexp_count(text, F.lit(f"[{chars}]")), F.length(text))


def hiragana_share(text: Column) -> Column:
    return class_share(text, HIRAGANA)


def katakana_share(text: Column) -> Column:
    return class_share(text, KATAKANA)


def script_share(text: Column) -> Column:
    """Kana, kanji and ideographic punctuation."""
    return class_share(text, HIRAGANA + KATAKANA + KANJI + PUNCTUATION)


def kana_view(text: Column, letters: str | None = None, marks: bool = True) -> Column:
    source, target = kana_map(marks=marks) if letters is None else kana_map(letters, marks)
    return F.translate(text, source, target)


def ellipsis_view(text: Column, key: Column) -> Column:
    """The marks at the end of every third sentence become an ellipsis in every fifth document: a constructed column."""
    return F.when(key % 5 == 0, F.regexp_replace(text, r"([^.\n]+)\.([^.\n]+)\.([^.\n]+)\.", "$1.$2.$3…")).otherwise(text)


def sentences(text: Column) -> Column:
    """Runs up to and with their terminators, or to the end of a line; trimmed, empty ones dropped."""
    found = F.transform(F.regexp_extract_all(text, F.lit(SENTENCE), F.lit(0)), lambda s: F.trim(s))
    return F.filter(found, lambda s: s != "")


def total_length(parts: Column) -> Column:
    return F.aggregate(parts, F.lit(0), lambda n, s: n + F.length(s))


def mean_length(parts: Column, text: Column) -> Column:
    """Mean length; a text without parts counts as one."""
    return F.when(F.size(parts) == 0, F.length(text).cast("double")).otherwise(total_length(parts) / F.greatest(F.size(parts), F.lit(1)))


def longest(parts: Column, text: Column) -> Column:
    return F.coalesce(F.array_max(F.transform(parts, F.length)), F.length(text))


def ends_in_ellipsis(sentence: Column) -> Column:
    """Closing quotes and brackets are ignored, and one full stop after a one-character ellipsis."""
    bare = F.regexp_replace(sentence, r"[\"'”’」』)）\]]+$", "")
    stop = F.regexp_replace(bare, r"([…‥])[.。]$", "$1")
    out = F.lit(False)
    for mark in ELLIPSES:
        out = out | stop.endswith(mark)
    return out


def ellipsis_share(parts: Column) -> Column:
    return ratio(F.size(F.filter(parts, ends_in_ellipsis)), F.size(parts))


def lines(text: Column) -> Column:
    return F.filter(F.split(text, "\n", -1), lambda s: s != "")


def paragraphs(text: Column) -> Column:
    return F.filter(F.split(text, "\n\\s*\n", -1), lambda s: s != "")


def words(text: Column) -> Column:
    """Lower-cased Latin words."""
    return F.regexp_extract_all(F.lower(text), F.lit(WORD), F.lit(0))


def tokens(text: Column) -> Column:
    """White-space tokens."""
    return F.regexp_extract_all(text, F.lit(r"[^ \n\t\r]+"), F.lit(0))


def ngrams(parts: Column, n: int) -> Column:
    """All runs of n parts, joined by a space.

    Shifted slices are zipped, so that parts never stands inside a lambda, where it would be computed anew for each element.
    For wide windows hold() the parts first and use windows_of().
    """
    size = F.greatest(F.size(parts) - (n - 1), F.lit(0))
    out = F.slice(parts, F.lit(1), size)
    for k in range(1, n):
        out = F.zip_with(out, F.slice(parts, F.lit(k + 1), size), lambda a, b: F.concat_ws(" ", a, b))
    return out


def windows_of(held: Column, n: int) -> Column:
    """ngrams of a column that is held (an attribute of its table, not an expression)."""
    return F.when(F.size(held) < n, F.array().cast("array<string>")).otherwise(F.transform(F.sequence(F.lit(1), F.greatest(F.size(held) - (n - 1), F.lit(1))), lambda i: F.array_join(F.slice(held, i, F.lit(n)), " ")))


def hold(df: DataFrame, **columns: Column) -> DataFrame:
    """df with computed columns that later lambdas may use freely: a generator keeps the optimizer from copying them in."""
    made = F.explode(F.array(F.struct(*[c.alias(n) for n, c in columns.items()]))).alias("_held")
    return df.select("*", made).select(*[F.col(f"`{c}`") for c in df.columns if c not in columns], *[F.col(f"_held.{n}").alias(n) for n in columns])


#: Input, as the plan estimates it, that spread() deals anew.
SMALL_BYTES = 256 << 20


def spread(df: DataFrame) -> DataFrame:
    """A small input dealt over all cores: a file of one row group is one task otherwise. Larger inputs, which have enough
    splits of their own, stay as they are.
    """
    size = df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(cores) if cores > 1 and int(str(size)) <= SMALL_BYTES else df


def md5_long(text: Column, digits: int = 15) -> Column:
    """The first hex digits of md5 as a long: a hash that SQL engines share."""
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, digits), 16, 10).cast("long")


def term_pattern(terms: list[str] | tuple[str, ...]) -> str:
    """Alternation with the longest terms first, so that overlapping terms count once."""
    special = set(".^$*+?{}[]\\|()")
    return "|".join("".join("\\" + c if c in special else c for c in t) for t in sorted(terms, key=lambda t: (-len(t), t)))


#: Terms from which on an automaton looks for them; a pattern of alternatives tries each at every place.
MANY_TERMS = 1000


def _covered(terms: list[str]):
    """Column function: characters inside terms, leftmost and longest first, by an Aho-Corasick automaton in an Arrow pass."""

    @F.pandas_udf("int")
    def covered(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        import ahocorasick

        automaton = ahocorasick.Automaton()
        for t in terms:
            if t:
                automaton.add_word(t, len(t))
        automaton.make_automaton()
        for texts in parts:
            yield pd.Series([sum(n for _, n in automaton.iter_long(t)) if t else 0 for t in texts], dtype="int32")

    return covered


def term_share(text: Column, terms: list[str] | tuple[str, ...]) -> Column:
    """Characters inside terms over all characters, lower-cased; no terms or empty text 0."""
    if not terms:
        return F.lit(0.0)
    low = F.lower(text)
    if len(terms) > MANY_TERMS:
        return ratio(_covered(list(terms))(low), F.length(low))
    return ratio(F.length(low) - F.length(F.regexp_replace(low, term_pattern(terms), "")), F.length(low))


def contains_term(text: Column, terms: list[str] | tuple[str, ...]) -> Column:
    return F.lower(text).rlike(term_pattern(terms)) if terms else F.lit(False)
