"""Cleaning that never removes a page: punctuation of the target script, and footer lines left at the end."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from ..functions.textstats import term_pattern
from ..profiles import FOOTER_LINES, HIRAGANA, KANJI, KATAKANA

_JA = rf"[{HIRAGANA}{KATAKANA}{KANJI}]"
# Western marks and their ideographic forms.
BETWEEN = [(",", "、"), (r"\.", "。"), ("!", "！"), (r"\?", "？")]


def punctuation(text: Column) -> Column:
    """Full-width comma and stop always; ASCII marks only between two characters of the script. Idempotent."""
    t = F.translate(text, "，．", "、。")
    for mark, ideographic in BETWEEN:
        for _ in range(2):  # a match takes its right neighbour along, which may be the next one's left neighbour
            t = F.regexp_replace(t, rf"({_JA}){mark}({_JA})", f"$1{ideographic}$2")
    return t


def punctuation_ascii(text: Column) -> Column:
    """The reverse need of English recipes: typographic quotes, dashes and ellipses to ASCII."""
    t = F.translate(text, "“”„«»‘’‚–—", "\"\"\"\"\"'''--")
    return F.replace(t, F.lit("…"), F.lit("..."))


def footer_pattern(listed: list[str] = FOOTER_LINES, most: int = 5, width: int = 120) -> str:
    """One footer line at the end of a text, with the break before it, at most width long."""
    return rf"\n[ \t]*([^\n]{{0,{width}}}(?i:{term_pattern(listed)})[^\n]{{0,{width}}})[ \t\n]*$"


def trim_footer(text: Column, listed: list[str] = FOOTER_LINES, most: int = 5) -> Column:
    """Drops up to most closing lines that hold a footer phrase; the first line always stays, so no page is emptied."""
    for _ in range(most):
        text = F.regexp_replace(text, footer_pattern(listed), "")
    return text


def truecase(df: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, text) with each word in its commonest casing outside sentence starts; ties to the least form."""
    tokens = df.select(key, F.posexplode(F.split(text, " ")).alias("pos", "w"))
    starts = (F.col("pos") == 0) | F.coalesce(F.col("before").rlike(r"[.!?\n]$"), F.lit(True))
    from pyspark.sql import Window

    seen = tokens.withColumn("before", F.lag("w").over(Window.partitionBy(key).orderBy("pos"))).filter(~starts)
    forms = seen.groupBy(F.lower("w").alias("low"), "w").agg(F.count("*").alias("n"))
    best = forms.groupBy("low").agg(F.min_by("w", F.struct(F.negative("n"), "w")).alias("best"))
    cased = tokens.join(best, F.lower("w") == F.col("low"), "left").select(key, "pos", F.coalesce("best", "w").alias("w"))
    return cased.groupBy(key).agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("pos", "w"))), lambda s: s["w"]), " ").alias("text"))


def run(df: DataFrame, text: str = "text") -> DataFrame:
    """The cleaning stage; the number of rows never changes."""
    return df.withColumn(text, trim_footer(punctuation(F.col(text))))
