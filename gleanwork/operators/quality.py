"""Quality filtering: seven rules, harmful-term share, and the stage that combines them. Narrow plans, no shuffle."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from ..functions import textstats as ts
from ..profiles import LanguageProfile, Thresholds

RULES = ["length", "hiragana", "katakana", "script", "mean_sentence", "longest_sentence", "ellipsis"]


def rule_values(text: Column, parts: Column | None = None) -> dict[str, Column]:
    """parts: the text's sentences, where they are held already."""
    parts = ts.sentences(text) if parts is None else parts
    return {
        "length": F.length(text).cast("double"),
        "hiragana": ts.hiragana_share(text),
        "katakana": ts.katakana_share(text),
        "script": ts.script_share(text),
        "mean_sentence": ts.mean_length(parts, text),
        "longest_sentence": ts.longest(parts, text).cast("double"),
        "ellipsis": ts.ellipsis_share(parts),
    }


def rule_flags(values: dict[str, Column], t: Thresholds) -> dict[str, Column]:
    """True: the rule removes the text. Equality keeps."""
    tests = {
        "length": lambda v: v < t.min_chars,
        "hiragana": lambda v: v < t.min_hiragana,
        "katakana": lambda v: v > t.max_katakana,
        "script": lambda v: v < t.min_script,
        "mean_sentence": lambda v: (v < t.mean_sentence[0]) | (v > t.mean_sentence[1]),
        "longest_sentence": lambda v: v > t.max_sentence,
        "ellipsis": lambda v: v > t.max_ellipsis,
    }
    return {k: tests[k](v) for k, v in values.items()}


def annotate(df: DataFrame, profile: LanguageProfile, text: str = "text", rules: list[str] | None = None) -> DataFrame:
    """df with q_<rule> values, q_harmful, and reasons (names of the rules that remove the text); keeps every row.

    Null text counts as empty. Kana rules take part only in profiles of such scripts.
    """
    names = rules or [r for r in RULES if profile.kana_rules or r not in ("hiragana", "katakana", "script")]
    columns = df.columns
    # Text and sentences are computed once; left as expressions they would be copied into every rule.
    df = ts.hold(df, _body=F.coalesce(F.col(text), F.lit("")))
    df = ts.hold(df, _sentences=ts.sentences(F.col("_body")))
    values = {k: v for k, v in rule_values(F.col("_body"), F.col("_sentences")).items() if k in names}
    df = ts.hold(df, **{f"q_{k}": v for k, v in values.items()}, q_harmful=ts.term_share(F.col("_body"), profile.harmful))
    flags = rule_flags({k: F.col(f"q_{k}") for k in values}, profile.thresholds) | {"harmful": F.col("q_harmful") > profile.thresholds.max_harmful}
    reasons = F.array_compact(F.array(*[F.when(f, F.lit(k)) for k, f in flags.items()])).alias("reasons")
    return df.select(*[F.col(f"`{c}`") for c in columns], *[f"q_{k}" for k in values], "q_harmful", reasons)


def apply(df: DataFrame, profile: LanguageProfile, text: str = "text", rules: list[str] | None = None) -> DataFrame:
    """The rows that no rule removes, with df's columns."""
    return annotate(df, profile, text, rules).filter(F.size("reasons") == 0).select(df.columns)


def rule_report(annotated: DataFrame) -> DataFrame:
    """Removals by rule: overlapping (all texts a rule hits) and exclusive (texts that it alone hits)."""
    return annotated.select(F.explode("reasons").alias("rule"), (F.size("reasons") == 1).alias("alone")).groupBy("rule").agg(F.count("*").alias("hits"), F.count_if("alone").alias("exclusive"))
