"""Cost and accuracy measures: confusion counts, funnels, sizes, pair quality, answer metrics, corpus profiles."""

from __future__ import annotations

from collections import Counter

import pandas as pd
from pyspark.sql import Column, DataFrame, Window, functions as F, types as T

from ..functions import textstats as ts


def divide(a: Column, b: Column) -> Column:
    """Null where b is 0."""
    return F.try_divide(a.cast("double"), b.cast("double"))


def confusion(df: DataFrame, truth: Column, pred: Column, by: list[str] | None = None) -> DataFrame:
    """tp, fp, fn, tn, precision, recall, f1, lost (share of true rows that are missed), in one pass."""
    t, p = F.coalesce(truth, F.lit(False)), F.coalesce(pred, F.lit(False))
    counts = df.groupBy(*(by or [])).agg(F.count_if(t & p).alias("tp"), F.count_if(~t & p).alias("fp"), F.count_if(t & ~p).alias("fn"), F.count_if(~t & ~p).alias("tn"))
    return counts.withColumns({"precision": divide(F.col("tp"), F.col("tp") + F.col("fp")), "recall": divide(F.col("tp"), F.col("tp") + F.col("fn")), "f1": divide(2 * F.col("tp"), 2 * F.col("tp") + F.col("fp") + F.col("fn")), "lost": divide(F.col("fn"), F.col("tp") + F.col("fn"))})


def f1_of(precision: float, recall: float) -> float:
    return 2 * precision * recall / (precision + recall)


def speedup(cost_off: float, cost_on: float) -> float:
    return cost_off / cost_on


def stage_sizes(stages: list[tuple[str, DataFrame]], text: str = "text") -> DataFrame:
    """(ix, stage, pages, chars): one aggregate for each stage."""
    out = None
    for i, (name, df) in enumerate(stages):
        row = df.agg(F.lit(i).alias("ix"), F.lit(name).alias("stage"), F.count("*").alias("pages"), F.coalesce(F.sum(F.length(text)), F.lit(0)).cast("long").alias("chars"))
        out = row if out is None else out.union(row)
    return out


def funnel_ratios(sizes: DataFrame) -> DataFrame:
    """Adds stage-to-stage and end-to-end retention of pages and characters, and characters a page."""
    w = Window.partitionBy(F.lit(0)).orderBy("ix")
    return sizes.select("*", divide(F.col("pages"), F.lag("pages").over(w)).alias("page_ratio"), divide(F.col("chars"), F.lag("chars").over(w)).alias("char_ratio"), divide(F.col("pages"), F.first("pages").over(w)).alias("page_total"), divide(F.col("chars"), F.first("chars").over(w)).alias("char_total"), divide(F.col("chars"), F.col("pages")).alias("chars_per_page"))


def language_share(df: DataFrame, lang: Column) -> DataFrame:
    total = Window.partitionBy(F.lit(0))
    return df.groupBy(lang.alias("lang")).agg(F.count("*").alias("n")).select("lang", "n", divide(F.col("n"), F.sum("n").over(total)).alias("share"))


def sizes(df: DataFrame, text: str = "text") -> DataFrame:
    """Letters (code points), words, tokens (words and marks), bytes."""
    t = F.col(text)
    return df.agg(F.sum(F.length(t)).alias("letters"), F.sum(F.size(ts.tokens(t))).alias("words"), F.sum(F.regexp_count(t, F.lit(r"[A-Za-z0-9À-ÿœ]+|[^A-Za-z0-9À-ÿœ \n\t\r]"))).alias("tokens"), F.sum(F.octet_length(t)).alias("bytes"))


def pair_quality(found: DataFrame, truth: DataFrame) -> DataFrame:
    """Precision and recall of pairs (a, b)."""
    f, t = found.select("a", "b", F.lit(True).alias("f")), truth.select("a", "b", F.lit(True).alias("t"))
    return confusion(f.join(t, ["a", "b"], "full"), F.col("t"), F.col("f"))


def majority_share(df: DataFrame, label: str) -> DataFrame:
    counts = df.groupBy(F.col(label).cast("string").alias("value")).agg(F.count("*").alias("n"))
    return counts.agg(F.lit(label).alias("label"), F.max_by("value", F.struct("n", "value")).alias("majority"), divide(F.max("n"), F.sum("n")).alias("share"))


def exact_match(pred: Column, gold: Column) -> Column:
    return (F.trim(pred) == F.trim(gold)).cast("int")


@F.pandas_udf(T.DoubleType())
def char_f1(pred: pd.Series, gold: pd.Series) -> pd.Series:
    """F1 of the two texts' bags of characters."""
    def one(p, g):
        common = sum((Counter(p) & Counter(g)).values())
        return 2.0 * common / (len(p) + len(g)) if p or g else 0.0

    return pd.Series([one(p or "", g or "") for p, g in zip(pred, gold)], dtype=float)


def numeric_match(pred: Column, gold: Column) -> Column:
    """The last number of both texts is the same."""
    last = lambda t: F.try_element_at(F.regexp_extract_all(F.replace(t, F.lit(","), F.lit("")), F.lit(r"-?[0-9]+(?:\.[0-9]+)?"), F.lit(0)), F.lit(-1)).cast("double")
    return F.coalesce((last(pred) == last(gold)).cast("int"), F.lit(0))


def lcs_recall(pred: str, gold: str) -> float:
    """Longest common subsequence of words over the words of gold."""
    a, b = pred.split(), gold.split()
    row = [0] * (len(b) + 1)
    for x in a:
        left = 0
        for j, y in enumerate(b, 1):
            left, row[j] = row[j], left + 1 if x == y else max(row[j], row[j - 1])
    return row[-1] / len(b) if b else 0.0


def ngram_precision(pred: str, gold: str, most: int = 4) -> float:
    """Geometric mean of clipped word n-gram precisions with a brevity penalty; 0 where one is 0."""
    import math

    a, b = pred.split(), gold.split()
    logs = 0.0
    for n in range(1, most + 1):
        x, y = (Counter(zip(*(w[i:] for i in range(n)))) for w in (a, b))
        hit, total = sum((x & y).values()), sum(x.values())
        if not hit:
            return 0.0
        logs += math.log(hit / total) / most
    return math.exp(logs) * math.exp(min(0.0, 1 - len(b) / len(a)))


def answer_metrics(df: DataFrame, pred: str, gold: str) -> DataFrame:
    """df with exact_match, char_f1, numeric_match, lcs_recall and ngram_precision."""

    @F.pandas_udf(T.DoubleType())
    def lcs(p, g):
        import pandas as pd

        return pd.Series([lcs_recall(x or "", y or "") for x, y in zip(p, g)], dtype=float)

    @F.pandas_udf(T.DoubleType())
    def bleu(p, g):
        import pandas as pd

        return pd.Series([ngram_precision(x or "", y or "") for x, y in zip(p, g)], dtype=float)

    p, g = F.col(pred), F.col(gold)
    return df.withColumns({"exact_match": exact_match(p, g), "char_f1": char_f1(p, g), "numeric_match": numeric_match(p, g), "lcs_recall": lcs(p, g), "ngram_precision": bleu(p, g)})


def contamination(df: DataFrame, benchmark: DataFrame, n: int = 13, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, hits): distinct benchmark n-grams of words in each text, as a share of contamination; a semi-join on hashes."""
    grams = lambda d, *cols: d.select(*cols, F.explode(ts.ngrams(ts.words(F.col(text)), n)).alias("g")).select(*cols, ts.md5_long(F.col("g")).alias("h")).distinct()
    return grams(df, key).join(grams(benchmark).select("h").distinct(), "h", "left_semi").groupBy(key).agg(F.count("*").alias("hits"))


def corpus_profile(df: DataFrame, flags: dict[str, Column], text: str = "text") -> DataFrame:
    """A cheap stand-in for training: sizes and the rate of each flag, in one pass."""
    return df.agg(F.count("*").alias("texts"), F.avg(F.length(text)).alias("mean_chars"), *[F.avg(F.coalesce(c, F.lit(False)).cast("double")).alias(f"rate_{n}") for n, c in flags.items()])
