"""Repetition statistics of a text: duplicate lines and paragraphs, top n-grams, duplicated n-grams.

Two forms of the same statistics: DataFrame operations (features by SQL functions), and one Arrow pass that gives all of
them for a text at once, which is the form for large runs.
"""

from __future__ import annotations

import re
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F, types as T
from pyspark.sql.window import Window

from ..functions import textstats as ts

# Published thresholds; a text above one is removed.
THRESHOLDS = {
    "dup_lines": 0.30, "dup_paragraphs": 0.30, "dup_line_chars": 0.20, "dup_paragraph_chars": 0.20, "top_2": 0.20, "top_3": 0.18, "top_4": 0.16,
    "dup_5": 0.15, "dup_6": 0.14, "dup_7": 0.13, "dup_8": 0.12, "dup_9": 0.11, "dup_10": 0.10,
}


def duplicate_fraction(parts: Column) -> Column:
    """Parts that occurred before, over all parts."""
    return ts.ratio(F.size(parts) - F.size(F.array_distinct(parts)), F.size(parts))


def duplicate_chars(parts: Column, text: Column) -> Column:
    return ts.ratio(ts.total_length(parts) - ts.total_length(F.array_distinct(parts)), F.length(text))


def _tokens(text: str) -> list[str]:
    return [w for w in re.split(r"[ \n\t\r]+", text) if w]


def _tops(words: list[str], sizes: tuple[int, ...]) -> dict[int, tuple[int, int]]:
    """n: (count, length) of the most frequent n-gram; ties go to the longest. Sizes beyond the number of words are left out.

    Words and then grams are numbered, so that counting sorts numbers.
    """
    ids: dict[str, int] = {}
    word = np.fromiter((ids.setdefault(w, len(ids)) for w in words), np.int64, len(words))
    ends = np.concatenate(([0], np.cumsum(np.fromiter(map(len, words), np.int64, len(words)))))
    out, gram = {}, word
    for n in range(1, min(max(sizes), len(words)) + 1):
        if n > 1:
            gram = gram[:-1] * len(ids) + word[n - 1 :]
        _, at, gram, counts = np.unique(gram, return_index=True, return_inverse=True, return_counts=True)
        if n in sizes:
            at = at[counts == counts.max()]
            out[n] = int(counts.max()), int((ends[at + n] - ends[at]).max()) + n - 1
    return out


def top_ngrams(df: DataFrame, sizes: tuple[int, ...], key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, n, share): count times length of the most frequent word n-gram over all characters, for each n of sizes; texts with
    fewer words have no row. One Arrow pass, no shuffle.
    """
    schema = T.StructType([df.schema[key], T.StructField("n", T.IntegerType()), T.StructField("share", T.DoubleType())])

    def run(batches):
        for b in batches:
            rows = []
            for i, t in enumerate(b.column(1).to_pylist()):
                rows += [(i, n, count * length / len(t)) for n, (count, length) in _tops(_tokens(t or ""), sizes).items()]
            at, n, share = zip(*rows) if rows else ((), (), ())
            yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(at, pa.int64())), pa.array(n, pa.int32()), pa.array(share, pa.float64())], names=[key, "n", "share"])

    return df.select(key, F.col(text).cast("string")).mapInArrow(run, schema)


def top_ngram(df: DataFrame, n: int, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, share) of top_ngrams."""
    return top_ngrams(df, (n,), key, text).select(key, "share")


def duplicated_ngrams(df: DataFrame, n: int, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, share): characters of words inside n-grams seen before in the text, each once, over all characters."""
    body = df.select(key, F.length(text).alias("chars"), ts.tokens(F.col(text)).alias("w"))
    grams = body.select(key, F.posexplode(ts.ngrams(F.col("w"), n)).alias("pos", "gram"))
    again = grams.withColumn("rn", F.row_number().over(Window.partitionBy(key, "gram").orderBy("pos"))).filter("rn > 1")
    covered = again.select(key, F.explode(F.sequence(F.col("pos"), F.col("pos") + n - 1)).alias("pos")).distinct()
    lengths = body.select(key, F.posexplode("w").alias("pos", "word"))
    sums = covered.join(lengths, [key, "pos"]).groupBy(key).agg(F.sum(F.length("word")).alias("dup"))
    return body.select(key, "chars").join(sums, key, "left").select(key, ts.ratio(F.coalesce("dup", F.lit(0)), F.col("chars")).alias("share"))


def _of_text(text: str) -> list[float]:
    chars = len(text)
    if not chars:
        return [0.0] * len(THRESHOLDS)
    lines = [x for x in text.split("\n") if x]
    paragraphs = [x for x in re.split(r"\n\s*\n", text) if x]
    out = [(len(x) - len(set(x))) / len(x) if x else 0.0 for x in (lines, paragraphs)]
    out += [(sum(map(len, x)) - sum(map(len, set(x)))) / chars for x in (lines, paragraphs)]
    words = _tokens(text)
    ends = [0]
    for w in words:
        ends.append(ends[-1] + len(w))
    tops = _tops(words, (2, 3, 4))
    for n in (2, 3, 4):
        count, length = tops.get(n, (0, 0))
        out.append(count * length / chars)
    for n in range(5, 11):
        seen, covered, upto = set(), 0, 0
        for i, g in enumerate(zip(*(words[k:] for k in range(n)))):
            if g in seen:
                start = max(i, upto)
                covered += ends[i + n] - ends[start]
                upto = i + n
            seen.add(g)
        out.append(covered / chars)
    return out


def features(df: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, one column for each statistic of THRESHOLDS); null and empty texts have 0 in all. One Arrow pass, no shuffle."""
    schema = T.StructType([df.schema[key], *(T.StructField(n, T.DoubleType()) for n in THRESHOLDS)])
    names = [key, *THRESHOLDS]

    def run(batches):
        for b in batches:
            rows = [_of_text(t or "") for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array([r[i] for r in rows], pa.float64()) for i in range(len(THRESHOLDS)))], names=names)

    return df.select(key, F.col(text).cast("string")).mapInArrow(run, schema)


def is_repetitive(thresholds: dict[str, float] | None = None) -> Column:
    out = F.lit(False)
    for name, most in (thresholds or THRESHOLDS).items():
        out = out | (F.col(name) > most)
    return out
