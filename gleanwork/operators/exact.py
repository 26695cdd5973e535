"""Exact deduplication of units inside texts: lines, paragraphs, sentence windows, URLs, repeated token spans.

Only (hash, id, position) is shuffled for corpus-wide decisions; positions that stay are gathered for each document and joined
to its units once, which is the only time that texts move.
"""

from __future__ import annotations

import hashlib
import re

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window, functions as F, types as T

from ..functions import textstats as ts
from .hosts import url_key


def unit_hash(unit: Column, kind: str = "md5") -> Column:
    """64-bit keys: md5 prefix (SQL engines agree on it), sha1 (first 64 bits), or murmur-like xxhash64."""
    if kind == "sha1":
        return F.substring(F.sha1(unit.cast("binary")), 1, 16)
    return F.xxhash64(unit) if kind == "xxhash64" else F.substring(F.md5(unit.cast("binary")), 1, 16)


def dedup_units(df: DataFrame, units: Column, joiner: str, key: str = "doc_id", kind: str = "md5") -> DataFrame:
    """(key, text, kept, dropped): units seen earlier in (key, position) order, anywhere in the corpus, are dropped.

    First occurrences come from a min per hash with partial sums, so a unit that stands in a third of all texts is no hot
    spot; every text with units stays, perhaps with none left.
    """
    body = ts.hold(df, _units=units).select(key, "_units").filter(F.size("_units") > 0)
    rows = body.select(key, F.posexplode("_units").alias("pos", "unit")).select(key, "pos", unit_hash(F.col("unit"), kind).alias("h"))
    first = rows.groupBy("h").agg(F.min(F.struct(key, "pos")).alias("at"))
    kept = first.groupBy(F.col(f"at.{key}").alias(key)).agg(F.array_sort(F.collect_list("at.pos")).alias("_kept"))
    joined = body.join(kept, key, "left").select(key, "_units", F.coalesce("_kept", F.array().cast("array<int>")).alias("_kept"))
    text = F.array_join(F.transform("_kept", lambda p: F.element_at("_units", p + 1)), joiner)
    return joined.select(key, text.alias("text"), F.size("_kept").cast("long").alias("kept"), (F.size("_units") - F.size("_kept")).cast("long").alias("dropped"))


def dedup_lines(df: DataFrame, key: str = "doc_id", text: str = "text", kind: str = "md5") -> DataFrame:
    return dedup_units(df, ts.lines(F.col(text)), "\n", key, kind)


def dedup_paragraphs(df: DataFrame, key: str = "doc_id", text: str = "text", kind: str = "sha1") -> DataFrame:
    return dedup_units(df, ts.paragraphs(F.col(text)), "\n\n", key, kind)


def _sentences(text: str) -> list[str]:
    """textstats.sentences of a text."""
    return [s for x in re.findall(ts.SENTENCE, text) if (s := x.strip(" "))]


def dedup_spans(df: DataFrame, width: int = 3, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, sentences, dropped): sentences inside a window of width sentences that occurred earlier in the corpus.

    An Arrow pass gives 8 bytes of md5 for each window that differs inside its text. First occurrences come from a min per hash
    with partial sums; a text's other windows are those that occurred before, so no window is joined to its copies and no
    text moves.
    """
    body = df.select(key, F.col(text).cast("string").alias("_t"))
    hashed = T.StructType([df.schema[key], T.StructField("pos", T.IntegerType()), T.StructField("h", T.LongType())])
    counted = T.StructType([df.schema[key], T.StructField("sentences", T.IntegerType())])

    def windows(batches):
        for b in batches:
            at, pos, h = [], [], []
            for i, t in enumerate(b.column(1).to_pylist()):
                s, seen = _sentences(t or ""), set()
                for p in range(len(s) - width + 1):
                    x = int.from_bytes(hashlib.md5(" ".join(s[p : p + width]).encode("utf-8", "surrogatepass"), usedforsecurity=False).digest()[:8], "big", signed=True)
                    if x not in seen:
                        seen.add(x)
                        at.append(i)
                        pos.append(p)
                        h.append(x)
            yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(at, pa.int64())), pa.array(pos, pa.int32()), pa.array(h, pa.int64())], names=[key, "pos", "h"])

    def sizes(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([None if t is None else len(_sentences(t)) for t in b.column(1).to_pylist()], pa.int32())], names=[key, "sentences"])

    first = body.mapInArrow(windows, hashed).groupBy("h").agg(F.min(key).alias("_at"), F.min_by("pos", key).alias("_pos"))
    kept = first.groupBy(F.col("_at").alias(key)).agg(F.collect_list("_pos").alias("_kept"))
    joined = body.mapInArrow(sizes, counted).join(kept, key, "left")
    last = F.coalesce(F.col("sentences") - width, F.lit(-1))
    every = F.when(last >= 0, F.sequence(F.lit(0), F.greatest(last, F.lit(0)))).otherwise(F.array().cast("array<int>"))
    again = F.array_except(every, F.coalesce("_kept", F.array().cast("array<int>")))
    covered = F.array_distinct(F.flatten(F.transform(again, lambda p: F.sequence(p, p + width - 1))))
    return joined.select(key, "sentences", F.size(covered).cast("long").alias("dropped"))


def dedup_urls(pages: DataFrame, url: str = "url", key: str = "page_id", canonical: bool = True) -> DataFrame:
    """Keys that stay: the least of each (canonical) URL."""
    u = url_key(F.col(url)) if canonical else F.col(url)
    return pages.groupBy(u.alias("url_key")).agg(F.min(key).alias(key), F.count("*").alias("copies"))


def dedup_paragraphs_within(text: Column) -> Column:
    """A text with each paragraph once, in order."""
    return F.array_join(F.array_distinct(ts.paragraphs(text)), "\n\n")


def repeated_spans(df: DataFrame, width: int = 50, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, tokens, removed, chars_removed): tokens inside windows of width tokens that occurred earlier in the corpus.

    Windows are hashed and only hashes are shuffled; overlapping windows merge because a token is counted once.
    """
    body = ts.hold(df, w=ts.tokens(F.col(text))).select(key, "w")
    windows = body.select(key, F.posexplode(ts.windows_of(F.col("w"), width)).alias("pos", "g")).select(key, "pos", unit_hash(F.col("g")).alias("h"))
    first = windows.groupBy("h").agg(F.min(F.struct(key, "pos")).alias("at"), F.count("*").alias("n")).filter("n > 1")
    again = windows.join(first, "h").filter(F.struct(key, "pos") > F.col("at"))
    covered = again.select(key, F.explode(F.sequence(F.col("pos"), F.col("pos") + width - 1)).alias("pos")).distinct().groupBy(key).agg(F.array_sort(F.collect_list("pos")).alias("gone"))
    out = body.join(covered, key, "left").select(key, "w", F.coalesce("gone", F.array().cast("array<int>")).alias("gone"))
    return out.select(key, F.size("w").alias("tokens"), F.size("gone").alias("removed"), F.aggregate("gone", F.lit(0), lambda n, p: n + F.length(F.element_at("w", (p + 1).cast("int")))).alias("chars_removed"))


def remove_repeated_spans(df: DataFrame, width: int = 50, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, text) without the tokens of repeated_spans; tokens are joined by one space."""
    body = ts.hold(df, w=ts.tokens(F.col(text))).select(key, "w")
    windows = body.select(key, F.posexplode(ts.windows_of(F.col("w"), width)).alias("pos", "g")).select(key, "pos", unit_hash(F.col("g")).alias("h"))
    first = windows.groupBy("h").agg(F.min(F.struct(key, "pos")).alias("at"), F.count("*").alias("n")).filter("n > 1")
    again = windows.join(first, "h").filter(F.struct(key, "pos") > F.col("at"))
    covered = again.select(key, F.explode(F.sequence(F.col("pos"), F.col("pos") + width - 1)).alias("pos")).distinct().groupBy(key).agg(F.collect_list("pos").alias("gone"))
    kept = F.filter("w", lambda x, i: ~F.array_contains(F.coalesce("gone", F.array().cast("array<int>")), i))
    return body.join(covered, key, "left").select(key, F.array_join(kept, " ").alias("text"))


def first_per_group(df: DataFrame, group: Column, key: str = "doc_id") -> DataFrame:
    return df.withColumn("_g", group).withColumn("_rn", F.row_number().over(Window.partitionBy("_g").orderBy(key))).filter("_rn = 1").drop("_g", "_rn")
