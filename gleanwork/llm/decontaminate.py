"""Benchmark decontamination with one FM-index for each shard of training text.

Each partition of the documents is cut into shards of bounded size. A shard is indexed once; all benchmark windows are
found in it by backward search, their occurrences located through sampled suffix positions, and overlapping occurrences
merged into removal spans. Only runs of benchmark words that are as long as the shortest window are indexed, since no
occurrence can reach outside such a run. There is no shuffle.
"""

from __future__ import annotations

import re
import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F, types as T

from .common import SLICE_BYTES, slices, table, to_arrow_schema, total_bytes
from .fmindex import FMIndex

WINDOW = 13
#: Benchmark text searched at a time; a larger benchmark is searched in groups of items, one after another, over the same rows.
#: A word is at least two bytes with its space and takes 4 * WINDOW + 12 bytes in the broadcast windows, three times that while
#: they are made: 130 and 390 MB at most, about a third of it for usual words.
BENCHMARK_BYTES = 4 << 20
#: Words of one shard's index.
SHARD_WORDS = 1 << 20
#: Occurrences located at a time.
_ROWS = 1 << 18
_FOLD = bytes(c + 32 if 65 <= c <= 90 else c if 48 <= c <= 57 or 97 <= c <= 122 or c >= 128 else 32 for c in range(256))
_LOWER = {c: c + 32 for c in range(65, 91)}
_WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def words(text: str | None) -> list[bytes]:
    """Lower-cased words (A-Z only) as UTF-8; null has none."""
    return text.encode("utf-8", "surrogatepass").translate(_FOLD).split() if text else []


class Windows:
    """Distinct windows of one width, sorted, and the items (numbers) that have each: names[bounds[k]:bounds[k + 1]]."""

    def __init__(self, rows: np.ndarray, owner: np.ndarray):
        order, items = np.lexsort(rows.T[::-1]), int(owner.max(initial=0)) + 1
        rows, owner = rows[order], owner[order]
        first = np.flatnonzero(np.r_[True, (rows[1:] != rows[:-1]).any(axis=1)])
        pairs = np.unique(np.repeat(np.arange(len(first)), np.diff(np.r_[first, len(rows)])) * items + owner)
        self.rows, self.names = rows[first], (pairs % items).astype(np.int32)
        self.bounds = np.searchsorted(pairs // items, np.arange(len(first) + 1))

    def items(self, windows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(place in windows, item) for each item of each window."""
        n = self.bounds[windows + 1] - self.bounds[windows]
        place = np.repeat(np.arange(len(windows)), n)
        return place, self.names[np.arange(len(place)) + np.repeat(self.bounds[windows] - np.cumsum(n) + n, n)]


def windows_of(items: list[tuple[str | None, str | None]], width: int) -> tuple[dict[bytes, int], list[str | None], dict[int, Windows]]:
    """Vocabulary (ids from 1), the items' ids, and the windows by their width; items are numbers in them."""
    vocabulary: dict[bytes, int] = {}
    names: list[str | None] = []
    rows: dict[int, list[np.ndarray]] = {}
    owner: dict[int, list[np.ndarray]] = {}
    for item, text in items:
        ids = np.array([vocabulary.setdefault(w, len(vocabulary) + 1) for w in words(text)], np.int32)
        if len(ids):
            n = min(width, len(ids))
            found = np.lib.stride_tricks.sliding_window_view(ids, n)
            rows.setdefault(n, []).append(found)
            owner.setdefault(n, []).append(np.full(len(found), len(names), np.int64))
            names.append(item)
    return vocabulary, names, {n: Windows(np.concatenate(rows[n]), np.concatenate(owner[n])) for n in rows}


def _char_spans(text: str, spans: list[list[int]]) -> list[tuple[int, int]]:
    at = [m.span() for m in _WORD.finditer(text.translate(_LOWER))]
    return [(at[a][0], at[b - 1][1]) for a, b in spans]


class _Shard:
    """Documents whose words are indexed together."""

    def __init__(self):
        self.held: list[pa.RecordBatch] = []  # key and text of each document, cut as the batches were
        self.docs: list[tuple] = []  # (text, number of words, runs and items that earlier groups found)
        self.pieces: list[np.ndarray] = []
        self.owner: list[int] = []
        self.offset: list[int] = []
        self.size = 0

    def add(self, text, ids: np.ndarray, shortest: int, runs, items) -> None:
        n = len(self.docs)
        self.docs.append((text, len(ids), runs or [], items or []))
        edge = np.flatnonzero(np.diff(np.r_[0, (ids != 0).astype(np.int8), 0]))
        starts, ends = edge[::2], edge[1::2]
        long = ends - starts >= shortest
        for a, b in zip(starts[long].tolist(), ends[long].tolist()):
            self.pieces.append(ids[a:b])
            self.owner.append(n)
            self.offset.append(a)
            self.size += b - a + 1

    def hits(self, by_width: dict[int, Windows], names: list) -> dict[int, tuple[list, list]]:
        """For each document with hits: merged word spans and items."""
        if not self.pieces:
            return {}
        runs = np.array([len(p) + 1 for p in self.pieces])
        begin = np.r_[0, np.cumsum(runs)]
        text = np.zeros(begin[-1], np.int64)
        for a, p in zip(begin.tolist(), self.pieces):
            text[a : a + len(p)] = p
        index = FMIndex(text)
        owner, offset = np.array(self.owner), np.array(self.offset)
        marks = np.zeros(len(text) + 1, np.int64)
        seen = [np.zeros(0, np.int64)]
        for width, w in by_width.items():
            lo, hi = index.search(w.rows)
            before = np.r_[0, np.cumsum(hi - lo)]
            for start in range(0, int(before[-1]), _ROWS):
                at = np.arange(start, min(int(before[-1]), start + _ROWS))
                window = np.searchsorted(before, at, "right") - 1
                places = index.locate(lo[window] + at - before[window])
                np.add.at(marks, places, 1)
                np.add.at(marks, places + width, -1)
                pairs = np.unique(owner[np.searchsorted(begin, places, "right") - 1] * len(w.rows) + window)
                place, item = w.items(pairs % len(w.rows))
                seen.append(np.unique((pairs // len(w.rows))[place] * len(names) + item))
        out: dict[int, tuple[list, list]] = {}
        for pair in np.unique(np.concatenate(seen)).tolist():
            d, item = divmod(pair, len(names))
            out.setdefault(d, ([], []))[1].append(names[item])
        covered = np.flatnonzero(np.diff(np.r_[0, (np.cumsum(marks[:-1]) > 0).astype(np.int8), 0]))
        for a, b in zip(covered[::2].tolist(), covered[1::2].tolist()):
            r = int(np.searchsorted(begin, a, "right")) - 1
            d, shift = int(owner[r]), int(offset[r] - begin[r])
            out[d][0].append([a + shift, b + shift])
        return out


def _merge(spans: list) -> list[list[int]]:
    out: list[list[int]] = []
    for a, b in sorted(spans):
        if out and out[-1][1] >= a:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return out


def _search(df: DataFrame, items: list[tuple], width: int, shard_words: int, out: T.StructType, last: bool, keep_text: bool) -> DataFrame:
    """One group of items against all rows; a row carries what earlier groups found, and its text until the last group."""
    shared = df.sparkSession.sparkContext.broadcast(windows_of(items, width))
    arrow = to_arrow_schema(out)

    def run(batches):
        known, names, by_width = shared.value
        shortest = min(by_width, default=1)

        def flush(shard):
            hits = shard.hits(by_width, names) if by_width else {}
            cols = [[] for _ in arrow][2:]
            for d, (body, n, runs, earlier) in enumerate(shard.docs):
                spans, found = hits.get(d, ([], []))
                spans = _merge([*runs, *spans])
                chars = _char_spans(body, spans) if spans and last else []
                for col, x in zip(cols, (spans, sorted({*earlier, *(i for i in found if i is not None)}), n, sum(b - a for a, b in spans), [{"start": a, "end": b} for a, b in chars])):
                    col.append(x)
            passed = [pa.concat_arrays([h.column(k) for h in shard.held]) for k in (0, 1)]
            if last and not keep_text:
                passed[1] = pa.nulls(len(shard.docs), arrow.field(1).type)
            passed = [c if c.type == f.type else c.cast(f.type) for c, f in zip(passed, arrow)]
            return pa.RecordBatch.from_arrays([*passed, *(pa.array(c, f.type) for c, f in zip(cols, list(arrow)[2:]))], schema=arrow)

        shard, held = _Shard(), 0
        for batch in batches:
            for piece in slices(batch, "text"):
                start = 0
                for i, (body, runs, found) in enumerate(zip(*(c.to_pylist() for c in piece.columns[1:4]))):
                    shard.add(body, np.array([known.get(w, 0) for w in words(body)], np.int64), shortest, runs, found)
                    held += len(body or "")
                    if shard.size >= shard_words or held >= SLICE_BYTES:
                        shard.held.append(piece.slice(start, i + 1 - start))
                        yield flush(shard)
                        shard, held, start = _Shard(), 0, i + 1
                if start < piece.num_rows:
                    shard.held.append(piece.slice(start))
        if shard.docs:
            yield flush(shard)

    return df.mapInArrow(run, out)


def find_contamination(docs: DataFrame, benchmark: DataFrame, key: str = "doc_id", text: str = "text", item: str = "item_id", item_text: str = "text", width: int = WINDOW, shard_words: int = SHARD_WORDS, group_bytes: int = BENCHMARK_BYTES, keep_text: bool = False) -> DataFrame:
    """One row for each input row: key, n_words, n_hit, items (sorted strings), spans (code points, merged).

    The key passes through as it came, so it may be a struct of a row's other columns; with keep_text the text comes back too
    (as column text), and rows are decided without a join.
    Null and empty texts have no words; an item without words has no window; an item with a null id marks words but is not
    listed; repeated item ids count once; repeated rows give repeated rows; an empty benchmark hits nothing. Other columns
    of either table are not read, so they may have any name.
    """
    pair = T.StructType([T.StructField("start", T.LongType()), T.StructField("end", T.LongType())])
    out = T.StructType(
        [T.StructField("key", docs.schema[key].dataType), T.StructField("text", T.StringType()), T.StructField("runs", T.ArrayType(T.ArrayType(T.LongType()))), T.StructField("items", T.ArrayType(T.StringType()))]
        + [T.StructField("n_words", T.LongType()), T.StructField("n_hit", T.LongType()), T.StructField("spans", T.ArrayType(pair))]
    )
    side = benchmark.select(F.col(item).cast("string").alias("item"), F.col(item_text).cast("string").alias("body"))
    groups = max(1, -(-total_bytes(side, "body") // group_bytes))
    df = docs.select(F.col(key).alias("key"), F.col(text).cast("string").alias("text"), F.lit(None).cast("array<array<bigint>>").alias("runs"), F.lit(None).cast("array<string>").alias("items"))
    for g in range(groups):
        part = side if groups == 1 else side.filter(F.pmod(F.xxhash64("item", "body"), F.lit(groups)) == g)
        df = _search(df, [(r["item"], r["body"]) for r in part.collect()], width, shard_words, out, g == groups - 1, keep_text)
    return df.select(F.col("key").alias(key), *(["text"] if keep_text else []), "n_words", "n_hit", "items", "spans")


def remove_spans(text: Column, spans: Column) -> Column:
    """Text without its removal spans (code points, sorted, disjoint)."""
    start = F.struct(F.lit(0).cast("long").alias("at"), F.lit("").alias("out"))
    kept = F.aggregate(
        spans,
        start,
        lambda acc, s: F.struct(s["end"].alias("at"), F.concat(acc["out"], F.substring(text, (acc["at"] + 1).cast("int"), (s["start"] - acc["at"]).cast("int"))).alias("out")),
    )
    return F.when(F.size(spans) > 0, F.concat(kept["out"], F.substring(text, (kept["at"] + 1).cast("int"), F.length(text)))).otherwise(text)


def contaminated(n_hit: Column, n_words: Column) -> Column:
    """The contract's rule: at least one word in twenty lies in an occurrence."""
    return (n_hit > 0) & (20 * n_hit >= n_words)


def op1_decontaminate(spark, sf_dir: str) -> DataFrame:
    found = find_contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return found.select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ",").cast("binary"), 256).alias("items_sha256"), contaminated(F.col("n_hit"), F.col("n_words")).alias("contaminated"))
