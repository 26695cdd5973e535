"""Toxicity by a classifier chain.

Linear models stand in a fixed order; each sees the text's features and the probabilities of the categories before it.
While training, those probabilities are out-of-fold predictions, and features are picked anew in each fold, so a later model
never sees what an earlier one learned by heart. Features are counts of words and of word beginnings, since many abusive words
share a stem.

The categories before the last are induced from the labelled toxic texts: kinds of toxic text, told apart by which of the
telling features they hold (spherical k-means). The last is labels.toxic itself, and its threshold, chosen on out-of-fold
predictions, decides.
"""

from __future__ import annotations

import re
import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import DataFrame, functions as F, types as T

from .common import discard, map_text, materialise, table

KINDS, LAST = 3, "toxic"
#: Labelled keys of each kind that the models are fitted on, at most (documented bound; all else covers all rows).
TRAIN_ROWS = 3000
FEATURES, BUCKETS, FOLDS = 1000, 1 << 20, 5
STEMS = (4, 5, 6, 7)
#: Words whose features a worker remembers, and the longest of them.
MEMO, LONGEST = 1 << 17, 64
_WORD = re.compile(r"\w+")


def hashes(word: str) -> list[int]:
    """Feature numbers of a lower-case word: the word, and its beginnings (itself again in place of those it is too short for)."""
    b = word.encode("utf-8", "surrogatepass")
    keys = [zlib.crc32(b) % BUCKETS]
    for k in STEMS:
        if len(word) <= k:
            return [*keys, zlib.crc32(b"^" + b) % BUCKETS]
        keys.append(zlib.crc32(b"^" + word[:k].encode("utf-8", "surrogatepass")) % BUCKETS)
    return keys


def word_counts(text: str | None) -> Counter:
    return Counter(_WORD.findall((text or "").lower()))


def features(text: str | None) -> tuple[np.ndarray, np.ndarray]:
    """Sorted hashed features with counts: whole words and their beginnings, lower-cased."""
    found: dict[int, int] = {}
    for w, n in word_counts(text).items():
        for h in hashes(w):
            found[h] = found.get(h, 0) + n
    order = sorted(found)
    return np.array(order, np.int32), np.array([found[h] for h in order], np.int32)


@dataclass
class Chain:
    """slots: bucket -> column (0: unused); weights of each category over columns, then over earlier categories, then bias."""

    names: list[str]
    slots: np.ndarray
    columns: int
    weights: list[np.ndarray] = field(default_factory=list)
    threshold: float = 0.5

    def rows(self, texts: list[str | None], memo: dict[str, list[int]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(row, column, value) of the known features of texts; memo remembers the columns of words."""
        row, col, values = [], [], []
        for i, t in enumerate(texts):
            found: dict[int, int] = {}
            for w, n in word_counts(t).items():
                columns = memo.get(w)
                if columns is None:
                    columns = [int(c) - 1 for c in self.slots[hashes(w)] if c]
                    if len(w) <= LONGEST:
                        if len(memo) >= MEMO:
                            memo.clear()
                        memo[w] = columns
                for c in columns:
                    found[c] = found.get(c, 0) + n
            row += [i] * len(found)
            col += found
            values += found.values()
        return np.array(row, np.int64), np.array(col, np.int64), np.log1p(np.array(values, np.float64))

    def predict(self, texts: list[str | None], memo: dict[str, list[int]] | None = None) -> tuple[np.ndarray, np.ndarray]:
        """Probabilities of the categories (a column for each), and the verdicts; a text without any known feature is never
        rejected."""
        row, col, values = self.rows(texts, {} if memo is None else memo)
        n, out = self.columns, np.zeros((len(texts), len(self.weights)))
        for k, w in enumerate(self.weights):
            z = np.bincount(row, w[col] * values, minlength=len(texts)) + out[:, :k] @ w[n : n + k] + w[-1]
            out[:, k] = 1 / (1 + np.exp(-np.clip(z, -30, 30)))
        return out, (np.bincount(row, minlength=len(texts)) > 0) & (out[:, -1] >= self.threshold)


def _fit(x: np.ndarray, y: np.ndarray, weight: np.ndarray, used: np.ndarray, l2: float = 1e-4, steps: int = 150) -> np.ndarray:
    """Weighted logistic regression by accelerated gradient steps over the used columns; the last column of x is 1 and is not
    shrunk."""
    w = look = np.zeros(x.shape[1], np.float32)
    share = weight / weight.sum()
    rate = 4.0 / max(1e-6, float(np.einsum("i,ij,ij->", share, x, x)))
    rate = min(rate * 8, 4.0)
    shrink = np.full(x.shape[1], l2, np.float32)
    shrink[-1] = 0
    loss = np.inf
    t = 1.0
    for _ in range(steps):
        z = x @ look
        p = 1 / (1 + np.exp(-np.clip(z, -30, 30)))
        now = float(share @ (np.logaddexp(0, z) - y * z))
        if now > loss + 1e-9:
            look, t, rate = w, 1.0, rate / 2
            loss = np.inf
            continue
        loss = now
        nxt = look - rate * used * (x.T @ (share * (p - y)).astype(np.float32) + shrink * look)
        t2 = (1 + np.sqrt(1 + 4 * t * t)) / 2
        look, w, t = nxt + np.float32((t - 1) / t2) * (nxt - w), nxt, t2
    return w


def _gain(with_: np.ndarray, without: np.ndarray, n1: int, n0: int, size: int) -> np.ndarray:
    """Numbers of the telling features, best first: how often texts of either kind hold them."""
    p, q = (with_ + 0.5) / (max(n1, 1) + 1), (without + 0.5) / (max(n0, 1) + 1)
    gain = n1 * (p - q) * np.log(p / q)
    gain[with_ + without < 3] = 0
    return np.argsort(-gain, kind="stable")[: min(size, int((gain > 0).sum()))]


def kinds_of(x: np.ndarray, kinds: int = KINDS, rounds: int = 20) -> np.ndarray:
    """A kind for each row of x by spherical k-means, the largest kind first; the same for the same rows."""
    unit = x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-9)
    if not len(x):
        return np.zeros(0, np.int64)
    middle = unit.sum(axis=0)
    centres = [unit[int(np.argmax(unit @ middle))]]
    while len(centres) < kinds:
        centres.append(unit[int(np.argmin((unit @ np.array(centres).T).max(axis=1)))])
    c = np.array(centres)
    for _ in range(rounds):
        of = np.argmax(unit @ c.T, axis=1)
        c = np.array([unit[of == k].sum(axis=0) if (of == k).any() else c[k] for k in range(kinds)])
        c /= np.maximum(np.linalg.norm(c, axis=1, keepdims=True), 1e-9)
    sizes = np.bincount(of, minlength=kinds)
    return np.argsort(np.argsort(-sizes, kind="stable"), kind="stable")[of]


def fit_chain(rows: list[tuple[np.ndarray, np.ndarray]], toxic: np.ndarray, fold: np.ndarray, weight: np.ndarray, held: dict[int, np.ndarray], kinds: int = KINDS) -> Chain:
    """rows: (feature numbers, counts), toxic (0 or 1), fold and weight (how many texts it stands for) of each row; held: the
    features picked without each fold, and under -1 those picked from all rows."""
    n_rows, everything = len(rows), np.unique(np.concatenate([np.zeros(0, np.int64), *held.values()])).astype(np.int64)
    slots = np.zeros(BUCKETS, np.int32)
    slots[everything] = np.arange(1, len(everything) + 1)
    n = len(everything)
    names = [*(f"kind{k + 1}" for k in range(kinds)), LAST]
    # Features, earlier categories (0 until they are predicted), bias. Every model is fitted on this one matrix: rows of a
    # fold are left out by weight, features that a fold did not pick stay at 0.
    x = np.zeros((n_rows, n + kinds + 1), np.float32)
    x[:, -1] = 1
    for i, (ids, counts) in enumerate(rows):
        cols = slots[ids]
        x[i, cols[cols > 0] - 1] = np.log1p(counts[cols > 0])
    y = np.zeros((n_rows, kinds + 1), np.float32)
    y[:, -1] = toxic
    bad = np.flatnonzero(toxic)
    y[bad, kinds_of(x[bad][:, slots[held[-1]] - 1], kinds)] = 1

    def used(f: int) -> np.ndarray:
        out = np.zeros(x.shape[1], np.float32)
        out[slots[held[f]] - 1] = 1
        out[n:] = 1
        return out

    models, oof = [], np.zeros(n_rows, np.float32)
    for k in range(kinds + 1):
        for f in np.unique(fold).tolist():
            out_of = fold == f
            if not out_of.all():
                w = _fit(x, y[:, k], weight * ~out_of, used(f))
                oof[out_of] = 1 / (1 + np.exp(-np.clip(x[out_of] @ w, -30, 30)))
        models.append(_fit(x, y[:, k], weight, used(-1)) if n_rows else np.r_[np.zeros(n + kinds), -30.0])
        if k < kinds:
            x[:, n + k] = oof
    # Only the columns that all rows picked have weights in the end.
    columns = slots[held[-1]] - 1
    slots[:] = 0
    slots[held[-1]] = np.arange(1, len(columns) + 1)
    chain = Chain(names, slots, len(columns), [np.r_[w[columns], w[n : n + k], w[-1]].astype(np.float64) for k, w in enumerate(models)])
    cuts = np.linspace(0.05, 0.95, 91)
    score = [2 * (weight * (oof >= c) * toxic).sum() / max(1e-9, (weight * (oof >= c)).sum() + (weight * toxic).sum()) for c in cuts]
    if n_rows:
        chain.threshold = float(cuts[max(i for i, s in enumerate(score) if s >= max(score) - 1e-6)])  # of equals, the strictest
    return chain


def train(docs: DataFrame, labels: DataFrame, train_rows: int = TRAIN_ROWS, key: str = "doc_id", text: str = "text", size: int = FEATURES, folds: int = FOLDS) -> Chain:
    """Fit on at most train_rows toxic and train_rows other labelled keys, picked by a hash of the key.

    Rows with a null key or label are left out; a key labelled twice counts as toxic if one label says so; of several texts
    with one key one is taken. Without labels the chain calls nothing toxic. Features of the picked texts are counted and
    picked by executors; the driver gets counts of at most BUCKETS features and, of a text, the picked features alone.
    """
    known = labels.filter(F.col(key).isNotNull() & F.col("toxic").isNotNull()).groupBy(F.col(key).alias("key")).agg(F.max("toxic").alias("toxic"))
    sizes = {r["toxic"]: r["n"] for r in known.groupBy("toxic").agg(F.count("*").alias("n")).collect()}
    part = [known.filter(F.col("toxic") == t).orderBy(F.xxhash64("key"), "key").limit(train_rows) for t in (0, 1)]
    picked = part[0].union(part[1])
    joined = docs.select(docs[key].alias("key"), docs[text].cast("string").alias("text")).join(F.broadcast(picked), "key").select("key", "toxic", "text")
    lists = T.ArrayType(T.IntegerType())
    schema = T.StructType([T.StructField("key", docs.schema[key].dataType), T.StructField("toxic", T.IntegerType()), T.StructField("ids", lists), T.StructField("counts", lists)])

    def work(blocks):
        for (keys, toxic), texts in blocks:
            found = [features(t) for t in texts]
            yield [keys, toxic, pa.array([a for a, _ in found], pa.list_(pa.int32())), pa.array([b for _, b in found], pa.list_(pa.int32()))]

    first = F.xxhash64("ids", "counts")
    seen = map_text(joined, ["key", "toxic"], "text", schema, work).groupBy("key").agg(F.min_by(F.struct("toxic", "ids", "counts"), first).alias("r"))
    seen = materialise(seen.select("key", "r.*", F.pmod(F.xxhash64("key", F.lit(7)), F.lit(folds)).cast("int").alias("fold")), "labelled")
    each = seen.select("toxic", "fold", F.explode("ids").alias("id")).groupBy("id", "toxic", "fold").agg(F.count("*").alias("n"))
    # A feature that fewer than three of the texts hold is never picked.
    counted = each.groupBy("id").agg(F.collect_list(F.struct("toxic", "fold", "n")).alias("c"), F.sum("n").alias("n")).filter("n >= 3").select("id", F.inline("c"))
    table_, texts = counted.toArrow(), {(r["toxic"], r["fold"]): r["n"] for r in seen.groupBy("toxic", "fold").agg(F.count("*").alias("n")).collect()}
    ids, toxic, fold, n = (table_.column(c).to_numpy() for c in ("id", "toxic", "fold", "n"))
    number = np.unique(ids)
    held = {}
    for f in (-1, *range(folds)):
        of = lambda t: np.bincount(np.searchsorted(number, ids[(toxic == t) & (fold != f)]), n[(toxic == t) & (fold != f)], minlength=len(number))  # noqa: E731, B023
        total = [sum(m for (kind, g), m in texts.items() if kind == t and g != f) for t in (0, 1)]
        held[f] = number[_gain(of(1), of(0), total[1], total[0], size)]
    union = docs.sparkSession.sparkContext.broadcast(np.unique(np.concatenate(list(held.values()))))

    def narrow(batches):
        for b in batches:
            lists = []
            for i, c in zip(b.column(2), b.column(3)):
                i, c = np.array(i.values, np.int32), np.array(c.values, np.int32)
                keep = np.isin(i, union.value)
                lists.append((i[keep], c[keep]))
            yield pa.RecordBatch.from_arrays([*b.columns[:2], *(pa.array([x[k] for x in lists], pa.list_(pa.int32())) for k in (0, 1)), b.column(4)], names=["key", "toxic", "ids", "counts", "fold"])

    got = seen.mapInArrow(narrow, seen.schema).toArrow()
    discard(seen)
    order = pa.compute.sort_indices(got.column("key")).to_pylist()
    columns = [got.column(c) for c in ("ids", "counts")]
    rows = [tuple(c[i].values.to_numpy() for c in columns) for i in order]
    toxic, fold = (got.column(c).to_numpy()[order] if order else np.zeros(0, np.int64) for c in ("toxic", "fold"))
    weight = np.array([sizes.get(t, 0) / max(1, int((toxic == t).sum())) for t in toxic.tolist()], np.float32)
    return fit_chain(rows, toxic, fold, weight, held)


def score(docs: DataFrame, chain: Chain, key: str = "doc_id", text: str = "text", carry: list[str] | None = None) -> DataFrame:
    """(key, one probability for each category, toxic) for each row; carry: other columns to keep beside them.

    Null, empty and wholly unknown texts get the models' bias alone and are not toxic; repeated rows repeat. No shuffle.
    """
    shared = docs.sparkSession.sparkContext.broadcast(chain)
    carry = carry or []
    probs = [f"p_{n}" for n in chain.names]
    schema = T.StructType([docs.schema[c] for c in [key, *carry]] + [T.StructField(p, T.DoubleType()) for p in probs] + [T.StructField("is_toxic", T.BooleanType())])

    def work(blocks):
        model, memo = shared.value, {}
        for cols, texts in blocks:
            p, bad = model.predict(texts, memo)
            yield [*cols[: 1 + len(carry)], *(pa.array(p[:, k]) for k in range(len(probs))), pa.array(bad)]

    if text in carry:
        raise ValueError("the text is read anyway; join it back or use keep_clean()")
    return map_text(docs, [key, *carry], text, schema, work)


def keep_clean(docs: DataFrame, chain: Chain, text: str = "text") -> DataFrame:
    """The rows of docs that the chain does not call toxic, all columns as they were; rows whose text is null, empty or unknown
    stay, repeated rows share their verdict."""
    shared = docs.sparkSession.sparkContext.broadcast(chain)

    @F.pandas_udf(T.BooleanType())
    def toxic(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        memo: dict = {}
        for texts in parts:
            yield pd.Series(shared.value.predict(texts.tolist(), memo)[1], dtype=bool)

    return docs.filter(~toxic(docs[text].cast("string")))


def op8_toxicity(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return score(docs, train(docs, table(spark, sf_dir, "labels"))).withColumnRenamed("is_toxic", "toxic")
