"""Language-model scoring by cross-entropy difference.

A target model (texts labelled good) and a background model (all texts) are matched: word bigrams interpolated with
unigrams, one smoothing, one vocabulary. A document's score is its mean loss under the target model minus its mean loss
under the background model; low scores are like the target.

Counts cover the whole corpus, and both models use every bigram. Partitions count first, a shuffle sums. What is broadcast is
bounded by parameters: VOCABULARY words, and the commonest bigrams, at most BIGRAMS. The others stay a distributed table; a
document's own, counted for each document, are joined to it. The split changes where a loss is looked up, never its value.
"""

from __future__ import annotations

from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, functions as F, types as T

from .common import map_text, materialise, table, to_arrow_schema
from .decontaminate import words

VOCABULARY, BIGRAMS = 1 << 15, 1 << 20
#: Distinct words a worker counts before it passes them on, grams it counts at a time, distinct grams it holds, and target
#: ids that are broadcast rather than joined by a shuffle.
HELD, BLOCK, GRAMS, TARGET_IDS = 1 << 17, 1 << 19, 1 << 20, 1 << 19
LAMBDA, ALPHA = 0.6, 0.1


def vocabulary(docs: DataFrame, text: str, size: int) -> list[bytes]:
    """The commonest words of all texts, ties by bytes."""
    schema = T.StructType([T.StructField("word", T.BinaryType()), T.StructField("n", T.LongType())])

    def work(blocks):
        counts: Counter = Counter()
        for _, texts in blocks:
            for t in texts:
                counts.update(words(t))
                if len(counts) > HELD:
                    yield [list(counts), list(counts.values())]
                    counts = Counter()
        yield [list(counts), list(counts.values())]

    counted = map_text(docs, [], text, schema, work).groupBy("word").agg(F.sum("n").alias("n"))
    return [r["word"] for r in counted.orderBy(F.desc("n"), "word").limit(size).collect()]


def _ids(known: dict[bytes, int], text: str | None) -> np.ndarray:
    unknown = len(known)
    return np.array([known.get(w, unknown) for w in words(text)], np.int64)


class Held:
    """Sorted distinct grams with their counts in target texts and in all, merged block by block."""

    def __init__(self):
        self.keys = self.target = self.everything = np.zeros(0, np.int64)

    @property
    def size(self) -> int:
        return len(self.keys)

    def add(self, raw: list[np.ndarray], flags: list[bool]) -> None:
        if not raw:
            return
        for grams, marked in ((raw, False), ([g for g, f in zip(raw, flags) if f], True)):
            if grams:
                self._merge(*np.unique(np.concatenate(grams), return_counts=True), marked)

    def _merge(self, keys: np.ndarray, n: np.ndarray, marked: bool) -> None:
        every = np.concatenate([self.keys, keys])
        order = np.argsort(every, kind="stable")
        every = every[order]
        first = np.flatnonzero(np.r_[True, every[1:] != every[:-1]])
        none = np.zeros(len(keys), np.int64)
        add = lambda old, new: np.add.reduceat(np.concatenate([old, new])[order], first)
        self.target, self.everything = add(self.target, n if marked else none), add(self.everything, none if marked else n)
        self.keys = every[first]

    def empty(self) -> list[pa.Array]:
        out = [pa.array(self.keys), pa.array(self.target), pa.array(self.everything)]
        self.__init__()
        return out


class Models:
    """Both models over one vocabulary: counts of words, and of broadcast bigrams by sorted key."""

    def __init__(self, size: int, unigrams: np.ndarray, keys: np.ndarray, pairs: np.ndarray):
        self.size, self.keys = size, keys  # size: words and the unknown one
        self.first = np.maximum(unigrams, 1)
        self.single = (unigrams + ALPHA) / (unigrams.sum(axis=1, keepdims=True) + ALPHA * size)
        self.base = np.log((1 - LAMBDA) * self.single)
        self.both = self.together(keys, pairs)
        self.start = np.log(self.single)

    def together(self, keys: np.ndarray, pairs: np.ndarray) -> np.ndarray:
        """Log probabilities of bigrams from their counts, a row for each model."""
        first, second = keys // self.size, keys % self.size
        return np.log(LAMBDA * pairs / self.first[:, first] + (1 - LAMBDA) * self.single[:, second])

    def gains(self, keys: np.ndarray, pairs: np.ndarray) -> np.ndarray:
        """What bigrams add to the log probability that their second word has alone."""
        return self.together(keys, pairs) - self.base[:, keys % self.size]

    def sums(self, ids: np.ndarray) -> tuple[float, float, np.ndarray]:
        """Log probability under the target and the background model, and the bigrams scored by their second word alone."""
        if not len(ids):
            return 0.0, 0.0, np.zeros(0, np.int64)
        key = ids[:-1] * self.size + ids[1:]
        at = np.minimum(np.searchsorted(self.keys, key), max(0, len(self.keys) - 1))
        held = self.keys[at] == key if len(self.keys) else np.zeros(len(key), bool)
        out = []
        for m in (0, 1):
            rest = np.where(held, self.both[m][at], self.base[m][ids[1:]]) if len(self.keys) else self.base[m][ids[1:]]
            out.append(float(self.start[m][ids[0]] + rest.sum()))
        return out[0], out[1], key[~held]


def train(docs: DataFrame, target: DataFrame, key: str = "doc_id", text: str = "text", size: int = VOCABULARY, bigrams: int = BIGRAMS, target_ids: int = TARGET_IDS) -> tuple[list[bytes], Models, DataFrame | None]:
    """Fit both models; target has the keys of the target texts (column key). Null keys are never in the target.

    Gives the vocabulary, the models with at most bigrams bigrams, and what each other one adds: (gram, target, background),
    None if there is no other.
    """
    spark = docs.sparkSession
    listed = vocabulary(docs, text, size)
    n = len(listed) + 1
    shared = spark.sparkContext.broadcast(listed)
    wanted = target.select(F.col(key).alias("t")).filter("t IS NOT NULL").dropDuplicates()
    body = docs.select(docs[key].alias("key"), docs[text].alias("text"))
    side = F.broadcast(wanted) if wanted.limit(target_ids + 1).count() <= target_ids else wanted
    marked = body.join(side, body["key"] == side["t"], "left").select("text", F.col("t").isNotNull().alias("flag"))
    schema = T.StructType([T.StructField("gram", T.LongType()), T.StructField("target", T.LongType()), T.StructField("all", T.LongType())])

    def work(blocks):
        known = {w: i for i, w in enumerate(shared.value)}
        raw, flags, waiting, held = [], [], 0, Held()
        for (marks,), texts in blocks:
            for f, t in zip(marks, texts):
                w = _ids(known, t)
                for i in range(0, len(w), BLOCK):
                    part = w[i : i + BLOCK + 1]
                    grams = np.concatenate([-1 - part[:BLOCK], part[:-1] * n + part[1:]])  # below 0: single words
                    raw.append(grams)
                    flags.append(f)
                    waiting += len(grams)
                    if waiting >= BLOCK:
                        held.add(raw, flags)
                        raw, flags, waiting = [], [], 0
                        if held.size > GRAMS:
                            yield held.empty()
        held.add(raw, flags)
        yield held.empty()

    counts = map_text(marked, ["flag"], "text", schema, work).groupBy("gram").agg(F.sum("target").alias("target"), F.sum("all").alias("all"))
    counts = materialise(counts, "grams")
    unigrams = np.zeros((2, n))
    for r in counts.filter("gram < 0").toLocalIterator():
        unigrams[:, -1 - r["gram"]] = r["target"], r["all"]
    grams, top = counts.filter("gram >= 0"), 1 << 16
    # Counts from top on are told apart by powers of two only.
    step = F.when(F.col("all") < top, F.col("all")).otherwise(F.pow(F.lit(2.0), F.floor(F.log2("all"))).cast("long"))
    sizes = {r["c"]: r["n"] for r in grams.groupBy(step.alias("c")).agg(F.count("*").alias("n")).collect()}
    least, total = 1, 0
    for c in sorted(sizes, reverse=True):
        total += sizes[c]
        if total > bigrams:
            least = c + 1 if c < top else 2 * c
            break
    kept = grams.filter(F.col("all") >= least).toArrow()
    keys = kept.column("gram").to_numpy()
    order = np.argsort(keys)
    pairs = np.stack([kept.column("target").to_numpy()[order], kept.column("all").to_numpy()[order]]).astype(float)
    models = Models(n, unigrams, keys[order], pairs)
    if least == 1:
        return listed, models, None
    held = spark.sparkContext.broadcast(models)

    def gains(batches):
        for b in batches:
            keys, target, everything = (c.to_numpy(zero_copy_only=False) for c in b.columns)
            t, a = held.value.gains(keys, np.stack([target, everything]).astype(float))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(t), pa.array(a)], names=["gram", "target", "background"])

    return listed, models, grams.filter(F.col("all") < least).select("gram", "target", "all").mapInArrow(gains, "gram long, target double, background double")


def score(docs: DataFrame, listed: list[bytes], models: Models, others: DataFrame | None = None, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, n_tokens, target_loss, background_loss, score) for each row; null and empty texts have no tokens and score 0."""
    shared = docs.sparkSession.sparkContext.broadcast((listed, models))
    many, others_joined = T.ArrayType(T.LongType()), others is not None
    schema = T.StructType([T.StructField("key", docs.schema[key].dataType), T.StructField("n_tokens", T.LongType()), T.StructField("target", T.DoubleType()), T.StructField("background", T.DoubleType())])
    if others_joined:
        for c, kind in (("row", T.LongType()), ("grams", many), ("times", many)):
            schema = schema.add(c, kind)

    def work(blocks):
        found, m = shared.value
        known = {w: i for i, w in enumerate(found)}
        row = TaskContext.get().partitionId() << 40
        for (keys,), texts in blocks:
            lengths, sums, grams, times = [], [], [], []
            for t in texts:
                ids = _ids(known, t)
                *logs, rest = m.sums(ids)
                lengths.append(len(ids))
                sums.append(logs)
                if others_joined:
                    g, c = np.unique(rest, return_counts=True)
                    grams.append(g)
                    times.append(c)
            cols = [keys, lengths, [x[0] for x in sums], [x[1] for x in sums]]
            if others_joined:
                cols += [np.arange(row, row + len(keys)), _lists(grams), _lists(times)]
                row += len(keys)
            yield cols

    out = map_text(docs.select(docs[key].alias("key"), docs[text].alias("text")), ["key"], "text", schema, work)
    target, background = F.col("target"), F.col("background")
    if others_joined:
        # Written, so that every use sees the same row numbers.
        out = materialise(out, "scored")
        each = out.select("row", F.explode(F.arrays_zip("grams", "times")).alias("g")).select("row", F.col("g.grams").alias("gram"), F.col("g.times").alias("times"))
        added = each.join(others, "gram").groupBy("row").agg(F.sum(F.col("times") * target).alias("t"), F.sum(F.col("times") * background).alias("b"))
        out = out.drop("grams", "times").join(added, "row", "left")
        target, background = target + F.coalesce("t", F.lit(0.0)), background + F.coalesce("b", F.lit(0.0))
    loss = lambda total: F.when(F.col("n_tokens") > 0, -total / F.col("n_tokens")).otherwise(0.0)
    out = out.select(F.col("key").alias(key), "n_tokens", loss(target).alias("target_loss"), loss(background).alias("background_loss"))
    return out.withColumn("score", F.col("target_loss") - F.col("background_loss"))


def _lists(parts: list[np.ndarray]) -> pa.Array:
    ends = np.cumsum([0, *map(len, parts)]).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate([np.zeros(0, np.int64), *parts]).astype(np.int64)), type=to_arrow_schema(T.StructType([T.StructField("x", T.ArrayType(T.LongType()))])).field(0).type)


def op4_lm_score(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    good = table(spark, sf_dir, "labels").filter("quality = 1").select("doc_id")
    return score(docs, *train(docs, good))
