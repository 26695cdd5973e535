"""Language detection: a linear binary classifier for each language, and the detectors other recipes use.

Two linear detectors share one interface idea, score above threshold: fixed weights on function words (plain columns, with
SQL as oracle), and weights trained on hashed character n-grams (a trained model, applied in an Arrow pass).
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F, types as T

from ..functions import chargrams, textstats as ts
from ..profiles import FUNCTION_WORDS
from .dedup import save

THRESHOLD = 0.05
BITS, TRAIN_ROWS = 18, 5_000


def own_words(code: str) -> list[str]:
    """Function words of one language that no other lists."""
    others = {w for c, ws in FUNCTION_WORDS.items() if c != code for w in ws}
    return [w for w in FUNCTION_WORDS[code] if w not in others]


def foreign_words(code: str) -> list[str]:
    mine = set(FUNCTION_WORDS[code])
    return sorted({w for c, ws in FUNCTION_WORDS.items() if c != code for w in ws if w not in mine})


def score_of(w: Column, code: str) -> Column:
    """(own - foreign function words) / words, of a list of words; an empty one 0. Hold the words where several uses follow."""
    return ts.ratio(_hits(w, own_words(code)) - _hits(w, foreign_words(code)), F.size(w))


def score(text: Column, code: str) -> Column:
    return score_of(ts.words(text), code)


def in_language(df: DataFrame, code: str, text: str = "text", threshold: float = THRESHOLD) -> DataFrame:
    """The rows whose text is in the language; the words are taken once."""
    held = ts.hold(df, _words=ts.words(F.col(text)))
    return held.filter(F.coalesce(score_of(F.col("_words"), code) > threshold, F.lit(False))).select(df.columns)


def is_target(text: Column, code: str, threshold: float = THRESHOLD) -> Column:
    return F.coalesce(score(text, code) > threshold, F.lit(False))


def function_word_vote(text: Column) -> Column:
    """The language with most function words; a tie or no hit gives 'und'."""
    return vote_of(ts.words(text))


def vote_of(w: Column) -> Column:
    votes = {c: _hits(w, ws) for c, ws in FUNCTION_WORDS.items()}
    top = F.greatest(*votes.values())
    ties = sum(((v == top).cast("int") for v in votes.values()), F.lit(0))
    winner = F.coalesce(*[F.when(v == top, F.lit(c)) for c, v in votes.items()])
    return F.when((ties > 1) | (top == 0), "und").otherwise(winner)


def _hits(w: Column, listed: list[str]) -> Column:
    return F.size(F.filter(w, lambda x: x.isin(listed)))


#: Multipliers that mix the code points of a gram into its feature number, by length of the gram.
_MIX = [np.array(m, np.uint64) for m in ([0x9E3779B97F4A7C15], [0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9], [0xD6E8FEB86659FD93, 0xA0761D6478BD642F, 0xE7037ED1A0B428DB])]


def ngram_counts(text: str) -> tuple[np.ndarray, np.ndarray]:
    """(feature numbers, values): hashed counts of character 1- to 3-grams of the whole lower-cased text, L2-normalised."""
    if not text:
        return np.zeros(0, np.int64), np.zeros(0)
    code = np.frombuffer(f" {text.lower()} ".encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    found = []
    for mix in _MIX:
        h = sum((code[k : len(code) - len(mix) + 1 + k] * m for k, m in enumerate(mix)), np.uint64(len(mix)))
        found.append((h ^ h >> np.uint64(31)) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(64 - BITS))
    ids, counts = np.unique(np.concatenate(found), return_counts=True)
    return ids.astype(np.int64), counts / np.sqrt((counts.astype(float) ** 2).sum())


@dataclass
class LangModel:
    weights: np.ndarray  # the last is the bias
    threshold: float

    def score(self, text: str | None) -> float:
        ids, values = ngram_counts(text or "")
        return float(self.weights[ids] @ values + self.weights[-1]) if len(ids) else -1e9


def train(df: DataFrame, label: Column, key: str = "doc_id", text: str = "text", rows: int = TRAIN_ROWS, epochs: int = 12) -> LangModel:
    """Logistic regression on at most rows labelled texts picked by a hash of the key; threshold of maximal F1 on a fifth."""
    picked = df.select(F.col(text).cast("string").alias("t"), label.cast("int").alias("y"), F.xxhash64(key).alias("h")).filter("t IS NOT NULL AND y IS NOT NULL").orderBy("h", "t").limit(rows).toArrow()
    data = [(*ngram_counts(t), y) for t, y in zip(picked.column("t").to_pylist(), picked.column("y").to_pylist()) if t]
    w = np.zeros((1 << BITS) + 1)
    fit, held = [d for i, d in enumerate(data) if i % 5], [d for i, d in enumerate(data) if i % 5 == 0]
    rng = np.random.default_rng(1)
    for epoch in range(epochs):
        for i in rng.permutation(len(fit)):
            ids, v, y = fit[i]
            p = 1 / (1 + np.exp(-np.clip(w[ids] @ v + w[-1], -30, 30)))
            step = 4.0 / (1 + epoch) * (p - y)
            w[ids] -= step * v
            w[-1] -= 0.1 * step
    scores = sorted(((float(w[ids] @ v + w[-1]), y) for ids, v, y in held), reverse=True)
    best, at, tp, positive = -1.0, 0.0, 0, max(1, sum(y for _, y in scores))
    for i, (s, y) in enumerate(scores):
        tp += y
        if (f1 := 2 * tp / (i + 1 + positive)) > best:
            best, at = f1, s
    return LangModel(w.astype(np.float32), at)


def apply(df: DataFrame, model: LangModel, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, score, is_target); null and empty texts are not in the language."""
    shared = df.sparkSession.sparkContext.broadcast(model)
    schema = T.StructType([df.schema[key], T.StructField("score", T.DoubleType()), T.StructField("is_target", T.BooleanType())])

    def run(batches):
        for b in batches:
            s = [shared.value.score(t) for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(s, pa.float64()), pa.array([x >= shared.value.threshold for x in s])], names=[key, "score", "is_target"])

    return df.select(key, F.col(text).cast("string")).mapInArrow(run, schema)


#: Grams of a naive Bayes model that go to the texts; a larger model is joined.
MODEL_GRAMS = 1 << 19


def naive_bayes(train_df: DataFrame, df: DataFrame, label: str = "lang", key: str = "doc_id", text: str = "text", n: int = 2, k: float = 0.5) -> DataFrame:
    """(key, predicted): multinomial naive Bayes over character n-grams of whole texts; a text without a known gram has no row.

    The grams of the labelled texts are counted in an Arrow pass. The model goes to the texts, which stay in place; one of more
    than MODEL_GRAMS grams is joined to the distinct grams of each text.
    """
    low = lambda d, *cols: d.select(*cols, F.lower(F.col(text)).alias("_t"))
    counts = save(chargrams.gram_counts(low(train_df, label), n, label, "_t"), "grams")
    by_gram = counts.groupBy("gram").agg(F.map_from_entries(F.collect_list(F.struct(label, "n"))).alias("c"))
    totals = {r[0]: r[1] for r in counts.groupBy(label).agg(F.sum("n")).collect()}
    labels, size = sorted(totals), by_gram.count()
    weight = [F.log((F.coalesce(F.col("c")[F.lit(x)], F.lit(0)) + k) / (totals[x] + k * size)) for x in labels]
    model = by_gram.select("gram", F.array(*weight).cast("array<double>").alias("lp"))
    schema = T.StructType([df.schema[key], T.StructField("predicted", train_df.schema[label].dataType)])
    if not labels:
        return df.sparkSession.createDataFrame([], schema)
    best = lambda s: max(range(len(labels)), key=lambda i: (s[i], labels[i]))
    if size > MODEL_GRAMS:
        return _joined_bayes(low(df, key), model, labels, key, n)
    table = model.toArrow()
    shared = df.sparkSession.sparkContext.broadcast((table.column("gram").to_pylist(), np.array(table.column("lp").to_pylist()).reshape(size, len(labels))))

    def run(batches):
        grams, weights = shared.value
        at = {g: i for i, g in enumerate(grams)}
        alphabet = np.unique(chargrams.codes_of(grams)) if any(grams) else np.zeros(0, np.uint32)
        a = len(alphabet) + 1  # rank 0 is a character that the model does not know
        dense = a**n <= 1 << 24
        if dense:
            rank = np.zeros(0x110000, np.int64)
            rank[alphabet] = np.arange(1, a)
            row = np.full(a**n, size, np.int32)
            whole = [g for g in grams if len(g) == n]
            r = rank[chargrams.codes_of(whole)].reshape(-1, n)
            row[sum(r[:, j] * a ** (n - 1 - j) for j in range(n)) if whole else []] = [at[g] for g in whole]
        for batch in batches:
            ids, said = [], []
            for i, t in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                if t is None:
                    continue
                if dense and len(t) >= n:
                    c = rank[chargrams.codes_of([t])]
                    m = np.bincount(row[sum(c[j : len(c) - n + 1 + j] * a ** (n - 1 - j) for j in range(n))], minlength=size + 1)[:size]
                    known, m = np.flatnonzero(m), m[m > 0]
                else:
                    held = {at[g]: x for g, x in chargrams.count_grams([t], n).items() if g in at}
                    known, m = np.array(sorted(held), np.int64), np.array([held[x] for x in sorted(held)])
                if len(known):
                    ids.append(i)
                    said.append(labels[best((m[:, None] * weights[known]).sum(axis=0))])
            yield pa.RecordBatch.from_arrays([pa.array(ids, batch.schema.field(0).type), pa.array(said)], names=[key, "predicted"])

    return low(df, key).mapInArrow(run, schema)


def _joined_bayes(low: DataFrame, model: DataFrame, labels: list, key: str, n: int) -> DataFrame:
    """naive_bayes with a model too large for one task: distinct grams of each text meet the model."""
    schema = T.StructType([low.schema[key], T.StructField("gram", T.StringType()), T.StructField("m", T.LongType())])

    def run(batches):
        for batch in batches:
            for i, t in zip(batch.column(0), batch.column(1).to_pylist()):
                if t is not None:
                    found = chargrams.count_grams([t], n)
                    yield pa.RecordBatch.from_arrays([pa.array([i.as_py()] * len(found), batch.schema.field(0).type), pa.array(list(found), pa.string()), pa.array(list(found.values()), pa.int64())], names=[key, "gram", "m"])

    sums = low.mapInArrow(run, schema).join(model, "gram").groupBy(key).agg(*[F.sum(F.col("m") * F.col("lp")[i]).alias(f"s{i}") for i in range(len(labels))])
    ranked = F.array_max(F.array(*[F.struct(F.col(f"s{i}").alias("s"), F.lit(x).alias("label")) for i, x in enumerate(labels)]))
    return sums.select(key, ranked["label"].alias("predicted"))
