"""n-gram language models as tables: likelihood of texts under a reference, and cuts by quantile."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from ..functions import textstats as ts
from .dedup import save

UNKNOWN = "<unk>"


def reference_vocabulary(reference: DataFrame, least: int = 2, text: str = "text") -> DataFrame:
    """(word): words that the reference has at least so often."""
    return reference.select(F.explode(ts.words(F.col(text))).alias("word")).groupBy("word").agg(F.count("*").alias("c")).filter(F.col("c") >= least).select("word")


#: Words of a vocabulary that go into the plan as a set; a larger one is joined, word by word.
BROADCAST_WORDS = 1 << 13


def known_words(df: DataFrame, vocabulary: DataFrame, key: str, text: str = "text") -> DataFrame:
    """(key, w): a text's words in order; those outside the vocabulary become unknown.

    A small vocabulary goes to the documents, which then stay in place. Beyond, words are joined to it and gathered again.
    """
    body = ts.hold(df, w=ts.words(F.col(text))).select(key, "w")
    listed = [r["word"] for r in vocabulary.limit(BROADCAST_WORDS + 1).collect()]
    if 0 < len(listed) <= BROADCAST_WORDS:
        # A set of literals is looked up by hash; a map would be searched from its start. Words hold letters only.
        known = ", ".join(f"'{w}'" for w in sorted(listed))
        return body.select(key, F.expr(f"transform(w, x -> if(x IN ({known}), x, '{UNKNOWN}'))").alias("w"))
    rows = body.select(key, F.posexplode("w").alias("pos", "x")).join(vocabulary, F.col("x") == F.col("word"), "left")
    parts = rows.groupBy(key).agg(F.array_sort(F.collect_list(F.struct("pos", F.coalesce("word", F.lit(UNKNOWN)).alias("token")))).alias("s"))
    return parts.select(key, F.transform("s", lambda s: s["token"]).alias("w"))


def grams(tokens: DataFrame, n: int, key: str) -> DataFrame:
    """(key, context, gram) from the n-th token of a text on."""
    return ts.hold(tokens, _w=F.col("w")).select(key, F.explode(ts.ngrams(F.col("_w"), n)).alias("g")).select(key, F.regexp_extract("g", r"^(.*) [^ ]+$", 1).alias("context"), F.col("g").alias("gram"))


def train_ngram(reference: DataFrame, vocabulary: DataFrame, n: int = 3, key: str = "item_id", text: str = "text") -> tuple[DataFrame, DataFrame]:
    """Counts of n-grams (gram, c) and of their contexts (context, t)."""
    g = grams(known_words(reference, vocabulary, key, text), n, key)
    return g.groupBy("gram").agg(F.count("*").alias("c")), g.groupBy("context").agg(F.count("*").alias("t"))


def log_likelihood(df: DataFrame, reference: DataFrame, n: int = 3, k: float = 0.1, key: str = "doc_id", text: str = "text", ref_key: str = "item_id", least: int = 2) -> DataFrame:
    """(key, score): mean log-probability of a text's n-grams, add-k smoothed; texts with fewer tokens have no row."""
    vocabulary = reference_vocabulary(reference, least, text)
    counts, contexts = train_ngram(reference, vocabulary, n, ref_key, text)
    size = vocabulary.agg((F.count("*") + 1).alias("v"))
    g = grams(known_words(df, vocabulary, key, text), n, key).groupBy(key, "context", "gram").agg(F.count("*").alias("m"))
    p = g.join(counts, "gram", "left").join(contexts, "context", "left").crossJoin(F.broadcast(size))
    logp = F.log((F.coalesce("c", F.lit(0)) + k) / (F.coalesce("t", F.lit(0)) + F.col("v") * k))
    return p.groupBy(key).agg((F.sum(F.col("m") * logp) / F.sum("m")).alias("score"))


def exact_quantiles(df: DataFrame, value: str, qs: list[float], cells: int = 4096, most: int = 1 << 16) -> list[float | None]:
    """Interpolated quantiles, exact, without gathering all values: cells of the range are counted, and only the cells that hold
    the ranks asked for are divided again, until they have few distinct values. The driver sees counts of cells alone.
    """
    v = df.select(F.col(value).cast("double").alias("v")).filter("v IS NOT NULL AND NOT isnan(v)")
    n, low, high = v.agg(F.count("*"), F.min("v"), F.max("v")).first()
    if not n:
        return [None] * len(qs)

    def at_rank(k: int, rows: DataFrame, low: float, high: float) -> float:
        while low < high:
            counts = rows.groupBy("v").agg(F.count("*").alias("n"))
            if counts.limit(most + 1).count() <= most:
                for r in sorted(counts.collect()):
                    if k < r["n"]:
                        return r["v"]
                    k -= r["n"]
            cell = F.least(F.floor((F.col("v") - low) / (high - low) * cells), F.lit(cells - 1))
            rows = rows.withColumn("c", cell)
            for r in sorted(rows.groupBy("c").agg(F.count("*").alias("n"), F.min("v").alias("a"), F.max("v").alias("b")).collect()):
                if k < r["n"]:
                    rows, low, high = rows.filter(F.col("c") == r["c"]).select("v"), r["a"], r["b"]
                    break
                k -= r["n"]
        return low

    out = []
    for q in qs:
        place = q * (n - 1)
        below = at_rank(int(place), v, low, high)
        part = place - int(place)
        out.append(below if not part else below + (at_rank(int(place) + 1, v, low, high) - below) * part)
    return out


def quantile_cut(scored: DataFrame, q: float, keep_above: bool = True, score: str = "score") -> DataFrame:
    """Rows at or above (or at or below) the exact q-quantile of the scores."""
    scored = save(scored, "scored")
    cut = exact_quantiles(scored, score, [q])[0]
    return scored.filter(F.col(score) >= F.lit(cut) if keep_above else F.col(score) <= F.lit(cut))


def terciles(scored: DataFrame, score: str = "score") -> DataFrame:
    """head, middle and tail by the scores' terciles."""
    scored = save(scored, "scored")
    low, high = exact_quantiles(scored, score, [1 / 3, 2 / 3])
    part = F.when(F.col(score) >= F.lit(high), "head").when(F.col(score) >= F.lit(low), "middle").otherwise("tail")
    return scored.withColumn("part", part)


def harmful_reference(docs: DataFrame, labels: DataFrame, key: str = "doc_id") -> DataFrame:
    return docs.join(labels.filter("toxic = 1").select(key), key, "left_semi")


def drop_harmful(scored: DataFrame, q: float = 0.9) -> DataFrame:
    """Texts less likely under the harmful model than the q-quantile."""
    return quantile_cut(scored, q, keep_above=False)


def rounded(c: Column, digits: int = 6) -> Column:
    return F.round(c, digits)
