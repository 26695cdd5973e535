"""Statistics that come from one pass over a text: the same rows as plain recomputation, in time linear in the text."""

import math
from collections import Counter

from pyspark.sql import functions as F

from gleanwork.functions import chargrams
from gleanwork.operators import exact, langid, mixture, recipes, repetition


def grams_of(t, n):
    return [t[i : i + n] for i in range(max(1, len(t) - n + 1))]


def test_gram_counts():
    texts = ["", "a", "ab", "abab", "日本🎉日本", "ab\nab"]
    for n in (1, 2, 3, 9):
        want = Counter(g for t in texts for g in grams_of(t, n))
        assert chargrams.count_grams(texts, n) == want
    wide = ["".join(map(chr, range(0x4E00, 0x5A00)))] * 2
    assert chargrams.count_grams(wide, 6) == Counter(g for t in wide for g in grams_of(t, 6))


def test_naive_bayes(spark, monkeypatch):
    train = [(1, "Abra ba", "x"), (2, "bubu ub", "y"), (3, None, "x"), (4, "zz", None), (5, "", "y"), (6, "q", "x")]
    texts = [(1, "ABBA"), (2, "ubu🎉"), (3, None), (4, ""), (5, "q"), (6, "ΩΩ"), (7, "ab" * 150_000)]
    counts = {x: Counter(g for _, t, y in train if t is not None and y == x for g in grams_of(t.lower(), 2)) for x in "xy"}
    size = len(set(counts["x"]) | set(counts["y"]))
    want = {}
    for i, t in texts:
        known = [g for g in grams_of(t.lower(), 2) if g in counts["x"] or g in counts["y"]] if t is not None else []
        if known:
            want[i] = max((sum(math.log((counts[x][g] + 0.5) / (counts[x].total() + 0.5 * size)) for g in known), x) for x in "xy")[1]
    df, labelled = spark.createDataFrame(texts, "doc_id long, text string"), spark.createDataFrame(train, "doc_id long, text string, lang string")
    found = lambda: {r["doc_id"]: r["predicted"] for r in langid.naive_bayes(labelled, df).collect()}
    assert found() == want and 6 not in want and len(want) == 5
    monkeypatch.setattr(langid, "MODEL_GRAMS", 0)
    assert found() == want


def test_vocabulary_of_long_texts(spark):
    texts = ["ABCAB" * 60_000, "b", None, "", "日本🎉日本"]
    want = Counter(g for t in texts if t for g in grams_of(t.lower(), 2) if len(g) == 2)
    df, base = spark.createDataFrame([(t,) for t in texts], "text string"), spark.createDataFrame([("bc",)], "gram string")
    found = mixture.vocabulary_candidates(df, 100, 2, base)
    assert [(r["gram"], r["n"]) for r in found.collect()] == sorted(((g, c) for g, c in want.items() if g != "bc"), key=lambda x: (-x[1], x[0]))
    assert "Generate" not in found._jdf.queryExecution().executedPlan().toString()  # no row for each character


def test_top_ngrams_in_place(spark):
    texts = [(1, "a b  a b\na b"), (2, "a"), (3, None), (4, ""), (5, "longer word tied word longer tie")]
    found = repetition.top_ngrams(spark.createDataFrame(texts, "doc_id long, text string"), (2, 3))
    assert {(r["doc_id"], r["n"]): r["share"] for r in found.collect()} == {(1, 2): 9 / 12, (1, 3): 10 / 12, (5, 2): 11 / 32, (5, 3): 16 / 32}
    assert "Exchange" not in found._jdf.queryExecution().executedPlan().toString()


def test_roots_of_long_texts(spark):
    long = "le chat 🎉 dort. " * 20_000
    texts = [(1, long), (2, "ab"), (3, ""), (4, "0123456789" * 3 + "x"), (5, "the a b c d e the a b c d e")]
    found = {r["doc_id"]: r for r in recipes.roots(spark.createDataFrame(texts, "doc_id long, text string")).collect()}
    tens = lambda t: [t[i : i + 10] for i in range(0, max(len(t) - 9, 1), 10)]
    for i, t in texts:
        w = t.split()
        five = [tuple(w[k : k + 5]) for k in range(max(len(w) - 4, 0))]
        assert math.isclose(found[i]["char_repetition"], 1 - len(set(tens(t))) / len(tens(t)), abs_tol=1e-12)
        assert math.isclose(found[i]["word_repetition"], 1 - len(set(five)) / len(five) if five else 0.0, abs_tol=1e-12)
        assert found[i]["few_words"] == (len(w) < 50)
    whole = spark.createDataFrame(texts, "doc_id long, text string").select("doc_id", recipes.char_repetition(F.col("text")).alias("c"), recipes.word_repetition(F.col("text")).alias("w"))
    assert all(math.isclose(r["c"], found[r["doc_id"]]["char_repetition"], abs_tol=1e-12) and math.isclose(r["w"], found[r["doc_id"]]["word_repetition"], abs_tol=1e-12) for r in whole.collect())
    assert "substring(" not in whole._jdf.queryExecution().optimizedPlan().toString()  # which would start anew for each chunk


def test_spans_of_repeated_sentences(spark):
    texts = [(1, "A. B. C. D."), (2, "x. A. B. C. y."), (3, "A. B. C. A. B. C."), (4, None), (5, ""), (6, "B. C. D."), (7, "only. two.")]
    seen, want = set(), {}
    for i, t in texts:
        s = [x + "." for x in (t or "").replace(" ", "").split(".") if x]
        gone = set()
        for p in range(len(s) - 2):
            gone |= set(range(p, p + 3)) if tuple(s[p : p + 3]) in seen else set()
            seen.add(tuple(s[p : p + 3]))
        want[i] = (len(s) if t is not None else None, len(gone))
    found = exact.dedup_spans(spark.createDataFrame(texts, "doc_id long, text string"))
    assert {r["doc_id"]: (r["sentences"], r["dropped"]) for r in found.collect()} == want
    plan = found._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("Join") == 1  # windows are not joined to their copies
