"""Detectors read whole texts."""

import numpy as np
from pyspark.sql import functions as F

from gleanwork.operators import langid


def test_language_after_a_long_start(spark):
    rows = [(i, ("xyzzy quux " if i % 2 else "aloha mele ") * 30, "x" if i % 2 else "a") for i in range(40)]
    train = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    mixed = spark.createDataFrame([(1, "aloha mele " * 250 + "xyzzy quux " * 2500), (2, "xyzzy quux " * 1000 + "aloha mele " * 9000), (3, None), (4, "")], "doc_id long, text string")
    bayes = {r["doc_id"]: r["predicted"] for r in langid.naive_bayes(train, mixed).collect()}
    assert bayes[1] == "x" and bayes[2] == "a"
    # The corpus counts cover the end of each text as well.
    late = spark.createDataFrame([(1, "n " * 2000 + "xyzzy quux " * 300, "x"), (2, "n " * 2000 + "aloha mele " * 300, "a")], "doc_id long, text string, lang string")
    assert {r["doc_id"]: r["predicted"] for r in langid.naive_bayes(late, train.select("doc_id", "text").filter("doc_id < 2")).collect()} == {0: "a", 1: "x"}
    trained = langid.LangModel(langid.train(train, F.col("lang") == "x").weights, 0.0)
    found = {r["doc_id"]: r["is_target"] for r in langid.apply(mixed, trained).collect()}
    assert found == {1: True, 2: False, 3: False, 4: False}
    w = np.zeros((1 << langid.BITS) + 1)
    short, long = langid.ngram_counts("b" * 20_000), langid.ngram_counts("b" * 20_000 + "z" * 9_000)
    assert set(long[0]) - set(short[0]) and abs((long[1] ** 2).sum() - 1) < 1e-9 and langid.LangModel(w, 0.5).score("b") == 0.0
