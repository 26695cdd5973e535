"""Nothing of the input is left out: bigrams beyond the broadcast ones, addresses without an at sign, rows that share an id or have none."""

import math
from collections import Counter

import corpus_pipeline
from gleanwork.llm import lmscore, pii


def brute_losses(texts, good, size):
    """Mean losses under both models with every bigram, from plain counters."""
    split = {i: t.encode().split() for i, t in texts.items()}
    singles, pairs = [Counter(), Counter()], [Counter(), Counter()]
    for i, w in split.items():
        for m in (0, 1) if i in good else (1,):
            singles[m].update(w)
            pairs[m].update(zip(w, w[1:]))
    out = {}
    for i, w in split.items():
        losses = []
        for m in (0, 1):
            one = lambda x: (singles[m][x] + lmscore.ALPHA) / (sum(singles[m].values()) + lmscore.ALPHA * size)  # noqa: B023, E731
            logs = [math.log(one(w[0]))] + [math.log(lmscore.LAMBDA * pairs[m][a, b] / max(1, singles[m][a]) + (1 - lmscore.LAMBDA) * one(b)) for a, b in zip(w, w[1:])]
            losses.append(-sum(logs) / len(w))
        out[i] = losses
    return out


def test_language_model_uses_every_bigram(spark):
    texts = {i: " ".join(f"w{(i * k * k + k) % 23}" for k in range(5 + i % 7)) for i in range(40)}
    df = spark.createDataFrame([*texts.items(), (None, "w1 w2 w3"), (99, None)], "doc_id long, text string")
    good = {i for i in texts if i % 3 == 0}
    target = df.filter("doc_id % 3 = 0").select("doc_id")
    want = brute_losses({**texts, -1: "w1 w2 w3"}, good, len({w for t in texts.values() for w in t.split()}) + 1)
    for bigrams in (1 << 20, 20, 0):  # all broadcast, some, none
        rows = lmscore.score(df, *lmscore.train(df, target, bigrams=bigrams)).collect()
        assert len(rows) == 42
        for r in rows:
            if r["doc_id"] == 99:
                assert (r["n_tokens"], r["score"]) == (0, 0.0)
                continue
            t, b = want[-1 if r["doc_id"] is None else r["doc_id"]]
            assert math.isclose(r["target_loss"], t, abs_tol=1e-9) and math.isclose(r["background_loss"], b, abs_tol=1e-9) and math.isclose(r["score"], t - b, abs_tol=1e-9)
    # Documents the models were not fitted on, whose bigrams no table has.
    new = spark.createDataFrame([(1, "w1 w22 w1 zz")], "doc_id long, text string")
    one, two = (lmscore.score(new, *lmscore.train(df, target, bigrams=n)).first() for n in (1 << 20, 0))
    assert all(math.isclose(one[c], two[c], abs_tol=1e-9) for c in ("target_loss", "background_loss", "score"))


def test_addresses_without_digit_or_at_sign(spark):
    texts = ["write to jane.doe (at) host.org", "x " * 400 + "contact: bob.smith[at]example.com, or call" + " y" * 400, "write to the host"]
    rows = {r["doc_id"]: r for r in pii.find_pii(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), pii.default_tagger()).collect()}
    found = [[(s["kind"], t[s["start"] : s["end"]]) for s in rows[i]["spans"]] for i, t in enumerate(texts)]
    assert found == [[("email", "jane.doe (at) host.org")], [("email", "bob.smith[at]example.com")], []]
    # A stretch cuts no token, and stretches do not overlap.
    text = "q " * 50 + "u" * 90 + "[at]" + "h" * 90 + ".org " + "q " * 50 + "k" * 70 + "123" + "k" * 70
    where = pii.stretches(text)
    assert [text[a:b].strip(" q") for a, b in where] == ["u" * 90 + "[at]" + "h" * 90 + ".org", "k" * 70 + "123" + "k" * 70]


def words_of(seed):
    return " ".join(f"w{(seed * 7919 + k * k * (seed + 3)) % 997}" for k in range(60))


def test_rows_of_one_id_are_decided_one_by_one(spark, data):
    stages = dict(corpus_pipeline.STAGES)
    a, b, c, d, e = (words_of(i) for i in range(5))
    rows = [(None, a, "x"), (None, b, "x"), (None, b, "x"), (1, c, "x"), (None, c, "x"), (7, d, "x"), (7, e, "x"), (7, e, None), (8, e, "x"), (2, None, None), (None, None, "x")]
    kept = stages["near_dedup"](spark, spark.createDataFrame(rows, "doc_id long, text string, source string"), data).collect()
    assert sorted((r["doc_id"] or 0, r["text"] or "") for r in kept) == sorted([(0, a), (0, b), (1, c), (7, d), (7, e), (2, "")])
    # Null columns tell rows apart.
    assert corpus_pipeline.identified(spark.createDataFrame([(1, "y", None), (1, None, "y")], "doc_id long, text string, source string")).select("row").distinct().count() == 2
    passage = spark.read.parquet(f"{data}/benchmark.parquet").filter("length(text) > 100").first()["text"]
    rows = [(None, passage), (None, a), (None, a), (5, passage), (5, b), (6, None)]
    clean = stages["decontamination"](spark, spark.createDataFrame(rows, "doc_id long, text string"), data).collect()
    assert sorted((r["doc_id"] or 0, r["text"] or "") for r in clean) == sorted([(0, a), (0, a), (5, b), (6, "")])
