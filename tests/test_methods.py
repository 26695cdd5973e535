"""Units: thresholds on hand-written strings, detection curve, survivor rules, published tables, plans, robustness."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from gleanwork.functions import textstats as ts
from gleanwork.operators import dedup, exact, gate, hosts, htmltext, langid, metrics, minhash, normalize, quality, repetition, tables
from gleanwork.profiles import ENCYCLOPEDIA_SUFFIX, JA, LATIN, kana_map
from gleanwork.sources import archive
from gleanwork.streaming import ingest


def flags(spark, rule, texts):
    df = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "i int, t string")
    v = quality.rule_values(F.col("t"))[rule]
    return [r["f"] for r in df.select("i", quality.rule_flags({rule: v}, JA.thresholds)[rule].alias("f")).orderBy("i").collect()]


def sentence(n):
    return "あ" * (n - 1) + "。"


@pytest.mark.parametrize(
    "rule, texts, want",
    [
        ("length", ["あ" * 399, "あ" * 400], [True, False]),
        ("hiragana", ["あ" + "漢" * 5, "あ" + "漢" * 4, ""], [True, False, True]),
        ("katakana", ["アー" + "あ", "アー" + "ああ", "ｱｱ" + "あ"], [True, False, True]),
        ("script", ["あ" + "a" * 2, "あ漢" + "aa", "、。" + "aaa"], [True, False, True]),
        ("mean_sentence", [sentence(19), sentence(20), sentence(90), sentence(91)], [True, False, False, True]),
        ("longest_sentence", [sentence(200), sentence(201)], [False, True]),
        ("ellipsis", ["あ。" * 4 + "い…", "あ。" * 3 + "い…\nう…", "あ。\nい・・・\n", "あ。い‥」"], [False, True, True, True]),
    ],
)
def test_rules_at_their_thresholds(spark, rule, texts, want):
    assert flags(spark, rule, texts) == want


def test_kana_map_is_one_to_one():
    a, b = kana_map()
    assert len(a) == len(b) == len(set(a)) == len(set(b))


def test_harmful_share_counts_overlaps_once(spark):
    df = spark.createDataFrame([("ababa xx",), ("",), ("AB",)], "t string")
    assert [round(r[0], 4) for r in df.select(ts.term_share(F.col("t"), ["ab", "aba"])).collect()] == [0.375, 0.0, 1.0]


def test_declared_language_forms(spark):
    rows = ['<html lang="ja">', "<html lang='ja-JP'>", "<HTML LANG=JA>", '<html class="x" lang="ja">', "<html>", '<body lang="ja">', None]
    df = spark.createDataFrame([(i, h) for i, h in enumerate(rows)], "i int, h string")
    assert [r[0] for r in df.orderBy("i").select(gate.declared_language(F.col("h"))).collect()] == ["ja", "ja", "ja", "ja", "", "", None]


def test_gate_modes(spark, data):
    pages = gate.gate_view(spark.read.parquet(f"{data}/pages.parquet"))
    ids = {m: {r[0] for r in gate.rapid_gate(pages, "fr", m).select("page_id").collect()} for m in ("either", "declared", "title", "off")}
    assert ids["either"] == ids["declared"] | ids["title"] and ids["either"] <= ids["off"] and len(ids["off"]) == 50


def test_published_f1():
    assert round(metrics.f1_of(0.888, 0.967), 3) == 0.926


def test_detection_probability(spark):
    df = spark.range(1).select(minhash.detection_probability(F.lit(0.9), F.lit(20), F.lit(40)).alias("a"), minhash.detection_probability(F.lit(0.9), F.lit(20), F.lit(20)).alias("b"))
    assert [round(x, 5) for x in df.first()] == [0.99440, 0.92517]


@pytest.mark.parametrize(
    "edges, pairwise, component, greedy",
    [([(1, 2)], {2, 3}, {2, 3}, {2, 3}), ([(1, 2), (2, 3)], {3}, {3}, {1, 3}), ([(1, 2), (1, 3)], {2, 3}, {3}, {2, 3}), ([(1, 2), (2, 3), (1, 3)], {3}, {3}, {3})],
)
def test_survivors_of_small_graphs(spark, edges, pairwise, component, greedy):
    rank = spark.createDataFrame([(i, 0) for i in (1, 2, 3)], "doc_id long, ts int")
    e = spark.createDataFrame(edges, "a long, b long")
    rows = [(0, str(i), x) for i, pair in enumerate(edges) for x in pair]
    keys = spark.createDataFrame(rows, "band int, bucket string, doc_id long").join(rank, "doc_id")
    gone = lambda df: {1, 2, 3} - {r[0] for r in df.collect()}
    assert gone(dedup.keep_newest(keys, ["ts"])) == pairwise
    assert gone(dedup.keep_component(e, rank, ["ts"])) == component
    assert gone(dedup.keep_greedy(e, rank, ["ts"])) == greedy


def test_signature_recall(spark, data):
    docs = spark.read.parquet(f"{data}/documents.parquet")
    truth = {(r["a"], r["b"]) for r in minhash.exact_pairs(docs, 0.9).collect()}
    found = {(r["a"], r["b"]) for r in minhash.candidate_pairs(minhash.band_keys(minhash.signatures(docs))).collect()}
    assert len(truth) == 20 and len(truth & found) >= 19


def test_one_permutation_estimates_jaccard():
    rng = np.random.default_rng(0)
    x = rng.choice(minhash.PRIME, 2000, replace=False)
    y = np.r_[x[:1600], rng.choice(minhash.PRIME, 400, replace=False)]
    true = len(np.intersect1d(x, y)) / len(np.union1d(x, y))
    same = (minhash.one_permutation(np.unique(x), 800) == minhash.one_permutation(np.unique(y), 800)).mean()
    assert abs(same - true) < 0.08


def test_cleaning_is_idempotent_and_keeps_pages(spark):
    rows = ["あ,い,う.え 3.14 a,b", "本文。\nAll rights reserved", "Copyright 2023", "", "x\n© y\nshare this\n"]
    df = spark.createDataFrame([(i, t) for i, t in enumerate(rows)], "i int, text string")
    once = normalize.run(df).orderBy("i")
    out = [r["text"] for r in once.collect()]
    assert out[:3] == ["あ、い、う。え 3.14 a,b", "本文。", "Copyright 2023"] and out[4] == "x"
    assert [r["text"] for r in normalize.run(once).orderBy("i").collect()] == out


def test_globs(spark):
    df = spark.createDataFrame([("a" + ENCYCLOPEDIA_SUFFIX, 1), ("x.example.net", 2), ("example.net", 3)], "h string, i int")
    got = [r[0] for r in df.orderBy("i").select(hosts.glob(F.col("h"), "*.example.net")).collect()]
    assert got == [False, True, False]


def test_table_of_scores(spark):
    s = tables.scores(spark)
    assert all(abs(r["mean"] - r["printed"]) <= 0.00501 for r in tables.averages(s).collect())
    own = [r["gain"] for r in tables.gains(s).filter("task = 'Avg' AND model LIKE '%+corpus'").collect()]
    assert (min(own), max(own)) == (6.98, 8.07)


def test_published_funnel_ratios(spark):
    df = spark.createDataFrame([(i, *r) for i, r in enumerate(tables.PUBLISHED_FUNNEL)], "ix int, stage string, pages long, chars long")
    got = [(round(r["page_ratio"] or 0, 4), round(r["char_total"], 4)) for r in metrics.funnel_ratios(df).orderBy("ix").collect()]
    assert got == [(0, 1.0), (0.2406, 0.3265), (0.2875, 0.0959), (0.9332, 0.0849), (1.0, 0.0847)]


def test_robust_rows(spark):
    rows = [(1, None), (2, ""), (3, "x"), (4, " \n\t"), (5, "😀" * 50), (6, "a" * 300_000), (7, "x")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    a = quality.annotate(df, LATIN["en"])
    assert a.count() == 7 and a.filter("array_contains(reasons, 'length')").count() == 6
    assert repetition.features(df).count() == 7
    assert minhash.signatures(df, 4, 8).count() == 5
    assert exact.dedup_lines(df).count() == 5
    assert langid.apply(df, langid.LangModel(np.zeros((1 << langid.BITS) + 1), 0.5)).filter("is_target").count() == 0
    empty = df.limit(0)
    assert quality.apply(empty, LATIN["en"]).count() == 0 and dedup.run(empty.withColumn("crawl_ts", F.current_timestamp()), 2, 2).count() == 0


def test_malformed_html():
    for h in (None, "", "<p>a<p>b", "<div><b>x</div>y", "<html lang=en<p>z", "text only"):
        htmltext.by_density(h), htmltext.by_stopwords(h)
    assert htmltext.by_density("<nav>n</nav><p>a <b>b</b><p>c<footer>f") == "a b\nc"


def test_archive_round_trip(spark, tmp_path):
    good = [archive.write_record(f"http://h/{i}", f"<p>é{i}", i, "2023-05-27T22:35:15Z", i % 3) for i in range(5)]
    (tmp_path / "a.warc.gz").write_bytes(b"".join(good) + archive.write_record("x", "y", 9, "2023-05-27T22:35:15Z", 1, "request"))
    (tmp_path / "b.warc.gz").write_bytes(good[0] + archive.write_record("x", "y", 9, "no date", 1) + b"\x1f\x8b\x08broken")
    rows = archive.read_archive(spark, str(tmp_path / "*.gz")).collect()
    assert sorted(r["html"] for r in rows if r["html"]) == sorted([f"<p>é{i}" for i in range(5)] + ["<p>é0"])
    assert sum(r["_corrupt"] is not None for r in rows) == 2
    spark.dataSource.register(archive.ArchiveSource)
    assert spark.read.format("page_archive").load(str(tmp_path / "a*.gz")).count() == 5


def test_increment_evicts(spark):
    cols = "doc_id long, band int, bucket string"
    store, _ = ingest.dedup_increment(spark.createDataFrame([(1, 0, "x"), (2, 1, "y")], cols), None, [])
    merged, evicted = ingest.dedup_increment(spark.createDataFrame([(5, 0, "x")], cols), store, [])
    assert {tuple(r) for r in merged.select("doc_id", "bucket").collect()} == {(5, "x"), (2, "y")}
    assert [r[0] for r in evicted.collect()] == [1]


def plan_of(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_plans(spark, data):
    docs = spark.read.parquet(f"{data}/documents.parquet")
    ix, when = dedup.recency(F.col("doc_id"))
    losers = dedup.keep_newest(minhash.band_keys(minhash.signatures(docs, 4, 8), 4, 8), [])
    assert "Cartesian" not in plan_of(losers) and "NestedLoop" not in plan_of(losers)
    for line in plan_of(losers).splitlines():
        assert "Exchange" not in line or "text" not in line
    assert "PushedFilters: [IsNotNull(n_chars), LessThan(n_chars,400)]" in plan_of(docs.filter("n_chars < 400").select("doc_id"))
    assert "Exchange" not in plan_of(quality.annotate(docs, LATIN["en"]))
