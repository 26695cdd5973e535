"""The whole quality stage and pipelines on a hand-made input."""

import random

import __spark_entry__ as entry
from gleanwork.operators import langid
from gleanwork.plans.corpus import LISTED, SITE_TERMS


def body(seed, sentences=30):
    rng = random.Random(seed)
    known = langid.own_words("fr")
    word = lambda i: known[rng.randrange(len(known))] if i % 2 else "".join(rng.choice("bcdfgklmnprstv") + rng.choice("aeiou") for _ in range(3))
    return " ".join(" ".join(word(i) for i in range(8)).capitalize() + "." for _ in range(sentences))


def test_whole_stages(spark, tmp_path):
    long = body(1, 120)
    texts = {1: long, 2: body(2), 4: long + " Fin.", 5: "Une phrase que la page redit encore et encore. " * 30, 8: body(8) + f" {SITE_TERMS[0]}.", 10: "Court.", 11: body(11)}
    rows = [(i, t, "fr", "bad" if i == 8 else "good", len(t)) for i, t in texts.items()]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    urls = {i: f"https://{LISTED[0] if i == 8 else 'host.example'}/{i}" for i in texts}
    spark.createDataFrame([(i, urls[i], f'<html lang="fr"><head><title>t</title></head><body><p>{t}</p></body></html>') for i, t in texts.items()], "page_id long, url string, html string").write.parquet(f"{tmp_path}/pages.parquet")
    queries = entry.queries()
    pages = lambda name: {r["stage"]: r["pages"] for r in queries[name](spark, str(tmp_path)).collect()}
    assert pages("w27b_quality_stage_whole") == {"raw": 7, "quality": 5}
    assert pages("w45c_funnel_whole") == {"raw": 7, "quality": 5, "dedup": 4, "hosts": 3, "clean": 3}
    found = pages("w46d_pages_pipeline_whole")
    assert {k: found[k] for k in ("quality", "dedup", "hosts", "clean")} == {"quality": 5, "dedup": 4, "hosts": 3, "clean": 3}
    assert pages("w27_quality_stage")["quality"] == 5 and pages("w27c_quality_stage_rules_only")["quality"] == 6  # rules alone keep the repetitive page
    assert pages("w46_pages_pipeline")["clean"] == 3 and list(pages("w45b_funnel_printed_setting")) == ["raw", "quality", "dedup", "hosts", "clean"]
