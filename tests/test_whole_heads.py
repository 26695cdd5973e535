"""The gate looks beyond a long head."""

from pyspark.sql import functions as F

from gleanwork.operators import gate


def test_long_heads(spark):
    note, style = "<!-- " + "c" * 5000 + " -->", "<style>" + "s" * 70_000 + "</style>"
    pages = [f'{note}<html lang="FR"><title>a</title>', f'<html lang="de">{style}<title>late &amp; long</title>', '<html lang="de"><title>b</title>' + note + '<html lang="fr">', "no tags", None]
    df = spark.createDataFrame(list(enumerate(pages)), "page_id long, html string")
    got = {r[0]: (r[1], r[2]) for r in df.select("page_id", gate.declared_language(F.col("html")), gate.title(F.col("html"))).collect()}
    assert got == {0: ("fr", "a"), 1: ("de", "late & long"), 2: ("de", "b"), 3: ("", ""), 4: (None, None)}
