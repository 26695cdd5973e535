"""Pairs of embeddings: none is left out."""

import itertools
import math

import __spark_entry__ as entry
from gleanwork.operators import digests


def test_all_close_pairs(spark, data):
    rows = {r["vec_id"]: r["embedding"] for r in spark.read.parquet(f"{data}/embeddings.parquet").limit(300).collect()}
    rows |= {10**6 + 1: rows[min(rows)], 10**6 + 3: [2 * x for x in rows[min(rows)]]}
    cos = lambda x, y: sum(p * q for p, q in zip(x, y)) / math.sqrt(sum(p * p for p in x) * sum(q * q for q in y))
    least = 0.3
    want = {(a, b) for a, b in itertools.combinations(sorted(rows), 2) if cos(rows[a], rows[b]) >= least}
    df = spark.createDataFrame([*rows.items(), (5 * 10**6, None), (5 * 10**6 + 1, [0.0] * len(rows[min(rows)]))], "vec_id long, embedding array<float>")
    for block in (2048, 50):
        got = [(r["a"], r["b"]) for r in digests.close_pairs(df, least, block=block).collect()]
        assert len(got) == len(set(got)) and set(got) == want and (10**6 + 1, 10**6 + 3) in want


def test_pairs_across_labels_and_ids(spark, tmp_path):
    rows = [(11, [1.0, 0.0], 1), (12, [1.0, 0.1], 2), (13, [0.0, 1.0], 1), (200, [0.1, 1.0], 2), (300, [0.0, 0.0], 2), (400, None, 2)]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").write.parquet(f"{tmp_path}/embeddings.parquet")
    run = lambda name: {(r["a"], r["b"]) for r in entry.queries()[name](spark, str(tmp_path)).collect()}
    assert run("w76_embedding_near_dup") == {(200, 13)} and run("w76b_embedding_near_dup_whole") == {(11, 12), (13, 200)}
    df = spark.read.parquet(f"{tmp_path}/embeddings.parquet")
    for block in (1, 2, 100):
        assert {(r["a"], r["b"]) for r in digests.search(df, df, 0.9, block=block).collect()} == {(11, 12), (12, 11), (13, 200), (200, 13)}
