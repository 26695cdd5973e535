"""Fingerprints of other recipes: SimHash over word 6-grams with block equi-joins, and a locality digest."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F, types as T

from ..functions import textstats as ts

BITS, BLOCKS = 60, 4


def simhash(df: DataFrame, n: int = 6, key: str = "doc_id", text: str = "text", bits: int = BITS) -> DataFrame:
    """(key, fp): the sign of each bit's sum over the hashes of word n-grams; texts with fewer words have no row."""
    grams = df.select(key, F.explode(ts.ngrams(ts.tokens(F.col(text)), n)).alias("g")).select(key, ts.md5_long(F.col("g")).alias("h"))
    sums = grams.groupBy(key).agg(*[F.sum(F.shiftright("h", k).bitwiseAND(F.lit(1)) * 2 - 1).alias(f"b{k}") for k in range(bits)])
    fp = F.lit(0).cast("long")
    for k in range(bits):
        fp = fp + F.when(F.col(f"b{k}") > 0, F.lit(1 << k)).otherwise(F.lit(0))
    return sums.select(key, fp.alias("fp"))


def simhash_pairs(fps: DataFrame, most: int = 3, key: str = "doc_id", bits: int = BITS, blocks: int = BLOCKS) -> DataFrame:
    """(a, b, distance): pairs within most bits. most + 1 blocks of bits: such a pair agrees on one, so blocks are joined.

    Equal fingerprints are one class: pairs are listed between the least keys of classes, and each other member beside its
    class's least key, with distance 0.
    """
    if blocks <= most:
        raise ValueError("more blocks than differing bits are needed")
    width = bits // blocks
    cut = F.array(*[F.shiftright("fp", i * width).bitwiseAND(F.lit((1 << width) - 1)) for i in range(blocks)])
    classes = fps.select("fp").distinct()
    rows = classes.select("fp", F.posexplode(cut).alias("block", "value"))
    near = rows.withColumnRenamed("fp", "x").join(rows.withColumnRenamed("fp", "y"), ["block", "value"]).filter("x < y")
    near = near.select("x", "y", F.bit_count(F.col("x").bitwiseXOR(F.col("y"))).alias("distance")).filter(F.col("distance") <= most).distinct()
    reps = fps.groupBy("fp").agg(F.min(key).alias("rep"))
    left, right = reps.select(F.col("rep").alias("p"), F.col("fp").alias("x")), reps.select(F.col("rep").alias("q"), F.col("fp").alias("y"))
    pairs = near.join(left, "x").join(right, "y").select(F.least("p", "q").alias("a"), F.greatest("p", "q").alias("b"), F.col("distance").cast("int").alias("distance"))
    members = fps.join(reps, "fp").filter(F.col(key) > F.col("rep")).select(F.col("rep").alias("a"), F.col(key).alias("b"), F.lit(0).alias("distance"))
    return pairs.union(members)


def locality_digest(text: str | None) -> bytes | None:
    """Header (checksum, length class) and 128 two-bit quartile codes of hashed byte triplets in a window of five."""
    data = np.frombuffer((text or "").encode("utf-8", "surrogatepass"), np.uint8).astype(np.int64)
    if len(data) < 50:
        return None
    counts = np.zeros(128, np.int64)
    window = [data[4 - k : len(data) - k] for k in range(5)]
    for salt, (i, j, k) in enumerate(((0, 1, 2), (0, 1, 3), (0, 2, 3), (0, 2, 4), (0, 1, 4), (0, 3, 4)), 2):
        h = (window[i] * 251 + window[j] * 65_521 + window[k] * 16_777_213 + salt * 97) % 2_147_483_647
        counts += np.bincount((h ^ (h >> 11)) & 127, minlength=128)
    q = np.quantile(counts, [0.25, 0.5, 0.75])
    codes = (counts[:, None] > q[None, :]).sum(axis=1).astype(np.uint8)
    head = [int(data.sum() & 255), int(min(255, np.log(len(data)) / np.log(1.1)))]
    return bytes(head) + bytes(codes[0::4] | codes[1::4] << 2 | codes[2::4] << 4 | codes[3::4] << 6)


def digest_distance(a: bytes, b: bytes) -> int:
    """Sum of code differences (3 counts as 6), and of the length classes."""
    x, y = (np.frombuffer(v[2:], np.uint8) for v in (a, b))
    parts = [np.abs((x >> s & 3).astype(int) - (y >> s & 3).astype(int)) for s in (0, 2, 4, 6)]
    return int(sum(np.where(p == 3, 6, p).sum() for p in parts)) + abs(a[1] - b[1]) + (a[0] != b[0])


def digests(df: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, digest binary); texts under 50 bytes have null."""
    schema = T.StructType([df.schema[key], T.StructField("digest", T.BinaryType())])

    def run(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([locality_digest(t) for t in b.column(1).to_pylist()], pa.binary())], names=[key, "digest"])

    return df.select(key, F.col(text).cast("string")).mapInArrow(run, schema)


def digest_pairs(found: DataFrame, most: int = 30, key: str = "doc_id", bands: int = 8) -> DataFrame:
    """(a, b, distance) of pairs that share one of the digest's bands of codes, within the distance. Approximate by design."""
    width = 32 // bands
    rows = found.filter("digest IS NOT NULL").select(key, "digest", F.explode(F.array(*[F.struct(F.lit(k).alias("band"), F.substring(F.col("digest"), 3 + k * width, width).alias("v")) for k in range(bands)])).alias("e")).select(key, "digest", "e.band", "e.v")
    pairs = rows.select(F.col(key).alias("a"), F.col("digest").alias("x"), "band", "v").join(rows.select(F.col(key).alias("b"), F.col("digest").alias("y"), "band", "v"), ["band", "v"]).filter("a < b").select("a", "b", "x", "y").distinct()

    @F.pandas_udf(T.IntegerType())
    def distance(x, y):
        import pandas as pd

        return pd.Series([digest_distance(p, q) for p, q in zip(x, y)], dtype="int32")

    return pairs.select("a", "b", distance("x", "y").alias("distance")).filter(F.col("distance") <= most)


def cosine(x: Column, y: Column) -> Column:
    dot = F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, v: s + v)
    norm = lambda v: F.sqrt(F.aggregate(v, F.lit(0.0), lambda s, e: s + e.cast("double") * e.cast("double")))
    return dot / (norm(x) * norm(y))


def close_pairs(df: DataFrame, least: float, key: str = "vec_id", vector: str = "embedding", block: int = 2048) -> DataFrame:
    """(a, b, cosine), a < b, of all pairs of cosine least or more. Exact: every block of vectors meets every other.

    The work grows with the square of the vectors, and each vector is sent once for each block. Null and zero vectors have no pair.
    """
    blocks = max(1, -(-df.count() // block))
    mine = F.pmod(F.xxhash64(key), F.lit(blocks))
    rows = df.filter(F.col(vector).isNotNull() & F.col(key).isNotNull()).select(F.col(key).alias("id"), F.col(vector).cast("array<double>").alias("v"), mine.alias("at"))
    sent = rows.select("id", "v", "at", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("other"))
    sent = sent.select("id", "v", "at", F.least("at", "other").alias("i"), F.greatest("at", "other").alias("j"))
    kind = df.schema[key].dataType
    schema = T.StructType([T.StructField("a", kind), T.StructField("b", kind), T.StructField("cosine", T.DoubleType())])

    def solve(t: pa.Table) -> pa.Table:
        i, j = t.column("i")[0].as_py(), t.column("j")[0].as_py()
        at, ids = t.column("at").to_numpy(), t.column("id").to_numpy()
        v = np.array(t.column("v").to_pylist(), float)
        norm = np.sqrt((v * v).sum(axis=1))
        ids, at, v = ids[norm > 0], at[norm > 0], v[norm > 0] / norm[norm > 0, None]
        left, right = np.flatnonzero(at == i), np.flatnonzero(at == j)
        c = v[left] @ v[right].T
        x, y = np.nonzero(c >= least)
        a, b, c = ids[left[x]], ids[right[y]], c[x, y]
        # Inside a block each pair is met from both sides.
        keep = a < b if i == j else a != b
        return pa.table({"a": np.minimum(a, b)[keep], "b": np.maximum(a, b)[keep], "cosine": c[keep]})

    return sent.groupBy("i", "j").applyInArrow(solve, schema)


def search(df: DataFrame, queries: DataFrame, least: float, key: str = "vec_id", vector: str = "embedding", block: int = 2048) -> DataFrame:
    """(a, b, cosine): vectors b of df within cosine least of query a, another key. Exact, by blocks of queries and of rows.

    A block of queries meets a block of rows in one matrix product; the work is queries times rows. Null and zero vectors have no
    partner.
    """
    def dealt(d: DataFrame, mine: str, others: str, n: int, m: int, query: bool) -> DataFrame:
        d = d.filter(F.col(vector).isNotNull() & F.col(key).isNotNull())
        every = F.explode(F.sequence(F.lit(0).cast("long"), F.lit(m - 1).cast("long"))).alias(others)
        return d.select(F.col(key).alias("id"), F.col(vector).cast("array<double>").alias("v"), F.lit(query).alias("q"), F.pmod(F.xxhash64(key), F.lit(n)).alias(mine), every)

    n, m = (max(1, -(-d.count() // block)) for d in (queries, df))
    sent = dealt(queries, "i", "j", n, m, True).unionByName(dealt(df, "j", "i", m, n, False))
    kind = df.schema[key].dataType
    schema = T.StructType([T.StructField("a", kind), T.StructField("b", kind), T.StructField("cosine", T.DoubleType())])

    def solve(t: pa.Table) -> pa.Table:
        ids, asks = t.column("id").to_numpy(), t.column("q").to_numpy()
        v = np.array(t.column("v").to_pylist(), float)
        norm = np.sqrt((v * v).sum(axis=1))
        v = v / np.maximum(norm, 1e-300)[:, None]
        left, right = np.flatnonzero(asks & (norm > 0)), np.flatnonzero(~asks & (norm > 0))
        c = v[left] @ v[right].T
        x, y = np.nonzero(c >= least)
        a, b, c = ids[left[x]], ids[right[y]], c[x, y]
        return pa.table({"a": a[a != b], "b": b[a != b], "cosine": c[a != b]})

    return sent.groupBy("i", "j").applyInArrow(solve, schema)
