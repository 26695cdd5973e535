"""SimHash near-duplicates: exact pairs within a Hamming reach, found by vantage-point trees over shards.

1. One pass over the texts gives 64-bit fingerprints (text is not read again).
2. Equal fingerprints become one class, so copies never meet each other.
3. A router (the top of a vantage-point tree, from a bounded sample of classes) gives each class a home shard and sends it
   as a query to every shard whose region its reach overlaps; a shard builds its own tree and links all its pairs.
4. Links between classes are joined to components; members take the least doc_id of their component.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, functions as F, types as T

from .common import map_text, materialise, table, temporary
from .components import connected_components
from .vptree import Router, link

REACH = 2
SHINGLE = 3
#: Least number of shards, classes in a shard beyond that, and classes in the sample that shapes the router.
MIN_SHARDS, SHARD_CLASSES, SAMPLE = 64, 1 << 18, 1 << 14
#: Queries, about, that one task asks of a shard; a shard that is asked more is copied to several tasks.
TASK_QUERIES = 1 << 20
_UPPER = {c: c + 32 for c in range(65, 91)}
_SPACE = dict.fromkeys([9, 10, 11, 12, 13], 32)
_FOLD = bytes(c + 32 if 65 <= c <= 90 else 32 if 9 <= c <= 13 else c for c in range(256))


def fingerprint(text: str | None, width: int = SHINGLE) -> int:
    """Signed 64-bit SimHash of word shingles (repeats count); no words give 0."""
    found = text.encode("utf-8", "surrogatepass").translate(_FOLD).split(b" ") if text else []
    found = [w for w in found if w]
    if not found:
        return 0
    joined = b" ".join(found)
    if len(found) <= width:
        h = np.array([xxhash.xxh64_intdigest(joined, 42)], np.uint64)
    else:
        ends = np.cumsum(np.fromiter(map(len, found), np.int64, len(found)) + 1) - 1
        starts = np.r_[0, ends[:-1] + 1]
        digest = xxhash.xxh64_intdigest
        h = np.fromiter([digest(joined[a:b], 42) for a, b in zip(starts[: 1 - width].tolist(), ends[width - 1 :].tolist())], np.uint64, len(found) - width + 1)
    ones = np.zeros(64, np.int64)
    for i in range(0, len(h), 1 << 15):
        ones += np.unpackbits(h[i : i + (1 << 15)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    bits = (2 * ones > len(h)).astype(np.uint8)
    return int(np.packbits(bits, bitorder="little").view(np.int64)[0])


def fingerprints(docs: DataFrame, key: str = "doc_id", text: str = "text", width: int = SHINGLE, row: str | None = None) -> DataFrame:
    """(key, row where asked for, fp long) for each row; null and empty texts have fingerprint 0."""
    named = {"key": key, "row": row} if row else {"key": key}
    schema = T.StructType([*(T.StructField(name, docs.schema[c].dataType) for name, c in named.items()), T.StructField("fp", T.LongType())])

    def work(blocks):
        for carried, texts in blocks:
            yield [*carried, pa.array([fingerprint(t, width) for t in texts], pa.int64())]

    return map_text(docs.select(*(docs[c].alias(name) for name, c in named.items()), docs[text].alias("text")), list(named), "text", schema, work)


def class_links(classes: DataFrame, reach: int = REACH, min_shards: int = MIN_SHARDS, shard_classes: int = SHARD_CLASSES, sample: int = SAMPLE, task_queries: int = TASK_QUERIES) -> DataFrame:
    """classes(fp), distinct -> (a, b): for each component within a shard, its members and its least member.

    A shard's own classes go to each of its tasks, which share the queries, so that a task stays bounded when queries go to many
    shards.
    """
    spark = classes.sparkSession
    n = classes.count()
    depth = max(1, math.ceil(math.log2(max(min_shards, n / shard_classes))))
    # At least 16 sampled classes for each shard; a router node is 16 bytes.
    picked = classes.select("fp").orderBy(F.xxhash64("fp"), "fp").limit(max(sample, 16 << depth)).toArrow().column("fp").to_numpy()
    sampled = picked.view(np.uint64)
    router = Router(sampled, depth)
    asked = len(router.route(sampled, reach)[0]) / max(1, len(sampled)) * n / (1 << depth)
    tasks, router = max(1, math.ceil(asked / task_queries)), spark.sparkContext.broadcast(router)

    def send(batches):
        for b in batches:
            fp = b.column(0).to_numpy(zero_copy_only=False)
            for i in range(0, len(fp), 1 << 16):
                part = fp[i : i + (1 << 16)]
                row, leaf, home = router.value.route(part.view(np.uint64), reach)
                mine = (part.view(np.uint64)[row] * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(40)).astype(np.int64) % tasks
                for t in range(tasks):
                    asks = mine == t
                    some = asks | home
                    yield pa.RecordBatch.from_arrays([pa.array(leaf[some]), pa.array(np.full(int(some.sum()), t)), pa.array(part[row[some]]), pa.array(home[some]), pa.array(asks[some])], names=["leaf", "task", "fp", "home", "asks"])

    def solve(t: pa.Table) -> pa.Table:
        fp, home, asks = (t.column(c).to_numpy() for c in ("fp", "home", "asks"))
        points, queries = np.unique(fp[home]).view(np.uint64), np.unique(fp[asks]).view(np.uint64)
        labels = link(points, queries, reach)
        values = np.concatenate([points, queries]).view(np.int64)
        root = np.full(len(values), np.iinfo(np.int64).max)
        np.minimum.at(root, labels, values)
        b = root[labels]
        keep = values != b
        return pa.table({"a": values[keep], "b": b[keep]})

    sent = classes.select("fp").mapInArrow(send, "leaf long, task long, fp long, home boolean, asks boolean")
    return sent.groupBy("leaf", "task").applyInArrow(solve, "a long, b long")


def near_duplicates(docs: DataFrame, key: str = "doc_id", text: str = "text", reach: int = REACH, width: int = SHINGLE, row: str | None = None, **router) -> DataFrame:
    """(key, fp, component) for each input row; component is the least key that links of fingerprints reach.

    With row, a column that tells rows apart, also that column as row, and root: one fingerprint for each component, which tells
    components apart whose least keys are equal or null.

    Texts that are null, empty or without words share fingerprint 0 and link like others. Repeated rows give repeated rows.
    A null key never names a component unless all its keys are null. An empty table gives no rows. Every link of every
    size of group is followed; only classes of equal fingerprints are compared, never their members.
    """
    with temporary() as keep:
        fps = keep(materialise(fingerprints(docs, key, text, width, row), "fingerprints"))
        classes = materialise(fps.groupBy("fp").agg(F.min("key").alias("rep")), "classes")
        members = materialise(connected_components(class_links(classes, reach, **router)), "members")
        reps = members.join(classes, members["node"] == classes["fp"]).select("fp", "root", "rep")
        least = reps.groupBy("root").agg(F.min("rep").alias("least"))
        linked = members.join(least, "root").select(F.col("node").alias("fp"), "root", "least")
        # A table of its own, so that both sides of the last join are plain exchanges and a hot fingerprint can be split.
        of_class = keep(materialise(classes.join(linked, "fp", "left").select("fp", F.coalesce("root", "fp").alias("root"), F.coalesce("least", "rep").alias("component")), "components"))
    return fps.join(of_class, "fp").select(F.col("key").alias(key), "fp", "component", *(["row", "root"] if row else []))


def op7_simhash(spark, sf_dir: str) -> DataFrame:
    found = near_duplicates(table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), F.col("component").alias("component_id"))
