"""Which of several duplicates stays: the newest. Three readings of the rule, without ever listing pairs in the first.

pairwise: a document goes if some duplicate is newer, that is, if it is not the newest of one of its buckets.
component: one newest document for each connected component.
greedy: newest first, a document goes only against documents that stay.
"""

from __future__ import annotations

import os
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession, functions as F

from . import minhash

#: Keys that are broadcast at most.
BROADCAST_ROWS = 1 << 20


def recency(key: Column, snapshots: int = 21, days: int = 50) -> tuple[Column, Column]:
    """(snapshot_ix, crawl_ts): a stand-in for crawl time, from the id."""
    ix = F.pmod(key, F.lit(snapshots)).cast("int")
    return ix, F.to_timestamp(F.date_add(F.lit("2020-09-20").cast("date"), ix * days))


def shared_folder(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir, or a temporary one where it is unset, on one machine only."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        folder = "file://" + tempfile.mkdtemp(prefix=f"gleanwork-{os.getpid()}-")
    return f"{folder.rstrip('/')}/gleanwork"


def save(df: DataFrame, label: str) -> DataFrame:
    """A written table in the shared folder: cuts lineage, and lost executors cost nothing."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def without(df: DataFrame, losers: DataFrame, key: str) -> DataFrame:
    """df without the keys of losers, a written table: broadcast while it has at most BROADCAST_ROWS, so that texts stay where
    they are; beyond, joined by a shuffle.
    """
    few = losers.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS
    return df.join(F.broadcast(losers) if few else losers, key, "left_anti")


def keep_newest(keys: DataFrame, order: list[str], key: str = "doc_id") -> DataFrame:
    """Losers of the pairwise reading, distinct keys. keys: (key, band, bucket, *order).

    The newest of each bucket comes from a max with partial sums, and only buckets of several rows are joined back, so a hot
    bucket is never one task's window. Linear in any bucket.
    """
    rank = F.struct(*order, key)
    newest = keys.groupBy("band", "bucket").agg(F.max(rank).alias("_newest"), F.count("*").alias("_n")).filter("_n > 1")
    return keys.join(newest, ["band", "bucket"]).filter(rank < F.col("_newest")).select(key).distinct()


def newest_of_digests(found: DataFrame, order: list[str], key: str = "doc_id") -> DataFrame:
    """Losers of the pairwise reading from minhash.digests(), which is a written table.

    Rows of one signature share all their buckets: the newest of them stands for all, the others lose. Only those that stand
    for others are dealt to buckets, so copies never make a bucket hot.
    """
    rank = F.struct(*order, key)
    best = found.groupBy("whole").agg(F.max(rank).alias("_best"), F.count("*").alias("_n"))
    copies = found.join(best.filter("_n > 1"), "whole").filter(rank < F.col("_best")).select(key)
    alone = found.join(best, "whole").filter(rank == F.col("_best"))
    keys = alone.select(key, *order, F.posexplode("buckets").alias("band", "bucket"))
    return copies.union(keep_newest(keys, order, key)).distinct()


def components(edges: DataFrame) -> DataFrame:
    """(node, root): least node reachable, for nodes of edges(a, b). Rounds of hash-to-least with a table each."""
    state = save(edges.select(F.col("a").alias("u"), F.col("b").alias("v")).union(edges.select("b", "a")).filter("u != v").distinct(), "edges")
    label = state.select(F.col("u").alias("node")).distinct().withColumn("root", F.col("node"))
    label = save(label, "labels")
    while True:
        offered = state.join(label, state["v"] == label["node"]).select(F.col("u").alias("node"), "root")
        best = label.union(offered).groupBy("node").agg(F.min("root").alias("root"))
        # A root's own root shortens chains.
        jump = best.alias("x").join(best.alias("y"), F.col("x.root") == F.col("y.node")).select("x.node", F.col("y.root").alias("root"))
        nxt = save(jump, "labels")
        changed = nxt.alias("n").join(label.alias("o"), "node").filter("n.root != o.root").limit(1).count()
        label = nxt
        if not changed:
            return label


def keep_component(edges: DataFrame, rank: DataFrame, order: list[str], key: str = "doc_id") -> DataFrame:
    """Losers of the component reading. rank: (key, *order) of all documents."""
    of = components(edges)
    ranked = of.join(rank, of["node"] == rank[key]).select("root", F.struct(*order, key).alias("r"))
    best = ranked.groupBy("root").agg(F.max("r").alias("best"))
    return ranked.join(best, "root").filter(F.col("r") < F.col("best")).select(F.col(f"r.{key}").alias(key))


def keep_greedy(edges: DataFrame, rank: DataFrame, order: list[str], key: str = "doc_id") -> DataFrame:
    """Losers of the greedy reading: rounds in which every undecided document whose newer neighbours are all gone stays."""
    r = rank.select(F.col(key).alias("id"), F.struct(*order, key).alias("r"))
    e = edges.join(r.select(F.col("id").alias("a"), F.col("r").alias("ra")), "a").join(r.select(F.col("id").alias("b"), F.col("r").alias("rb")), "b")
    # old -> new
    arcs = save(e.select(F.when(F.col("ra") < F.col("rb"), F.col("a")).otherwise(F.col("b")).alias("old"), F.when(F.col("ra") < F.col("rb"), F.col("b")).otherwise(F.col("a")).alias("new")).distinct(), "arcs")
    open_ = save(arcs.select(F.explode(F.array("old", "new")).alias("id")).distinct(), "open")
    lost = None
    while open_.limit(1).count():
        live = arcs.join(open_.withColumnRenamed("id", "old"), "old", "left_semi").join(open_.withColumnRenamed("id", "new"), "new", "left_semi")
        stays = save(open_.join(live.select(F.col("old").alias("id")).distinct(), "id", "left_anti"), "stays")
        gone = save(live.join(stays.withColumnRenamed("id", "new"), "new", "left_semi").select(F.col("old").alias("id")).distinct(), "gone")
        lost = gone if lost is None else lost.union(gone)
        open_ = save(open_.join(stays, "id", "left_anti").join(gone, "id", "left_anti"), "open")
    return (lost if lost is not None else open_).select(F.col("id").alias(key))


def run(df: DataFrame, bands: int = minhash.BANDS, rows: int = minhash.ROWS, n: int = minhash.SHINGLE, order: tuple[str, ...] = ("crawl_ts",), mode: str = "pairwise", family: str = "poly", key: str = "doc_id", text: str = "text", seed: int = 1) -> DataFrame:
    """df without the documents that lose. df has the order columns; empty texts have no buckets and stay."""
    if mode not in ("pairwise", "component", "greedy"):
        raise ValueError("mode is pairwise, component or greedy")
    if mode == "pairwise":
        found = save(minhash.digests(df, rows, bands, n, family, seed, key, text, tuple(order)), "digests")
        return without(df, save(newest_of_digests(found, list(order), key), "losers"), key)
    keys = minhash.band_keys(minhash.signatures(df, rows, bands, n, family, seed, key, text), rows, bands, key)
    pairs = save(minhash.candidate_pairs(keys, key, star=mode == "component"), "pairs")
    losers = (keep_component if mode == "component" else keep_greedy)(pairs, df.select(key, *order), list(order), key)
    return without(df, save(losers.distinct(), "losers"), key)


def survival_by(df: DataFrame, survivors: DataFrame, period: str, key: str = "doc_id") -> DataFrame:
    """(period, pages, kept, rate): the non-duplicate rate of each crawl period."""
    kept = survivors.select(F.col(key).alias("_k")).distinct()
    return df.join(kept, df[key] == kept["_k"], "left").groupBy(period).agg(F.count("*").alias("pages"), F.count("_k").alias("kept")).withColumn("rate", F.col("kept") / F.col("pages"))
