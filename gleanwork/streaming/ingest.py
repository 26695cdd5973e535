"""Structured Streaming: snapshot ingest, incremental newest-wins deduplication, and event windows."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, functions as F

from ..operators import dedup, minhash


def scratch(spark: SparkSession, label: str) -> str:
    return f"{dedup.shared_folder(spark)}/{label}-{uuid.uuid4().hex}"


def read_stream(spark: SparkSession, path: str, per_batch: int = 1) -> DataFrame:
    """A parquet folder, or one file (copied into nothing: its own path as a glob), as a stream."""
    schema = spark.read.parquet(path).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", per_batch).parquet(path)


def events_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """events with an event time that watermarks accept."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    raw = spark.readStream.schema(schema).option("pathGlobFilter", "*events*").parquet(sf_dir) if not _is_folder(spark, f"{sf_dir}/events.parquet") else spark.readStream.schema(schema).parquet(f"{sf_dir}/events.parquet")
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def _is_folder(spark: SparkSession, path: str) -> bool:
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(p).isDirectory()


def finish(df: DataFrame, mode: str = "append", label: str = "stream") -> DataFrame:
    """Run a streaming plan over what is there now and read its table back."""
    spark = df.sparkSession
    if mode == "append":
        out = scratch(spark, label)
        q = df.writeStream.outputMode("append").format("parquet").option("path", out).option("checkpointLocation", f"{out}-state").trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.read.schema(df.schema).parquet(out)
    name = f"{label}_{uuid.uuid4().hex}"
    last: dict[str, str] = {}

    def put(batch: DataFrame, epoch: int) -> None:
        path = scratch(spark, f"{label}-{epoch}")
        batch.write.parquet(path)
        last["path"] = path

    q = df.writeStream.outputMode(mode).foreachBatch(put).option("checkpointLocation", scratch(spark, name)).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(df.schema).parquet(last["path"])


def tumbling(events: DataFrame, width: str = "1 day", late: str = "2 hours") -> DataFrame:
    w = events.withWatermark("ts", late).groupBy(F.window("ts", width), "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("total"))
    return w.select(F.col("window.start").alias("start"), "event_type", "n", "total")


def sliding(events: DataFrame, width: str = "2 days", step: str = "1 day", late: str = "2 hours") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.window("ts", width, step)).agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "2 hours") -> DataFrame:
    w = events.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"))
    return w.select("user_id", F.col("session_window.start").alias("start"), F.col("session_window.end").alias("end"), "n")


def first_per_user(events: DataFrame, late: str = "10000 days") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["user_id", "event_type"]).select("user_id", "event_type")


def static_anti(stream: DataFrame, static: DataFrame, on: str) -> DataFrame:
    """Stream rows whose key the static table does not list."""
    marked = stream.join(static.select(on).distinct().withColumn("_hit", F.lit(True)), on, "left")
    return marked.filter(F.col("_hit").isNull()).drop("_hit")


def click_to_purchase(events: DataFrame, within: str = "1 hour", late: str = "2 hours") -> DataFrame:
    """Pairs of a click and a purchase of the same user within the interval: a join of two watermarked streams."""
    a = events.filter("event_type = 'click'").select(F.col("event_id").alias("click_id"), "user_id", F.col("ts").alias("click_ts")).withWatermark("click_ts", late)
    b = events.filter("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), F.col("user_id").alias("buyer"), F.col("ts").alias("purchase_ts")).withWatermark("purchase_ts", late)
    return a.join(b, F.expr(f"user_id = buyer AND purchase_ts >= click_ts AND purchase_ts <= click_ts + INTERVAL {within}")).select("click_id", "purchase_id")


def foreach_upsert(stream: DataFrame, fold: Callable[[DataFrame | None, DataFrame], DataFrame], label: str) -> DataFrame:
    """Keep a table up to date batch by batch: fold(old table or None, batch) -> new table."""
    spark = stream.sparkSession
    state: dict[str, DataFrame] = {}

    def put(batch: DataFrame, epoch: int) -> None:
        state["now"] = dedup.save(fold(state.get("now"), batch), f"{label}-{epoch}")

    q = stream.writeStream.foreachBatch(put).option("checkpointLocation", scratch(spark, label)).trigger(availableNow=True).start()
    q.awaitTermination()
    return state["now"]


def newest_by_key(old: DataFrame | None, batch: DataFrame, key: list[str], order: list[str]) -> DataFrame:
    """One row for each key: the greatest by order among the table and the batch."""
    both = batch if old is None else old.unionByName(batch)
    rest = [c for c in both.columns if c not in key]
    best = both.groupBy(*key).agg(F.max_by(F.struct(*rest), F.struct(*order)).alias("r"))
    return best.select(*key, *[F.col(f"r.{c}").alias(c) for c in rest]).select(both.columns)


def dedup_increment(new_keys: DataFrame, store: DataFrame | None, order: list[str], key: str = "doc_id") -> tuple[DataFrame, DataFrame]:
    """(new store, evicted keys). store holds the newest document of each bucket; a newer copy evicts stored ones."""
    rank = [*order, key]
    keep = new_keys.select("band", "bucket", *rank)
    merged = newest_by_key(store, keep, ["band", "bucket"], rank)
    evicted = keep.select(key).distinct() if store is None else keep.select(key).union(store.select(key)).distinct()
    everything = keep if store is None else keep.unionByName(store.select(keep.columns))
    losing = everything.alias("e").join(merged.alias("m"), ["band", "bucket"]).filter(F.col(f"e.{key}") != F.col(f"m.{key}")).select(F.col(f"e.{key}").alias(key)).distinct()
    return merged, evicted.join(losing, key, "left_semi")


def keys_of(docs: DataFrame, rows: int, bands: int, family: str = "poly") -> DataFrame:
    return minhash.band_keys(minhash.signatures(docs, rows, bands, family=family), rows, bands)
