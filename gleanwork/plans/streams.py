"""Streaming and sink workloads: each runs over what is there now and returns a static table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from ..operators import dedup, hosts
from ..sources import archive
from ..streaming import ingest
from .corpus import HOST_SQL, LISTED, keys_sql, lst, small_keys, table

Q: dict[str, tuple] = {}


def query(name: str, sql: str | None = None):
    def keep(f):
        Q[name] = (f, sql)
        return f

    return keep


def end(c):
    return c.cast("timestamp_ntz")


WM = "(SELECT max(ts) - INTERVAL 2 HOUR AS wm FROM events)"


@query("op_stream_tumbling", f"SELECT date_trunc('day', ts) AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events WHERE date_trunc('day', ts) + INTERVAL 1 DAY <= (SELECT wm FROM {WM}) GROUP BY 1, 2")
def tumbling(spark, d):
    out = ingest.finish(ingest.tumbling(ingest.events_stream(spark, d)))
    return out.select(end(F.col("start")).alias("start"), "event_type", "n", F.round("total", 4).alias("total"))


@query("op_stream_sliding", f"SELECT s AS start, count(*) AS n FROM (SELECT date_trunc('day', ts) - INTERVAL 1 DAY AS s FROM events UNION ALL SELECT date_trunc('day', ts) FROM events) GROUP BY s HAVING s + INTERVAL 2 DAY <= (SELECT wm FROM {WM})")
def sliding(spark, d):
    out = ingest.finish(ingest.sliding(ingest.events_stream(spark, d), "2 days", "1 day"))
    return out.select(end(F.col("start")).alias("start"), "n")


@query("op_stream_session", f"""WITH g AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER w + INTERVAL 30 MINUTE THEN 1 ELSE 0 END AS cut FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT user_id, ts, sum(cut) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g)
  SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 30 MINUTE AS "end", count(*) AS n FROM s GROUP BY user_id, k HAVING max(ts) + INTERVAL 30 MINUTE <= (SELECT wm FROM {WM})""")
def session(spark, d):
    out = ingest.finish(ingest.sessions(ingest.events_stream(spark, d)))
    return out.select("user_id", end(F.col("start")).alias("start"), end(F.col("end")).alias("end"), "n")


@query("op_stream_dedup", "SELECT DISTINCT user_id, event_type FROM events")
def stream_dedup(spark, d):
    return ingest.finish(ingest.first_per_user(ingest.events_stream(spark, d)))


@query("op_stream_late", "SELECT count(*) FILTER (ts >= m) AS kept, count(*) FILTER (ts < m) AS late FROM events, (SELECT max(ts) - INTERVAL 10 DAY AS m FROM events)")
def stream_late(spark, d):
    """Rows behind the newest time seen by more than the allowance are counted apart, batch by batch."""

    def fold(old: DataFrame | None, batch: DataFrame) -> DataFrame:
        m = batch.agg((F.max("ts") - F.expr("INTERVAL 10 DAYS")).alias("m"))
        new = batch.crossJoin(F.broadcast(m)).agg(F.count_if(F.col("ts") >= F.col("m")).alias("kept"), F.count_if(F.col("ts") < F.col("m")).alias("late"))
        return new if old is None else old.union(new).agg(F.sum("kept").alias("kept"), F.sum("late").alias("late"))

    return ingest.foreach_upsert(ingest.events_stream(spark, d), fold, "late")


def pages_stream(spark: SparkSession, d: str) -> DataFrame:
    path = f"{d}/pages.parquet"
    schema = spark.read.parquet(path).schema
    return spark.readStream.schema(schema).option("pathGlobFilter", "*pages*").parquet(d) if not ingest._is_folder(spark, path) else spark.readStream.schema(schema).parquet(path)


@query("op_stream_static_anti", f"SELECT page_id FROM pages WHERE NOT list_contains({lst(LISTED)}, {HOST_SQL})")
def static_anti(spark, d):
    s = pages_stream(spark, d).select("page_id", hosts.host_of(F.col("url")).alias("host"))
    return ingest.finish(ingest.static_anti(s, spark.createDataFrame([(x,) for x in LISTED], "host string"), "host").select("page_id"))


@query("op_stream_stream", "SELECT c.event_id AS click_id, p.event_id AS purchase_id FROM events c JOIN events p ON c.user_id = p.user_id AND c.event_type = 'click' AND p.event_type = 'purchase' AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 1 HOUR")
def stream_stream(spark, d):
    return ingest.finish(ingest.click_to_purchase(ingest.events_stream(spark, d), "1 HOUR"))


@query("op_stream_state", "SELECT user_id, event_type, max(event_id) AS event_id FROM events GROUP BY user_id, event_type")
def stream_state(spark, d):
    s = ingest.events_stream(spark, d).select("user_id", "event_type", "event_id")
    return ingest.foreach_upsert(s, lambda old, batch: ingest.newest_by_key(old, batch, ["user_id", "event_type"], ["event_id"]), "state")


@query("op_stream_dedup_increment", f"SELECT band, bucket, max(doc_id) AS doc_id FROM {keys_sql(4, 8)} GROUP BY band, bucket")
def dedup_increment(spark, d):
    """Two snapshots one after the other give the same store as one run over both."""
    k = small_keys(spark, d)
    k = dedup.save(k, "keys")
    old, _ = ingest.dedup_increment(k.filter("doc_id % 21 < 10"), None, [])
    store, _ = ingest.dedup_increment(k.filter("doc_id % 21 >= 10"), dedup.save(old, "store"), [])
    return store.select("band", "bucket", "doc_id")


@query("op_sink_roundtrip", "SELECT f AS format, count(*) AS rows, sum(doc_id)::BIGINT AS ids, sum(length(text))::BIGINT AS chars FROM documents, (VALUES ('parquet'), ('orc'), ('json'), ('csv')) v(f) GROUP BY f")
def sink_roundtrip(spark, d):
    docs = table(spark, d, "documents").select("doc_id", "lang", "text")
    out = None
    for kind in ("parquet", "orc", "json", "csv"):
        path = ingest.scratch(spark, kind)
        w = docs.write.partitionBy("lang").option("maxRecordsPerFile", 200)
        r = spark.read.schema("doc_id long, text string, lang string")
        if kind == "csv":
            w, r = w.option("quoteAll", True).option("escape", '"'), r.option("multiLine", True).option("escape", '"')
        if kind == "json":
            w = w.option("compression", "gzip")
        w.format(kind).save(path)
        row = r.format(kind).load(path).agg(F.lit(kind).alias("format"), F.count("*").alias("rows"), F.sum("doc_id").alias("ids"), F.sum(F.length("text")).alias("chars"))
        out = row if out is None else out.union(row)
    return out


@query("op_datasource_archive", "SELECT page_id, url, md5(html) AS md5, page_id % 21 AS snapshot_ix FROM pages")
def datasource_archive(spark, d):
    """pages written as crawl archives, and read by the binaryFile form of the reader."""
    path = ingest.scratch(spark, "archive")
    p = archive.from_pages(table(spark, d, "pages"))
    archive.write_archive_table(p, path)
    back = archive.read_archive_table(spark, path)
    return back.select("page_id", "url", F.md5(F.col("html").cast("binary")).alias("md5"), F.col("snapshot_ix").cast("long").alias("snapshot_ix"))
