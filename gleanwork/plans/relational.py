"""Relational operators around the corpus methods, over the star-schema, event and text tables.

Most are SQL that both engines take as it stands; where dialects differ, the DuckDB form stands beside it. Operators whose
point is the DataFrame API (hints, windows of events, rewrites) are written with it.
"""

from __future__ import annotations

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window, functions as F, types as T

from .. import sqlapi
from ..functions import textstats as ts
from ..operators import hosts
from .corpus import HOST_SQL, LISTED, lst, r6, of_reps, rep_keys, keys_sql, table

Q: dict[str, tuple] = {}
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def views(spark: SparkSession, d: str) -> None:
    for name in TABLES:
        table(spark, d, name).createOrReplaceTempView(name)


def both(name: str, spark_sql: str, duck_sql: str | None = None) -> None:
    def f(spark, d):
        views(spark, d)
        return spark.sql(spark_sql)

    Q[name] = (f, duck_sql or spark_sql)


def query(name: str, sql: str | None = None):
    def keep(f):
        Q[name] = (f, sql)
        return f

    return keep


both("op_scan_filter_project", "SELECT l_orderkey, l_linenumber, l_returnflag, round(l_extendedprice * (1 - l_discount), 4) AS net FROM lineitem WHERE l_shipdate >= TIMESTAMP '1995-01-01 00:00:00' AND l_shipdate < TIMESTAMP '1996-01-01 00:00:00'")
both("op_null_safe_filter", "SELECT d.doc_id, l.toxic FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id WHERE l.quality <=> NULL", "SELECT d.doc_id, l.toxic FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id WHERE l.quality IS NOT DISTINCT FROM NULL")
both("op_like_in_between", "SELECT p_partkey, p_type, p_size FROM part WHERE p_type LIKE '%A%' AND p_size IN (1, 5, 9, 13, 21) AND p_retailprice BETWEEN 900 AND 1500")
both("op_json_props", "SELECT event_type, count(get_json_object(props, '$.k')) AS with_k, sum(CAST(get_json_object(props, '$.k') AS DOUBLE)) AS k FROM events GROUP BY event_type", "SELECT event_type, count(json_extract_string(props, '$.k')) AS with_k, sum(CAST(json_extract_string(props, '$.k') AS DOUBLE)) AS k FROM events GROUP BY event_type")
both("op_join_broadcast", "SELECT /*+ BROADCAST(n), BROADCAST(r) */ r_name, n_name, count(*) AS customers, round(sum(c_acctbal), 2) AS balance FROM customer c JOIN nation n ON c_nationkey = n_nationkey JOIN region r ON n_regionkey = r_regionkey GROUP BY r_name, n_name", "SELECT r_name, n_name, count(*) AS customers, round(sum(c_acctbal), 2) AS balance FROM customer c JOIN nation n ON c_nationkey = n_nationkey JOIN region r ON n_regionkey = r_regionkey GROUP BY r_name, n_name")
_SMJ = "o_orderpriority, count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_orderpriority"
both("op_join_sortmerge", f"SELECT /*+ MERGE(orders) */ {_SMJ}", f"SELECT {_SMJ}")
_SHJ = "c_mktsegment, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment"
both("op_join_shufflehash", f"SELECT /*+ SHUFFLE_HASH(customer) */ {_SHJ}", f"SELECT {_SHJ}")
both("op_join_left_outer", "SELECT d.doc_id, l.quality, l.toxic FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id")
both("op_join_right_outer", "SELECT c.c_custkey, o.o_orderkey FROM orders o RIGHT JOIN customer c ON o.o_custkey = c.c_custkey")
both("op_join_full_outer", "SELECT d.doc_id AS doc, b.item_id AS item FROM documents d FULL OUTER JOIN benchmark b ON d.doc_id = b.item_id * 50")
both("op_join_semi", "SELECT o_orderkey FROM orders LEFT SEMI JOIN (SELECT l_orderkey FROM lineitem WHERE l_quantity > 45) l ON o_orderkey = l_orderkey", "SELECT o_orderkey FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem WHERE l_quantity > 45)")
both("op_join_anti", "SELECT c_custkey FROM customer LEFT ANTI JOIN orders ON c_custkey = o_custkey", "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)")
both("op_anti_blocked_hosts", f"SELECT page_id FROM (SELECT page_id, lower(regexp_extract(url, '^[a-zA-Z]+://([^/?#:]+)', 1)) AS host FROM pages) p LEFT ANTI JOIN (SELECT explode(array({', '.join(repr(x) for x in LISTED)})) AS host) b ON p.host = b.host", f"SELECT page_id FROM pages WHERE NOT list_contains({lst(LISTED)}, {HOST_SQL})")
both("op_join_lateral", "SELECT c_custkey, t.o_orderkey, t.o_totalprice FROM customer, LATERAL (SELECT o_orderkey, o_totalprice FROM orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 1) t")
both("op_agg_basic", "SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) AS sum_qty, round(sum(l_extendedprice), 2) AS sum_base, round(sum(l_extendedprice * (1 - l_discount)), 2) AS sum_disc, round(avg(l_quantity), 6) AS avg_qty, count(*) AS n FROM lineitem WHERE l_shipdate <= TIMESTAMP '1998-09-02 00:00:00' GROUP BY l_returnflag, l_linestatus")
both("op_agg_distinct", "SELECT l_partkey, count(DISTINCT l_suppkey) AS suppliers, count(DISTINCT l_orderkey) AS orders FROM lineitem GROUP BY l_partkey")
both("op_agg_percentile", "SELECT lang, round(percentile(n_chars, 0.5), 4) AS median, round(percentile(n_chars, 0.95), 4) AS p95 FROM documents GROUP BY lang", "SELECT lang, round(quantile_cont(n_chars, 0.5), 4) AS median, round(quantile_cont(n_chars, 0.95), 4) AS p95 FROM documents GROUP BY lang")
both("op_agg_filter", "SELECT user_id % 10 AS g, count_if(event_type = 'click') AS clicks, count_if(event_type = 'purchase') AS purchases, round(sum(value) FILTER (WHERE event_type = 'purchase'), 4) AS spent FROM events GROUP BY user_id % 10", "SELECT user_id % 10 AS g, count(*) FILTER (event_type = 'click') AS clicks, count(*) FILTER (event_type = 'purchase') AS purchases, round(sum(value) FILTER (WHERE event_type = 'purchase'), 4) AS spent FROM events GROUP BY user_id % 10")
both("op_agg_maxby_mode", "SELECT source, max_by(doc_id, n_chars * 1000000 + doc_id) AS longest, max(n_chars) AS n FROM documents GROUP BY source")
both("op_agg_collect", "SELECT conv_id, md5(array_join(transform(array_sort(collect_list(struct(turn, text))), s -> s.text), '|')) AS joined, count(*) AS turns FROM conversations GROUP BY conv_id", "SELECT conv_id, md5(string_agg(text, '|' ORDER BY turn, text)) AS joined, count(*) AS turns FROM conversations GROUP BY conv_id")
_G = "lang, source, quality, count(*) AS n FROM documents LEFT JOIN labels USING (doc_id) GROUP BY"
both("op_grouping_sets", f"SELECT {_G} GROUPING SETS ((lang, source), (lang, quality), ())")
both("op_rollup", f"SELECT {_G} ROLLUP (lang, source, quality)")
both("op_cube", f"SELECT {_G} CUBE (lang, source, quality)")
both("op_pivot", "SELECT lang, coalesce(`0`, 0) AS bad, coalesce(`1`, 0) AS good FROM (SELECT lang, quality, doc_id FROM documents JOIN labels USING (doc_id)) PIVOT (count(doc_id) FOR quality IN (0, 1))", "SELECT lang, count(*) FILTER (quality = 0) AS bad, count(*) FILTER (quality = 1) AS good FROM documents JOIN labels USING (doc_id) GROUP BY lang")
both("op_unpivot", "SELECT doc_id, name, v FROM labels UNPIVOT (v FOR name IN (quality, toxic))", "SELECT doc_id, 'quality' AS name, quality AS v FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels")
both("op_win_rank", "SELECT * FROM (SELECT doc_id, source, row_number() OVER w AS rn, rank() OVER (PARTITION BY source ORDER BY n_chars DESC) AS rk, dense_rank() OVER (PARTITION BY source ORDER BY n_chars DESC) AS dr, ntile(4) OVER w AS nt, round(percent_rank() OVER (PARTITION BY source ORDER BY n_chars DESC), 6) AS pr, round(cume_dist() OVER (PARTITION BY source ORDER BY n_chars DESC), 6) AS cd FROM documents WINDOW w AS (PARTITION BY source ORDER BY n_chars DESC, doc_id)) WHERE rn <= 3")
both("op_win_lag_gap", "SELECT event_id, CAST(unix_timestamp(ts) - unix_timestamp(lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id)) AS BIGINT) AS gap FROM (SELECT event_id, user_id, CAST(ts AS TIMESTAMP) AS ts FROM events)", "SELECT event_id, (epoch(date_trunc('second', ts)) - epoch(date_trunc('second', lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id))))::BIGINT AS gap FROM events")
both("op_win_running", "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING), 4) AS run, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS moving, count(*) OVER (PARTITION BY user_id ORDER BY event_id RANGE BETWEEN 100 PRECEDING AND CURRENT ROW) AS near FROM events")
both("op_win_first_last", "SELECT DISTINCT user_id, CAST(CAST(ts AS DATE) AS VARCHAR(10)) AS day, first_value(event_id) OVER w AS first_id, last_value(event_id) OVER w AS last_id FROM events WINDOW w AS (PARTITION BY user_id, CAST(ts AS DATE) ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
both("op_win_islands", "WITH g AS (SELECT event_id, user_id, ts, CASE WHEN ts > lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 30 MINUTES THEN 1 ELSE 0 END AS cut FROM events), s AS (SELECT *, sum(cut) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS island FROM g) SELECT user_id, CAST(island AS BIGINT) AS island, count(*) AS n, min(event_id) AS first_id FROM s GROUP BY user_id, island")
both("op_topk", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
both("op_topk_group", "SELECT c_mktsegment, c_custkey, rn FROM (SELECT c_mktsegment, c_custkey, row_number() OVER (PARTITION BY c_mktsegment ORDER BY c_acctbal DESC, c_custkey) AS rn FROM customer) WHERE rn <= 5")
both("op_limit_offset", "SELECT p_partkey, p_name FROM part ORDER BY p_partkey LIMIT 10 OFFSET 25")
both("op_union", "SELECT user_id FROM events WHERE event_type = 'click' UNION SELECT user_id FROM events WHERE event_type = 'purchase'")
both("op_union_all", "SELECT lang AS v FROM documents UNION ALL SELECT source FROM documents")
both("op_intersect", "SELECT user_id FROM events WHERE event_type = 'click' INTERSECT SELECT user_id FROM events WHERE event_type = 'purchase'")
both("op_intersect_all", "SELECT user_id FROM events WHERE event_type = 'click' INTERSECT ALL SELECT user_id FROM events WHERE event_type = 'purchase'")
both("op_except", "SELECT c_nationkey FROM customer EXCEPT SELECT s_nationkey FROM supplier WHERE s_acctbal > 5000")
both("op_except_all", "SELECT user_id FROM events WHERE event_type = 'click' EXCEPT ALL SELECT user_id FROM events WHERE event_type = 'purchase'")
both("op_subq_scalar", "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.8 FROM orders)")
both("op_subq_exists", "SELECT s_suppkey FROM supplier s WHERE EXISTS (SELECT 1 FROM lineitem l WHERE l.l_suppkey = s.s_suppkey AND l.l_discount >= 0.1)")
both("op_subq_correlated", "SELECT o_orderkey FROM orders o WHERE o_totalprice > (SELECT avg(i.o_totalprice) FROM orders i WHERE i.o_custkey = o.o_custkey)")
both("op_string_funcs", "SELECT doc_id, length(text) AS chars, upper(substring(source, 1, 3)) AS s, md5(replace(text, 'e', 'E')) AS m, sha1(source) AS h, levenshtein(lang, source) AS d, reverse(lang) AS r, lpad(lang, 5, '*') AS p, instr(text, 'a') AS i FROM documents", "SELECT doc_id, length(text) AS chars, upper(substring(source, 1, 3)) AS s, md5(replace(text, 'e', 'E')) AS m, sha1(source) AS h, levenshtein(lang, source) AS d, reverse(lang) AS r, lpad(lang, 5, '*') AS p, instr(text, 'a') AS i FROM documents")
both("op_regex_funcs", "SELECT doc_id, regexp_count(text, '[0-9]+') AS numbers, regexp_extract(text, '([A-Za-z]+)', 1) AS first_word, md5(regexp_replace(text, '[aeiou]', '_')) AS m FROM documents", "SELECT doc_id, len(regexp_extract_all(text, '[0-9]+')) AS numbers, regexp_extract(text, '([A-Za-z]+)', 1) AS first_word, md5(regexp_replace(text, '[aeiou]', '_', 'g')) AS m FROM documents")
both("op_url_parts", "SELECT page_id, parse_url(url, 'PROTOCOL') AS scheme, parse_url(url, 'HOST') AS host, coalesce(parse_url(url, 'QUERY'), '') AS query FROM pages", "SELECT page_id, regexp_extract(url, '^([a-z]+)://', 1) AS scheme, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host, regexp_extract(url, '\\?([^#]*)', 1) AS query FROM pages")
both("op_date_funcs", "SELECT CAST(CAST(date_trunc('MONTH', o_orderdate) AS DATE) AS STRING) AS month, quarter(max(o_orderdate)) AS q, count(*) AS n, max(datediff(TIMESTAMP_NTZ '1999-01-01 00:00:00', o_orderdate)) AS age FROM orders GROUP BY date_trunc('MONTH', o_orderdate)", "SELECT CAST(CAST(date_trunc('month', o_orderdate) AS DATE) AS VARCHAR) AS month, quarter(max(o_orderdate)) AS q, count(*) AS n, max(date_diff('day', o_orderdate::DATE, DATE '1999-01-01')) AS age FROM orders GROUP BY date_trunc('month', o_orderdate)")
both("op_math_bits", "SELECT o_orderkey, round(ln(o_totalprice), 6) AS l, round(pow(o_custkey, 0.5), 6) AS r, bit_count(o_orderkey) AS bits, o_orderkey & 255 AS low, o_orderkey ^ o_custkey AS x, shiftright(o_orderkey, 3) AS s, pmod(-o_orderkey, 7) AS m FROM orders", "SELECT o_orderkey, round(ln(o_totalprice), 6) AS l, round(pow(o_custkey, 0.5), 6) AS r, bit_count(o_orderkey) AS bits, o_orderkey & 255 AS low, xor(o_orderkey, o_custkey) AS x, o_orderkey >> 3 AS s, ((-o_orderkey % 7) + 7) % 7 AS m FROM orders")
both("op_array_funcs", "SELECT vec_id, size(embedding) AS n, round(sqrt(aggregate(embedding, CAST(0 AS DOUBLE), (s, v) -> s + CAST(v AS DOUBLE) * CAST(v AS DOUBLE))), 4) AS norm, array_position(embedding, array_max(embedding)) AS top FROM embeddings", "SELECT vec_id, len(embedding) AS n, round(sqrt(list_sum(list_transform(embedding, lambda v: v::DOUBLE * v::DOUBLE))), 4) AS norm, list_position(embedding, list_max(embedding)) AS top FROM embeddings")
both("op_map_funcs", "SELECT doc_id, k, v FROM (SELECT doc_id, explode(map_from_entries(collect_list(struct(w, n)))) AS (k, v) FROM (SELECT doc_id, w, count(*) AS n FROM (SELECT doc_id, explode(split(lower(substring(text, 1, 200)), '[^a-z]+', -1)) AS w FROM documents) WHERE w <> '' GROUP BY doc_id, w) GROUP BY doc_id)", "SELECT doc_id, w AS k, count(*) AS v FROM (SELECT doc_id, unnest(regexp_split_to_array(lower(substring(text, 1, 200)), '[^a-z]+')) AS w FROM documents) WHERE w <> '' GROUP BY doc_id, w")
both("op_sample_hash", "SELECT doc_id FROM documents WHERE conv(substring(md5(CAST(doc_id AS STRING)), 1, 8), 16, 10) % 10 = 0", "SELECT doc_id FROM documents WHERE ('0x' || substr(md5(doc_id::VARCHAR), 1, 8))::BIGINT % 10 = 0")
both("op_cte_chain", "WITH big AS (SELECT o_custkey, sum(o_totalprice) AS t FROM orders GROUP BY o_custkey), r AS (SELECT c_nationkey, max(t) AS m FROM big JOIN customer ON o_custkey = c_custkey GROUP BY c_nationkey) SELECT n_name, round(m, 2) AS best FROM r JOIN nation ON c_nationkey = n_nationkey")


@query("op_join_theta", "SELECT x.p_partkey AS a, y.p_partkey AS b FROM part x JOIN part y ON x.p_partkey < y.p_partkey AND abs(x.p_retailprice - y.p_retailprice) <= 0.05")
def join_theta(spark, d):
    """Price band join: bucketed, a row meets its own bucket and the one above."""
    p = table(spark, d, "part").select("p_partkey", "p_retailprice")
    x = p.select(F.col("p_partkey").alias("a"), F.col("p_retailprice").alias("pa"), F.floor(F.col("p_retailprice") / 0.1).alias("k"))
    y = p.select(F.col("p_partkey").alias("b"), F.col("p_retailprice").alias("pb"), F.explode(F.array(*[F.floor(F.col("p_retailprice") / 0.1) + i for i in (-1, 0, 1)])).alias("k"))
    return x.join(y, "k").filter((F.col("a") < F.col("b")) & (F.abs(F.col("pa") - F.col("pb")) <= 0.05)).select("a", "b")


@query("op_join_theta_nested_loop", "SELECT r.r_name, n.n_name FROM region r JOIN nation n ON r.r_regionkey < n.n_regionkey")
def join_nested(spark, d):
    """A true theta join; both tables are fixed dimensions of 5 and 25 rows."""
    r, n = table(spark, d, "region"), table(spark, d, "nation")
    return n.join(F.broadcast(r), F.col("r_regionkey") < F.col("n_regionkey")).select("r_name", "n_name")


@query("op_join_range", "SELECT p.event_id AS purchase_id, c.event_id AS click_id FROM events p JOIN events c ON p.user_id = c.user_id AND p.event_type = 'purchase' AND c.event_type = 'click' AND c.ts BETWEEN p.ts - INTERVAL 10 MINUTE AND p.ts + INTERVAL 10 MINUTE")
def join_range(spark, d):
    """Interval join by buckets of the interval's width: an equi-join on user and bucket, then the exact test."""
    e = table(spark, d, "events").withColumn("s", F.unix_micros(F.col("ts").cast("timestamp")))
    width = 600_000_000
    p = e.filter("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), "user_id", F.col("s").alias("ps"), F.explode(F.array(*[F.floor(F.col("s") / width) + i for i in (-1, 0, 1)])).alias("k"))
    c = e.filter("event_type = 'click'").select(F.col("event_id").alias("click_id"), "user_id", F.col("s").alias("cs"), F.floor(F.col("s") / width).alias("k"))
    return p.join(c, ["user_id", "k"]).filter(F.abs(F.col("ps") - F.col("cs")) <= width).select("purchase_id", "click_id")


@query("op_join_asof", "SELECT p.event_id AS purchase_id, c.event_id AS click_id FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = 'click' GROUP BY user_id, ts) c ON p.user_id = c.user_id AND p.ts >= c.ts")
def join_asof(spark, d):
    """The last click at or before each purchase: one union, one sorted window."""
    e = table(spark, d, "events").filter("event_type IN ('click', 'purchase')")
    w = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "click", 0).otherwise(1), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    last = F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(w)
    return e.withColumn("click_id", last).filter("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), "click_id")


@query("op_join_suffix", f"SELECT page_id FROM pages WHERE len(list_filter({lst(LISTED)}, lambda x: {HOST_SQL} = x OR ends_with({HOST_SQL}, '.' || x))) > 0")
def join_suffix(spark, d):
    p = table(spark, d, "pages").select("page_id", hosts.host_of(F.col("url")).alias("host"))
    listed = spark.createDataFrame([(x,) for x in LISTED], "domain string")
    return p.join(hosts.in_blocklist(p.select("host").distinct(), listed), "host", "left_semi").select("page_id")


@query("op_self_join_keys", f"SELECT x.band, x.doc_id AS a, y.doc_id AS b FROM {of_reps(keys_sql(4, 8))} x JOIN {of_reps(keys_sql(4, 8))} y ON x.band = y.band AND x.bucket = y.bucket AND x.doc_id < y.doc_id")
def self_join(spark, d):
    """Different texts that share a key, by their representatives."""
    k = rep_keys(spark, d)
    return k.select("band", "bucket", F.col("doc_id").alias("a")).join(k.select("band", "bucket", F.col("doc_id").alias("b")), ["band", "bucket"]).filter("a < b").select("band", "a", "b")


@query("op_agg_approx")
def agg_approx(spark, d):
    e = table(spark, d, "events")
    return e.groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("approx"), F.countDistinct("user_id").alias("exact"), F.hll_sketch_estimate(F.hll_sketch_agg("user_id")).alias("sketch"))


@query("op_udf_scalar", "SELECT doc_id, round(length(regexp_replace(text, '[^aeiou]', '', 'g')) / greatest(length(text), 1)::DOUBLE, 6) AS share FROM documents")
def udf_scalar(spark, d):
    """A SQL scalar function, inlined by the optimizer."""
    sqlapi.register(spark)
    views(spark, d)
    return spark.sql("SELECT doc_id, round(class_share(text, 'aeiou'), 6) AS share FROM documents")


@query("op_udf_arrow", "SELECT doc_id, len(list_distinct(string_split(text, ' '))) AS distinct_words FROM documents")
def udf_arrow(spark, d):
    schema = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("distinct_words", T.LongType())])

    def run(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([len(set(t.split(" "))) for t in b.column(1).to_pylist()], pa.int64())], names=["doc_id", "distinct_words"])

    return table(spark, d, "documents").select("doc_id", "text").mapInArrow(run, schema)


@query("op_udaf", "SELECT lang, round(sum(n_chars * (doc_id % 7)) / sum(n_chars)::DOUBLE, 6) AS weighted FROM documents GROUP BY lang")
def udaf(spark, d):
    @F.pandas_udf(T.DoubleType())
    def weighted(v: pd.Series, w: pd.Series) -> float:
        return float((v * w).sum() / w.sum())

    return table(spark, d, "documents").groupBy("lang").agg(weighted(F.col("doc_id") % 7, F.col("n_chars")).alias("weighted")).select("lang", r6(F.col("weighted")).alias("weighted"))


@query("op_grouped_map", "SELECT lang, doc_id, rank() OVER (PARTITION BY lang ORDER BY n_chars DESC) AS r FROM documents")
def grouped_map(spark, d):
    def rank(g: pd.DataFrame) -> pd.DataFrame:
        return g.assign(r=g["n_chars"].rank(method="min", ascending=False).astype("int64"))[["lang", "doc_id", "r"]]

    return table(spark, d, "documents").select("lang", "doc_id", "n_chars").groupBy("lang").applyInPandas(rank, "lang string, doc_id long, r long")


@query("op_udtf", "SELECT doc_id, pos, md5(s) AS md5 FROM (SELECT doc_id, unnest(range(0, len(s))) AS pos, unnest(s) AS s FROM (SELECT doc_id, list_filter(string_split(text, chr(10)), lambda x: x <> '') AS s FROM documents))")
def udtf(spark, d):
    sqlapi.register(spark)
    views(spark, d)
    return spark.sql("SELECT doc_id, t.pos, md5(t.line) AS md5 FROM documents, LATERAL text_lines(text) t")


@query("op_sql_surface", "SELECT doc_id, length(text) < 400 AS short FROM documents")
def sql_surface(spark, d):
    sqlapi.register(spark)
    views(spark, d)
    return spark.sql("SELECT doc_id, is_short(text) AS short FROM documents")


@query("op_window_json_variant", "SELECT event_id, event_type, k, k - lag(k) OVER (PARTITION BY event_type ORDER BY event_id) AS step FROM (SELECT event_id, event_type, json_extract(props, '$.k')::INT AS k FROM events) WHERE k >= 50")
def json_variant(spark, d):
    """A value of a variant, filtered by, and compared with the one before it."""
    e = table(spark, d, "events").withColumn("k", F.try_variant_get(F.try_parse_json("props"), "$.k", "int")).filter("k >= 50")
    return e.select("event_id", "event_type", "k", (F.col("k") - F.lag("k").over(Window.partitionBy("event_type").orderBy("event_id"))).alias("step"))
