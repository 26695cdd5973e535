"""Filtering by host: a block list from five criteria, all equi-joins or plain predicates."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from ..functions import textstats as ts


def host_of(url: Column) -> Column:
    """Lower-cased host: what follows the scheme up to a slash, question mark, hash or colon."""
    return F.lower(F.regexp_extract(url, r"^[a-zA-Z]+://([^/?#:]+)", 1))


def suffixes(host: Column) -> Column:
    """A host and its parent domains."""
    labels = F.split(host, r"\.")
    return F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))


def in_blocklist(hosts: DataFrame, listed: DataFrame, host: str = "host") -> DataFrame:
    """Hosts that are listed or have a listed parent domain; listed(domain). Spark broadcasts the list while it is small."""
    return hosts.select(host, F.explode(suffixes(F.col(host))).alias("domain")).join(listed.select("domain").distinct(), "domain").select(host).distinct()


def term_page_share(df: DataFrame, terms: list[str], host: str = "host", text: str = "text") -> DataFrame:
    """(host, pages, share): pages with at least one term over a host's pages; partial sums before the shuffle."""
    return df.select(host, F.coalesce(ts.contains_term(F.col(text), terms), F.lit(False)).alias("hit")).groupBy(host).agg(F.count("*").alias("pages"), F.avg(F.col("hit").cast("double")).alias("share"))


def glob(host: Column, pattern: str) -> Column:
    """'*x' matches any host that ends in x; '*.x' needs a further label before x."""
    return host.endswith(pattern[1:]) if pattern.startswith("*") else host == pattern


def build_blocklist(df: DataFrame, listed: DataFrame, site_terms: list[str], ng_terms: list[str], globs: list[str], site_share: float = 0.001, ng_share: float = 0.005, min_pages: int = 1, host: str = "host", text: str = "text") -> DataFrame:
    """(host, reasons): union of the criteria; statistics of all pages of a host in one aggregate."""
    flags = df.select(host, F.coalesce(ts.contains_term(F.col(text), site_terms), F.lit(False)).cast("double").alias("s"), F.coalesce(ts.contains_term(F.col(text), ng_terms), F.lit(False)).cast("double").alias("n"))
    stats = flags.groupBy(host).agg(F.count("*").alias("pages"), F.avg("s").alias("site"), F.avg("n").alias("ng"))
    blocked = in_blocklist(stats.select(host), listed, host).withColumn("listed", F.lit(True))
    joined = stats.join(blocked, host, "left")
    big = F.col("pages") >= min_pages
    tests = [("listed", F.coalesce("listed", F.lit(False))), ("site_terms", big & (F.col("site") > site_share)), ("ng_terms", big & (F.col("ng") > ng_share))]
    tests += [(f"glob {g}", glob(F.col(host), g)) for g in globs]
    return joined.select(host, "pages", F.array_compact(F.array(*[F.when(t, F.lit(n)) for n, t in tests])).alias("reasons")).filter(F.size("reasons") > 0)


def apply(df: DataFrame, blocklist: DataFrame, host: str = "host") -> DataFrame:
    return df.join(blocklist.select(host), host, "left_anti")


def report(blocklist: DataFrame) -> DataFrame:
    return blocklist.select(F.explode("reasons").alias("reason"), "pages").groupBy("reason").agg(F.count("*").alias("hosts"), F.sum("pages").alias("pages"))


def url_key(url: Column) -> Column:
    """Canonical form: no scheme, no www/m/blog label, no query, fragment, .html or closing slash."""
    u = F.regexp_replace(F.lower(url), r"^[a-z]+://", "")
    u = F.regexp_replace(u, r"^(www|m|blog)\.", "")
    u = F.regexp_replace(u, r"[?#].*$", "")
    u = F.regexp_replace(u, r"\.html?$", "")
    return F.regexp_replace(u, r"/+$", "")
