"""Training-data pipeline: toxicity, near duplicates, benchmark contamination, mixing, sharding.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; run() writes each result as Parquet into the shared folder
and reads it again as the next stage's docs.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from gleanwork.llm.common import discard, materialise, small, table, temporary
from gleanwork.llm.decontaminate import contaminated, find_contamination
from gleanwork.llm.mixing import mixed_documents
from gleanwork.llm.shard import place
from gleanwork.llm.simhash import near_duplicates
from gleanwork.llm.toxicity import keep_clean, train


#: Rows that leave (or repeat), as two numbers each, that are broadcast to the texts; beyond, texts are joined by row.
BROADCAST_ROWS = 1 << 20


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that the classifier chain rejects; the models are fitted on the labelled ones among docs.

    Rows without a text, or without a word that the models know, stay; repeated rows share their verdict; an empty table stays
    empty.
    """
    return keep_clean(docs, train(docs, table(spark, sf_dir, "labels")))


def identified(docs: DataFrame) -> DataFrame:
    """(r, row): each row of docs as a struct, and 128 bits of hash over all its columns and which of them are null."""
    parts = [x for c in docs.columns for x in (F.col(f"r.`{c}`").isNull(), F.col(f"r.`{c}`"))]
    half = lambda seed: F.xxhash64(F.lit(seed), *parts)
    return docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("r")).select("r", F.struct(half(1).alias("a"), half(2).alias("b")).alias("row"))


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps of each component one row: one with the least doc_id.

    A row without an id stays if no row with an id is in its component. Rows of one doc_id in several components are as many
    documents. Rows are told apart by all their columns; of equal rows one stays. Texts that are null, empty or without words are
    one component. An empty table stays empty. Texts are not shuffled while the rows that leave are few enough to broadcast.
    """
    rows = identified(docs)
    with temporary() as stay:
        found = near_duplicates(rows.select("row", F.col("r.doc_id").alias("doc_id"), F.col("r.text").alias("text")), row="row")
        alike = materialise(found.groupBy("root", "doc_id", "row").agg(F.count("*").alias("n")), "alike")
        first = F.struct(F.col("doc_id").isNull(), "doc_id", "row")
        kept = alike.groupBy("root").agg(F.min_by("row", first).alias("kept")).select("kept")
        marked = alike.join(kept, alike["row"] == kept["kept"], "left").select("row", "n", F.col("kept").isNotNull().alias("stays"))
        # Rows that leave, and those that stay once though they are there n times.
        special = stay(materialise(marked.filter("NOT stays OR n > 1").select(F.col("row").alias("special"), "stays"), "special"))
    side = F.broadcast if small(special, BROADCAST_ROWS) else lambda df: df
    plain = rows.join(side(special.select("special")), rows["row"] == F.col("special"), "left_anti").select("r.*")
    repeated = special.filter("stays").select("special")
    if not repeated.take(1):
        return plain
    once = rows.join(side(repeated), rows["row"] == F.col("special"), "left_semi").groupBy("row").agg(F.first("r").alias("r"))
    return plain.union(once.select("r.*"))


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops rows with at least one word in twenty inside a benchmark window; other rows of the same doc_id stay.

    The rows go through the search as they are, so nothing is joined or shuffled. Rows without words stay, equal rows share their
    verdict, an empty benchmark drops nothing, an empty table stays empty.
    """
    # The text travels once, beside the other columns.
    packed = docs.select(F.struct(F.lit(0), *[F.col(f"`{c}`") for c in docs.columns if c != "text"]).alias("row"), F.col("text"))
    found = find_contamination(packed, table(spark, sf_dir, "benchmark"), key="row", keep_text=True)
    clean = found.filter(~contaminated(F.col("n_hit"), F.col("n_words")))
    return clean.select(*[F.col("text") if c == "text" else F.col(f"row.`{c}`").alias(c) for c in docs.columns])


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mix takes it; texts without words are never taken, equal rows are taken alike, rows without
    a source are a source of their own, an empty table stays empty."""
    return mixed_documents(docs)


def sharding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The mixed documents with their shard; rows without an id share one, copies of a row share one."""
    return place(docs)


STAGES = [("toxicity", toxicity), ("near_dedup", near_dedup), ("decontamination", decontaminate), ("mixing", mixing), ("sharding", sharding)]

#: Trained models and vantage-point trees have no SQL form; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The rows of the last stage. What a stage read is deleted once its own result is written."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        before = docs
        with temporary() as keep:
            docs = keep(materialise(stage(spark, before, sf_dir), f"pipeline-{name}"))
        discard(before)
    return STAGES[-1][1](spark, docs, sf_dir)
