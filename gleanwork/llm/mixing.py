"""Mixing sources to target weights by Pareto order sampling.

A source's target is shared out by weight, with a cap of max_repeats times its size. Of that, whole copies of all its
documents are certain; the rest is a sample of fixed size (in words) with unequal inclusion odds: long documents are
likelier, in proportion to the root of their size class, up to certainty. Each document draws U from a hash of its key and
text and ranks by (U / (1 - U)) / (p / (1 - p)); the first documents whose words reach the rest are taken.

The cut is found without sorting a source in one task: words are summed in cells of the rank, the cell where the sum
reaches the rest is found, and only the documents of that cell (and of as many after it as make EDGE documents) are walked
in order. The number of cells grows with the rows, so that the walk stays short.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame, Window, functions as F

from .common import materialise, small, table, temporary

BUDGET, MAX_REPEATS, WEIGHTS = 1.5, 2, (5.0, 2.0, 1.0)
#: Least and most cells of a source's ranks, rows for each cell between the two, and documents that are walked at least.
CELLS, MOST_CELLS, CELL_ROWS, EDGE = 512, 1 << 20, 1 << 8, 256
#: Sources, and documents at the cuts, that are broadcast; beyond, decisions are joined by key and hash of the text.
BROADCAST_SOURCES, BROADCAST_EDGE = 1 << 14, 1 << 18


def words_of(text: Column) -> Column:
    """Runs other than space and U+0009 to U+000D; null has none."""
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def _fill(df: DataFrame, by: list[str], weight: Column, cap: Column, total: Column, out: str) -> DataFrame:
    """Share total (one value in each group) among its rows by weight, none above its cap, the excess reshared.

    Rows in order of cap / weight: some first rows are capped, the others share by weight what is left. The rows here are
    sources, or size classes of a source, never documents.
    """
    group = Window.partitionBy(*by) if by else Window.partitionBy(F.lit(0))
    before = group.orderBy("_ratio").rowsBetween(Window.unboundedPreceding, -1)
    df = df.withColumn("_weight", weight).withColumn("_cap", cap).withColumn("_total", total)
    df = df.withColumn("_ratio", F.coalesce(F.try_divide("_cap", "_weight"), F.lit(0.0)))
    df = df.withColumn("_left", F.col("_total") - F.coalesce(F.sum("_cap").over(before), F.lit(0.0))).withColumn("_rest", F.sum("_weight").over(group) - F.coalesce(F.sum("_weight").over(before), F.lit(0.0)))
    df = df.withColumn("_level", F.coalesce(F.try_divide(F.greatest(F.lit(0.0), F.col("_left")), F.col("_rest")), F.lit(0.0)))
    level = F.max(F.when(F.col("_level") <= F.col("_ratio"), F.col("_level"))).over(group)
    return df.withColumn(out, F.least(F.col("_cap"), F.coalesce(level * F.col("_weight"), F.col("_cap")))).drop("_weight", "_cap", "_total", "_ratio", "_left", "_rest", "_level")


def targets(sizes: DataFrame, budget: float = BUDGET, weights: tuple = WEIGHTS, max_repeats: int = MAX_REPEATS) -> DataFrame:
    """sizes(source, source_size) -> with target (double). Sources by code point, null last; weights repeat."""
    ordered = Window.partitionBy(F.lit(0)).orderBy(F.col("source").asc_nulls_last())
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.pmod(F.row_number().over(ordered) - 1, F.lit(len(weights))) + 1).cast("int"))
    total = F.sum("source_size").over(Window.partitionBy(F.lit(0))).cast("double") * float(budget)
    df = sizes.withColumn("_w", weight).withColumn("_t", total)
    return _fill(df, [], F.col("_w"), F.col("source_size").cast("double") * float(max_repeats), F.col("_t"), "target").drop("_w", "_t")


def draw(docs: DataFrame, key: str, text: str, source: str, seed: int) -> DataFrame:
    """docs with the columns that the mix needs: _key, _source, _size, _class, _h."""
    size = words_of(docs[text])
    df = docs.withColumns({"_key": docs[key].cast("string"), "_source": docs[source].cast("string"), "_size": size, "_h": F.xxhash64(docs[key], docs[text], F.lit(seed))})
    return df.withColumn("_class", F.when(F.col("_size") > 0, F.floor(F.log2(F.col("_size").cast("double"))).cast("int")))


def _rank(h: Column, p: Column) -> Column:
    """Monotone image in [0, 1] of U's odds over p's odds."""
    u = (F.pmod(h, F.lit(1 << 52)) + 0.5) / float(1 << 52)
    q = u / (1 - u) * F.try_divide(1 - p, p)
    return F.when(p >= 1, 0.0).when(F.coalesce(p, F.lit(0.0)) <= 0, 1.0).otherwise(q / (1 + q))


def _walk(rows: pd.DataFrame) -> pd.DataFrame:
    """In rank order, take what brings the words nearer to what is left; equal rows go together."""
    rows = rows.sort_values(["rank", "key", "h"], kind="stable")
    left, taken = float(rows["rest_left"].iloc[0]) if len(rows) else 0.0, []
    for size in rows["words"]:
        take = 2 * left >= size
        left -= size if take else 0
        taken.append(bool(take))
    return pd.DataFrame({"d_key": rows["key"], "d_h": rows["h"], "d_take": taken})


class Mix:
    """What was decided for a corpus: a row for each source, and a row for each document at a cut."""

    def __init__(self, drawn: DataFrame, budget: float, weights: tuple, max_repeats: int):
        classes = materialise(drawn.groupBy("_source", "_class").agg(F.sum("_size").alias("words"), F.count("*").alias("n")), "mix-classes").withColumnRenamed("_source", "source")
        most = classes.groupBy("source").agg(F.sum("n").alias("n")).agg(F.max("n")).first()[0] or 0
        self.cells = 1 << max(CELLS, min(MOST_CELLS, most // CELL_ROWS)).bit_length() - 1
        goal = targets(classes.groupBy("source").agg(F.sum("words").alias("source_size")), budget, weights, max_repeats)
        goal = goal.withColumn("base", F.coalesce(F.floor(F.try_divide(F.col("target"), F.col("source_size").cast("double"))), F.lit(0)).cast("int"))
        goal = materialise(goal.withColumn("rest", F.col("target") - F.col("base") * F.col("source_size")), "mix-goal")
        odds = classes.filter("words > 0").alias("c").join(goal.alias("g"), F.col("c.source").eqNullSafe(F.col("g.source"))).select("c.source", "_class", F.col("words").cast("double").alias("words"), "rest")
        odds = _fill(odds, ["source"], F.col("words") * F.pow(F.lit(2.0), F.col("_class") / 2.0), F.col("words"), F.col("rest"), "share")
        odds = odds.groupBy("source").agg(F.map_from_entries(F.collect_list(F.struct("_class", F.col("share") / F.col("words")))).alias("odds"))
        self.goal = materialise(goal.alias("g").join(odds.alias("o"), F.col("g.source").eqNullSafe(F.col("o.source")), "left").select("g.*", "odds"), "mix-odds")
        cell = self._ranked(drawn).filter("_size > 0").groupBy("source", "_cell").agg(F.sum("_size").alias("words"), F.count("*").alias("n"))
        per_source = cell.groupBy("source").agg(F.array_sort(F.collect_list(F.struct("_cell", "words", "n"))).alias("cells"))
        begin = F.struct(F.lit(0).cast("long").alias("sum"), F.lit(None).cast("int").alias("at"), F.lit(None).cast("long").alias("before"), F.lit(0).cast("long").alias("n"), F.lit(None).cast("int").alias("upto"))

        def step(rest):
            def f(a, c):
                opens = a["at"].isNull() & (a["sum"] + c["words"] >= rest)
                walking = opens | (a["at"].isNotNull() & (a["n"] < EDGE))
                return F.struct((a["sum"] + c["words"]).alias("sum"), F.when(opens, c["_cell"]).otherwise(a["at"]).alias("at"), F.when(opens, a["sum"]).otherwise(a["before"]).alias("before"), F.when(walking, a["n"] + c["n"]).otherwise(a["n"]).alias("n"), F.when(walking, c["_cell"]).otherwise(a["upto"]).alias("upto"))

            return f

        with_rest = per_source.alias("p").join(self.goal.alias("g"), F.col("p.source").eqNullSafe(F.col("g.source"))).select("p.source", "cells", "rest")
        # Where nothing is left to draw there is no cut, and no document is walked.
        cuts = with_rest.filter("rest > 0").select("source", "rest", F.aggregate("cells", begin, step(F.col("rest"))).alias("c")).select("source", "c.at", "c.upto", (F.col("rest") - F.col("c.before")).alias("rest_left"))
        self.goal = materialise(self.goal.alias("g").join(cuts.alias("c"), F.col("g.source").eqNullSafe(F.col("c.source")), "left").select("g.*", "at", "upto", "rest_left"), "mix-cuts")
        edge = self._ranked(drawn).filter((F.col("_size") > 0) & F.col("_cell").between(F.col("at"), F.col("upto")))
        edge = edge.groupBy(F.col("_key").alias("key"), F.col("_h").alias("h"), "source").agg(F.sum("_size").alias("words"), F.first("_rank").alias("rank"), F.first("rest_left").alias("rest_left"))
        self.edge = materialise(edge.groupBy("source").applyInPandas(_walk, "d_key string, d_h long, d_take boolean"), "mix-edge")
        self.few = small(self.goal, BROADCAST_SOURCES) and small(self.edge, BROADCAST_EDGE)

    few = False

    def _side(self, df: DataFrame) -> DataFrame:
        return F.broadcast(df) if self.few else df

    def _ranked(self, drawn: DataFrame) -> DataFrame:
        df = drawn.join(self._side(self.goal), F.col("_source").eqNullSafe(self.goal["source"]), "left").drop("_source")
        df = df.withColumn("_rank", _rank(F.col("_h"), F.try_element_at(F.col("odds"), F.col("_class"))))
        return df.withColumn("_cell", F.least(F.floor(F.col("_rank") * self.cells), F.lit(self.cells - 1)).cast("int"))

    def apply(self, drawn: DataFrame, keep: list[str]) -> DataFrame:
        """keep, size, source_size, target, copies, taken for each drawn row."""
        df = self._ranked(drawn)
        df = df.join(self._side(self.edge), F.col("_key").eqNullSafe(F.col("d_key")) & (F.col("_h") == F.col("d_h")) & F.col("_cell").between(F.col("at"), F.col("upto")), "left")
        extra = F.coalesce(F.col("_cell") < F.col("at"), F.lit(False)) | F.coalesce(F.col("d_take"), F.lit(False)) | (F.col("at").isNull() & (F.col("rest") > 0))
        copies = F.when(F.col("_size") > 0, F.col("base") + extra.cast("int")).otherwise(F.lit(0))
        return df.select(*keep, F.col("_size").alias("size"), "source_size", "target", copies.alias("copies")).withColumn("taken", F.col("copies") * F.col("size"))


def plan_mix(docs: DataFrame, key: str = "doc_id", text: str = "text", source: str = "source", budget: float = BUDGET, weights: tuple = WEIGHTS, max_repeats: int = MAX_REPEATS, seed: int = 1) -> tuple[Mix, DataFrame]:
    """The decisions for docs, and a table (_key, _h, key, source, size) that apply() takes; the texts are read once.

    Null and empty texts have size 0 and are never taken; a null source is a source of its own; rows equal in key and text
    are taken alike; an empty table gives no rows. Reruns agree: ranks are hashes of key, text and seed. Extra columns are
    not read.
    """
    with temporary() as keep:
        drawn = keep(materialise(draw(docs, key, text, source, seed).select(F.col(key).alias("key"), "_key", "_source", "_size", "_class", "_h"), "mix-drawn"))
        decided = Mix(drawn, budget, weights, max_repeats)
        keep(decided.goal), keep(decided.edge)
    return decided, drawn


def mix(docs: DataFrame, key: str = "doc_id", **how) -> DataFrame:
    """(key, size, source_size, target, copies, taken) for each input row; see plan_mix()."""
    decided, drawn = plan_mix(docs, key=key, **how)
    return decided.apply(drawn, ["key"]).withColumnRenamed("key", key)


def mixed_documents(docs: DataFrame, key: str = "doc_id", text: str = "text", source: str = "source", seed: int = 1, **how) -> DataFrame:
    """docs with each row as often as the mix takes it, all columns as they were; odd rows as in plan_mix().

    Where the sources and the documents at the cuts are few (the usual case) they are broadcast and texts are not shuffled.
    Beyond, the decisions of the narrow table are joined to the rows, by key and hash of the text, which no source makes hot.
    """
    decided, drawn = plan_mix(docs, key=key, text=text, source=source, seed=seed, **how)
    rows = docs.select(F.struct(*docs.columns).alias("_row"), docs[key], docs[text], docs[source])
    if decided.few:
        copies = decided.apply(draw(rows, key, text, source, seed).select("_row", "_key", "_source", "_size", "_class", "_h"), ["_row"])
    else:
        alike = decided.apply(drawn, ["_key", "_h"]).groupBy(F.col("_key").alias("d_key"), F.col("_h").alias("d_h")).agg(F.max("copies").alias("copies")).filter("copies > 0")
        tagged = rows.select("_row", rows[key].cast("string").alias("_key"), F.xxhash64(rows[key], rows[text], F.lit(seed)).alias("_h"))
        copies = tagged.join(alike, F.col("_key").eqNullSafe(F.col("d_key")) & (F.col("_h") == F.col("d_h")))
    return copies.filter("copies > 0").withColumn("_n", F.explode(F.sequence(F.lit(1), F.col("copies")))).select("_row.*")


def op3_mixing(spark, sf_dir: str) -> DataFrame:
    return mix(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken", "copies")
