"""Training-mixture planning, deterministic sampling, vocabulary candidates, and the learning-rate schedule."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window, functions as F

from ..functions import chargrams
from ..functions.textstats import md5_long


@dataclass(frozen=True)
class Component:
    name: str
    ratio: float | None = None  # of the whole budget
    fixed: float | None = None  # tokens, taken out of the named part below
    within: str | None = None


def plan(spark: SparkSession, components: list[Component], seq_len: int = 4096, batch: int = 1024, steps: int = 25_000) -> DataFrame:
    """(component, tokens, share): a fixed component is taken out of the one it lies within."""
    budget = seq_len * batch * steps
    fixed = {c.name: c.fixed for c in components if c.fixed is not None}
    inside = {c.within: sum(x.fixed for x in components if x.within == c.within) for c in components if c.within}
    rows = [(c.name, float(fixed[c.name] if c.name in fixed else budget * c.ratio - inside.get(c.name, 0.0))) for c in components]
    return spark.createDataFrame([(n, t, t / budget) for n, t in rows], "component string, tokens double, share double")


def supply(budgets: DataFrame, docs: DataFrame, size: Column, component: Column) -> DataFrame:
    """budgets with the words that a component's texts hold, and how often they have to be read for its tokens."""
    held = docs.groupBy(component.alias("component")).agg(F.sum(size).cast("long").alias("available"))
    out = budgets.join(held, "component", "left").withColumn("available", F.coalesce("available", F.lit(0).cast("long")))
    return out.withColumn("epochs", F.col("tokens") / F.nullif(F.col("available"), F.lit(0)))


SECOND_PLAN = [Component("target_web", 0.72), Component("encyclopedia", fixed=1.6e9, within="target_web"), Component("english_web", 0.28)]
PAPER_PLAN = [Component("target_web", 0.90), Component("encyclopedia", fixed=1.6e9, within="target_web"), Component("english_web", 0.05), Component("papers", 0.05)]


def unit(key, seed: int):
    """A uniform number in (0, 1] from md5 of key and seed: every engine draws the same."""
    return (md5_long(F.concat(key.cast("string"), F.lit(f":{seed}")), 13) + 1) / float(1 << 52)


def sample(df: DataFrame, component: str, budgets: DataFrame, size, key: str = "doc_id", seed: int = 1, cells: int = 1024) -> DataFrame:
    """Rows in hash order while a component's running size stays within its budget; budgets(component, tokens).

    Sums over cells of the hash find the cell of the cut, and only that cell is ordered: no component is sorted in one task.
    """
    u = unit(F.col(key), seed)
    rows = df.withColumn("_size", size).withColumn("_u", u).withColumn("_cell", F.least(F.floor(F.col("_u") * cells), F.lit(cells - 1)).cast("int"))
    sums = rows.groupBy(component, "_cell").agg(F.sum("_size").alias("_s"))
    run = F.sum("_s").over(Window.partitionBy(component).orderBy("_cell"))
    before = sums.withColumn("_upto", run).withColumn("_before", F.col("_upto") - F.col("_s")).select(component, "_cell", "_before", "_upto")
    goal = budgets.select(F.col("component").alias(component), F.col("tokens").alias("_goal"))
    joined = rows.join(before.join(goal, component), [component, "_cell"])
    whole = joined.filter(F.col("_upto") <= F.col("_goal"))
    edge = joined.filter((F.col("_upto") > F.col("_goal")) & (F.col("_before") <= F.col("_goal")))
    edge = edge.withColumn("_run", F.col("_before") + F.sum("_size").over(Window.partitionBy(component, "_cell").orderBy("_u", key))).filter(F.col("_run") <= F.col("_goal"))
    return whole.select(df.columns).union(edge.select(df.columns))


def visit_weighted(df: DataFrame, visits: DataFrame, k: int, key: str = "page_id", seed: int = 1) -> DataFrame:
    """k keys drawn in proportion to visits(key, visits): the smallest -ln(u) / w. Unvisited keys are never drawn."""
    w = df.select(key).join(visits.filter("visits > 0"), key)
    return w.withColumn("draw", -F.log(unit(F.col(key), seed)) / F.col("visits")).orderBy("draw", key).limit(k)


def vocabulary_candidates(df: DataFrame, k: int = 100, order: int = 2, base: DataFrame | None = None, text: str = "text") -> DataFrame:
    """(gram, n): the commonest character n-grams, without those of base(gram)."""
    counts = chargrams.gram_counts(df.select(F.lower(F.col(text)).alias("_low")), order, text="_low").filter(F.length("gram") == order)
    if base is not None:
        counts = counts.join(base.select("gram"), "gram", "left_anti")
    return counts.orderBy(F.desc("n"), "gram").limit(k)


def lr_schedule(spark: SparkSession, steps: int = 25_000, warmup: int = 1000, peak: float = 1e-4, final_ratio: float = 1 / 30, shape: str = "cosine") -> DataFrame:
    """(step, lr): linear warm-up, then cosine or linear decay to peak * final_ratio."""
    s = F.col("step")
    x = (s - warmup) / float(steps - warmup)
    low = peak * final_ratio
    fall = low + (peak - low) * (1 + F.cos(F.lit(3.141592653589793) * x)) / 2 if shape == "cosine" else peak + (low - peak) * x
    return spark.range(0, steps + 1).withColumnRenamed("id", "step").select("step", F.when(s < warmup, s * (peak / warmup)).otherwise(fall).alias("lr"))


def texts_by_step(schedule: DataFrame, docs: DataFrame, steps: int = 25_000, key: str = "doc_id", seed: int = 1) -> DataFrame:
    """schedule with the number of texts that each step trains on, which a hash of the key deals over all steps."""
    at = F.least(F.floor(unit(F.col(key), seed) * (steps + 1)), F.lit(steps)).cast("long")
    dealt = docs.filter(F.col(key).isNotNull()).groupBy(at.alias("step")).agg(F.count("*").alias("texts"))
    return schedule.join(dealt, "step", "left").withColumn("texts", F.coalesce("texts", F.lit(0).cast("long")))
