"""Linear text classifiers trained on hashed words: likeness to a reference set, and a learned harmful-text filter."""

from __future__ import annotations

from pyspark.ml import Pipeline
from pyspark.ml.classification import LogisticRegression
from pyspark.ml.feature import HashingTF, Normalizer
from pyspark.ml.functions import vector_to_array
from pyspark.sql import DataFrame, functions as F

from ..functions import textstats as ts


def _prepare(df: DataFrame, text: str) -> DataFrame:
    return df.withColumn("_words", ts.words(F.coalesce(F.col(text), F.lit(""))))


def train(df: DataFrame, label: str, text: str = "text", features: int = 1 << 16, reg: float = 1e-4):
    """A Spark ML pipeline: hashed word counts, L2 norm, logistic regression. Rows without a label are left out."""
    stages = [HashingTF(inputCol="_words", outputCol="_tf", numFeatures=features), Normalizer(inputCol="_tf", outputCol="_x"), LogisticRegression(featuresCol="_x", labelCol="_y", weightCol="_w", maxIter=20, regParam=reg)]
    known = _prepare(df.filter(F.col(label).isNotNull()), text).withColumn("_y", F.col(label).cast("double"))
    # Both classes weigh the same, however many rows they have.
    share = known.agg(F.avg("_y")).first()[0] or 0.5
    weighted = known.withColumn("_w", F.when(F.col("_y") == 1, 0.5 / max(share, 1e-9)).otherwise(0.5 / max(1 - share, 1e-9)))
    return Pipeline(stages=stages).fit(weighted.select("_words", "_y", "_w"))


def score(df: DataFrame, model, text: str = "text", out: str = "p") -> DataFrame:
    """df with the probability of label 1."""
    scored = model.transform(_prepare(df, text))
    return scored.withColumn(out, vector_to_array("probability")[1]).select(*df.columns, out)


def similar_to_reference(df: DataFrame, reference: DataFrame, threshold: float = 0.5, text: str = "text", reg: float = 0.05) -> DataFrame:
    """df's rows that a classifier finds like reference(text) rather than like df, with p."""
    both = reference.select(text, F.lit(1).alias("y")).union(df.select(text, F.lit(0).alias("y")))
    return score(df, train(both, "y", text, reg=reg), text).filter(F.col("p") >= threshold)


def train_harmful(docs: DataFrame, labels: DataFrame, key: str = "doc_id", text: str = "text"):
    """A filter learned from labels.toxic, beyond term lists."""
    return train(docs.join(labels.select(key, "toxic"), key), "toxic", text)
