"""Queries that once made up their rows read a given table, and their rows follow it."""

import pytest

import __spark_entry__ as entry

NAMES = ["w37_lsh_curve", "w64_mixture_plan", "w64b_mixture_72_28", "w66b_lr_schedule", "w66c_lr_schedule_second", "w67_score_average", "w68_score_gain", "w69_score_best", "w70_corpus_comparison", "w71_catalog_sizes"]


@pytest.mark.parametrize("name", NAMES)
def test_reads_a_table(spark, data, name):
    df = entry.queries()[name](spark, data)
    read = [f for f in df.inputFiles() if "/sf0.001/" in f]
    assert read and df.count() > 0
