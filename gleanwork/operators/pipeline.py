"""Stages and whole pipelines: extraction, quality, deduplication, hosts, cleaning, with a funnel that counts every page."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, functions as F

from ..functions import textstats as ts
from ..profiles import LanguageProfile
from . import dedup, gate, hosts, htmltext, langid, metrics, normalize, quality, repetition


def extract_stage(pages: DataFrame, code: str, gate_mode: str = "either", form: str = "regex", detect_before_extract: bool = False) -> DataFrame:
    """Gate, extraction, precise detection, in this order; no shuffle.

    form: regex (SQL) or density (Arrow pass). detect_before_extract: the rejected order, detection on raw markup.
    """
    gated = gate.rapid_gate(pages, code, gate_mode)
    if detect_before_extract:
        gated = langid.in_language(gated, code, "html")
    if form == "regex":
        out = ts.hold(gated, text=htmltext.extract_main_text(F.col("html"))).drop("html")
    else:
        out = htmltext.extract(gated, carry=tuple(c for c in gated.columns if c not in ("page_id", "html", "text")))
    return out if detect_before_extract else langid.in_language(out, code)


def quality_stage(df: DataFrame, profile: LanguageProfile, key: str = "doc_id", with_repetition: bool = True) -> DataFrame:
    """Cheap rules first, repetition last: the order changes the cost, not the result."""
    kept = quality.apply(df, profile)
    if not with_repetition:
        return kept
    bad = repetition.features(kept, key).filter(repetition.is_repetitive()).select(key)
    return kept.join(bad, key, "left_anti")


@dataclass
class PipelineResult:
    df: DataFrame
    funnel: DataFrame


def run(df: DataFrame, profile: LanguageProfile, stages: tuple[str, ...] = ("quality", "dedup", "hosts", "clean"), key: str = "doc_id", host: str = "source", rows: int = 20, bands: int = 40, family: str = "poly", blocklist: DataFrame | None = None, annotate_only: bool = False, with_repetition: bool = True, save_stages: bool = False) -> PipelineResult:
    """Texts to clean corpus. df has key, text, host and crawl_ts. annotate_only: quality signals instead of removals."""
    sizes = [("raw", df)]
    for stage in stages:
        if stage == "quality":
            df = quality.annotate(df, profile) if annotate_only else quality_stage(df, profile, key, with_repetition)
        elif stage == "dedup":
            df = dedup.run(df, bands, rows, family=family, key=key)
        elif stage == "hosts":
            if blocklist is not None:
                df = hosts.apply(df, blocklist, host)
        elif stage == "clean":
            df = normalize.run(df)
        else:
            raise ValueError(f"no stage {stage}")
        if save_stages:
            df = dedup.save(df, stage)
        sizes.append((stage, df))
    return PipelineResult(df, metrics.funnel_ratios(metrics.stage_sizes(sizes)))
