"""The corpus operators' queries, each over its whole table, and their DuckDB twins."""

from __future__ import annotations

import corpus_pipeline
import public_tokenizers

from . import byte_bpe, language_model, licenses, neardup, neighbours, packing, pages, quality, substrings, toxicity
from .common import table


def op1_license_scan(spark, sf_dir):
    return licenses.scan(table(spark, sf_dir, "documents"))


def op2_toxicity(spark, sf_dir):
    return toxicity.query(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op3_near_duplicates(spark, sf_dir):
    return neardup.grouped(table(spark, sf_dir, "documents"))


def op6_quality_rules(spark, sf_dir):
    return quality.query(table(spark, sf_dir, "documents"))


def op7_nearest_neighbours(spark, sf_dir):
    return neighbours.query(table(spark, sf_dir, "embeddings"))


def op8_substring_dedup(spark, sf_dir):
    return substrings.digest(table(spark, sf_dir, "documents"))


def op4_language_model(spark, sf_dir):
    return language_model.query(table(spark, sf_dir, "documents"))


def op5_packing(spark, sf_dir):
    return packing.pack(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))


def op9_html_extraction(spark, sf_dir):
    return pages.extract(table(spark, sf_dir, "pages"))


def op10_byte_bpe(spark, sf_dir):
    return byte_bpe.digests(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_multi_50k.tiktoken"))


def queries() -> dict:
    found = {k: v for k, v in globals().items() if k.startswith("op") and callable(v)}
    return found | {"pipeline": corpus_pipeline.run}


def oracle_sql() -> dict:
    return {"op1_license_scan": licenses.oracle(), "op3_near_duplicates": neardup.oracle(), "op6_quality_rules": quality.oracle(), "op8_substring_dedup": substrings.oracle()}
