"""The registered queries opN_<name>: each applies one operator to its whole table and returns its full result."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

import corpus_pipeline
from spatial_links.llm.common import materialise, new_path, table


def _vocabulary(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    from spatial_links.llm import token_files

    path = new_path(spark, "tokens")
    token_files.write_tokens(table(spark, sf_dir, "documents"), path, _vocabulary("byte_bpe_50k.json"), end_id=2)
    return token_files.with_starts(materialise(token_files.digest(token_files.read_tokens(spark, path)), "digest"))


def op3_mixing_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    from spatial_links.llm.mixing_model import scores

    return scores(table(spark, sf_dir, "documents"))


def op4_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    from spatial_links.llm.secret_scan import scan

    return scan(table(spark, sf_dir, "documents"))


def op5_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    from spatial_links.llm.decontaminate import leaks

    return leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op8_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    from spatial_links.llm.license_scan import scan

    return scan(table(spark, sf_dir, "documents"))


def op6_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    from spatial_links.llm.repetition import quality_rules

    return quality_rules(table(spark, sf_dir, "documents"))


def op9_quality_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    from spatial_links.llm.quality_model import scored

    return scored(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op10_kd_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    from spatial_links.llm.kd_shards import shard

    return shard(table(spark, sf_dir, "documents"), shards=40)


def op7_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from spatial_links.llm.packing import pack

    return pack(table(spark, sf_dir, "documents"), _vocabulary("word_bpe_49k.json"), end_id=0, capacity=2048)


def op2_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from spatial_links.llm.near_dedup import near_duplicates

    return near_duplicates(table(spark, sf_dir, "documents"), width=2, percent=80)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_token_files": op1_token_files,
        "op2_near_dedup": op2_near_dedup,
        "op3_mixing_model": op3_mixing_model,
        "op4_secret_scan": op4_secret_scan,
        "op5_decontamination": op5_decontamination,
        "op6_quality_rules": op6_quality_rules,
        "op7_best_fit_packing": op7_best_fit_packing,
        "op8_license_scan": op8_license_scan,
        "op9_quality_model": op9_quality_model,
        "op10_kd_shards": op10_kd_shards,
        "pipeline": corpus_pipeline.run,
    }


def oracle_sql() -> dict[str, str]:
    from spatial_links.llm import license_scan

    return {"op8_license_scan": license_scan.oracle()}
