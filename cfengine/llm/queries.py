"""One query for each operator, with production parameters over the whole intended table."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from ..shipping import ship
from .common import table


def op1_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .language_id import language_id

    return language_id(table(ship(spark), sf_dir, "documents"))


def op2_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .source_mix import source_mix

    return source_mix(table(ship(spark), sf_dir, "documents"))


def op3_nearest_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .permutation_index import nearest_neighbours

    return nearest_neighbours(table(ship(spark), sf_dir, "embeddings"))


def op4_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .quality_rules import quality_rules

    return quality_rules(table(spark, sf_dir, "documents"))


def op5_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .packing import best_fit_packing

    return best_fit_packing(table(ship(spark), sf_dir, "documents"))


def op6_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .near_dedup import near_duplicates

    return near_duplicates(table(ship(spark), sf_dir, "documents"))


def op7_quality_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .quality_model import quality_scores

    return quality_scores(table(ship(spark), sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op8_hidden_markov(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .hidden_markov import hmm_scores

    return hmm_scores(table(ship(spark), sf_dir, "documents"))


def op9_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .secret_scan import scan_secrets

    return scan_secrets(table(ship(spark), sf_dir, "documents"))


def op10_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .url_filter import judge_urls

    return judge_urls(table(spark, sf_dir, "pages"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_language_id": op1_language_id,
        "op2_source_mix": op2_source_mix,
        "op3_nearest_neighbours": op3_nearest_neighbours,
        "op4_quality_rules": op4_quality_rules,
        "op5_best_fit_packing": op5_best_fit_packing,
        "op6_near_dedup": op6_near_dedup,
        "op7_quality_model": op7_quality_model,
        "op8_hidden_markov": op8_hidden_markov,
        "op9_secret_scan": op9_secret_scan,
        "op10_url_filter": op10_url_filter,
    }


def oracle_sql() -> dict[str, str]:
    from . import quality_rules, url_filter

    return {"op4_quality_rules": quality_rules.ORACLE, "op10_url_filter": url_filter.ORACLE}
