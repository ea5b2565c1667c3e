"""The operators' registered queries and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from ordjoin.llm import oracles, quality_rules
from ordjoin.llm.class_lm import op5_brown_class_bigrams
from ordjoin.llm.decontamination import op6_latent_decontamination
from ordjoin.llm.host_reputation import op9_host_reputation
from ordjoin.llm.license_scan import op8_license_scan
from ordjoin.llm.near_duplicates import op10_count_vector_join
from ordjoin.llm.packing import op4_concat_packing
from ordjoin.llm.quality_rules import op1_quality_rules
from ordjoin.llm.sharding import op7_consistent_hash_shards
from ordjoin.llm.substring_dedup import op2_substring_dedup
from ordjoin.llm.suffix_dedup import op3_suffix_array_dedup

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (
        op1_quality_rules,
        op2_substring_dedup,
        op3_suffix_array_dedup,
        op4_concat_packing,
        op5_brown_class_bigrams,
        op6_latent_decontamination,
        op7_consistent_hash_shards,
        op8_license_scan,
        op9_host_reputation,
        op10_count_vector_join,
    )
}
ORACLES: dict[str, str] = {
    "op1_quality_rules": quality_rules.ORACLE,
    "op2_substring_dedup": oracles.substring_dedup(),
    "op3_suffix_array_dedup": oracles.suffix_dedup(),
    "op10_count_vector_join": oracles.near_duplicates(),
}
