"""The registered queries of this subpackage: one per operator, over its whole table, and their SQL where it exists."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from .decontamination import op3_decontamination
from .line_dedup import op5_line_dedup
from .mixing import op9_mixing
from .ngram_join import op7_ngram_join
from .personal_data import op10_personal_data
from .quality import op8_quality
from .secret_scan import op6_secret_scan
from .sharding import op1_sharding
from .substring_dedup import op2_substring_dedup
from .url_filter import op4_url_filter

Query = Callable[[SparkSession, str], DataFrame]


def queries() -> dict[str, Query]:
    return {
        "op1_sharding": op1_sharding,
        "op2_substring_dedup": op2_substring_dedup,
        "op3_decontamination": op3_decontamination,
        "op4_url_filter": op4_url_filter,
        "op5_line_dedup": op5_line_dedup,
        "op6_secret_scan": op6_secret_scan,
        "op7_ngram_join": op7_ngram_join,
        "op8_quality": op8_quality,
        "op9_mixing": op9_mixing,
        "op10_personal_data": op10_personal_data,
    }


def oracle_sql() -> dict[str, str]:
    from .oracles import ORACLES

    return dict(ORACLES)
