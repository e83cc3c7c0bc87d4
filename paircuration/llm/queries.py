"""Queries of the training-data operators, for the entry module."""

from __future__ import annotations

from paircuration.llm.decontaminate import OP7_SQL, op7_benchmark_decontamination
from paircuration.llm.exact_dedup import OP2_SQL, op2_exact_dedup
from paircuration.llm.mixing import op6_source_mixing
from paircuration.llm.quality import op3_quality_classifier
from paircuration.llm.secrets import op9_secret_scans
from paircuration.llm.sharding import op5_sharding
from paircuration.llm.simhash import op10_simhash
from paircuration.llm.token_output import op8_token_output
from paircuration.llm.toxicity import op1_toxicity
from paircuration.llm.url_filter import op4_url_filters

QUERIES = {
    "op1_toxicity": op1_toxicity,
    "op2_exact_dedup": op2_exact_dedup,
    "op3_quality_classifier": op3_quality_classifier,
    "op4_url_filters": op4_url_filters,
    "op5_sharding": op5_sharding,
    "op6_source_mixing": op6_source_mixing,
    "op7_benchmark_decontamination": op7_benchmark_decontamination,
    "op8_token_output": op8_token_output,
    "op9_secret_scans": op9_secret_scans,
    "op10_simhash": op10_simhash,
}
ORACLES = {"op2_exact_dedup": OP2_SQL, "op7_benchmark_decontamination": OP7_SQL}
