"""Queries against their SQL counterparts on the smallest tables."""

import pytest
from compare import same

from paircuration.plans import curation, relational, streams

CURATION = ["function_pairs", "page_extract", "stage1_rules", "stage1_rules_boundary", "stage1_survivors", "quality_scores", "quality_sweep", "label_agreement", "exact_groups",
            "jaccard_pairs", "minhash_signatures", "lsh_edges_exact", "near_dedup_greedy_exact", "near_dedup_greedy_none", "near_dedup_components",
            "detector_scores", "detector_per_match", "detector_truth", "detector_repeated_structure", "funnel", "split_rows", "packed_sequences", "bleu_sentence", "bleu_corpus",
            "cyclomatic_proxy", "benchmark_overlap", "lsh_band_choice", "lcs_overlap", "source_files", "function_extract", "function_signatures", "repo_selection_licence_activity", "baseline_comparison", "supplier_coverage", "repo_gini", "corpus_summary"]
RELATIONAL = ["roundtrip_json", "bucketed_join", "join_salted", "join_range_band", "join_interval", "join_asof", "agg_cube", "win_range_interval", "sort_global", "topk_per_group",
              "set_except_all", "fn_array_hof", "udf_sql_names", "udtf_functions", "join_self_bucket", "udf_iter_pandas", "udaf_grouped_agg"]
STREAMS = ["stream_tumbling", "stream_late_drop", "stream_near_dedup"]


@pytest.mark.parametrize("name", CURATION + RELATIONAL + STREAMS)
def test_query_matches_sql(spark, sf, duck, name):
    module = next(m for m in (curation, relational, streams) if name in m.QUERIES)
    same(module.QUERIES[name](spark, sf), duck.sql(module.ORACLES[name]))
